"""The corpus pipeline on the smallest tables, stage by stage."""

import os

import pytest

SF = "/root/testdata/sf0.001"


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the given tables")
def test_stages(spark):
    import corpus_pipeline as C

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert [n for n, _ in C.STAGES] == ["quality", "near_duplicates", "decontamination", "mixing", "sharding"]
    seen = docs
    for name, stage in C.STAGES:
        out = stage(spark, seen, SF).cache()
        ids = {r.doc_id for r in out.select("doc_id").collect()}
        assert ids <= {r.doc_id for r in seen.select("doc_id").collect()} and ids
        if name != "sharding":
            assert out.columns == docs.columns
        if name in ("quality", "near_duplicates", "decontamination"):
            assert out.count() <= seen.count()
        seen = out
    assert {"slot", "shard_id"} <= set(seen.columns)
