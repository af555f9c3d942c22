"""Streams give what a batch over the same rows gives."""

import os

import pytest
from pyspark.sql import functions as F

from auditvec.streaming import epochs

SF = "/root/testdata/sf0.001"


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the given tables")
def test_stream_counts_equal_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.repartition(4).write.parquet(str(tmp_path / "in"))
    got = []
    stream = epochs.epoch_counts(epochs.deduplicated(epochs.read_events(spark, str(tmp_path / "in")), "40 days"))
    run = stream.writeStream.outputMode("complete").foreachBatch(lambda df, n: got.append(df.collect())).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    run.awaitTermination()
    assert sorted(map(tuple, got[-1])) == sorted(map(tuple, epochs.epoch_counts(events).collect()))


def test_epochs_publish_versions(spark, tmp_path):
    """Two epochs of updates: each is built, committed and published; a rerun publishes nothing; the batch way agrees."""
    import numpy as np

    from auditvec.config import Config
    from auditvec.operators import commit
    from auditvec.plans.snapshot import build_snapshot
    from auditvec.sources import store

    rng = np.random.default_rng(3)
    vectors = spark.createDataFrame([(i, [float(x) for x in v]) for i, v in enumerate(rng.normal(0, 1, (24, 4)))], "vec_id long, embedding array<double>")
    events = spark.read.parquet(f"{SF}/events.parquet").orderBy("ts").limit(30)
    for part in (0, 1):
        events.filter(f"event_id % 2 = {part}").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    cfg, registry, how = Config(4, 2, 1, 16, 2, 2, 3), str(tmp_path / "registry"), {"init": "stride", "iters": 0}
    for _ in range(2):
        stream = epochs.read_events(spark, str(tmp_path / "in"), 1)
        epochs.publish_epochs(stream, vectors, cfg, 9.0, registry, str(tmp_path / "out"), str(tmp_path / "c"), **how).trigger(availableNow=True).start().awaitTermination()
    found = {r.version: r for r in store.versions(spark, registry).collect()}
    assert sorted(found) == [0, 1]
    now = vectors
    for n in (0, 1):
        taken = spark.read.parquet(str(tmp_path / "in")).withColumn("f", F.input_file_name())
        files = [r[0] for r in taken.select("f").distinct().collect()]
        both = [epochs.changed_vectors(now, taken.filter(F.col("f") == f)) for f in files]
        versions = [commit.commit(build_snapshot(x, cfg, 9.0, **how)) for x in both]
        at = next(i for i, v in enumerate(versions) if v == store.load_version(spark, registry, n))
        now = both[at].cache()
    snap = store.read_snapshot(spark, str(tmp_path / "out" / "1" / "snapshot"))
    assert commit.commit(snap) == store.load_version(spark, registry, 1) != store.load_version(spark, registry, 0)


def test_streams_of_queries_verdicts_and_challenges(spark, tmp_path):
    from auditvec.config import Config
    from auditvec.operators import search
    from auditvec.plans.snapshot import build_snapshot, encode_queries

    vectors = spark.createDataFrame([(i, [float(i % 5), float(i % 3), 1.0, float(i)]) for i in range(20)], "vec_id long, embedding array<double>")
    snap = build_snapshot(vectors, Config(4, 2, 1, 16, 2, 2, 3), init="stride", iters=0)
    asked = encode_queries(vectors.select(F.col("vec_id").alias("query_id"), "embedding"), snap)
    asked.write.parquet(str(tmp_path / "q"))
    run = epochs.search_stream(spark.readStream.schema(asked.schema).parquet(str(tmp_path / "q")), snap, str(tmp_path / "a"), str(tmp_path / "c")).trigger(availableNow=True).start()
    run.awaitTermination()
    cols = ["query_id", "rank", "item", "dist"]
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "a")).select(*cols).collect())) == sorted(map(tuple, search.search(asked, snap).select(*cols).collect()))

    spark.createDataFrame([(1, True), (1, False), (2, True), (1, True)], "user_id long, ok boolean").write.parquet(str(tmp_path / "v"))
    got = []
    run = epochs.verdict_rates(spark.readStream.schema("user_id long, ok boolean").parquet(str(tmp_path / "v"))).writeStream.outputMode("update").foreachBatch(lambda df, n: got.extend(map(tuple, df.collect()))).option("checkpointLocation", str(tmp_path / "c2")).trigger(availableNow=True).start()
    run.awaitTermination()
    assert sorted(got) == [(1, 3, 1), (2, 1, 0)]

    import datetime as dt

    at = lambda m: dt.datetime(2024, 1, 1, 0, m)
    spark.createDataFrame([(1, at(0)), (2, at(1))], "query_id long, ts timestamp").write.parquet(str(tmp_path / "ans"))
    spark.createDataFrame([(1, at(30)), (2, at(0))], "query_id long, ts timestamp").write.parquet(str(tmp_path / "req"))
    source = lambda p: spark.readStream.schema("query_id long, ts timestamp").parquet(str(tmp_path / p))
    seen = []
    run = epochs.audited(source("ans"), source("req")).writeStream.foreachBatch(lambda df, n: seen.extend(r.query_id for r in df.collect())).option("checkpointLocation", str(tmp_path / "c3")).trigger(availableNow=True).start()
    run.awaitTermination()
    assert seen == [1]
    old, late = epochs.late_rows(spark.read.parquet(str(tmp_path / "ans")), at(1))
    assert (old.count(), late.count()) == (1, 1)
