"""The training-corpus pipeline: five stages over `documents`, each on all that the one before it kept.

Quality filter, near-duplicate removal, benchmark decontamination, mixing to target weights, sharding. A stage takes
(spark, docs, sf_dir) and returns a DataFrame; run() writes each stage's rows as Parquet in the shared folder and
reads them back as the next one's docs.
"""

from __future__ import annotations

from auditvec.llm import decontam, lshforest, mixing, quality, sharding
from auditvec.llm.shared import new_path, table


def quality_filter(spark, docs, sf_dir):
    """Documents that the classifier, trained on the labelled ones, scores as good."""
    return quality.keep_quality(docs, quality.train(docs, table(spark, sf_dir, "labels")))


def near_duplicate_removal(spark, docs, sf_dir):
    """One document of each group linked by a similarity of 0.8 or more over five-word shingles."""
    return lshforest.keep_one(docs)


def benchmark_decontamination(spark, docs, sf_dir):
    """Documents of which less than a twentieth of the words lie in benchmark windows."""
    return decontam.remove_contaminated(docs, table(spark, sf_dir, "benchmark"))


def source_mixing(spark, docs, sf_dir):
    """The mix by source weights: a document stands as often as the mix repeats it, or not at all."""
    return mixing.mix_documents(docs)


def shard_placement(spark, docs, sf_dir):
    """Every row with its slot and shard."""
    return sharding.assign_shards(docs)


STAGES = [
    ("quality", quality_filter),
    ("near_duplicates", near_duplicate_removal),
    ("decontamination", benchmark_decontamination),
    ("mixing", source_mixing),
    ("sharding", shard_placement),
]

#: A learned classifier decides the first stage, which SQL cannot express; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = new_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
