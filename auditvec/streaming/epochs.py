"""Streams of vector updates, audit requests and queries."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import search as S

EVENTS = "event_id BIGINT, ts TIMESTAMP, user_id BIGINT, event_type STRING, value DOUBLE, props STRING"


def read_events(spark: SparkSession, path: str, files_per_trigger: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(EVENTS)
    return (reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader).parquet(path)


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def epoch_counts(events: DataFrame, size: str = "1 day") -> DataFrame:
    """Upserts, inserts and deletes by epoch: (epoch, n, inserts, deletes)."""
    kinds = F.col("event_type")
    out = events.groupBy(F.window("ts", size).alias("w")).agg(F.count("*").alias("n"), F.count_if(kinds == "signup").alias("inserts"), F.count_if(kinds == "error").alias("deletes"))
    return out.select(F.col("w.start").alias("epoch"), "n", "inserts", "deletes")


def sliding_load(events: DataFrame, size: str = "2 days", step: str = "1 day") -> DataFrame:
    out = events.groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n"), F.sum("value").alias("load"))
    return out.select(F.col("w.start").alias("since"), "n", "load")


def request_sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    out = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("w.start").alias("begin"), F.col("w.end").alias("finish"), "n")


def audited(answers: DataFrame, requests: DataFrame, within: str = "1 hour") -> DataFrame:
    """Interval join of the stream of answers with the stream of challenges to them."""
    a = answers.withWatermark("ts", "1 hour").alias("a")
    r = requests.withWatermark("ts", "1 hour").alias("r")
    on = F.expr(f"a.query_id = r.query_id AND r.ts >= a.ts AND r.ts <= a.ts + INTERVAL {within}")
    return a.join(r, on).select(F.col("a.query_id"), F.col("a.ts").alias("answered"), F.col("r.ts").alias("challenged"))


def search_stream(queries: DataFrame, snap: S.Snapshot, sink: str, checkpoint: str, k: int | None = None):
    """Answer a stream of (query_id, q): each micro-batch is one batched search, appended to a table by batch id, so a
    batch that is run again overwrites its own rows only."""

    def each(batch: DataFrame, number: int) -> None:
        S.search(batch, snap, k).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return queries.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint)


def epoch_builder(events: DataFrame, apply_epoch, checkpoint: str):
    """Run apply_epoch(number, events) for each micro-batch; the batch id is the version, so a rerun publishes the
    same version again, which the registry takes as done."""
    return events.writeStream.foreachBatch(lambda batch, number: apply_epoch(number, batch)).option("checkpointLocation", checkpoint)


def changed_vectors(vectors: DataFrame, events: DataFrame) -> DataFrame:
    """vectors (vec_id, embedding, ...) after an epoch's events on them: of each vector the last event counts; 'error'
    deletes it, any other one moves it a little along its first coordinate."""
    n = vectors.agg(F.max("vec_id")).first()[0] + 1
    last = events.groupBy((F.col("event_id") % n).alias("vec_id")).agg(F.max_by("event_type", F.struct("ts", "event_id")).alias("kind"), F.count("*").alias("times"))
    moved = F.transform("embedding", lambda x, i: F.when((i == 0) & F.col("times").isNotNull(), x + F.col("times") / 1000).otherwise(x))
    kept = vectors.join(last, "vec_id", "left").filter(F.col("kind").isNull() | (F.col("kind") != "error"))
    return kept.select("vec_id", moved.alias("embedding"))


def publish_epochs(events: DataFrame, vectors: DataFrame, cfg, v_max: float, registry: str, folder: str, checkpoint: str, **how):
    """A stream of updates as versions: each micro-batch applies to what the version before it left, and the new
    snapshot is written, committed and published under the batch's number before anything is served from it. A batch
    that is run again finds its version published and changes nothing. (late rows of a closed epoch are part of the
    batch that brings them, so they count from its version on.)"""
    from ..operators import commit
    from ..plans.snapshot import build_snapshot
    from ..sources import store

    def apply(number: int, batch: DataFrame) -> None:
        spark = batch.sparkSession
        if not store.versions(spark, registry).filter(F.col("version") == number).isEmpty():
            return
        base = vectors if number == 0 else spark.read.parquet(f"{folder}/{number - 1}/vectors")
        changed_vectors(base, batch).write.mode("overwrite").parquet(f"{folder}/{number}/vectors")
        now = spark.read.parquet(f"{folder}/{number}/vectors")
        snap = build_snapshot(now, cfg, v_max, **how)
        store.write_snapshot(snap, f"{folder}/{number}/snapshot", overwrite=True)
        store.publish(spark, registry, number, commit.commit(snap), now.count())

    return epoch_builder(events, apply, checkpoint)


def late_rows(batch: DataFrame, closed_until) -> tuple[DataFrame, DataFrame]:
    """(in time, late): late rows belong to an epoch that is published already and go into the next one."""
    late = F.col("ts") < F.lit(closed_until)
    return batch.filter(~late), batch.filter(late)


def verdict_rates(verdicts: DataFrame) -> DataFrame:
    """Running count of verdicts and failures by user: (user_id, n, failed), one row a user and micro-batch."""

    def step(key, frames, state):
        n, failed = state.get if state.exists else (0, 0)
        for f in frames:
            n, failed = n + len(f), failed + int((~f["ok"]).sum())
        state.update((n, failed))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "failed": [failed]})

    return verdicts.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, failed long", "n long, failed long", "update", "NoTimeout")
