"""Snapshots and the version registry on storage."""

from __future__ import annotations

import datetime
import json

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import Config
from ..operators.commit import Version
from ..operators.search import Snapshot

REGISTRY = "version BIGINT, root_mk STRING, root_cb STRING, config_digest STRING, published_at TIMESTAMP, n0 BIGINT, note STRING"


def write_snapshot(snap: Snapshot, path: str, bucket: int = 64, overwrite: bool = False) -> None:
    """Slots by ranges of lists (one folder a range, sorted), so a probe reads its ranges only; the config last."""
    mode = "overwrite" if overwrite else "errorifexists"
    slots = snap.slots.withColumn("list_bucket", F.expr(f"list_id div {bucket}"))
    slots.repartition("list_bucket").sortWithinPartitions("list_id", "slot").write.mode(mode).partitionBy("list_bucket").parquet(f"{path}/slots")
    snap.centroids.write.mode(mode).parquet(f"{path}/centroids")
    snap.codebooks.write.mode(mode).parquet(f"{path}/codebooks")
    text = json.dumps({"cfg": snap.cfg.__dict__, "v_max": snap.v_max, "bucket": bucket})
    snap.slots.sparkSession.range(1).select(F.lit(text).alias("value")).write.mode(mode).text(f"{path}/config")


def read_snapshot(spark: SparkSession, path: str) -> Snapshot:
    conf = json.loads(spark.read.text(f"{path}/config").first()[0])
    read = lambda name: spark.read.parquet(f"{path}/{name}")
    slots = read("slots").select("list_id", "slot", "valid", "item", "codes", F.col("list_bucket").cast("int").alias("list_bucket"))
    return Snapshot(Config(**conf["cfg"]), conf["v_max"], read("centroids"), read("codebooks"), slots, extra={"bucket": conf["bucket"]})


def versions(spark: SparkSession, registry: str) -> DataFrame:
    try:
        return spark.read.schema(REGISTRY).parquet(registry)
    except AnalysisException as e:
        if e.getCondition() != "PATH_NOT_FOUND":
            raise
        return spark.createDataFrame([], REGISTRY)


def publish(spark: SparkSession, registry: str, number: int, version: Version, n0: int, note: str = "", at: datetime.datetime | None = None) -> bool:
    """Append a version. Publishing the same version again does nothing; another one under its number is an error."""
    old = versions(spark, registry).filter(F.col("version") == number).collect()
    if old:
        if (old[0]["root_mk"], old[0]["root_cb"], old[0]["config_digest"]) != (version.root_mk, version.root_cb, version.config_digest):
            raise ValueError(f"version {number} is published already, with other content")
        return False
    row = (number, version.root_mk, version.root_cb, version.config_digest, at or datetime.datetime.now(), n0, note)
    spark.createDataFrame([row], REGISTRY).coalesce(1).write.mode("append").parquet(registry)
    return True


def load_version(spark: SparkSession, registry: str, number: int) -> Version:
    r = versions(spark, registry).filter(F.col("version") == number).first()
    if r is None:
        raise KeyError(number)
    return Version(r["root_mk"], r["root_cb"], r["config_digest"])


def version_as_of(requests: DataFrame, published: DataFrame, at: str = "ts") -> DataFrame:
    """Each request with the latest version published up to its time: versions are spread over the days they hold, so
    the join is an equality on the day and not a scan of all versions."""
    day = lambda c: F.to_date(c)
    spans = published.select("version", "published_at", F.lead("published_at").over(_by_time()).alias("until"))
    last = requests.agg(F.max(at)).first()[0]
    until = F.coalesce("until", F.lit(last))
    days = spans.filter(until >= F.col("published_at")).select("version", "published_at", "until", F.explode(F.sequence(day("published_at"), day(until))).alias("day"))
    inside = (F.col(at) >= F.col("published_at")) & (F.col("until").isNull() | (F.col(at) < F.col("until")))
    joined = requests.withColumn("day", day(at)).alias("r").join(days.alias("v"), (F.col("r.day") == F.col("v.day")) & inside, "left")
    return joined.select("r.*", "v.version").drop("day")


def _by_time():
    from pyspark.sql.window import Window

    return Window.orderBy("published_at", "version")
