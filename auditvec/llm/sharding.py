"""Sharding by a permutation-filled lookup table.

Every shard owns a permutation of the slots of a prime-sized table. Shards take turns, each claiming the first
slot of its permutation that is still free, until the table is full; a key hashes to a slot and so to a shard.
Losing or adding a shard moves few keys besides its own. The table has a fixed size, so broadcasting it is safe
at any input size.

Defined results: a null key is placed like the text 'null'; equal keys always meet in one shard; an empty input
gives an empty result; input columns called like an output column are replaced.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import hash60

SHARDS, TABLE_SIZE, SEED = 16, 4099, 11


def _digest(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:15], 16)


def preference(shard: str, size: int, seed: int = SEED) -> tuple[int, int]:
    """Start and step of a shard's walk over the slots; a prime size makes every walk a permutation."""
    return _digest(f"{seed}|start|{shard}") % size, _digest(f"{seed}|step|{shard}") % (size - 1) + 1


def fill_table(shards: list[str], size: int = TABLE_SIZE, seed: int = SEED) -> list[int]:
    """Owner of each slot. Work is about size * log(size) steps on the driver, whatever the data's size."""
    if not shards or len(set(shards)) != len(shards):
        raise ValueError("shards must be distinct and at least one")
    if size < len(shards) or size < 3 or any(size % d == 0 for d in range(2, int(size**0.5) + 1)):
        raise ValueError("the table size must be a prime no smaller than the number of shards")
    walks = [preference(s, size, seed) for s in shards]
    owner, at, left = [-1] * size, [start for start, _ in walks], size
    while True:
        for k, (_, step) in enumerate(walks):
            while owner[at[k]] >= 0:
                at[k] = (at[k] + step) % size
            owner[at[k]] = k
            left -= 1
            if not left:
                return owner


def table_frame(spark: SparkSession, owners: list[int]) -> DataFrame:
    """The filled table as rows (__slot, __shard); one literal, unfolded by the JVM."""
    csv = F.lit(",".join(map(str, owners)))
    rows = spark.range(1).select(F.posexplode(F.split(csv, ",")).alias("__slot", "__shard"))
    return rows.select(F.col("__slot").cast("long"), F.col("__shard").cast("long"))


def slot_of(key: Column, size: int, seed: int = SEED) -> Column:
    return F.pmod(hash60(F.lit(seed), key), F.lit(size))


def assign_shards(df: DataFrame, key: str = "doc_id", shards: int | list[str] = SHARDS, size: int = TABLE_SIZE, seed: int = SEED) -> DataFrame:
    """df with slot and shard_id (both long): one broadcast hash lookup a row, no shuffle."""
    names = [f"shard-{i}" for i in range(shards)] if isinstance(shards, int) else list(shards)
    owners = F.broadcast(table_frame(df.sparkSession, fill_table(names, size, seed)))
    keep = [F.col(f"`{c}`") for c in df.columns if c.lower() not in ("slot", "shard_id")]
    placed = df.select(*keep, slot_of(F.col(f"`{key}`"), size, seed).alias("__slot"))
    return placed.join(owners, "__slot").select(*keep, F.col("__slot").alias("slot"), F.col("__shard").alias("shard_id"))


def write_shards(df: DataFrame, path: str, key: str = "doc_id", files_per_shard: int = 4, **how) -> None:
    """Write one folder per shard; rows of a shard are dealt over several tasks, so a full shard is no single task."""
    placed = assign_shards(df, key, **how)
    placed.repartition(F.col("shard_id"), F.pmod(F.xxhash64(f"`{key}`"), F.lit(files_per_shard))).write.partitionBy("shard_id").parquet(path)
