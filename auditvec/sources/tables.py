"""Inputs: the given tables, vector files, and vectors made from text or numbers."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

VECTORS = "vec_id BIGINT, embedding ARRAY<FLOAT>"


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_vectors(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = VECTORS) -> DataFrame:
    """(vec_id, embedding) from Parquet, JSON or CSV; in CSV the vector is one field, its numbers parted by spaces."""
    if fmt == "csv":
        raw = spark.read.schema("vec_id BIGINT, embedding STRING").csv(path)
        return raw.select("vec_id", F.split(F.trim("embedding"), " +").cast("array<float>").alias("embedding"))
    return spark.read.schema(schema).format(fmt).load(path)


def split_queries(vectors: DataFrame, every: int = 10) -> tuple[DataFrame, DataFrame]:
    """Database rows, and held-out rows as (query_id, embedding)."""
    return vectors.filter(F.col("vec_id") % every != 0), vectors.filter(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query_id"), "embedding")


def hash_vectors(df: DataFrame, id_col: str, text: str, dims: int) -> DataFrame:
    """(id, embedding array<double>): signed counts of words hashed into dims buckets; texts without words drop out.

    Each text's words are counted where it is read, a distinct word of a batch is hashed once, and what is shuffled are a
    text's buckets that are not zero; texts with one id are added.
    """
    words = df.select(id_col, F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"\s+"), lambda w: w != "").alias("w"))  # not filtered here, which would split twice

    def counted(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                part = part.filter(pc.greater(pc.list_value_length(part.column("w")), 0))
                said = part.column("w").flatten().dictionary_encode()
                h = np.array([int(hashlib.md5(w.encode()).hexdigest()[:8], 16) for w in said.dictionary.to_pylist()], np.int64)[said.indices.to_numpy()]
                row = np.repeat(np.arange(part.num_rows), part.column("w").value_lengths().to_numpy())
                sums = np.bincount(row * dims + h % dims, np.where(h // dims % 2 == 0, 1.0, -1.0), part.num_rows * dims).reshape(-1, dims)
                own, b = np.nonzero(sums)
                offsets = pa.array(np.searchsorted(own, np.arange(part.num_rows + 1)).astype(np.int32))
                yield pa.RecordBatch.from_arrays([part.column(id_col), pa.ListArray.from_arrays(offsets, pa.array(b.astype(np.int32))), pa.ListArray.from_arrays(offsets, pa.array(sums[own, b]))], names=[id_col, "b", "x"])

    kind = df.schema[id_col].dataType.simpleString()
    sums = words.mapInArrow(counted, f"`{id_col}` {kind}, b array<int>, x array<double>")
    kept = sums.groupBy(id_col).agg(F.collect_list(F.struct("b", "x")).alias("of")).select(id_col, F.flatten("of.b").alias("b"), F.flatten("of.x").alias("x"))

    def dense(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                place = np.repeat(np.arange(part.num_rows), part.column("b").value_lengths().to_numpy()) * dims + part.column("b").flatten().to_numpy()
                out = np.bincount(place, part.column("x").flatten().to_numpy(), part.num_rows * dims)
                offsets = pa.array(np.arange(part.num_rows + 1, dtype=np.int32) * dims)
                yield pa.RecordBatch.from_arrays([part.column(id_col), pa.ListArray.from_arrays(offsets, pa.array(out))], names=[id_col, "embedding"])

    return kept.mapInArrow(dense, f"`{id_col}` {kind}, embedding array<double>")


def numeric_vectors(df: DataFrame, id_col: str, cols: list[str]) -> DataFrame:
    """(id, embedding): z-scores of numeric columns; the moments are one aggregate row."""
    m = df.agg(*[f(c).alias(f"{n}_{c}") for c in cols for n, f in (("a", F.avg), ("s", F.stddev_pop))]).first()
    z = [((F.col(c) - F.lit(m[f"a_{c}"])) / F.lit(m[f"s_{c}"] or 1.0)).cast("double") for c in cols]
    return df.select(F.col(id_col), F.array(*z).alias("embedding"))
