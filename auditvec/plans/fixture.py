"""The vector fixtures that the catalogue's queries share: every tenth vector is a query, the rest the database."""

from __future__ import annotations

from functools import lru_cache

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..config import Config, next_power_of_two
from ..operators import coarse, encode
from ..operators import search as S
from ..session import written
from ..sources.tables import load_table, split_queries
from .snapshot import build_snapshot, encode_queries

DIMS, LISTS, TIGHT_LISTS, BLOCKS, CODES, PROBES, K = 64, 8, 32, 8, 16, 2, 10
#: Steps of k-means of the trained indexes, for centroids and for codebooks.
TRAIN_ITERS = 5


@lru_cache(maxsize=8)
def _bound(spark: SparkSession, sf_dir: str) -> tuple[float, int]:
    rows = load_table(spark, sf_dir, "embeddings")
    return encode.coordinate_bound(rows), rows.filter("vec_id % 10 <> 0").count()


def encoded(spark: SparkSession, sf_dir: str):
    """(vec_id, label, v): the database in fixed point."""
    bound, _ = _bound(spark, sf_dir)
    rows = load_table(spark, sf_dir, "embeddings").filter("vec_id % 10 <> 0")
    return rows.select("vec_id", "label", encode.fixed(F.col("embedding"), bound).alias("v"))


def roomy(n0: int) -> int:
    """Slots a list for about twice the vectors."""
    return next_power_of_two(-(-2 * n0 // LISTS))


def tight(n0: int) -> int:
    return next_power_of_two(-(-n0 // TIGHT_LISTS))


@lru_cache(maxsize=8)
def snapshot(spark: SparkSession, sf_dir: str) -> S.Snapshot:
    bound, n0 = _bound(spark, sf_dir)
    base, _ = split_queries(load_table(spark, sf_dir, "embeddings"))
    cfg = Config(DIMS, LISTS, PROBES, roomy(n0), BLOCKS, CODES, K)
    return build_snapshot(base.select("vec_id", "embedding"), cfg, bound, init="stride", iters=0)


@lru_cache(maxsize=8)
def swept(spark: SparkSession, sf_dir: str, lists: int) -> S.Snapshot:
    """The stride index on another number of lists; the same share of them is probed, with the same room."""
    if lists == LISTS:
        return snapshot(spark, sf_dir)
    bound, n0 = _bound(spark, sf_dir)
    base, _ = split_queries(load_table(spark, sf_dir, "embeddings"))
    cfg = Config(DIMS, lists, lists * PROBES // LISTS, next_power_of_two(-(-2 * n0 // lists)), BLOCKS, CODES, K)
    return build_snapshot(base.select("vec_id", "embedding"), cfg, bound, init="stride", iters=0)


def trained_config(n0: int) -> Config:
    """Lists by table size, half to one times the square root of the vectors; a quarter of them is probed."""
    lists = max(LISTS, next_power_of_two(-(-int(n0**0.5) // 2)))
    return Config(DIMS, lists, lists * PROBES // LISTS, next_power_of_two(-(-2 * n0 // lists)), BLOCKS, CODES, K)


@lru_cache(maxsize=8)
def trained(spark: SparkSession, sf_dir: str) -> S.Snapshot:
    """A trained index for queries that SQL does not repeat; it shares the bound, so queries() fit it."""
    bound, n0 = _bound(spark, sf_dir)
    base, _ = split_queries(load_table(spark, sf_dir, "embeddings"))
    return build_snapshot(base.select("vec_id", "embedding"), trained_config(n0), bound, init="hash", iters=TRAIN_ITERS)


@lru_cache(maxsize=8)
def queries(spark: SparkSession, sf_dir: str):
    _, held = split_queries(load_table(spark, sf_dir, "embeddings"))
    return written(encode_queries(held, snapshot(spark, sf_dir)), "queries")


@lru_cache(maxsize=8)
def tight_lists(spark: SparkSession, sf_dir: str):
    """(vec, centroids, assign, slots a list) of the layout with hardly any room."""
    _, n0 = _bound(spark, sf_dir)
    vec = written(encoded(spark, sf_dir), "tight-vectors")
    cent = written(coarse.stride_centroids(vec, TIGHT_LISTS), "tight-centroids")
    return vec, cent, written(coarse.assign_coarse(vec, cent), "tight-assign"), tight(n0)
