"""Coarse partition: centroids, assignment, residuals."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.vectors import difference
from ..session import rows_frame
from . import kernels


def as_table(centroids: DataFrame, col: str = "mu", order: str = "list_id") -> np.ndarray:
    """The centroids on the driver; their number is configuration, not data."""
    rows = centroids.select(order, col).orderBy(order).collect()
    return np.array([r[1] for r in rows], np.float64)


def stride_centroids(vec: DataFrame, n_list: int, col: str = "v") -> DataFrame:
    """Every s-th vector by id, s = count div n_list. The numbering sorts ids globally: a choice for audits and tests;
    hash_centroids needs no such sort."""
    stride = max(1, vec.count() // n_list)
    at = F.row_number().over(Window.orderBy("vec_id")) - 1
    ids = vec.select("vec_id", at.alias("i")).filter((F.col("i") % stride == 0) & (F.col("i") < stride * n_list))
    return vec.join(F.broadcast(ids), "vec_id").select((F.col("i") / stride).cast("int").alias("list_id"), F.col(col).alias("mu"))


def hash_centroids(vec: DataFrame, n_list: int, seed: int = 0, col: str = "v") -> DataFrame:
    picked = vec.orderBy(F.xxhash64(F.lit(seed), F.col("vec_id")), "vec_id").limit(n_list).collect()
    return rows_frame(vec.sparkSession, [(i, list(r[col])) for i, r in enumerate(picked)], f"list_id int, mu {vec.schema[col].dataType.simpleString()}")


def label_centroids(vec: DataFrame, label: str = "label", col: str = "v") -> DataFrame:
    """Mean vector by label, rounded half up: integer sums, so independent of order."""
    rows = vec.select(F.col(label).alias("list_id"), F.posexplode(col).alias("pos", "x"))
    mean = rows.groupBy("list_id", "pos").agg(F.floor(F.sum("x") / F.count("x") + 0.5).alias("x"))
    return mean.groupBy("list_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "x"))), lambda s: s["x"]).alias("mu"))


def lloyd(vec: DataFrame, start: np.ndarray, iters: int, col: str, exact: bool, on_empty: str = "farthest") -> np.ndarray:
    """Lloyd's iterations. Only (rows of the table) x (dimensions) numbers come to the driver each time."""
    table = start.copy()
    for _ in range(iters):
        got = kernels.partial_sums(vec, col, table).collect()
        new = table.copy()
        for r in got:
            s = np.array(r["sums"])
            new[r["list_id"]] = np.floor(s / r["n"] + 0.5) if exact else s / r["n"]
        empty = sorted(set(range(len(table))) - {r["list_id"] for r in got})
        if empty and on_empty == "farthest":
            far = kernels.nearest(vec, col, table, ["vec_id", col], exact).orderBy(F.desc("dist"), "vec_id").limit(len(empty)).collect()
            for i, r in zip(empty, far):
                new[i] = np.array(r[col], np.float64)
        if (new == table).all():
            break
        table = new
    return table


def train_coarse(vec: DataFrame, n_list: int, iters: int = 5, seed: int = 0, init: str = "hash", col: str = "v", exact: bool = True, on_empty: str = "farthest") -> DataFrame:
    """k-means centroids. init: hash, stride or label; iters=0 keeps the start."""
    first = {"hash": lambda: hash_centroids(vec, n_list, seed, col), "stride": lambda: stride_centroids(vec, n_list, col), "label": lambda: label_centroids(vec, col=col)}[init]()
    if not iters:
        return first
    table = lloyd(vec, as_table(first), iters, col, exact, on_empty)
    kind = int if exact else float
    return rows_frame(vec.sparkSession, [(i, [kind(x) for x in row]) for i, row in enumerate(table)], f"list_id int, mu array<{'bigint' if exact else 'double'}>")


def assign_coarse(vec: DataFrame, centroids: DataFrame, col: str = "v", exact: bool = True) -> DataFrame:
    """(vec_id, list_id, dist): the nearest centroid, ties to the smaller list."""
    return kernels.nearest(vec, col, as_table(centroids), ["vec_id"], exact)


def residuals(vec: DataFrame, assign: DataFrame, centroids: DataFrame, col: str = "v") -> DataFrame:
    """(vec_id, list_id, resid) against the centroid of the vector's list."""
    placed = vec.select("vec_id", F.col(col).alias("x")).join(assign.select("vec_id", "list_id"), "vec_id")
    return placed.join(centroids, "list_id").select("vec_id", "list_id", difference(F.col("x"), F.col("mu")).alias("resid"))
