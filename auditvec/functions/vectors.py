"""Vector columns: distances, blocks, norms; all native expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def sqdist(a: Column, b: Column, zero: Column | None = None) -> Column:
    """Squared Euclidean distance of two array columns, in their own arithmetic (exact for integers)."""
    start = F.lit(0).cast("long") if zero is None else zero
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), start, lambda s, x: s + x)


def difference(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def split_blocks(v: Column, blocks: int, width: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda m: F.slice(v, m * width + 1, F.lit(width)))


def norm(v: Column) -> Column:
    return F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))


def largest(v: Column) -> Column:
    return F.array_max(F.transform(v, lambda x: F.abs(x.cast("double"))))
