"""Fixed-point encoding: reals to signed integers within +-(2^bits - 1)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.field import let
from ..functions.field import to_field as field_of
from ..functions.vectors import largest, norm


def coordinate_bound(*frames: DataFrame, col: str = "embedding") -> float:
    """Largest absolute coordinate over all frames; one aggregate, one number to the driver."""
    parts = [f.select(F.max(largest(F.col(col))).alias("b")) for f in frames]
    return reduce(lambda a, b: a.union(b), parts).agg(F.max("b")).first()[0] or 0.0


def fixed(v: Column, v_max: float, bits: int = 16) -> Column:
    s = float((1 << bits) - 1)
    return F.transform(v, lambda x: F.round(x.cast("double") * s / F.lit(float(v_max))).cast("long"))


def encode_fixed(df: DataFrame, col: str = "embedding", v_max: float = 1.0, bits: int = 16, out: str | None = None) -> DataFrame:
    return df.withColumn(out or col, fixed(F.col(col), v_max, bits))


def decode_fixed(v: Column, v_max: float, bits: int = 16) -> Column:
    return F.transform(v, lambda x: x.cast("double") * F.lit(float(v_max)) / float((1 << bits) - 1))


def l2_normalize(df: DataFrame, col: str = "embedding", drop_zero: bool = True) -> DataFrame:
    """Unit vectors; rows without direction are dropped, or kept with a null vector."""
    out = df.withColumn(col, let(norm(F.col(col)), lambda n: F.when(n > 0, F.transform(F.col(col), lambda x: x.cast("double") / n))))
    return out.filter(F.col(col).isNotNull()) if drop_zero else out


def to_field(v: Column) -> Column:
    return F.transform(v, field_of)


def range_check(df: DataFrame, cols: list[str], lo: int, hi: int) -> DataFrame:
    """Rows with an entry outside [lo, hi]: the violations of the range relation."""
    bad = [F.exists(F.col(c), lambda x: (x < lo) | (x > hi)) if df.schema[c].dataType.typeName() == "array" else ~F.col(c).between(lo, hi) for c in cols]
    return df.filter(reduce(lambda a, b: a | b, bad))


def rejected(df: DataFrame, dims: int, id_col: str = "vec_id", col: str = "embedding") -> DataFrame:
    """Rows that cannot be indexed: null or repeated-length-breaking vectors, with the reason."""
    e = F.col(col)
    why = F.when(F.col(id_col).isNull(), "no id").when(e.isNull(), "no vector").when(F.size(e) != dims, "wrong length").when(F.exists(e, lambda x: x.isNull() | F.isnan(x)), "not a number")
    return df.withColumn("reason", why).filter(F.col("reason").isNotNull())
