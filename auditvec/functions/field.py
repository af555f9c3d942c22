"""Arithmetic modulo p = 2^61 - 1 on BIGINT columns, without leaving code generation.

A product is put together from 30- and 31-bit limbs; every intermediate stays below 2^63, so ANSI mode stays on and
would catch a mistake as an overflow.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

P = (1 << 61) - 1
#: Width of comparisons, from the size of the field; operands lie below half of the range.
T_CMP = 60


def let(x: Column, f) -> Column:
    """f of x, with x computed once however often f names it."""
    return F.get(F.transform(F.array(x), f), F.lit(0))


def _mod(x: Column) -> Column:
    return F.pmod(x, F.lit(P))


def to_field(x: Column) -> Column:
    return _mod(x.cast("long"))


def add(x: Column, y: Column) -> Column:
    return _mod(x + y)


def sub(x: Column, y: Column) -> Column:
    return _mod(x + (F.lit(P) - y))


def mul(x: Column, y: Column) -> Column:
    """The product of reduced operands. 2^62 is 2 modulo p, and bit 61 wraps to weight 1."""
    low = lambda v, n: v.bitwiseAND(F.lit((1 << n) - 1))
    xh, xl, yh, yl = F.shiftright(x, 31), low(x, 31), F.shiftright(y, 31), low(y, 31)
    mixed = xh * yl + xl * yh
    upper = _mod(xh * yh * 2 + F.shiftright(mixed, 30))
    lower = _mod(F.shiftleft(low(mixed, 30), 31) + _mod(xl * yl))
    return _mod(upper + lower)


def power(x: Column, n: int) -> Column:
    """x to a public exponent, by squaring along its bits."""
    bits = F.array(*[F.lit(b == "1") for b in bin(n)[2:]])
    return F.aggregate(bits, F.lit(1).cast("long"), lambda s, b: let(mul(s, s), lambda q: F.when(b, mul(q, x)).otherwise(q)))


def compress(cols: list[Column], beta: int) -> Column:
    """A tuple as one element: Horner's rule at beta, first entry lowest. 2L - 2 gates."""
    b = F.lit(beta).cast("long")
    if len(cols) == 1:
        return cols[0]
    return F.aggregate(F.array(*reversed(cols[:-1])), cols[-1], lambda s, c: _mod(mul(s, b) + c))


def inverse(x: int) -> int:
    """Of a public scalar, on the driver."""
    return pow(x, P - 2, P)


def less(x: Column, y: Column, t: int = T_CMP) -> Column:
    """x < y for operands in [0, 2^(t-1)): the top bit of the shifted difference."""
    return F.shiftright(x - y + F.lit(1 << (t - 1)), t - 1) == 0


def in_range(x: Column, t: int = T_CMP) -> Column:
    return (x >= 0) & (x < F.lit(1 << (t - 1)))


def product_by(values, column: str, alpha: int, keys: list[str] | None = None):
    """Product of (alpha - value) modulo p over all rows, or by keys: folds within chunks, then over the chunks."""
    keys = keys or []
    factor = sub(F.lit(alpha).cast("long"), F.col(column))
    fold = lambda xs: F.aggregate(xs, F.lit(1).cast("long"), lambda s, x: mul(s, x))
    dealt = values.select(*keys, factor.alias("f"), F.pmod(F.xxhash64(column), F.lit(256)).alias("chunk"), F.pmod(F.monotonically_increasing_id(), F.lit(64)).alias("part"))
    some = dealt.groupBy(*keys, "chunk", "part").agg(fold(F.collect_list("f")).alias("f"))
    return some.groupBy(*keys).agg(fold(F.collect_list("f")).alias("product"))
