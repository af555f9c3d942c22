"""Configuration selection under a fixed scan budget N_sel and code budget B."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .cost import gate_rows, padded_bin, with_costs


def feasible_codebooks(bits: int, cap: int = 256) -> list[int]:
    """Powers of two whose bit length divides the code budget."""
    return [1 << b for b in range(1, cap.bit_length()) if bits % b == 0]


def derive(capacity: int, bits: int, ratio_inverse: int, n_list: int, codes: int, dims: int, k: int = 1) -> dict:
    """The other knobs follow from the budgets: n = N / n_list, n_probe = r * n_list, M = B / log2 K."""
    return {"n_list": n_list, "D": dims, "n_probe": n_list // ratio_inverse, "n": capacity // n_list, "M": bits // (codes.bit_length() - 1), "K": codes, "k": k}


def search_config(capacity: int, bits: int, ratio_inverse: int, dims: int, max_lists: int, codebooks: list[int] | None = None, gates=gate_rows) -> dict:
    """The pruned search: the smallest layout fixes the best bin; while any codebook size stays in it, double the
    lists, dropping those that leave. The last layout with a survivor wins, with its largest codebook."""
    alive = codebooks or feasible_codebooks(bits)
    n_list, best, visited = ratio_inverse, None, 0
    found: dict = {}
    while alive and n_list <= max_lists:
        bins = {c: padded_bin(gates(derive(capacity, bits, ratio_inverse, n_list, c, dims))) for c in alive}
        visited += len(bins)
        best = min(bins.values()) if best is None else best
        alive = [c for c in alive if bins[c] == best]
        if alive:
            found = {"bin": best, "n_list": n_list, "K": max(alive)}
        n_list *= 2
    return found | {"visited": visited}


def grid(spark, capacity: int, bits: int, ratio_inverse: int, dims: int, max_lists: int) -> DataFrame:
    """Every layout within the bounds, with gates and bin."""
    lists, n = [], ratio_inverse
    while n <= max_lists:
        lists.append(n)
        n *= 2
    rows = [tuple(derive(capacity, bits, ratio_inverse, n, c, dims).values()) for n in lists for c in feasible_codebooks(bits)]
    return with_costs(spark.createDataFrame(rows, "n_list long, dims long, n_probe long, slots long, blocks long, codes long, k long"))


def grid_config(layouts: DataFrame) -> DataFrame:
    """The least bin; in it the most lists, then the largest codebook."""
    w = Window.orderBy("bin", F.desc("n_list"), F.desc("codes"))
    return layouts.withColumn("r", F.row_number().over(w)).filter("r = 1").select("bin", "n_list", "codes")


def high_acc_config(layouts: DataFrame) -> DataFrame:
    return layouts.orderBy(F.desc("n_list"), F.desc("codes")).limit(1).select("bin", "n_list", "codes")


def unimodal(layouts: DataFrame, x: str = "codes", y: str = "gates", by: str = "n_list") -> DataFrame:
    """(by, turns, unimodal): whether y falls and then rises along x."""
    w = Window.partitionBy(by).orderBy(x)
    step = layouts.withColumn("d", F.signum(F.col(y) - F.lag(y).over(w)))
    turn = step.withColumn("p", F.lag("d").over(w)).withColumn("turn", ((F.col("p") != F.col("d")) & F.col("p").isNotNull()).cast("int")).withColumn("up_down", ((F.col("p") > 0) & (F.col("d") < 0)).cast("int"))
    return turn.groupBy(by).agg(F.sum("turn").alias("turns"), (F.coalesce(F.sum("up_down"), F.lit(0)) == 0).alias("unimodal"))
