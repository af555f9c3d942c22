"""List shaping: capacity, rebalancing, padding."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import rows_frame, written
from . import kernels
from .coarse import as_table

MOVES = "round int, vec_id bigint, src int, dst int, delta bigint"


def list_sizes(assign: DataFrame, n_list: int, slots: int) -> DataFrame:
    """(list_id, n_i, excess, free) of every list, empty ones too."""
    n = assign.groupBy("list_id").agg(F.count("*").alias("n_i"))
    every = assign.sparkSession.range(n_list).select(F.col("id").cast("int").alias("list_id"))
    out = every.join(n, "list_id", "left").select("list_id", F.coalesce("n_i", F.lit(0)).cast("long").alias("n_i"))
    return out.select("list_id", "n_i", F.greatest(F.lit(0), F.col("n_i") - slots).alias("excess"), F.greatest(F.lit(0), F.lit(slots) - F.col("n_i")).alias("free"))


def naive_capacity(assign: DataFrame) -> int:
    """The baseline: as many slots a list as the largest list has members."""
    return assign.groupBy("list_id").count().agg(F.max("count")).first()[0] or 0


def move_candidates(vec: DataFrame, assign: DataFrame, centroids: DataFrame, sizes: DataFrame, col: str = "v") -> DataFrame:
    """All members of overfull lists with the nearest list that has room now: (vec_id, src, dst, delta, excess, free)."""
    open_lists = [r[0] for r in sizes.filter("free > 0").select("list_id").orderBy("list_id").collect()]
    over = assign.join(F.broadcast(sizes.filter("excess > 0").select("list_id", "excess")), "list_id")
    members = vec.select("vec_id", F.col(col)).join(over.select("vec_id", F.col("list_id").alias("src"), F.col("dist").alias("own"), "excess"), "vec_id")
    near = kernels.nearest(members, col, as_table(centroids)[open_lists], ["vec_id", "src", "own", "excess"])
    ids = F.array(*[F.lit(int(i)) for i in open_lists])
    near = near.withColumn("dst", F.element_at(ids, F.col("list_id") + 1)).select("vec_id", "src", "dst", "own", F.col("dist").alias("cost"), "excess")
    room = sizes.select(F.col("list_id").alias("dst"), "free")
    return near.join(F.broadcast(room), "dst").select("vec_id", "src", "dst", (F.col("cost") - F.col("own")).alias("delta"), F.col("cost"), "excess", "free")


def _admit_in_order(cand: DataFrame) -> list[tuple]:
    """The sequential rule on the driver, streaming candidates in order: for small candidate sets and as a reference."""
    left: dict = {}
    out = []
    for r in cand.orderBy("delta", "vec_id").toLocalIterator():
        s, t = ("s", r["src"]), ("t", r["dst"])
        if left.setdefault(s, r["excess"]) > 0 and left.setdefault(t, r["free"]) > 0:
            left[s] -= 1
            left[t] -= 1
            out.append((r["vec_id"], r["src"], r["dst"], r["delta"], r["cost"]))
    return out


def _admit_by_windows(cand: DataFrame) -> DataFrame:
    """The same admissions without an order of steps.

    Over the candidates not refused yet, one is surely admitted if, with all earlier ones counted as admitted, both
    its source's excess and its target's room still hold it; surely refused if the earlier admitted ones alone use
    either up. The first undecided one is always decidable, so the rounds end.
    """
    by_src = Window.partitionBy("src").orderBy("delta", "vec_id").rowsBetween(Window.unboundedPreceding, -1)
    by_dst = Window.partitionBy("dst").orderBy("delta", "vec_id").rowsBetween(Window.unboundedPreceding, -1)
    rows = cand.withColumn("admitted", F.lit(0))
    done = None
    while True:
        seen = rows
        for name, w in (("s", by_src), ("t", by_dst)):
            seen = seen.withColumn(f"yes_{name}", F.coalesce(F.sum("admitted").over(w), F.lit(0))).withColumn(f"all_{name}", F.count("*").over(w))
        sure = (F.col("all_s") < F.col("excess")) & (F.col("all_t") < F.col("free"))
        never = (F.col("admitted") == 0) & ((F.col("yes_s") >= F.col("excess")) | (F.col("yes_t") >= F.col("free")))
        rows = written(seen.filter(~never).withColumn("now", F.when((F.col("admitted") == 1) | sure, 1).otherwise(0)).drop("admitted").withColumnRenamed("now", "admitted").select(*rows.columns), "admission")
        left = rows.filter("admitted = 0").count()
        if not left or left == done:
            return rows.filter("admitted = 1").select("vec_id", "src", "dst", "delta", "cost")
        done = left


#: Candidates that one task admits in order; more go through windows, with the same admissions.
ONE_TASK = 1 << 21


def _admit_in_one_task(cand: DataFrame) -> DataFrame:
    """The sequential rule over sorted candidates in one task: a step each, where windows need a job for each round."""
    names = ["vec_id", "src", "dst", "delta", "cost"]

    def run(batches):
        excess, free = {}, {}
        for b in batches:
            took = []
            for i, (s, t, e, f) in enumerate(zip(*(b.column(c).to_pylist() for c in ("src", "dst", "excess", "free")))):
                if excess.setdefault(s, e) > 0 and free.setdefault(t, f) > 0:
                    excess[s] -= 1
                    free[t] -= 1
                    took.append(i)
            yield b.select(names).take(pa.array(took, pa.int64()))

    schema = ", ".join(f"{c} {cand.schema[c].dataType.simpleString()}" for c in names)
    return cand.coalesce(1).sortWithinPartitions("delta", "vec_id").mapInArrow(run, schema)


def _admit_fast(cand: DataFrame) -> DataFrame:
    """Not the reference rule: only each source's cheapest candidates try, each target takes its cheapest."""
    a = cand.withColumn("i", F.row_number().over(Window.partitionBy("src").orderBy("delta", "vec_id"))).filter("i <= excess")
    b = a.withColumn("j", F.row_number().over(Window.partitionBy("dst").orderBy("delta", "vec_id"))).filter("j <= free")
    return b.select("vec_id", "src", "dst", "delta", "cost")


def rebalance(vec: DataFrame, assign: DataFrame, centroids: DataFrame, n_list: int, slots: int, mode: str = "window", col: str = "v", n0: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Move vectors out of overfull lists until none is: (assignment, moves). modes: window (exact, distributed beyond ONE_TASK candidates),
    driver (exact, sequential), fast (approximate). Targets hold for a round; centroids stay."""
    spark = vec.sparkSession
    n0 = assign.count() if n0 is None else n0
    if n0 > n_list * slots:
        raise ValueError(f"{n0} vectors do not fit into {n_list} lists of {slots}")
    moves, turn = spark.createDataFrame([], MOVES), 0
    while True:
        sizes = written(list_sizes(assign, n_list, slots), "sizes")
        if sizes.filter("excess > 0").isEmpty():
            return assign, moves
        turn += 1
        cand = written(move_candidates(vec, assign, centroids, sizes, col), "candidates")
        if mode == "driver":
            got = rows_frame(spark, _admit_in_order(cand), "vec_id bigint, src int, dst int, delta bigint, cost bigint")
        else:
            exact = _admit_in_one_task if mode == "window" and cand.count() <= ONE_TASK else _admit_by_windows
            got = written(exact(cand) if mode == "window" else _admit_fast(cand), "admitted")
        moves = moves.unionByName(got.select(F.lit(turn).alias("round"), "vec_id", "src", "dst", "delta"))
        to = got.select("vec_id", F.col("dst"), F.col("cost"))
        assign = written(assign.join(to, "vec_id", "left").select("vec_id", F.coalesce("dst", "list_id").alias("list_id"), F.coalesce("cost", "dist").alias("dist")), "assign")


def pad_slots(codes: DataFrame, n_list: int, slots: int, blocks: int, payload: DataFrame | None = None) -> DataFrame:
    """Exactly n_list * slots rows (list_id, slot, valid, item, codes); members by vec_id, then zero padding."""
    rows = codes if payload is None else codes.join(payload, "vec_id")
    item = F.col("vec_id") if payload is None else F.col("payload")
    at = (F.row_number().over(Window.partitionBy("list_id").orderBy("vec_id")) - 1).cast("int")
    members = rows.select("list_id", at.alias("slot"), item.cast("long").alias("item"), "codes")
    lists = codes.sparkSession.range(n_list).select(F.col("id").cast("int").alias("list_id"))
    grid = lists.select("list_id", F.explode(F.sequence(F.lit(0), F.lit(slots - 1))).alias("slot"))
    zero = F.array_repeat(F.lit(0), blocks)
    return grid.join(members, ["list_id", "slot"], "left").select("list_id", "slot", F.col("codes").isNotNull().cast("tinyint").alias("valid"), F.coalesce("item", F.lit(0)).cast("long").alias("item"), F.coalesce("codes", zero).alias("codes"))
