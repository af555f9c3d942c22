"""The five-step search over a snapshot, batched over queries; every step's table can be kept as a trace."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..config import Config
from ..functions.vectors import difference, split_blocks, sqdist
from ..session import written
from . import kernels
from .coarse import as_table
from .codebook import as_words


@dataclass
class Snapshot:
    cfg: Config
    v_max: float
    centroids: DataFrame
    codebooks: DataFrame
    slots: DataFrame
    assign: DataFrame | None = None
    moves: DataFrame | None = None
    extra: dict = field(default_factory=dict)

    @property
    def exact(self) -> bool:
        return self.cfg.pipeline == "zk"


def centroid_distances(queries: DataFrame, snap: Snapshot) -> DataFrame:
    """Step 1: (query_id, list_id, dist) for all lists. queries: (query_id, q)."""
    return kernels.all_distances(queries, "query_id", "q", as_table(snap.centroids), snap.exact)


def select_probes(dist: DataFrame, n_probe: int) -> DataFrame:
    """Step 2: the nearest lists by (dist, list_id), with their rank."""
    w = Window.partitionBy("query_id").orderBy("dist", "list_id")
    return dist.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= n_probe).select("query_id", "rank", "list_id", "dist")


def adc_tables(probes: DataFrame, queries: DataFrame, snap: Snapshot) -> DataFrame:
    """Step 3: (query_id, list_id, m, code, val): squared distance of a residual block to each codeword."""
    cfg = snap.cfg
    rows = probes.select("query_id", "list_id").join(queries, "query_id").join(snap.centroids, "list_id")
    blocks = split_blocks(difference(F.col("q"), F.col("mu")), cfg.blocks, cfg.width)
    rows = rows.select("query_id", "list_id", F.posexplode(blocks).alias("m", "block"))
    zero = F.lit(0).cast("long" if snap.exact else "double")
    return rows.join(snap.codebooks, "m").select("query_id", "list_id", "m", "code", sqdist(F.col("block"), F.col("word"), zero).alias("val"))


def selected_entries(lut: DataFrame, probes: DataFrame, snap: Snapshot) -> DataFrame:
    """The table entries that step 4 reads: (query_id, list_id, slot, m, code, val), one a block of every probed slot."""
    codes = probes.select("query_id", "list_id").join(snap.slots, "list_id").select("query_id", "list_id", "slot", F.posexplode("codes").alias("m", "code"))
    return codes.join(lut, ["query_id", "list_id", "m", "code"]).select("query_id", "list_id", "slot", "m", "code", "val")


def selected_runs(lut: DataFrame, probes: DataFrame, snap: Snapshot, mark: Column | None = None) -> DataFrame:
    """The bag of selected_entries with equal entries as one row: (query_id, list_id, m, code, val, marked, n). A list's
    slots are counted by code before they meet the queries. mark: a condition on slot and m that parts entries."""
    marked = F.lit(False) if mark is None else mark
    held = snap.slots.select("list_id", "slot", F.posexplode("codes").alias("m", "code")).groupBy("list_id", "m", "code", marked.alias("marked")).agg(F.count("*").alias("n"))
    rows = lut.join(probes.select("query_id", "list_id"), ["query_id", "list_id"])
    return rows.join(held, ["list_id", "m", "code"]).select("query_id", "list_id", "m", "code", "val", "marked", "n")


def score_candidates(lut: DataFrame, probes: DataFrame, snap: Snapshot, where: Column | None = None) -> DataFrame:
    """Step 4: (query_id, list_id, slot, item, valid, adc, masked). A slot that is padding, or whose item fails
    `where`, gets the mask distance; no row is dropped.

    The tables of a query travel as one nested array to the slots of its lists, so slots are read once.
    """
    cfg = snap.cfg
    nested = lut.groupBy("query_id", "list_id", "m").agg(F.transform(F.array_sort(F.collect_list(F.struct("code", "val"))), lambda s: s["val"]).alias("vals"))
    nested = nested.groupBy("query_id", "list_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("m", "vals"))), lambda s: s["vals"]).alias("tables"))
    rows = nested.join(snap.slots, "list_id")
    zero = F.lit(0).cast("long" if snap.exact else "double")
    adc = F.aggregate(F.zip_with("tables", "codes", lambda t, c: F.element_at(t, c + 1)), zero, lambda s, x: s + x)
    ok = F.col("valid") == 1
    ok = ok if where is None else ok & F.coalesce(where, F.lit(False))
    rows = rows.select("query_id", "list_id", "slot", "item", ok.cast("tinyint").alias("valid"), adc.alias("adc"))
    mask = F.lit(cfg.d_max).cast("long") if snap.exact else F.lit(float("inf"))
    return rows.withColumn("masked", F.when(F.col("valid") == 1, F.col("adc")).otherwise(mask))


def top_k(cand: DataFrame, k: int) -> DataFrame:
    """Step 5: the k least by (distance, list, slot); each list gives its own k first."""
    inner = Window.partitionBy("query_id", "list_id").orderBy("masked", "slot")
    some = cand.withColumn("r", F.row_number().over(inner)).filter(F.col("r") <= k).drop("r")
    w = Window.partitionBy("query_id").orderBy("masked", "list_id", "slot")
    return some.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def answers_of(top: DataFrame) -> DataFrame:
    pad = F.col("valid") == 0
    return top.select("query_id", "rank", F.when(~pad, F.col("item")).alias("item"), F.col("masked").alias("dist"), pad.alias("is_padding"))


#: Queries that one task takes through a list; a list that more of them probe goes to several tasks.
PROBES_A_TASK = 4096
#: Scores that a task holds at once.
AT_ONCE = 1 << 21


def spread(probes: DataFrame, rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Both sides with a salt: rows of lists that are probed at all, once for every PROBES_A_TASK queries; each query
    with one of its list's salts."""
    per = written(probes.groupBy("list_id").agg(F.ceil(F.count("*") / PROBES_A_TASK).cast("int").alias("salts")), "probed-lists")
    rows = rows.join(per, "list_id").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).drop("salts")
    return probes.join(per, "list_id").withColumn("salt", F.pmod(F.xxhash64("query_id"), F.col("salts")).cast("int")).drop("salts"), rows


def scan_lists(probes: DataFrame, snap: Snapshot, k: int, where: Column | None = None) -> DataFrame:
    """Steps 3 to 5 inside a list: the k best (query_id, list_id, slot, item, valid, masked) of each query and probed
    list. Tables are made and read in the kernel; what is shuffled is a query's vector a probe and each list's codes."""
    cfg, exact = snap.cfg, snap.exact
    ok = F.col("valid") == 1
    ok = ok if where is None else ok & F.coalesce(where, F.lit(False))
    slots = snap.slots.select("list_id", "slot", "item", ok.alias("ok"), "codes")
    probes, slots = spread(probes.select("list_id", "query_id", "q"), slots)
    shipped = slots.sparkSession.sparkContext.broadcast((kernels.checked(as_table(snap.centroids)), kernels.checked(as_words(snap.codebooks))))
    mask = float(cfg.d_max) if exact else float("inf")

    def prepare(t: pa.Table):
        order = np.argsort(t["slot"].to_numpy(), kind="stable")
        codes = t["codes"].combine_chunks().flatten().to_numpy().reshape(-1, cfg.blocks)[order]
        return t["slot"].to_numpy()[order], t["item"].to_numpy()[order], t["ok"].to_numpy(zero_copy_only=False)[order], codes

    def score(list_id, ready, part):
        (slot, item, ok, codes), (cent, words) = ready, shipped.value
        for at in range(0, part.num_rows, max(1, AT_ONCE // len(slot))):
            some = part.slice(at, max(1, AT_ONCE // len(slot)))
            r = (kernels.matrix(some.column("q"), cfg.dims) - cent[list_id]).reshape(-1, cfg.blocks, cfg.width)
            adc = np.zeros((len(r), len(slot)))
            for m in range(cfg.blocks):
                adc += kernels.distances(r[:, m], words[m])[:, codes[:, m]]
            adc = np.where(ok, adc if exact else np.maximum(adc, 0), mask)
            best = kernels.least(adc, k)
            d = np.take_along_axis(adc, best, 1).ravel()
            of, best = pa.array(np.repeat(np.arange(len(r)), best.shape[1])), best.ravel()
            yield pa.RecordBatch.from_arrays([some.column("query_id").take(of), pa.array(np.full(len(best), list_id, np.int32)), pa.array(slot[best]), pa.array(item[best]), pa.array(ok[best].astype(np.int8)), pa.array(d.astype(np.int64) if exact else d)], names=["query_id", "list_id", "slot", "item", "valid", "masked"])

    return kernels.meet(probes, slots, prepare, score, f"query_id long, list_id int, slot int, item long, valid tinyint, masked {'long' if exact else 'double'}")


def found(queries: DataFrame, snap: Snapshot, k: int | None = None, n_probe: int | None = None, where: Column | None = None) -> DataFrame:
    """The k first candidates of each query with their rank and place."""
    probes = written(kernels.nearest_lists(queries, as_table(snap.centroids), n_probe or snap.cfg.n_probe, snap.exact), "probes")
    w = Window.partitionBy("query_id").orderBy("masked", "list_id", "slot")
    return scan_lists(probes, snap, k or snap.cfg.k, where).withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= (k or snap.cfg.k))


def search(queries: DataFrame, snap: Snapshot, k: int | None = None, n_probe: int | None = None, where: Column | None = None) -> DataFrame:
    """answers (query_id, rank, item, dist, is_padding). A rank that only padding can fill has a null item."""
    return answers_of(found(queries, snap, k, n_probe, where))


def search_one(vector: list, snap: Snapshot, k: int | None = None) -> DataFrame:
    """One query at low latency: steps 1 to 3 on the driver, then a scan pruned to the probed lists."""
    cfg, q = snap.cfg, np.array(vector, np.float64)
    cent, words = as_table(snap.centroids), as_words(snap.codebooks)
    d = kernels.distances(q[None], cent)[0]
    probed = np.lexsort((np.arange(len(d)), d))[: cfg.n_probe]
    kind, name = (int, "bigint") if snap.exact else (float, "double")
    rows = []
    for i in probed:
        blocks = (q - cent[i]).reshape(cfg.blocks, cfg.width)
        rows.append((0, int(i), [[kind(x) for x in kernels.distances(b[None], w)[0]] for b, w in zip(blocks, words)]))
    tables = snap.slots.sparkSession.createDataFrame(rows, f"query_id long, list_id int, tables array<array<{name}>>")
    lists = F.col("list_id").isin([int(i) for i in probed])
    if "list_bucket" in snap.slots.columns:
        lists = lists & F.col("list_bucket").isin(sorted({int(i) // snap.extra.get("bucket", 1) for i in probed}))
    part = replace(snap, slots=snap.slots.filter(lists))
    zero = F.lit(0).cast("long" if snap.exact else "double")
    adc = F.aggregate(F.zip_with("tables", "codes", lambda t, c: F.element_at(t, c + 1)), zero, lambda s, x: s + x)
    mask = F.lit(cfg.d_max).cast("long") if snap.exact else F.lit(float("inf"))
    cand = part.slots.join(F.broadcast(tables), "list_id").select("query_id", "list_id", "slot", "item", "valid", F.when(F.col("valid") == 1, adc).otherwise(mask).alias("masked"))
    return answers_of(top_k(cand, k or cfg.k))
