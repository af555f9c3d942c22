"""SQL surface: functions for field arithmetic and distances, table functions for search and reports."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .functions.field import P
from .operators import kernels
from .operators.coarse import as_table
from .operators.codebook import as_words
from .operators.search import Snapshot, search_one


def register_functions(spark: SparkSession) -> None:
    """sqdist, f_add, f_mul and bit_less as SQL functions, expanded into the plan (no Python at run time)."""
    low, high = "({0} & 2147483647L)", "shiftright({0}, 31)"
    xl, xh, yl, yh = low.format("x"), high.format("x"), low.format("y"), high.format("y")
    mixed = f"({xh} * {yl} + {xl} * {yh})"
    fold = lambda e: f"(({e}) & {P}L) + shiftright({e}, 61)"
    total = f"{fold(f'{xh} * {yh} * 2')} + shiftright({mixed}, 30)"
    rest = f"shiftleft({mixed} & 1073741823L, 31)"
    part_a = f"mod({total}, {P}L)"
    part_b = f"mod(mod({rest}, {P}L) + mod({xl} * {yl}, {P}L), {P}L)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION f_add(x BIGINT, y BIGINT) RETURNS BIGINT RETURN mod(x + y, {P}L)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION f_mul(x BIGINT, y BIGINT) RETURNS BIGINT RETURN mod({part_a} + {part_b}, {P}L)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bit_less(x BIGINT, y BIGINT) RETURNS BOOLEAN RETURN shiftright(x - y + 576460752303423488L, 59) = 0")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sqdist(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS BIGINT RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0L, (s, x) -> s + x)")


def publish_views(spark: SparkSession, snap: Snapshot, prefix: str = "") -> None:
    for name in ("centroids", "codebooks", "slots"):
        getattr(snap, name).createOrReplaceTempView(f"{prefix}{name}")


def vector_search(spark: SparkSession, snap: Snapshot, vector: list, k: int | None = None):
    """One encoded query against a snapshot; batches go through operators.search.search."""
    return search_one(vector, snap, k).select("rank", "item", "dist")


def register_search(spark: SparkSession, snap: Snapshot, name: str = "vector_search") -> None:
    """A table function for SQL users: name(array of a query's fixed-point coordinates, k) gives (rank, item, dist).

    It carries the whole fixed-point snapshot to the workers, so the snapshot's size is checked; larger ones go through
    operators.search, which reads the probed lists only.
    """
    cfg = snap.cfg
    size = cfg.capacity * (cfg.blocks * 4 + 17)
    if size > kernels.TABLE_BYTES:
        raise ValueError(f"a snapshot of {size} bytes is too large for a table function; use search")
    rows = snap.slots.orderBy("list_id", "slot").collect()
    codes = np.array([r["codes"] for r in rows], np.int32).reshape(cfg.n_list, cfg.slots, cfg.blocks)
    item = np.array([r["item"] for r in rows], np.int64).reshape(cfg.n_list, cfg.slots)
    valid = np.array([r["valid"] for r in rows], bool).reshape(cfg.n_list, cfg.slots)
    cent, words = as_table(snap.centroids), as_words(snap.codebooks)

    class Search:
        def eval(self, query, k: int):
            q = np.array(query, np.float64)
            probed = np.argsort(((q - cent) ** 2).sum(1), kind="stable")[: cfg.n_probe]
            found = []
            for i in probed:
                r = (q - cent[i]).reshape(cfg.blocks, cfg.width)
                adc = sum(((r[m] - words[m]) ** 2).sum(1)[codes[i, :, m]] for m in range(cfg.blocks))
                found += [(int(d) if ok else cfg.d_max, int(i), s, int(x) if ok else None) for s, (d, ok, x) in enumerate(zip(adc, valid[i], item[i]))]
            for rank, (d, _, _, x) in enumerate(sorted(found, key=lambda t: t[:3])[:k], 1):
                yield rank, x, d

    spark.udtf.register(name, udtf(Search, returnType="rank: int, item: bigint, dist: bigint"))


@udtf(returnType="relation: string, ok: boolean, gates: bigint")
class AuditReport:
    """Rows of a verdict that is stored as a JSON list."""

    def eval(self, text: str):
        for r in json.loads(text or "[]"):
            yield r["relation"], bool(r["ok"]), int(r.get("gates", 0))


def register_tables(spark: SparkSession) -> None:
    spark.udtf.register("audit_report", AuditReport)
