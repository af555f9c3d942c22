"""Versioned commitment: slot digests, list roots, the layout root, the codebook digest, openings."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import Config, next_power_of_two
from ..session import rows_frame
from .search import Snapshot

#: Leaves of a subtree that one row folds; the driver folds subtree roots only.
SUBTREE = 1024


def _sha(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()


def empty_digest(level: str) -> str:
    return _sha(f"empty|{level}")


@dataclass(frozen=True)
class Version:
    root_mk: str
    root_cb: str
    config_digest: str


def slot_digest(slots: DataFrame) -> DataFrame:
    """(list_id, slot, digest): the record with its place."""
    parts = [F.lit("slot"), F.col("list_id").cast("string"), F.col("slot").cast("string"), F.col("valid").cast("string"), F.col("item").cast("string"), F.array_join(F.transform("codes", lambda c: c.cast("string")), ",")]
    return slots.select("list_id", "slot", F.sha2(F.concat_ws("|", *parts), 256).alias("digest"))


def list_roots(slots: DataFrame, n: int) -> DataFrame:
    """(list_id, root): one shuffle by list; the levels are one array expression each, not a shuffle each."""
    per = slot_digest(slots).groupBy("list_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("slot", "digest"))), lambda s: s["digest"]).alias("hs"))
    full = next_power_of_two(n)
    if full > n:
        per = per.withColumn("hs", F.concat("hs", F.array_repeat(F.lit(empty_digest("slot")), full - n)))
    while full > 1:  # a column a level, so that no expression holds another level's twice
        full //= 2
        per = per.withColumn("hs", F.transform(F.sequence(F.lit(0), F.lit(full - 1)), lambda i: F.sha2(F.concat(F.lit("node|"), F.get("hs", i * 2), F.lit("|"), F.get("hs", i * 2 + 1)), 256)))
    return per.select("list_id", F.get("hs", F.lit(0)).alias("root"))


def list_leaf(centroids: DataFrame, roots: DataFrame) -> DataFrame:
    """(list_id, leaf): index, centroid and list root together."""
    mu = F.array_join(F.transform("mu", lambda x: x.cast("string")), ",")
    return centroids.join(roots, "list_id").select("list_id", F.sha2(F.concat_ws("|", F.lit("list"), F.col("list_id").cast("string"), mu, F.col("root")), 256).alias("leaf"))


def _pairs(xs: list[str]) -> list[str]:
    return [_sha(f"node|{a}|{b}") for a, b in zip(xs[::2], xs[1::2])]


def top_tree(leaves: DataFrame, n_list: int) -> list[tuple[int, int, str]]:
    """(level, pos, digest) of the tree over the leaves; level 0 are the leaves, padded to a power of two."""
    at = {r["list_id"]: r["leaf"] for r in leaves.collect()}
    xs = [at.get(i, empty_digest("list")) for i in range(next_power_of_two(n_list))]
    out, level = [], 0
    while True:
        out += [(level, i, x) for i, x in enumerate(xs)]
        if len(xs) == 1:
            return out
        xs, level = _pairs(xs), level + 1


def layout_root(leaves: DataFrame, n_list: int) -> str:
    """Root over all list leaves. Subtrees of SUBTREE leaves fold on the executors; the driver folds their roots."""
    full = next_power_of_two(n_list)
    if full <= SUBTREE:
        return top_tree(leaves, n_list)[-1][2]
    ids = leaves.sparkSession.range(full).select(F.col("id").cast("int").alias("list_id"))
    every = ids.join(leaves, "list_id", "left").select("list_id", F.coalesce("leaf", F.lit(empty_digest("list"))).alias("leaf"))
    sub = every.groupBy(F.expr(f"list_id div {SUBTREE}").alias("part")).agg(F.transform(F.array_sort(F.collect_list(F.struct("list_id", "leaf"))), lambda s: s["leaf"]).alias("hs"))
    n = SUBTREE
    while n > 1:
        n //= 2
        sub = sub.withColumn("hs", F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.sha2(F.concat(F.lit("node|"), F.get("hs", i * 2), F.lit("|"), F.get("hs", i * 2 + 1)), 256)))
    xs = [r["h"] for r in sub.select("part", F.get("hs", F.lit(0)).alias("h")).orderBy("part").collect()]
    while len(xs) > 1:
        xs = _pairs(xs)
    return xs[0]


def codebook_digest(codebooks: DataFrame) -> str:
    """All coordinates in order of block and code; the codebooks' size is configuration."""
    rows = codebooks.orderBy("m", "code").collect()
    return _sha("codebook|" + ",".join(str(x) for r in rows for x in r["word"]))


def config_digest(cfg: Config, v_max: float) -> str:
    return _sha(cfg.canonical(v_max))


def commit(snap: Snapshot, roots: DataFrame | None = None) -> Version:
    roots = list_roots(snap.slots, snap.cfg.slots) if roots is None else roots
    root = layout_root(list_leaf(snap.centroids, roots), snap.cfg.n_list)
    return Version(root, codebook_digest(snap.codebooks), config_digest(snap.cfg, snap.v_max))


def recommit(old_roots: DataFrame, snap: Snapshot, changed: list[int]) -> DataFrame:
    """List roots where only the changed lists are hashed again."""
    new = list_roots(snap.slots.filter(F.col("list_id").isin(changed)), snap.cfg.slots)
    return old_roots.filter(~F.col("list_id").isin(changed)).unionByName(new)


def merkle_paths(nodes: DataFrame, list_ids: DataFrame) -> DataFrame:
    """(list_id, path): siblings from the leaf upward; side 0 if the own node is the left one."""
    top = nodes.agg(F.max("level")).first()[0]
    if not top:
        return list_ids.select("list_id", F.array().cast("array<struct<level:int,side:int,digest:string>>").alias("path"))
    up = list_ids.select("list_id", F.explode(F.sequence(F.lit(0), F.lit(top - 1))).alias("level")).withColumn("own", F.expr("shiftright(list_id, level)"))
    rows = up.select("list_id", "level", (F.col("own") % 2).alias("side"), F.col("own").bitwiseXOR(F.lit(1)).alias("pos")).join(F.broadcast(nodes), ["level", "pos"])
    return rows.groupBy("list_id").agg(F.array_sort(F.collect_list(F.struct("level", "side", "digest"))).alias("path"))


def merkle_open(leaf: Column, path: Column) -> Column:
    """The root that a leaf and its path lead to."""
    step = lambda h, s: F.sha2(F.when(s["side"] == 0, F.concat(F.lit("node|"), h, F.lit("|"), s["digest"])).otherwise(F.concat(F.lit("node|"), s["digest"], F.lit("|"), h)), 256)
    return F.aggregate(path, leaf, step)


def slot_path(slots: DataFrame, list_id: int, slot: int) -> list[tuple[int, int, str]]:
    """(level, side, digest) from one slot to its list's root; one list's digests come to the driver."""
    xs = [r["digest"] for r in slot_digest(slots.filter(F.col("list_id") == list_id)).orderBy("slot").collect()]
    xs += [empty_digest("slot")] * (next_power_of_two(len(xs)) - len(xs))
    out, at, level = [], slot, 0
    while len(xs) > 1:
        out.append((level, at % 2, xs[at ^ 1]))
        xs, at, level = _pairs(xs), at // 2, level + 1
    return out


def nodes_frame(spark, leaves: DataFrame, n_list: int) -> DataFrame:
    return rows_frame(spark, top_tree(leaves, n_list), "level int, pos int, digest string")
