"""Audits: is an answer exactly what the five steps give on the committed snapshot?

Whatever is public comes from the verifier, as a Statement: the queries, the answers, the version, the configuration
with its coordinate bound, and k. Evidence is the prover's: snapshot parts and each step's table. No relation takes a
public value from the evidence, and each part of the evidence that a later relation builds on is tied to the
statement by an earlier one:

* the configuration to the version's digest, codebooks and centroids to its roots, probed lists to their digests;
* distances and lookup tables are computed again; selected entries are one a block of every bound slot, with the bound
  code, and lie in the tables; scores are their sums; masks and payloads are the bound slots';
* both orderings hold the same tuples as what they order (payload, flag and place included) and number them from 1;
* the answers are the first k rows of the last ordering.

This evaluates every relation of the chosen design in the open. It is not a succinct or hiding proof. Relations are
named, and each failing one is reported with the number of rows that violate it.
"""

from __future__ import annotations

import json
import re
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..config import Config
from ..functions.field import T_CMP
from ..plans.cost import step_gates_of
from ..session import rows_frame, written
from . import commit as C
from . import gadgets as G
from . import search as S
from . import traces as T

VERDICT = "query_id long, relation string, ok boolean, violations long, gates long, checked long"
ANSWER = ["query_id", "rank", "item", "dist", "is_padding"]
#: What an ordering of candidates must keep of each.
CANDIDATE = ["list_id", "slot", "item", "valid", "masked"]


@dataclass
class Statement:
    """What the verifier knows: queries (query_id, q), answers (ANSWER), the version, and the public parameters."""

    queries: DataFrame
    answers: DataFrame
    version: C.Version
    cfg: Config
    v_max: float
    k: int


@dataclass
class Evidence:
    """What the prover hands over: the snapshot parts it used, and each step's table in both orders."""

    snap: S.Snapshot
    roots: DataFrame
    dist: DataFrame
    probes: DataFrame
    lut: DataFrame
    selected: DataFrame
    cand: DataFrame
    order: DataFrame
    paths: DataFrame | None = None

    def tables(self) -> dict[str, DataFrame]:
        return {"roots": self.roots, "dist": self.dist, "probes": self.probes, "lut": self.lut, "selected": self.selected, "cand": self.cand, "order": self.order}


def prove(queries: DataFrame, snap: S.Snapshot, k: int | None = None, later: bool = False) -> tuple[DataFrame, Evidence]:
    """Answers, and the trace that they come from, as written tables. queries: (query_id, q). later: the tables of steps 3
    to 5 are plans that run when they are read; relations that bind the snapshot do not read them."""
    k = k or snap.cfg.k
    step = (lambda d, name: d) if later else written
    queries = written(queries, "queries")
    dist = written(S.centroid_distances(queries, snap), "dist")
    by = Window.partitionBy("query_id").orderBy("dist", "list_id")
    probes = written(dist.withColumn("rank", F.row_number().over(by)), "probe-order")
    first = probes.filter(F.col("rank") <= snap.cfg.n_probe)
    lut = step(S.adc_tables(first, queries, snap), "lut")
    selected = step(S.selected_entries(lut, first, snap), "selected")
    cand = step(S.score_candidates(lut, first, snap), "scores")
    w = Window.partitionBy("query_id").orderBy("masked", "list_id", "slot")
    order = step(cand.withColumn("rank", F.row_number().over(w)), "order")
    answers = step(answers_in(order, k), "answers")
    roots = written(C.list_roots(snap.slots, snap.cfg.slots), "roots")
    nodes = C.nodes_frame(dist.sparkSession, C.list_leaf(snap.centroids, roots), snap.cfg.n_list)
    paths = written(C.merkle_paths(nodes, first.select("list_id").distinct()), "paths")
    return answers, Evidence(snap, roots, dist, probes, lut, selected, cand, order, paths)


def answers_in(order: DataFrame, k: int) -> DataFrame:
    return S.answers_of(order.filter(F.col("rank") <= k)).select(*ANSWER)


def state(queries: DataFrame, answers: DataFrame, snap: S.Snapshot, version: C.Version, k: int | None = None) -> Statement:
    """The statement about a snapshot whose configuration the verifier knows."""
    return Statement(queries.select("query_id", "q"), answers.select(*ANSWER), version, snap.cfg, snap.v_max, k or snap.cfg.k)


def _count(bad: DataFrame) -> DataFrame:
    return bad.groupBy("query_id").agg(F.count("*").alias("violations"))


def _global(st: Statement, violations: int) -> DataFrame:
    return st.queries.select("query_id", F.lit(violations).cast("long").alias("violations"))


def _differ(a: DataFrame, b: DataFrame, cols: list[str]) -> DataFrame:
    """query_id of the rows that one of two bags has more often than the other."""
    return G.bag_difference(a, b, cols)


BINDING = ("bind.config", "bind.codebook", "bind.centroids", "bind.probed")


def binding_checks(st: Statement, ev: Evidence, binding: str = "direct", only: tuple[str, ...] = BINDING) -> dict[str, DataFrame]:
    """Configuration, codebooks, all centroids with all list digests, and the probed lists' contents; or only some."""
    made = {"bind.config": _config_bound, "bind.codebook": _codebook_bound, "bind.centroids": _centroids_bound, "bind.probed": lambda st, ev: _probed_bound(st, ev, binding)}
    return {name: made[name](st, ev) for name in only}


def _config_bound(st: Statement, ev: Evidence) -> DataFrame:
    return _global(st, int(C.config_digest(st.cfg, st.v_max) != st.version.config_digest))


def _codebook_bound(st: Statement, ev: Evidence) -> DataFrame:
    cfg, snap, version = st.cfg, ev.snap, st.version
    shape = snap.codebooks.agg(F.count("*"), F.count_distinct("m", "code"), F.count_if((F.size("word") != cfg.width) | ~F.col("m").between(0, cfg.blocks - 1) | ~F.col("code").between(0, cfg.codes - 1))).first()
    ok_words = tuple(shape) == (cfg.blocks * cfg.codes, cfg.blocks * cfg.codes, 0) and C.codebook_digest(snap.codebooks) == version.root_cb
    return _global(st, int(not ok_words))


def _centroids_bound(st: Statement, ev: Evidence) -> DataFrame:
    cfg, snap, version = st.cfg, ev.snap, st.version
    leaves = written(C.list_leaf(snap.centroids, ev.roots), "leaves")
    shape = snap.centroids.agg(F.count("*"), F.count_if((F.size("mu") != cfg.dims) | ~F.col("list_id").between(0, cfg.n_list - 1))).first()
    ok_lists = tuple(shape) == (cfg.n_list, 0) and leaves.count() == cfg.n_list and C.layout_root(leaves, cfg.n_list) == version.root_mk
    return _global(st, int(not ok_lists))


def _probed_bound(st: Statement, ev: Evidence, binding: str) -> DataFrame:
    cfg, snap, version = st.cfg, ev.snap, st.version
    probed = ev.probes.filter(F.col("rank") <= cfg.n_probe).select("query_id", "list_id")
    slots = snap.slots.join(probed.select("list_id").distinct(), "list_id", "left_semi")
    full = slots.groupBy("list_id").agg(((F.count("*") == cfg.slots) & (F.count_distinct("slot") == cfg.slots) & (F.min("slot") == 0) & (F.max("slot") == cfg.slots - 1)).alias("full"))
    again = written(C.list_roots(slots, cfg.slots).withColumnRenamed("root", "again").join(full, "list_id"), "probed-roots")
    rows = probed.join(again, "list_id", "left").join(ev.roots, "list_id", "left")
    bad = rows.filter(~F.coalesce(F.col("full"), F.lit(False)) | ~F.col("again").eqNullSafe(F.col("root"))).select("query_id", "list_id")
    if binding == "path":
        leaf = C.list_leaf(snap.centroids, again.select("list_id", F.col("again").alias("root")))
        opened = leaf.join(ev.paths, "list_id").select("list_id", C.merkle_open(F.col("leaf"), F.col("path")).alias("top"))
        bad = bad.unionByName(probed.join(opened, "list_id", "left").filter(~F.col("top").eqNullSafe(F.lit(version.root_mk))).select("query_id", "list_id"))
    return _count(bad)


def _ordered(rows: DataFrame, key: str, upto: int) -> DataFrame:
    w = Window.partitionBy("query_id").orderBy("rank")
    return rows.filter(F.col("rank") <= upto).withColumn("before", F.lag(key).over(w)).filter(F.col("before") > F.col(key))


def _boundary(rows: DataFrame, key: str, upto: int) -> DataFrame:
    edge = rows.filter(F.col("rank") <= upto).groupBy("query_id").agg(F.max(key).alias("edge"))
    return rows.filter(F.col("rank") > upto).join(edge, "query_id").filter(F.col(key) < F.col("edge"))


def _sizes(st: Statement, ev: Evidence) -> dict[str, tuple[DataFrame, int]]:
    """Each table of the trace with the rows a query that the configuration fixes."""
    cfg, scanned = st.cfg, st.cfg.scanned
    return {
        "dist": (ev.dist, cfg.n_list), "probes": (ev.probes, cfg.n_list), "lut": (ev.lut, cfg.n_probe * cfg.blocks * cfg.codes), "selected": (ev.selected, scanned * cfg.blocks),
        "cand": (ev.cand, scanned), "order": (ev.order, scanned), "answers": (st.answers, st.k),
    }


def _misshapen(st: Statement, ev: Evidence) -> DataFrame:
    parts, ids = [], st.queries.select("query_id")
    for name, (rows, n) in _sizes(st, ev).items():
        got = rows.groupBy("query_id").agg(F.count("*").alias("n"), *([F.count_distinct("rank").alias("d"), F.min("rank").alias("lo"), F.max("rank").alias("hi")] if "rank" in rows.columns else []))
        fits = F.col("n").eqNullSafe(F.lit(n))
        if "rank" in rows.columns:
            fits &= F.col("d").eqNullSafe(F.lit(n)) & F.col("lo").eqNullSafe(F.lit(1)) & F.col("hi").eqNullSafe(F.lit(n))
        parts.append(ids.join(got, "query_id", "left").filter(~fits).select("query_id"))
    return reduce(lambda a, b: a.unionByName(b), parts)


def shared_checks(st: Statement, ev: Evidence) -> dict[str, DataFrame]:
    """Relations that both designs have."""
    cfg, snap = st.cfg, replace(ev.snap, cfg=st.cfg, v_max=st.v_max)
    first = ev.probes.filter(F.col("rank") <= cfg.n_probe)
    dist = S.centroid_distances(st.queries, snap)
    lut = S.adc_tables(first, st.queries, snap)
    sums = ev.selected.groupBy("query_id", "list_id", "slot").agg(F.sum("val").alias("adc"))
    bound = first.select("query_id", "list_id").join(snap.slots, "list_id").select("query_id", "list_id", "slot", "item", "valid")
    masked = F.when(F.col("valid") == 1, F.col("adc")).otherwise(F.lit(cfg.d_max))
    unmasked = ev.cand.filter(~F.col("masked").eqNullSafe(masked)).select("query_id")
    far = st.queries.filter(F.col("q").isNull() | (F.size("q") != cfg.dims) | F.exists("q", lambda x: x.isNull() | (F.abs(x) > cfg.scale)))
    return {
        "dist.centroid": _count(_differ(dist, ev.dist, ["list_id", "dist"])),
        "lut.recompute": _count(_differ(lut, ev.lut, ["list_id", "m", "code", "val"])),
        "score.sum": _count(_differ(sums, ev.cand, ["list_id", "slot", "adc"])),
        "score.mask": _count(_differ(bound, ev.cand, ["list_id", "slot", "item", "valid"]).unionByName(unmasked)),
        "answer.prefix": _count(_differ(answers_in(ev.order, st.k), st.answers, ANSWER[1:])),
        "range.bounds": _count(far),
        "shape.counts": _count(_misshapen(st, ev)),
    }


def _codes_wrong(st: Statement, ev: Evidence) -> DataFrame:
    """Selected entries are one a block of every bound slot, with its code."""
    first = ev.probes.filter(F.col("rank") <= st.cfg.n_probe).select("query_id", "list_id")
    want = first.join(ev.snap.slots, "list_id").select("query_id", "list_id", "slot", F.posexplode("codes").alias("m", "code"))
    return _differ(want, ev.selected, ["list_id", "slot", "m", "code"])


def multiset_checks(st: Statement, ev: Evidence, pairs: list[tuple[int, int]]) -> dict[str, DataFrame]:
    """Probe and top-k selection by multiset equality and a boundary; table lookups by multiset inclusion."""
    cfg, k = st.cfg, st.k
    out: dict[str, list[DataFrame]] = {"probe.multiset": [], "topk.multiset": [], "lookup.inclusion": [_codes_wrong(st, ev)]}
    for alpha, beta in pairs:
        out["probe.multiset"].append(G.multiset_unequal(ev.dist, ev.probes, ["list_id", "dist"], alpha, beta))
        out["topk.multiset"].append(G.multiset_unequal(ev.cand, ev.order, CANDIDATE, alpha, beta))
        out["lookup.inclusion"].append(G.not_included(ev.selected, ev.lut, ["list_id", "m", "code", "val"], alpha, beta))
    done = {name: _count(reduce(lambda a, b: a.unionByName(b), parts)) for name, parts in out.items()}
    done |= {"probe.order": _count(_ordered(ev.probes, "dist", cfg.n_probe)), "probe.boundary": _count(_boundary(ev.probes, "dist", cfg.n_probe))}
    return done | {"topk.order": _count(_ordered(ev.order, "masked", k)), "topk.boundary": _count(_boundary(ev.order, "masked", k))}


def network_checks(st: Statement, ev: Evidence) -> dict[str, DataFrame]:
    """The same selections by comparison networks, and lookups by scanning each table."""
    cfg, k = st.cfg, st.k

    def prefix_of(rows, key, mate, pos, n):
        got = G.network_prefix(rows.withColumn("pos", pos), ["query_id"], key, mate, n)
        return got.select("query_id", F.posexplode("prefix").alias("i", "x")).select("query_id", (F.col("i") + 1).alias("rank"), F.col("x.key").alias("net"))

    probe = prefix_of(ev.dist, "dist", F.col("list_id").cast("long"), F.col("list_id").cast("long"), cfg.n_probe)
    score = prefix_of(ev.cand, "masked", F.col("item"), F.col("list_id").cast("long") * cfg.slots + F.col("slot"), k)
    tables = ev.lut.groupBy("query_id", "list_id", "m").agg(F.transform(F.array_sort(F.collect_list(F.struct("code", "val"))), lambda s: s["val"]).alias("t"))
    scan = ev.selected.join(tables, ["query_id", "list_id", "m"], "left").filter(~G.lookup_scan(F.col("t"), F.col("code")).eqNullSafe(F.col("val")))
    off = lambda net, rows, key, n: _count(rows.filter(F.col("rank") <= n).join(net, ["query_id", "rank"], "full").filter(~F.col("net").eqNullSafe(F.col(key))))
    return {
        "probe.multiset": _count(_differ(ev.dist, ev.probes, ["list_id", "dist"])), "probe.order": _count(_ordered(ev.probes, "dist", cfg.n_probe)), "probe.boundary": off(probe, ev.probes, "dist", cfg.n_probe),
        "topk.multiset": _count(_differ(ev.cand, ev.order, CANDIDATE)), "topk.order": _count(_ordered(ev.order, "masked", k)), "topk.boundary": off(score, ev.order, "masked", k),
        "lookup.inclusion": _count(scan.select("query_id").unionByName(_codes_wrong(st, ev))),
    }


#: Table of the trace whose rows a relation goes through.
CHECKED = {
    "dist.centroid": "dist", "probe.multiset": "probes", "probe.order": "probes", "probe.boundary": "probes", "lut.recompute": "lut", "lookup.inclusion": "selected", "score.sum": "cand", "score.mask": "cand",
    "topk.multiset": "order", "topk.order": "order", "topk.boundary": "order", "answer.prefix": "answers",
}


def relation_gates(cfg: Config, k: int, design: str) -> dict[str, int]:
    """Counters of the relations, by the gadgets' formulas."""
    n_sel, m, codes = cfg.scanned, cfg.blocks, cfg.codes
    if design == "network":
        probe, top, look = G.GATES["bubble"](cfg.n_list) * cfg.n_probe, G.GATES["bubble"](n_sel) * k, n_sel * m * codes
        return {"probe.boundary": probe, "topk.boundary": top, "lookup.inclusion": look}
    n_max = max(n_sel * m, cfg.n_probe * m * codes)
    return {
        "probe.multiset": G.GATES["multiset"](cfg.n_list) + 2 * cfg.n_list * G.GATES["compress"](2), "probe.order": (cfg.n_probe - 1) * T_CMP, "probe.boundary": (cfg.n_list - cfg.n_probe) * T_CMP,
        "topk.multiset": G.GATES["multiset"](n_sel) + 2 * n_sel * G.GATES["compress"](len(CANDIDATE)), "topk.order": (k - 1) * T_CMP, "topk.boundary": (n_sel - k) * T_CMP,
        "lookup.inclusion": (n_max - 1) * T_CMP + 2 * G.GATES["multiset"](n_max) + 2 * n_max * G.GATES["compress"](4),
    }


def verify(st: Statement, ev: Evidence, design: str = "multiset", binding: str = "direct", repeats: int = 2) -> DataFrame:
    """VERDICT: one row a query and relation; a query is accepted if all are ok. checked counts the rows of the trace
    that the relation went through for the query."""
    st.cfg.validate()
    if not 1 <= st.k <= st.cfg.scanned:
        raise ValueError("k must be between 1 and the number of scanned slots")
    checks = shared_checks(st, ev) | binding_checks(st, ev, binding)
    if design == "multiset":
        seed = "|".join(map(str, (st.version.root_mk, st.version.root_cb, st.version.config_digest, st.k)))
        digest = G.trace_digest(ev.tables() | {"answers": st.answers, "queries": st.queries})
        checks |= multiset_checks(st, ev, G.challenges(seed, digest, repeats))
    elif design == "network":
        checks |= network_checks(st, ev)
    else:
        raise ValueError("design is 'multiset' or 'network'")
    gates, by_step = relation_gates(st.cfg, st.k, design), step_gates_of(st.cfg, design)
    gates |= {"dist.centroid": by_step["distances"], "lut.recompute": by_step["tables"]}
    found = [bad.select("query_id", F.lit(name).alias("relation"), "violations") for name, bad in checks.items()]
    halves = [written(reduce(lambda a, b: a.unionByName(b), found[i::3]), "violations") for i in range(3)]  # smaller plans
    counts = [rows.groupBy("query_id").agg(F.count("*").alias("checked")).select("query_id", F.lit(t).alias("table"), "checked") for t, (rows, _) in _sizes(st, ev).items()]
    counts = reduce(lambda a, b: a.unionByName(b), counts)
    names = F.explode(F.array(*[F.struct(F.lit(n).alias("relation"), F.lit(CHECKED.get(n)).alias("table"), F.lit(int(gates.get(n, 0))).cast("long").alias("gates")) for n in checks]))
    every = st.queries.select("query_id", names.alias("x")).select("query_id", "x.*").join(counts, ["query_id", "table"], "left")
    out = every.join(reduce(lambda a, b: a.unionByName(b), halves), ["query_id", "relation"], "left").withColumn("violations", F.coalesce("violations", F.lit(0)).cast("long"))
    return out.select("query_id", "relation", (F.col("violations") == 0).alias("ok"), "violations", "gates", F.coalesce("checked", F.lit(0)).cast("long").alias("checked"))


#: Design and binding of lists.
WAYS = (("multiset", "path"), ("network", "direct"))


def verify_each(st: Statement, ev: Evidence, ways=WAYS, repeats: int = 2, chosen: DataFrame | None = None) -> DataFrame:
    """verify under several ways, with their design, for traces made and judged a query at a time (traces.py): what binds
    the snapshot is read from the evidence, whose later tables are not. A query without a verdict counts as a violation.
    chosen: (query_id, rank, list_id, slot) of told places in the last ordering."""
    st.cfg.validate()
    if not 1 <= st.k <= st.cfg.scanned:
        raise ValueError("k must be between 1 and the number of scanned slots")
    first = ev.probes.filter(F.col("rank") <= st.cfg.n_probe).select("query_id", "list_id")
    seen = written(T.judge(st, ev.snap, first, [(design, None, [*T.ON_TRACE]) for design, _ in ways], repeats, chosen), "judged")
    parts = []
    for turn, (design, binding) in enumerate(ways):
        bound = binding_checks(st, ev, binding)
        gates, by_step = relation_gates(st.cfg, st.k, design), step_gates_of(st.cfg, design)
        gates |= {"dist.centroid": by_step["distances"], "lut.recompute": by_step["tables"]}
        bad = written(reduce(lambda a, b: a.unionByName(b), [d.select("query_id", F.lit(name).alias("relation"), "violations") for name, d in bound.items()]), "violations")
        found = bad.withColumn("checked", F.lit(0).cast("long")).unionByName(seen.filter(F.col("turn") == turn).drop("turn"))
        names = [F.struct(F.lit(n).alias("relation"), F.lit(int(gates.get(n, 0))).cast("long").alias("gates"), F.lit(int(n in T.ON_TRACE)).alias("lacking")) for n in [*bound, *T.ON_TRACE]]
        every = st.queries.select("query_id", F.explode(F.array(*names)).alias("x")).select("query_id", "x.*").join(found, ["query_id", "relation"], "left")
        every = every.withColumn("violations", F.coalesce("violations", "lacking").cast("long")).withColumn("checked", F.coalesce("checked", F.lit(0)).cast("long"))
        parts.append(every.select("query_id", "relation", (F.col("violations") == 0).alias("ok"), "violations", "gates", "checked", F.lit(design).alias("design")))
    return reduce(lambda a, b: a.unionByName(b), parts)


def audit(queries: DataFrame, snap: S.Snapshot, version: C.Version, design: str = "multiset", binding: str = "direct") -> DataFrame:
    answers, ev = prove(queries, snap)
    return verify(state(queries, answers, snap, version), ev, design, binding)


def _scanned(queries: DataFrame, snap: S.Snapshot, named: DataFrame) -> DataFrame:
    """(query_id, item, dist, there): the scanned candidates with the items that are named for a query, by distance, and
    all scanned padding. named: (query_id, item)."""
    probes = written(S.select_probes(S.centroid_distances(queries, snap), snap.cfg.n_probe), "rerun-probes").select("query_id", "list_id")
    used = snap.slots.filter("valid = 1").join(named.filter("item is not null").distinct(), "item").join(probes, ["query_id", "list_id"])
    lut = S.adc_tables(used.select("query_id", "list_id").distinct(), queries, snap)
    codes = used.select("query_id", "list_id", "slot", "item", F.posexplode("codes").alias("m", "code"))
    adc = codes.join(lut, ["query_id", "list_id", "m", "code"]).groupBy("query_id", "list_id", "slot", "item").agg(F.sum("val").alias("dist"))
    padding = probes.join(snap.slots.filter("valid <> 1").groupBy("list_id").agg(F.count("*").alias("n")), "list_id")
    mask = F.lit(snap.cfg.d_max).cast("long") if snap.exact else F.lit(float("inf"))
    blank = padding.groupBy("query_id").agg(F.sum("n").alias("there")).select("query_id", F.lit(None).cast("long").alias("item"), mask.alias("dist"), "there")
    return adc.groupBy("query_id", "item", "dist").agg(F.count("*").alias("there")).unionByName(blank)


def verify_by_rerun(queries: DataFrame, snap: S.Snapshot, answers: DataFrame, k: int | None = None, again: DataFrame | None = None) -> DataFrame:
    """The baseline in which the client searches again: (query_id, ok). Distances must agree rank by rank, and every
    answer must be a scanned candidate at its distance, as often as there is one; ties may stand in any order. Of the
    candidates only those with an answer's item are made as rows. again: the client's own search, if it is at hand."""
    again = S.search(queries, snap, k) if again is None else again
    off = G.bag_difference(again, answers, ["rank", "dist", "is_padding"])
    there = _scanned(queries, snap, answers.select("query_id", "item"))
    told = answers.groupBy("query_id", F.col("item").alias("it"), F.col("dist").alias("d")).agg(F.count("*").alias("told"))
    met = told.join(there.withColumnRenamed("query_id", "q"), (F.col("query_id") == F.col("q")) & F.col("it").eqNullSafe(F.col("item")) & (F.col("d") == F.col("dist")), "left")
    false = met.filter(F.col("there").isNull() | (F.col("told") > F.col("there"))).select("query_id")
    bad = off.unionByName(false).distinct().withColumn("bad", F.lit(True))
    return queries.select("query_id").join(bad, "query_id", "left").select("query_id", F.col("bad").isNull().alias("ok"))


PARTS = {
    "centroids": "list_id int, mu array<bigint>", "roots": "list_id int, root string", "codebooks": "m int, code int, word array<bigint>", "slots": "list_id int, slot int, valid tinyint, item bigint, codes array<int>",
    "paths": "list_id int, path array<struct<level:int,side:int,digest:string>>", "chosen": "query_id bigint, rank int, list_id int, slot int",
}


def bundle_pieces(ev: Evidence, k: int, chosen: DataFrame | None = None):
    """The text of an opened bundle piece by piece: rows come to the driver one by one. chosen: places of the answers as
    (query_id, rank, list_id, slot), if they are at hand; else those of the ordering."""
    first = ev.probes.filter(F.col("rank") <= ev.snap.cfg.n_probe).select("list_id").distinct()
    chosen = ev.order.filter(F.col("rank") <= k).select("query_id", "rank", "list_id", "slot") if chosen is None else chosen
    parts = {"centroids": ev.snap.centroids, "roots": ev.roots, "codebooks": ev.snap.codebooks, "slots": ev.snap.slots.join(first, "list_id", "left_semi").drop("list_bucket"), "paths": ev.paths, "chosen": chosen}
    for i, name in enumerate(sorted(parts)):
        yield (", " if i else "{") + f"{json.dumps(name)}: ["
        for j, row in enumerate(written(parts[name], "opened").toLocalIterator()):
            yield ", " * bool(j) + json.dumps(row.asDict(True), sort_keys=True)
        yield "]"
    yield "}"


def open_bundle(ev: Evidence, k: int, chosen: DataFrame | None = None) -> str:
    """Portable evidence that reveals what it touches, as JSON: centroids, digests, codebooks, probed lists and their
    paths, and the places of the answers. Queries, answers and parameters are the verifier's own."""
    return "".join(bundle_pieces(ev, k, chosen))


#: Characters of a bundle that the driver gives to a table at once.
BUNDLE_CHARS = 1 << 20


def _rows_of(bundle: str):
    """(part, row as text) of a bundle, one by one."""
    decode, skip = json.JSONDecoder().raw_decode, lambda i: re.compile(r"[\s,]*").match(bundle, i).end()
    at = skip(bundle.index("{") + 1)
    while bundle[at] != "}":
        name, at = decode(bundle, at)
        at = skip(bundle.index("[", at) + 1)
        while bundle[at] != "]":
            end = decode(bundle, at)[1]
            yield name, bundle[at:end]
            at = skip(end)
        at = skip(at + 1)


def _parts_of(spark, bundle: str) -> dict[str, DataFrame]:
    """A bundle's parts as tables; the driver holds its text and a batch of rows."""
    tables, batch, chars = [], [], 0
    for name, row in _rows_of(bundle):
        batch.append((name, row))
        chars += len(row)
        if chars >= BUNDLE_CHARS:
            tables.append(written(rows_frame(spark, batch, "part string, row string"), "bundle"))
            batch, chars = [], 0
    rows = reduce(lambda a, b: a.unionByName(b), [*tables, rows_frame(spark, batch, "part string, row string")])
    part = lambda name, schema: rows.filter(F.col("part") == name).select(F.from_json("row", schema, {"mode": "FAILFAST"}).alias("x")).select("x.*")
    return {name: written(part(name, schema), name) for name, schema in PARTS.items()}


def verify_bundle(spark, bundle: str, st: Statement) -> DataFrame:
    """Check a statement with an opened bundle alone, without the corpus: the steps run again on the opened parts, with
    the answers' places as told, and every relation is checked, lists by their paths."""
    f = _parts_of(spark, bundle)
    snap = S.Snapshot(st.cfg, st.v_max, f["centroids"], f["codebooks"], f["slots"])
    _, ev = prove(st.queries, snap, st.k, later=True)
    return verify_each(st, replace(ev, roots=f["roots"], paths=f["paths"]), [("multiset", "path")], chosen=f["chosen"]).drop("design")
