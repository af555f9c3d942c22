"""The relations of audit.py on one query's trace at a time, as arrays inside a task.

A trace has an entry for each block of each scanned slot. As rows of tables these are sorted and shuffled over and over;
here a query's trace is made, handed from prover to verifier and judged in one task, and only verdicts leave it. Queries
that probe the same lists share a task and the rows of these lists. Challenges come from a query's own trace and public
values. What binds configuration, codebooks, centroids and lists stays in audit.binding_checks.

A table is a dict of equally long integer arrays; its rows are a bag.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Config
from ..functions.field import P
from ..session import written
from . import gadgets as G
from . import kernels
from .coarse import as_table
from .codebook import as_words

#: Candidates that one task goes through for an attack or design.
CANDIDATES_A_TASK = 1 << 20
MOST_PARTS = 4096
DIST, LUT, PLACE = ["list_id", "dist"], ["list_id", "m", "code", "val"], ["list_id", "slot"]
CANDIDATE = ["list_id", "slot", "item", "valid", "masked"]
ANSWER = ["rank", "item", "none", "dist", "is_padding"]
TABLES = ("dist", "probes", "lut", "selected", "cand", "order")


@dataclass
class Lists:
    """The bound contents of some lists in order of (list_id, slot), with all centroids and codewords."""

    list_id: np.ndarray
    slot: np.ndarray
    valid: np.ndarray
    item: np.ndarray
    codes: np.ndarray
    cent: np.ndarray
    words: np.ndarray

    def of(self, ids: np.ndarray) -> Lists:
        keep = np.isin(self.list_id, ids)
        return self if keep.all() else replace(self, **{c: getattr(self, c)[keep] for c in ("list_id", "slot", "valid", "item", "codes")})


@dataclass
class Told:
    """What the verifier knows of a query: q, the answers, and public values as one text."""

    q: np.ndarray
    answers: dict
    public: str


@dataclass
class Trace:
    dist: dict
    probes: dict
    lut: dict
    selected: dict
    cand: dict
    order: dict
    extra: dict = field(default_factory=dict)


# Bags of rows ---------------------------------------------------------------------------------------------------------


def size(t: dict) -> int:
    return len(next(iter(t.values())))


def take(t: dict, rows: np.ndarray) -> dict:
    return {c: x[rows] for c, x in t.items()}


def put(t: dict, **cols) -> dict:
    return t | {c: np.asarray(x, np.int64) for c, x in cols.items()}


def joined(a: dict, b: dict) -> dict:
    return {c: np.concatenate([a[c], b[c]]) for c in a}


def _same(a: dict, b: dict, cols: list[str]) -> bool:
    return all(np.array_equal(a[c], b[c]) for c in cols)


def differ(a: dict, b: dict, cols: list[str]) -> int:
    """Tuples that one bag has more often than the other."""
    if _same(a, b, cols):
        return 0
    rows = np.concatenate([np.stack([t[c] for c in cols], 1) for t in (a, b)])
    sign = np.repeat([1, -1], [size(a), size(b)])
    order = np.lexsort(rows.T[::-1])
    rows, sign = rows[order], sign[order]
    starts = np.flatnonzero(np.concatenate([[True], (rows[1:] != rows[:-1]).any(1)]))
    return int(np.count_nonzero(np.add.reduceat(sign, starts)))


def sums_of(selected: dict) -> dict:
    """(list_id, slot, adc): the entries of a slot together."""
    i, s, v = selected["list_id"], selected["slot"], selected["val"]
    if not len(i):
        return {"list_id": i, "slot": s, "adc": v}
    if ((i[1:] < i[:-1]) | ((i[1:] == i[:-1]) & (s[1:] < s[:-1]))).any():
        by = np.lexsort((s, i))
        i, s, v = i[by], s[by], v[by]
    starts = np.flatnonzero(np.concatenate([[True], (i[1:] != i[:-1]) | (s[1:] != s[:-1])]))
    return {"list_id": i[starts], "slot": s[starts], "adc": np.add.reduceat(v, starts)}


# Arithmetic modulo P, as in functions/field.py ------------------------------------------------------------------------


def _fold(x: np.ndarray) -> np.ndarray:
    """x modulo P for 0 <= x < 2^63."""
    x = (x & P) + (x >> 61)
    x -= P * (x >= P)
    return x


def mul(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    xh, xl, yh, yl = x >> 31, x & ((1 << 31) - 1), y >> 31, y & ((1 << 31) - 1)
    mixed = xh * yl + xl * yh
    upper = _fold(xh * yh * 2 + (mixed >> 30))
    return _fold(upper + _fold((mixed & ((1 << 30) - 1)) << 31) + _fold(xl * yl))


def compress(t: dict, cols: list[str], beta: int) -> np.ndarray:
    xs, b = [np.mod(t[c], P) for c in cols], np.int64(beta)
    out = xs[-1]
    for x in reversed(xs[:-1]):
        out = _fold(mul(out, b) + x)
    return out


def product(t: dict, cols: list[str], alpha: int, beta: int) -> int | None:
    """Product of (alpha - tuple) over a bag; None for an empty one."""
    f = _fold(np.int64(alpha) + (P - compress(t, cols, beta)))
    if not len(f):
        return None
    while len(f) > 1:
        odd, half = f[2 * (len(f) // 2) :], len(f) // 2
        f = np.concatenate([mul(f[:half], f[half : 2 * half]), odd])
    return int(f[0])


# Prover ---------------------------------------------------------------------------------------------------------------


def centroid_distances(q: np.ndarray, cent: np.ndarray) -> dict:
    d = kernels.distances(q[None].astype(np.float64), cent)[0].astype(np.int64)
    return {"list_id": np.arange(len(cent)), "dist": d}


def adc_tables(ids: np.ndarray, q: np.ndarray, lists: Lists) -> dict:
    """A row an entry, in order of (list_id, m, code)."""
    blocks, codes, width = lists.words.shape
    ids = np.sort(ids)
    r = (q[None].astype(np.float64) - lists.cent[ids]).reshape(-1, blocks, width)
    val = np.stack([kernels.distances(r[:, m], lists.words[m]) for m in range(blocks)], 1).astype(np.int64)
    return {"list_id": np.repeat(ids, blocks * codes), "m": np.tile(np.repeat(np.arange(blocks), codes), len(ids)), "code": np.tile(np.arange(codes), len(ids) * blocks), "val": val.ravel()}


def bound_entries(lists: Lists) -> dict:
    """(list_id, slot, m, code): one a block of every slot."""
    blocks = lists.codes.shape[1]
    return {"list_id": np.repeat(lists.list_id, blocks), "slot": np.repeat(lists.slot, blocks), "m": np.tile(np.arange(blocks), len(lists.slot)), "code": lists.codes.ravel()}


def ranked(cand: dict) -> dict:
    by = np.lexsort((cand["slot"], cand["list_id"], cand["masked"]))
    return take(cand, by) | {"rank": np.arange(1, len(by) + 1)}


def answers_in(order: dict, k: int) -> dict:
    top = take(order, order["rank"] <= k)
    top = take(top, np.argsort(top["rank"], kind="stable"))
    none = top["valid"] == 0
    return {"rank": top["rank"], "item": np.where(none, 0, top["item"]), "none": none.astype(np.int64), "dist": top["masked"], "is_padding": none.astype(np.int64)}


def prove(q: np.ndarray, lists: Lists, cfg: Config) -> Trace:
    dist = centroid_distances(q, lists.cent)
    by = np.lexsort((dist["list_id"], dist["dist"]))
    probes = take(dist, by) | {"rank": np.arange(1, len(by) + 1)}
    ids = probes["list_id"][: cfg.n_probe]
    lists, lut = lists.of(ids), adc_tables(ids, q, lists)
    blocks, codes, _ = lists.words.shape
    entries = bound_entries(lists)
    at = np.searchsorted(np.sort(ids), entries["list_id"]) * blocks * codes + entries["m"] * codes + entries["code"]
    selected = entries | {"val": lut["val"][at]}
    adc = selected["val"].reshape(-1, blocks).sum(1)
    cand = {"list_id": lists.list_id, "slot": lists.slot, "item": lists.item, "valid": lists.valid, "adc": adc, "masked": np.where(lists.valid == 1, adc, cfg.d_max)}
    return Trace(dist, probes, lut, selected, cand, ranked(cand))


# Verifier -------------------------------------------------------------------------------------------------------------


def digest(told: Told, tr: Trace) -> str:
    h = hashlib.sha256()
    for name, t in [(n, getattr(tr, n)) for n in TABLES] + [("answers", told.answers), ("q", {"q": told.q})]:
        for c in sorted(t):
            h.update(f"|{name}.{c}.{len(t[c])}|".encode())
            h.update(np.ascontiguousarray(t[c], np.int64))
    return h.hexdigest()


def _ordered(t: dict, key: str, upto: int) -> int:
    t = take(t, t["rank"] <= upto)
    x = t[key][np.argsort(t["rank"], kind="stable")]
    return int(np.count_nonzero(x[:-1] > x[1:]))


def _boundary(t: dict, key: str, upto: int) -> int:
    inside = t["rank"] <= upto
    return int(np.count_nonzero(t[key][~inside] < t[key][inside].max())) if inside.any() else 0


def sizes(told: Told, tr: Trace, cfg: Config, k: int) -> dict[str, tuple[dict, int]]:
    n = cfg.scanned
    want = {"dist": cfg.n_list, "probes": cfg.n_list, "lut": cfg.n_probe * cfg.blocks * cfg.codes, "selected": n * cfg.blocks, "cand": n, "order": n}
    return {name: (getattr(tr, name), m) for name, m in want.items()} | {"answers": (told.answers, k)}


def _misshapen(told: Told, tr: Trace, cfg: Config, k: int) -> int:
    bad = 0
    for t, n in sizes(told, tr, cfg, k).values():
        bad += size(t) != n or ("rank" in t and not np.array_equal(np.sort(t["rank"]), np.arange(1, n + 1)))
    return bad


def _net(t: dict, key: str, pos: np.ndarray, passes: int) -> np.ndarray:
    """The first keys after that many passes of the comparison network over the rows in order of pos."""
    x, out = t[key][np.lexsort((t[key], pos))], []
    for _ in range(min(passes, len(x))):
        x = x[G.bubble_pass(x)]
        out.append(x[0])
        x = x[1:]
    return np.array(out, np.int64)


def _off(net: np.ndarray, t: dict, key: str, n: int) -> int:
    """Ranks at which the network's key and the ordering's differ, and rows that only one of them has."""
    t, bad = take(t, t["rank"] <= n), 0
    inside = (t["rank"] >= 1) & (t["rank"] <= len(net))
    bad += int(np.count_nonzero(~inside)) + int(np.count_nonzero(net[t["rank"][inside] - 1] != t[key][inside]))
    return bad + len(net) - len(np.unique(t["rank"][inside]))


def _scan_wrong(tr: Trace) -> int:
    """Selected entries that a scan of their whole table with a one-hot selector does not give."""
    lut, sel = tr.lut, tr.selected
    at = np.lexsort((lut["val"], lut["code"], lut["m"], lut["list_id"]))
    key = lut["list_id"][at] * (1 << 20) + lut["m"][at]
    names, starts, n = np.unique(key, return_index=True, return_counts=True)
    table = np.zeros((len(names) + 1, n.max(initial=0)), np.int64)
    table[np.repeat(np.arange(len(names)), n), np.arange(len(key)) - np.repeat(starts, n)] = lut["val"][at]
    own = sel["list_id"] * (1 << 20) + sel["m"]
    row = np.searchsorted(names, own)
    known = np.append(names, -1)[row] == own
    val = np.zeros(len(own), np.int64)
    for code in range(table.shape[1]):
        val += np.where(sel["code"] == code, table[np.where(known, row, len(names)), code], 0)
    return int(np.count_nonzero(~known | (val != sel["val"])))


def _apart(selected: dict, lut: dict) -> dict:
    """Selected entries without those that equal, in all of LUT, a table's entry: equal tuples compress to equal values."""
    if not size(lut):
        return selected
    key = lambda t: (t["list_id"] << 40) + (t["m"] << 20) + t["code"]
    names, at = np.unique(key(lut), return_index=True)
    at = np.append(at, 0)[np.searchsorted(names, key(selected))]
    same = np.ones(len(at), bool)
    for c in LUT:
        same &= selected[c] == lut[c][at]
    return take(selected, ~same)


class Relations:
    """Each relation's number of violations in one trace; a dot in its name is an underscore here."""

    def __init__(self, told: Told, tr: Trace, lists: Lists, cfg: Config, k: int, design: str, repeats: int):
        self.told, self.tr, self.lists, self.cfg, self.k, self.design, self.repeats = told, tr, lists, cfg, k, design, repeats
        self.first = tr.probes["list_id"][tr.probes["rank"] <= cfg.n_probe]
        self.bound = lists.of(self.first)
        self._pairs = None

    def pairs(self) -> list[tuple[int, int]]:
        if self._pairs is None:
            self._pairs = G.challenges(self.told.public, digest(self.told, self.tr), self.repeats)
        return self._pairs

    def dist_centroid(self):
        return differ(centroid_distances(self.told.q, self.lists.cent), self.tr.dist, DIST)

    def lut_recompute(self):
        return differ(adc_tables(self.first, self.told.q, self.lists), self.tr.lut, LUT)

    def score_sum(self):
        return differ(sums_of(self.tr.selected), self.tr.cand, [*PLACE, "adc"])

    def score_mask(self):
        b, c = self.bound, self.tr.cand
        rows = {"list_id": b.list_id, "slot": b.slot, "item": b.item, "valid": b.valid}
        return differ(rows, c, list(rows)) + int(np.count_nonzero(c["masked"] != np.where(c["valid"] == 1, c["adc"], self.cfg.d_max)))

    def answer_prefix(self):
        return differ(answers_in(self.tr.order, self.k), self.told.answers, ANSWER)

    def range_bounds(self):
        q = self.told.q
        return int(len(q) != self.cfg.dims or bool((np.abs(q) > self.cfg.scale).any()))

    def shape_counts(self):
        return _misshapen(self.told, self.tr, self.cfg, self.k)

    def _bags(self, a: dict, b: dict, cols: list[str]) -> int:
        if self.design == "network":
            return differ(a, b, cols)
        return sum(product(a, cols, *p) != product(b, cols, *p) for p in self.pairs())

    def probe_multiset(self):
        return self._bags(self.tr.dist, self.tr.probes, DIST)

    def topk_multiset(self):
        return self._bags(self.tr.cand, self.tr.order, CANDIDATE)

    def lookup_inclusion(self):
        tr = self.tr
        bad = differ(bound_entries(self.bound), tr.selected, ["list_id", "slot", "m", "code"])
        if self.design == "network":
            return bad + _scan_wrong(tr)
        rest = _apart(tr.selected, tr.lut)
        for _, beta in self.pairs():
            have, z = np.unique(compress(tr.lut, LUT, beta)), compress(rest, LUT, beta)
            bad += bool((np.append(have, -1)[np.searchsorted(have, z)] != z).any())
        return bad

    def probe_order(self):
        return _ordered(self.tr.probes, "dist", self.cfg.n_probe)

    def topk_order(self):
        return _ordered(self.tr.order, "masked", self.k)

    def probe_boundary(self):
        t, n = self.tr, self.cfg.n_probe
        return _off(_net(t.dist, "dist", t.dist["list_id"], n), t.probes, "dist", n) if self.design == "network" else _boundary(t.probes, "dist", n)

    def topk_boundary(self):
        t, n = self.tr, self.cfg.slots
        return _off(_net(t.cand, "masked", t.cand["list_id"] * n + t.cand["slot"], self.k), t.order, "masked", self.k) if self.design == "network" else _boundary(t.order, "masked", self.k)


#: Relation -> table whose rows it goes through, for relations on traces.
ON_TRACE = {
    "dist.centroid": "dist", "probe.multiset": "probes", "probe.order": "probes", "probe.boundary": "probes", "lut.recompute": "lut", "lookup.inclusion": "selected", "score.sum": "cand", "score.mask": "cand",
    "topk.multiset": "order", "topk.order": "order", "topk.boundary": "order", "answer.prefix": "answers", "range.bounds": None, "shape.counts": None,
}
SEEN = "query_id long, turn int, relation string, violations long, checked long"


def placed(tr: Trace, chosen: list[tuple[int, int, int]], k: int) -> Trace:
    """The trace with the first places of its ordering as told, as (rank, list_id, slot); the rest follow in order."""
    c, told, rows = tr.cand, np.zeros(size(tr.cand), bool), []
    for rank, i, s in chosen:
        hit = (c["list_id"] == i) & (c["slot"] == s)
        told |= hit
        rows.append(put(take(c, hit), rank=np.full(np.count_nonzero(hit), rank)))
    order = put(ranked(take(c, ~told)))
    order["rank"] = order["rank"] + k
    for t in rows:
        order = joined(order, {n: t[n] for n in order})
    return replace(tr, order=order)


def judge(st, snap, probes: DataFrame, turns: list[tuple], repeats: int = 2, chosen: DataFrame | None = None) -> DataFrame:
    """SEEN: violations of each turn's relations for every query of a statement. A turn is (design, change or None,
    relations): change(told, trace, prover) gives what the verifier sees. probes: (query_id, list_id) of the probed lists. chosen:
    (query_id, rank, list_id, slot) of places in the ordering that are told."""
    cfg, k = st.cfg, st.k
    public = "|".join(map(str, (st.version.root_mk, st.version.root_cb, st.version.config_digest, k)))
    answers = st.answers.groupBy("query_id").agg(F.collect_list(F.struct("rank", "item", "dist", "is_padding")).alias("answers"))
    asked = st.queries.select("query_id", "q").join(probes.groupBy("query_id").agg(F.array_sort(F.collect_set("list_id")).alias("lists")), "query_id").join(answers, "query_id", "left")
    places = chosen is not None
    if places:
        asked = asked.join(chosen.groupBy("query_id").agg(F.collect_list(F.struct("rank", "list_id", "slot")).alias("chosen")), "query_id", "left")
    asked = written(asked, "asked")
    limit = max(1, CANDIDATES_A_TASK // max(1, cfg.scanned))
    sets = asked.groupBy("lists").agg(F.ceil(F.count("*") / limit).cast("int").alias("salts"))
    sets = written(sets.withColumn("set_id", F.monotonically_increasing_id()), "probed-sets")
    dealt = asked.join(sets, "lists").select(F.col("set_id").alias("list_id"), F.pmod(F.xxhash64("query_id"), F.col("salts")).cast("int").alias("salt"), *[c for c in asked.columns if c != "lists"])
    keys = sets.select("set_id", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), F.col("lists"))
    slots = keys.select("set_id", "salt", F.explode("lists").alias("list_id")).join(snap.slots, "list_id")
    slots = slots.select(F.col("set_id").alias("list_id"), "salt", F.col("list_id").alias("of"), "slot", "valid", "item", "codes")
    parts = min(MOST_PARTS, 2 * (sets.agg(F.sum("salts")).first()[0] or 1))
    shipped = dealt.sparkSession.sparkContext.broadcast((kernels.checked(as_table(snap.centroids)), kernels.checked(as_words(snap.codebooks))))
    ints = lambda x: x.to_numpy(zero_copy_only=False).astype(np.int64)

    def prepare(t: pa.Table) -> Lists:
        ids, slot = ints(t["of"].combine_chunks()), ints(t["slot"].combine_chunks())
        by = np.lexsort((slot, ids))
        codes = ints(t["codes"].combine_chunks().flatten()).reshape(len(ids), -1)[by]
        return Lists(ids[by], slot[by], ints(t["valid"].combine_chunks())[by], ints(t["item"].combine_chunks())[by], codes, *shipped.value)

    def score(_, lists: Lists, part):
        rows = []
        for i in range(part.num_rows):
            q = np.array(part.column("q")[i].as_py(), np.int64)
            got = sorted(part.column("answers")[i].as_py() or [], key=lambda a: a["rank"])
            cols = {"rank": [a["rank"] for a in got], "item": [a["item"] or 0 for a in got], "none": [a["item"] is None for a in got], "dist": [a["dist"] for a in got], "is_padding": [a["is_padding"] for a in got]}
            told = Told(q, put({}, **cols), f"{public}|{part.column('query_id')[i].as_py()}")
            tr = prove(q, lists, cfg)
            if places:
                tr = placed(tr, [(c["rank"], c["list_id"], c["slot"]) for c in part.column("chosen")[i].as_py() or []], k)
            for turn, (design, change, names) in enumerate(turns):
                seen_told, seen = (told, tr) if change is None else change(told, tr, lambda c: prove(q, lists, c), cfg, k)  # noqa: B023
                judged = Relations(seen_told, seen, lists, cfg, k, design, repeats)
                n = {name: size(t) for name, (t, _) in sizes(seen_told, seen, cfg, k).items()}
                rows += [(part.column("query_id")[i].as_py(), turn, r, getattr(judged, r.replace(".", "_"))(), n.get(ON_TRACE[r], 0)) for r in names]
        kinds = (pa.int64(), pa.int32(), pa.string(), pa.int64(), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=["query_id", "turn", "relation", "violations", "checked"])

    return kernels.meet(dealt, slots, prepare, score, SEEN, parts)
