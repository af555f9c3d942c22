"""What a cheating server may hand over, each with the relation that must fail; and two changes that must be accepted.

An attack takes the honest statement and evidence and gives the ones that the verifier sees. Only answers change in a
statement: queries, version, configuration and k are the verifier's.
"""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import audit as A
from . import traces as T


def _bump(df, col, rows, by=1):
    return df.withColumn(col, F.when(rows, F.col(col) + by).otherwise(F.col(col)))


def _reordered(st, ev, order):
    return replace(st, answers=A.answers_in(order, st.k)), replace(ev, order=order)


def _ranked(cand):
    return cand.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("masked", "list_id", "slot")))


# Changed traces -------------------------------------------------------------------------------------------------------


def fewer_probes(st, ev):
    """One list of each query is left out of the ordering."""
    p = st.cfg.n_probe
    return st, replace(ev, probes=ev.probes.filter(F.col("rank") != p).withColumn("rank", F.when(F.col("rank") > p, F.col("rank") - 1).otherwise(F.col("rank"))))


def downgraded_probes(st, ev):
    """An honest trace and answer of a search with one probe less."""
    answers, less = A.prove(st.queries, replace(ev.snap, cfg=replace(st.cfg, n_probe=st.cfg.n_probe - 1)), st.k)
    return replace(st, answers=answers), less


def wrong_probe(st, ev):
    """The last probe gives its place to the farthest list."""
    a, b = st.cfg.n_probe, st.cfg.n_list
    return st, replace(ev, probes=ev.probes.withColumn("rank", F.when(F.col("rank") == a, b).when(F.col("rank") == b, a).otherwise(F.col("rank"))))


def forged_distance(st, ev):
    return st, replace(ev, dist=_bump(ev.dist, "dist", F.col("list_id") == 0))


def forged_table(st, ev):
    return st, replace(ev, lut=_bump(ev.lut, "val", (F.col("m") == 0) & (F.col("code") == 0)))


def forged_entry(st, ev):
    return st, replace(ev, selected=_bump(ev.selected, "val", (F.col("m") == 0) & (F.col("slot") == 0)))


def doubled_block(st, ev):
    """The best candidate's entry of block 1 gives way to a second one of block 0, and scores, order and answers
    follow: counts and sums agree."""
    best = ev.order.filter("rank = 1").select("query_id", "list_id", "slot", F.lit(True).alias("best"))
    marked = ev.selected.join(best, ["query_id", "list_id", "slot"], "left")
    chosen = marked.filter(F.col("best").isNull() | (F.col("m") != 1)).drop("best")
    selected = chosen.unionByName(marked.filter("best and m = 0").drop("best"))
    sums = selected.groupBy("query_id", "list_id", "slot").agg(F.sum("val").alias("adc"))
    cand = ev.cand.drop("adc", "masked").join(sums, ["query_id", "list_id", "slot"]).withColumn("masked", F.when(F.col("valid") == 1, F.col("adc")).otherwise(F.lit(st.cfg.d_max)))
    return _reordered(st, replace(ev, selected=selected, cand=cand), _ranked(cand))


def forged_score(st, ev):
    return st, replace(ev, cand=_bump(ev.cand, "adc", F.col("slot") == 0))


def unmasked_padding(st, ev):
    return st, replace(ev, cand=ev.cand.withColumn("masked", F.col("adc")))


def dropped_candidate(st, ev):
    return _reordered(st, ev, ev.order.filter("rank <> 1").withColumn("rank", F.col("rank") - 1))


def duplicated_candidate(st, ev):
    """The best candidate stands twice, in place of the last one."""
    twice = ev.order.filter("rank = 1").withColumn("rank", F.lit(0))
    return _reordered(st, ev, ev.order.filter(F.col("rank") < st.cfg.scanned).unionByName(twice).withColumn("rank", F.col("rank") + 1))


def suppressed_best(st, ev):
    """The best item is shown as padding: its flag changes in the ordering alone."""
    return _reordered(st, ev, ev.order.withColumn("valid", F.when(F.col("rank") == 1, F.lit(0)).otherwise(F.col("valid")).cast("tinyint")))


def swapped_ranks(st, ev):
    k = st.k
    return _reordered(st, ev, ev.order.withColumn("rank", F.when(F.col("rank") == 1, k).when(F.col("rank") == k, 1).otherwise(F.col("rank"))))


def promoted_item(st, ev):
    """The worst candidate takes the last place of the answer."""
    k, last = st.k, st.cfg.scanned
    return _reordered(st, ev, ev.order.withColumn("rank", F.when(F.col("rank") == k, last).when(F.col("rank") == last, k).otherwise(F.col("rank"))))


def other_answer(st, ev):
    return replace(st, answers=_bump(st.answers, "item", F.col("rank") == 1, 1_000_000)), ev


def smaller_k(st, ev):
    """The answer has one item less than was asked for."""
    return replace(st, answers=st.answers.filter(F.col("rank") < st.k)), ev


# Changed snapshots ----------------------------------------------------------------------------------------------------


def _first_probed(ev):
    return ev.probes.filter("rank = 1").agg(F.min("list_id")).first()[0]


def _slots(ev, change):
    """Evidence in which slot 0 of one probed list is changed."""
    at = (F.col("list_id") == _first_probed(ev)) & (F.col("slot") == 0)
    return replace(ev, snap=replace(ev.snap, slots=change(ev.snap.slots, at)))


def altered_centroid(st, ev):
    cent = ev.snap.centroids.withColumn("mu", F.when(F.col("list_id") == 0, F.transform("mu", lambda x, i: F.when(i == 0, x + 1).otherwise(x))).otherwise(F.col("mu")))
    return st, replace(ev, snap=replace(ev.snap, centroids=cent))


def altered_digest(st, ev):
    return st, replace(ev, roots=ev.roots.withColumn("root", F.when(F.col("list_id") == 0, F.sha2("root", 256)).otherwise(F.col("root"))))


def altered_codebook(st, ev):
    at = (F.col("m") == 0) & (F.col("code") == 0)
    return st, replace(ev, snap=replace(ev.snap, codebooks=ev.snap.codebooks.withColumn("word", F.when(at, F.transform("word", lambda x, i: F.when(i == 0, x + 1).otherwise(x))).otherwise(F.col("word")))))


def wrong_code(st, ev):
    turn = F.transform("codes", lambda c, i: F.when(i == 0, (c + 1) % st.cfg.codes).otherwise(c))
    return st, _slots(ev, lambda s, at: s.withColumn("codes", F.when(at, turn).otherwise(F.col("codes"))))


def flipped_flag(st, ev):
    return st, _slots(ev, lambda s, at: s.withColumn("valid", F.when(at, 1 - F.col("valid")).otherwise(F.col("valid")).cast("tinyint")))


def foreign_payload(st, ev):
    return st, _slots(ev, lambda s, at: _bump(s, "item", at, 1_000_000))


def _older(snap):
    """The snapshot as it was: other payloads."""
    return replace(snap, slots=_bump(snap.slots, "item", F.col("valid") == 1, 7))


def stale_version(st, ev):
    """An honest trace and answer of an older snapshot."""
    answers, old = A.prove(st.queries, _older(ev.snap), st.k, later=True)
    return replace(st, answers=answers), old


def mixed_snapshots(st, ev):
    """One probed list comes from an older snapshot, everything else, list digests too, from the current one."""
    old = _older(ev.snap).slots.filter(F.col("list_id") == _first_probed(ev))
    slots = ev.snap.slots.filter(F.col("list_id") != _first_probed(ev)).unionByName(old)
    answers, mixed = A.prove(st.queries, replace(ev.snap, slots=slots), st.k, later=True)
    return replace(st, answers=answers), replace(mixed, roots=ev.roots, paths=ev.paths)


def forged_sibling(st, ev):
    """A digest on the way to the root is another one; seen where lists are bound by their paths."""
    at = F.col("list_id") == _first_probed(ev)
    path = F.transform("path", lambda s, i: s.withField("digest", F.when(i == 0, F.sha2(s["digest"], 256)).otherwise(s["digest"])))
    return st, replace(ev, paths=ev.paths.withColumn("path", F.when(at, path).otherwise(F.col("path"))))


def out_of_range(st, ev):
    """A query beyond the public bound: the verifier's own mistake, which must not pass."""
    return replace(st, queries=st.queries.withColumn("q", F.transform("q", lambda x, i: F.when(i == 0, F.lit(st.cfg.scale + 1).cast("long")).otherwise(x)))), ev


def other_config(st, ev):
    """The verifier's configuration is not the version's: its digest must tell."""
    return replace(st, v_max=st.v_max * 2), ev


#: Attack -> relation that names it: those that change a trace or the answers, and those that change the snapshot.
ON_TRACE = {
    fewer_probes: "shape.counts", wrong_probe: "probe.boundary", forged_distance: "dist.centroid", forged_table: "lut.recompute", forged_entry: "lookup.inclusion", doubled_block: "lookup.inclusion",
    forged_score: "score.sum", unmasked_padding: "score.mask", dropped_candidate: "topk.multiset", duplicated_candidate: "topk.multiset", suppressed_best: "topk.multiset", swapped_ranks: "topk.order",
    promoted_item: "topk.boundary", other_answer: "answer.prefix", smaller_k: "shape.counts", downgraded_probes: "shape.counts", out_of_range: "range.bounds",
}
ON_SNAPSHOT = {
    altered_centroid: "bind.centroids", altered_digest: "bind.centroids", altered_codebook: "bind.codebook", wrong_code: "bind.probed", flipped_flag: "bind.probed", foreign_payload: "bind.probed",
    stale_version: "bind.centroids", mixed_snapshots: "bind.probed", forged_sibling: "bind.probed", other_config: "bind.config",
}
MUST_FAIL = ON_TRACE | ON_SNAPSHOT


# The changes of traces on one query's arrays: (told, trace, prover, cfg, k) -> what the verifier sees ------------------------


def _bumped(t, col, rows, by=1):
    return T.put(t, **{col: t[col] + by * rows})


def _swapped(t, a, b):
    r = t["rank"]
    return T.put(t, rank=np.where(r == a, b, np.where(r == b, a, r)))


def _told_order(told, tr, k, order, **parts):
    return replace(told, answers=T.answers_in(order, k)), replace(tr, order=order, **parts)


def _fewer_probes(told, tr, prover, cfg, k):
    t = T.take(tr.probes, tr.probes["rank"] != cfg.n_probe)
    return told, replace(tr, probes=_bumped(t, "rank", t["rank"] > cfg.n_probe, -1))


def _downgraded_probes(told, tr, prover, cfg, k):
    less = prover(replace(cfg, n_probe=cfg.n_probe - 1))
    return replace(told, answers=T.answers_in(less.order, k)), less


def _doubled_block(told, tr, prover, cfg, k):
    i, s = (tr.order[c][tr.order["rank"] == 1] for c in ("list_id", "slot"))
    best = (tr.selected["list_id"] == i) & (tr.selected["slot"] == s)
    selected = T.joined(T.take(tr.selected, ~best | (tr.selected["m"] != 1)), T.take(tr.selected, best & (tr.selected["m"] == 0)))
    adc = T.sums_of(selected)["adc"]
    cand = T.put(tr.cand, adc=adc, masked=np.where(tr.cand["valid"] == 1, adc, cfg.d_max))
    return _told_order(told, tr, k, T.ranked(cand), selected=selected, cand=cand)


def _dropped_candidate(told, tr, prover, cfg, k):
    t = T.take(tr.order, tr.order["rank"] != 1)
    return _told_order(told, tr, k, _bumped(t, "rank", True, -1))


def _duplicated_candidate(told, tr, prover, cfg, k):
    r = tr.order["rank"]
    twice = T.put(T.take(tr.order, r == 1), rank=[0])
    return _told_order(told, tr, k, _bumped(T.joined(twice, T.take(tr.order, r < cfg.scanned)), "rank", True))


ON_ARRAYS = {
    "fewer_probes": _fewer_probes, "downgraded_probes": _downgraded_probes, "doubled_block": _doubled_block, "dropped_candidate": _dropped_candidate, "duplicated_candidate": _duplicated_candidate,
    "wrong_probe": lambda told, tr, prover, cfg, k: (told, replace(tr, probes=_swapped(tr.probes, cfg.n_probe, cfg.n_list))),
    "forged_distance": lambda told, tr, prover, cfg, k: (told, replace(tr, dist=_bumped(tr.dist, "dist", tr.dist["list_id"] == 0))),
    "forged_table": lambda told, tr, prover, cfg, k: (told, replace(tr, lut=_bumped(tr.lut, "val", (tr.lut["m"] == 0) & (tr.lut["code"] == 0)))),
    "forged_entry": lambda told, tr, prover, cfg, k: (told, replace(tr, selected=_bumped(tr.selected, "val", (tr.selected["m"] == 0) & (tr.selected["slot"] == 0)))),
    "forged_score": lambda told, tr, prover, cfg, k: (told, replace(tr, cand=_bumped(tr.cand, "adc", tr.cand["slot"] == 0))),
    "unmasked_padding": lambda told, tr, prover, cfg, k: (told, replace(tr, cand=T.put(tr.cand, masked=tr.cand["adc"]))),
    "suppressed_best": lambda told, tr, prover, cfg, k: _told_order(told, tr, k, T.put(tr.order, valid=np.where(tr.order["rank"] == 1, 0, tr.order["valid"]))),
    "swapped_ranks": lambda told, tr, prover, cfg, k: _told_order(told, tr, k, _swapped(tr.order, 1, k)),
    "promoted_item": lambda told, tr, prover, cfg, k: _told_order(told, tr, k, _swapped(tr.order, k, cfg.scanned)),
    "other_answer": lambda told, tr, prover, cfg, k: (replace(told, answers=_bumped(told.answers, "item", (told.answers["rank"] == 1) & (told.answers["none"] == 0), 1_000_000)), tr),
    "smaller_k": lambda told, tr, prover, cfg, k: (replace(told, answers=T.take(told.answers, told.answers["rank"] < k)), tr),
    "out_of_range": lambda told, tr, prover, cfg, k: (replace(told, q=np.concatenate([[cfg.scale + 1], told.q[1:]])), tr),
}


def together(st, ev, attacks, apart: int):
    """One statement and one evidence with many attacks on traces: those of the i-th have query ids from (i + 1) * apart
    on, the honest ones keep theirs. apart: beyond every query id."""
    shifted = lambda d, i: d.withColumn("query_id", F.col("query_id") + F.lit(i * apart).cast("long"))
    all_st, all_ev = [st], [ev]
    for i, attack in enumerate(attacks, 1):
        s, e = attack(st, ev)
        all_st.append(replace(s, queries=shifted(s.queries, i), answers=shifted(s.answers, i)))
        names = ("dist", "probes", "lut", "selected", "cand", "order")
        all_ev.append(replace(e, **{n: shifted(getattr(e, n), i) for n in names}))

    def joined(parts, name):
        out = getattr(parts[0], name)
        for p in parts[1:]:
            out = out.unionByName(getattr(p, name).select(*out.columns))
        return A.written(out, f"attacked-{name}")

    st = replace(st, queries=joined(all_st, "queries"), answers=joined(all_st, "answers"))
    return st, replace(ev, **{n: joined(all_ev, n) for n in ("dist", "probes", "lut", "selected", "cand", "order")})


# Accepted -------------------------------------------------------------------------------------------------------------


def tie_reorder(st, ev):
    """Candidates at one distance in another order: accepted, as only distances are ordered."""
    w = Window.partitionBy("query_id").orderBy("masked", F.desc("list_id"), F.desc("slot"))
    return _reordered(st, ev, ev.order.withColumn("rank", F.row_number().over(w)))


def shuffled_rows(st, ev):
    """The same tables in another order of rows and partitions: accepted."""
    return st, replace(ev, **{n: getattr(ev, n).repartition(3, F.rand(1)) for n in ("dist", "probes", "lut", "selected", "cand", "order", "roots")})


MUST_PASS = [tie_reorder, shuffled_rows]
