"""The retrieval engine: worked example, gadgets, audits, cost model."""

import hashlib
import random
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from auditvec import catalogue
from auditvec.config import Config
from auditvec.functions import field as FLD
from auditvec.operators import adversary, coarse, codebook, kernels, metrics, shaping
from auditvec.operators import audit as A
from auditvec.operators import commit as C
from auditvec.operators import gadgets as G
from auditvec.operators import search as S
from auditvec.plans import cost, tune
from auditvec.plans.snapshot import build_snapshot, encode_queries
from auditvec.sources import store, tables

VECTORS = [(0, 1, 0, 0), (2, 2, -1, 1), (1, 1, 0, 0), (4, 3, 5, 4), (2, 1, -2, 1), (11, 10, 9, 10), (12, 12, 8, 11)]


@pytest.fixture(scope="module")
def toy(spark):
    cfg = Config(4, 2, 1, 4, 2, 2, 3).validate(7)
    vec = spark.createDataFrame([(i, list(v)) for i, v in enumerate(VECTORS)], "vec_id long, v array<bigint>")
    cent = spark.createDataFrame([(0, [0] * 4), (1, [10] * 4)], "list_id int, mu array<bigint>")
    words = spark.createDataFrame([(0, 0, [0, 0]), (0, 1, [2, 2]), (1, 0, [0, 0]), (1, 1, [-2, 1])], "m int, code int, word array<bigint>")
    assign = coarse.assign_coarse(vec, cent)
    assign, moves = shaping.rebalance(vec, assign, cent, 2, 4)
    codes = codebook.encode_codes(coarse.residuals(vec, assign, cent), words)
    slots = shaping.pad_slots(codes, 2, 4, 2).cache()
    return S.Snapshot(cfg, 1.0, cent, words, slots, assign, moves)


@pytest.fixture(scope="module")
def q(spark):
    return spark.createDataFrame([(0, [1, 1, 0, 0])], "query_id long, q array<bigint>")


def test_worked_example(toy, q):
    assert [tuple(r) for r in toy.moves.collect()] == [(1, 3, 0, 1, 80)]
    got = {(r.list_id, r.slot): (r.valid, r["item"], list(r.codes)) for r in toy.slots.collect()}
    assert got[(1, 0)] == (1, 3, [0, 1]) and got[(1, 3)] == (0, 0, [0, 0]) and got[(0, 1)] == (1, 1, [1, 1]) and len(got) == 8
    assert [(r["item"], r.dist) for r in S.search(q, toy, k=4).orderBy("rank").collect()] == [(0, 2), (2, 2), (1, 7), (4, 7)]
    tail = S.search(q, toy, k=8, n_probe=2).orderBy("rank").collect()[4:]
    assert [(r["item"], r.dist) for r in tail] == [(3, 347), (5, 362), (6, 427), (None, 274869518401)] and tail[-1].is_padding
    assert [(r["item"], r.dist) for r in S.search_one([1, 1, 0, 0], toy).orderBy("rank").collect()] == [(0, 2), (2, 2), (1, 7)]


def test_worked_digests(toy):
    v = C.commit(toy)
    assert v.root_mk == "44d722d3e0203ff0bcf7fc36130e0b934f9e724d578af0c77fa01dc0b3cbda20"
    assert v.root_cb == "4165f50a29a556301dc060af1ad6efd3ebfa26479e179b0b16b877354df1fa88"
    assert C.commit(replace(toy, slots=toy.slots.repartition(7))).root_mk == v.root_mk
    path = C.slot_path(toy.slots, 0, 2)
    h = next(r.digest for r in C.slot_digest(toy.slots).collect() if (r.list_id, r.slot) == (0, 2))
    for _, side, other in path:
        h = C._sha(f"node|{other}|{h}" if side else f"node|{h}|{other}")
    assert h == next(r.root for r in C.list_roots(toy.slots, 4).collect() if r.list_id == 0)


def test_field(spark):
    rng = random.Random(0)
    edge = [0, 1, 2, FLD.P - 1, FLD.P - 2, 1 << 60, (1 << 31) - 1, 1 << 31]
    rows = [(a, b) for a in edge for b in edge] + [(rng.randrange(FLD.P), rng.randrange(FLD.P)) for _ in range(300)]
    df = spark.createDataFrame(rows, "a long, b long")
    out = df.select("a", "b", FLD.add(F.col("a"), F.col("b")).alias("s"), FLD.sub(F.col("a"), F.col("b")).alias("d"), FLD.mul(F.col("a"), F.col("b")).alias("m"), FLD.compress([F.col("a"), F.col("b"), F.col("a")], 678).alias("c"), FLD.power(F.col("a"), FLD.P - 2).alias("inv"))
    for r in out.collect():
        assert (r.s, r.d, r.m) == ((r.a + r.b) % FLD.P, (r.a - r.b) % FLD.P, r.a * r.b % FLD.P)
        assert r.c == (r.a + r.b * 678 + r.a * 678**2) % FLD.P and r.inv == pow(r.a, FLD.P - 2, FLD.P)
    vals = spark.createDataFrame([(1356,), (245437,)], "z long")
    assert FLD.product_by(vals, "z", 12345).first()[0] == (12345 - 1356) * (12345 - 245437) % FLD.P == 2305843006652245963


def test_rebalance_modes_agree(spark):
    rng = np.random.default_rng(3)
    vec = spark.createDataFrame([(i, [int(x) for x in v]) for i, v in enumerate(rng.normal(0, 100, (60, 4)))], "vec_id long, v array<bigint>").cache()
    cent = coarse.stride_centroids(vec, 4)
    assign = coarse.assign_coarse(vec, cent).cache()
    sizes = [r.n_i for r in shaping.list_sizes(assign, 4, 16).collect()]
    out = {}
    for mode in ("window", "driver", "fast"):
        got, moves = shaping.rebalance(vec, assign, cent, 4, 16, mode)
        out[mode] = sorted((r.vec_id, r.list_id) for r in got.collect())
        after = [r.n_i for r in shaping.list_sizes(got, 4, 16).collect()]
        assert max(after) <= 16 and sum(after) == 60 and moves.count() == sum(max(0, n - 16) for n in sizes)
    assert out["window"] == out["driver"]
    with pytest.raises(ValueError):
        shaping.rebalance(vec, assign, cent, 4, 8)


def test_bubble_pass_matches_sorting():
    rng = np.random.default_rng(0)
    for _ in range(50):
        k = rng.integers(0, 6, 9)
        order = G.bubble_pass(k)
        a = list(enumerate(k))
        for i in range(len(a) - 1, 0, -1):
            if a[i][1] < a[i - 1][1]:
                a[i], a[i - 1] = a[i - 1], a[i]
        assert [int(k[i]) for i in order] == [int(x) for _, x in a]


def test_inclusion(spark):
    t = spark.createDataFrame([(0, x) for x in (1, 2, 2, 5)], "query_id long, x long")
    for sel, bad in (([2, 2, 1, 5, 5, 5], 0), ([2], 0), ([2, 3], 1), ([7], 1)):
        s = spark.createDataFrame([(0, x) for x in sel], "query_id long, x long")
        assert G.not_included(s, t, ["x"], 999, 77).count() == bad == G.not_included_exact(s, t, ["x"]).count()
    a = spark.createDataFrame([(0, 1), (0, 1), (0, 2)], "query_id long, x long")
    b = spark.createDataFrame([(0, 1), (0, 2), (0, 2)], "query_id long, x long")
    for f in (lambda x, y: G.multiset_unequal(x, y, ["x"], 999, 77), lambda x, y: G.multiset_unequal_additive(x, y, ["x"], 999, 77), lambda x, y: G.multiset_unequal_exact(x, y, ["x"])):
        assert f(a, a).count() == 0 and f(a, b).count() == 1


DESIGNS = (("multiset", "path"), ("network", "direct"))
#: Attacks that change nothing where distances tie or no padding is scanned.
ONLY_SOME = {adversary.wrong_probe, adversary.swapped_ranks, adversary.promoted_item, adversary.unmasked_padding}


def failing(verdict):
    out = {}
    for r in verdict.filter("not ok").select("query_id", "relation").collect():
        out.setdefault(r.query_id, set()).add(r.relation)
    return out


@pytest.fixture(scope="module")
def several(spark):
    """A snapshot of four lists, two of them probed, with padding; three queries, statement and evidence."""
    rng = np.random.default_rng(11)
    rows = spark.createDataFrame([(i, [float(x) for x in v]) for i, v in enumerate(rng.normal(0, 1, (40, 4)))], "vec_id long, embedding array<double>")
    snap = build_snapshot(rows, Config(4, 4, 2, 16, 2, 4, 6), init="hash", iters=2)
    asked = encode_queries(rows.filter("vec_id < 3").select(F.col("vec_id").alias("query_id"), "embedding"), snap)
    answers, ev = A.prove(asked, snap)
    return A.state(asked, answers, snap, C.commit(snap)), ev


@pytest.mark.parametrize("design,binding", DESIGNS)
def test_attacks_on_traces_are_named(several, design, binding):
    """All attacks at once, each on its own range of query ids, beside the honest trace and changes that must pass."""
    attacks = [*adversary.ON_TRACE, *adversary.MUST_PASS]
    bad = failing(A.verify(*adversary.together(*several, attacks, 10), design, binding, repeats=1))
    for i, attack in enumerate([None, *attacks]):
        seen = [bad.get(10 * i + q, set()) for q in range(3)]
        if attack is None or attack in adversary.MUST_PASS:
            assert not any(seen), (attack, seen)
        else:
            named = [adversary.ON_TRACE[attack] in x for x in seen]
            assert any(named) if attack in ONLY_SOME else all(named), (attack.__name__, seen)


def test_attacks_on_snapshots_are_named(several):
    assert not any(bad.filter("violations > 0").count() for bad in A.binding_checks(*several, "path").values())
    for attack, relation in adversary.ON_SNAPSHOT.items():
        st, ev = attack(*several)
        assert A.binding_checks(st, ev, "path")[relation].filter("violations > 0").count(), attack.__name__
        if attack is not adversary.forged_sibling:
            assert A.binding_checks(st, ev, "direct")[relation].filter("violations > 0").count(), attack.__name__


def test_whole_verdict_rejects_a_smaller_search(several):
    st, ev = adversary.downgraded_probes(*several)
    for design, binding in DESIGNS:
        assert set(failing(A.verify(st, ev, design, binding, repeats=1))) == {0, 1, 2}
    with pytest.raises(ValueError):
        A.verify(replace(several[0], k=1000), several[1])


def test_verdict_counts_the_rows_it_checks(several):
    st, ev = several
    seen = {(r.query_id, r.relation): r for r in A.verify(st, ev, repeats=1).collect()}
    cfg = st.cfg
    want = {"dist.centroid": cfg.n_list, "lut.recompute": cfg.n_probe * cfg.blocks * cfg.codes, "lookup.inclusion": cfg.scanned * cfg.blocks, "topk.order": cfg.scanned, "answer.prefix": st.k}
    for q in range(3):
        for name, n in want.items():
            assert seen[q, name].checked == n and seen[q, name].ok


def test_bundle_and_rerun(spark, several):
    st, ev = several
    text = A.open_bundle(ev, st.k)
    assert not failing(A.verify_bundle(spark, text, st))
    forged = replace(st, answers=st.answers.withColumn("item", F.when(F.col("rank") == 1, F.lit(12345)).otherwise(F.col("item"))))
    assert set(failing(A.verify_bundle(spark, text, forged))) == {0, 1, 2}
    assert A.verify_by_rerun(st.queries, ev.snap, st.answers).filter("ok").count() == 3
    assert A.verify_by_rerun(st.queries, ev.snap, forged.answers).filter("ok").count() == 0


def test_trace_digest_does_not_hang_on_order(several, monkeypatch):
    _, ev = several
    whole = G.trace_digest({"cand": ev.cand})
    assert whole == G.trace_digest({"cand": ev.cand.repartition(5)}) != G.trace_digest({"cand": ev.cand.limit(5)})
    monkeypatch.setattr(G, "FOLD", 4)
    deep = G.trace_digest({"cand": ev.cand})
    assert deep == G.trace_digest({"cand": ev.cand.repartition(3)}) != whole


def greedy(rows, cent, assign, n):
    """Moves in plain Python: rounds, each with targets fixed at its start, cheapest first."""
    assign, moved = dict(assign), 0
    size = lambda i: sum(1 for x in assign.values() if x == i)
    dist = lambda v, i: int(((rows[v] - cent[i]) ** 2).sum())
    while any(size(i) > n for i in range(len(cent))):
        free = [i for i in range(len(cent)) if size(i) < n]
        over = {i: size(i) - n for i in range(len(cent)) if size(i) > n}
        room = {i: n - size(i) for i in free}
        moves = []
        for v, i in assign.items():
            if i in over:
                to = min(free, key=lambda j: (dist(v, j), j))
                moves.append((dist(v, to) - dist(v, i), v, i, to))
        for _, v, i, to in sorted(moves):
            if over[i] and room[to]:
                over[i], room[to], assign[v] = over[i] - 1, room[to] - 1, to
                moved += 1
    return assign, moved


def test_rebalancing_is_the_greedy_rule(spark):
    rng = np.random.default_rng(21)
    rows = rng.integers(-50, 50, (48, 2)) // np.array([[1, 3]])
    rows[:25] //= 8
    vec = spark.createDataFrame([(i, [int(x) for x in v]) for i, v in enumerate(rows)], "vec_id long, v array<bigint>").cache()
    cent = coarse.stride_centroids(vec, 6)
    table, assign = coarse.as_table(cent), {r.vec_id: r.list_id for r in coarse.assign_coarse(vec, cent).collect()}
    want, moved = greedy(rows, table, assign, 8)
    got, moves = shaping.rebalance(vec, coarse.assign_coarse(vec, cent), cent, 6, 8)
    assert {r.vec_id: r.list_id for r in got.collect()} == want and moves.count() == moved > 5


def test_search_on_small_shapes_and_hot_lists(spark, monkeypatch):
    """K=1, k=1, one probe, all probes, k beyond the valid slots; lists that several tasks share."""
    rng = np.random.default_rng(5)
    rows = spark.createDataFrame([(i, [float(x) for x in v]) for i, v in enumerate(rng.normal(0, 1, (30, 4)))], "vec_id long, embedding array<double>").cache()
    held = rows.select(F.col("vec_id").alias("query_id"), "embedding")
    one = build_snapshot(rows, Config(4, 2, 1, 32, 2, 1, 1), init="hash", iters=1)
    assert S.search(encode_queries(held, one), one).count() == 30
    snap = build_snapshot(rows, Config(4, 4, 4, 16, 2, 4, 40), init="hash", iters=1)
    asked = encode_queries(held, snap)
    ans = S.search(asked, snap)
    plain = sorted(map(tuple, ans.collect()), key=str)
    assert len(plain) == 30 * 40 and ans.filter("is_padding").count() == 30 * 10
    dist = S.centroid_distances(asked, snap)
    probes = S.select_probes(dist, 4)
    slow = S.answers_of(S.top_k(S.score_candidates(S.adc_tables(probes, asked, snap), probes, snap), 40))
    assert sorted(map(tuple, slow.collect()), key=str) == plain
    monkeypatch.setattr(S, "PROBES_A_TASK", 7)
    assert sorted(map(tuple, S.search(asked, snap).collect()), key=str) == plain
    from auditvec.operators import baselines

    vec, q = snap.extra["vec"], asked
    near = sorted(map(tuple, baselines.exact_knn(q, vec, 3).collect()))
    monkeypatch.setattr(baselines, "ROWS_A_PART", 9)
    monkeypatch.setattr(baselines, "QUERIES_A_PART", 8)
    assert sorted(map(tuple, baselines.exact_knn(q, vec, 3).collect())) == near
    x = {r.vec_id: np.array(r.v) for r in vec.collect()}
    want = [(i, r + 1, j, int(d)) for i in x for r, (d, j) in enumerate(sorted((((x[i] - x[j]) ** 2).sum(), j) for j in x)[:3])]
    assert near == sorted(want) and baselines.all_distances(q, vec).count() == 900


def test_sql_surface(spark, toy):
    from auditvec import sqlapi

    sqlapi.register_functions(spark)
    sqlapi.register_tables(spark)
    a, b = FLD.P - 5, 1 << 60
    r = spark.sql(f"SELECT f_add({a}L, {b}L) AS s, f_mul({a}L, {b}L) AS m, bit_less(3L, 4L) AS l, sqdist(array(1L, 2L), array(4L, 6L)) AS d").first()
    assert (r.s, r.m, r.l, r.d) == ((a + b) % FLD.P, a * b % FLD.P, True, 25)
    sqlapi.publish_views(spark, toy, "toy_")
    assert spark.sql("SELECT count(*) FROM toy_slots").first()[0] == 8
    sqlapi.register_search(spark, toy)
    found = spark.sql("SELECT * FROM vector_search(array(1L, 1L, 0L, 0L), 3) ORDER BY rank").collect()
    assert [(x["item"], x["dist"]) for x in found] == [(x["item"], x["dist"]) for x in sqlapi.vector_search(spark, toy, [1, 1, 0, 0]).orderBy("rank").collect()]
    told = spark.sql("""SELECT * FROM audit_report('[{"relation": "topk.order", "ok": false, "gates": 7}]')""").first()
    assert (told.relation, told.ok, told.gates) == ("topk.order", False, 7)


def test_single_passages(spark):
    from auditvec.plans.workloads import single_passages

    docs = spark.createDataFrame([(1, "x one two three four five six seven y"), (2, "(one two  three four five six seven)"), (3, "aone two three four five six sevenb"), (4, "short bit"), (5, None), (6, "")], "doc_id long, text string")
    bench = spark.createDataFrame([(10, "two three four five six seven y"), (11, "one two three four five six seven"), (12, "ort b"), (13, ""), (14, None), (15, "two  three four five six seven)")], "item_id long, text string")
    got = sorted(map(tuple, single_passages(docs, bench).collect()))
    want = [(i, [d for d, t in [(r[0], r[1]) for r in docs.collect()] if t and p in t]) for i, p in [tuple(r) for r in bench.collect()] if p]
    assert got == sorted((i, d[0]) for i, d in want if len(d) == 1)


def test_float_against_fixed_compares_trained_indexes(spark, tmp_path, monkeypatch):
    rng = np.random.default_rng(12)
    rows = [(i, [float(x) for x in v], i % 3) for i, v in enumerate(rng.normal(0, 1, (400, 64)))]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").write.parquet(str(tmp_path / "embeddings.parquet"))
    asked, train = [], coarse.train_coarse
    monkeypatch.setattr(coarse, "train_coarse", lambda vec, n, iters=5, *a, **b: asked.append((n, iters)) or train(vec, n, iters, *a, **b))
    monkeypatch.setattr(catalogue.X, "queries", lambda s, d: encode_queries(catalogue.X.split_queries(catalogue.load_table(s, d, "embeddings"))[1], catalogue.X.trained(s, d)))
    assert catalogue.QUERIES["std_zk_delta"](spark, str(tmp_path)).count() == 2
    assert len(asked) == 2 and len({n for n, _ in asked}) == 1 and all(iters > 0 for _, iters in asked)
    lists = [catalogue.X.trained_config(n).validate(n).n_list for n in (360, 1800, 45_000, 1_000_000)]
    assert lists == sorted(set(lists))


#: Published rows of the multiset design (fixed values): name, configuration, rows.
PRINTED = [({"n_list": 256, "D": 128, "n_probe": 16, "n": 32, "M": 8, "K": 16}, 21198), ({"n_list": 16, "D": 128, "n_probe": 1, "n": 512, "M": 8, "K": 1}, 5929), ({"n_list": 512, "D": 256, "n_probe": 64, "n": 128, "M": 16, "K": 256}, 915627)]


def test_cost_model_and_tuner(spark):
    for c, rows in PRINTED:
        assert abs(cost.gate_rows(c) / rows - 1) < 0.013 and cost.padded_bin(cost.gate_rows(c)) == cost.padded_bin(rows)
    assert tune.feasible_codebooks(64) == [2, 4, 16, 256]
    for capacity, dims, top, want in ((1 << 21, 128, 1024, (1024, 256, 1 << 18)), (1 << 21, 960, 1024, (512, 256, 1 << 19)), (1 << 24, 384, 8192, (2048, 256, 1 << 21))):
        got = tune.search_config(capacity, 64, 128, dims, top)
        assert (got["n_list"], got["K"], got["bin"]) == want
        best = tune.grid_config(tune.grid(spark, capacity, 64, 128, dims, top)).first()
        assert (best["n_list"], best["codes"], best["bin"]) == want
    low = dict(zip(("n_list", "D", "n_probe", "n", "M", "K", "k"), (16, 128, 1, 512, 8, 1, 1)))
    assert cost.query_gates(low, "network") < cost.query_gates(low, "multiset")
    large = dict(zip(("n_list", "D", "n_probe", "n", "M", "K", "k"), (512, 256, 64, 128, 16, 256, 128)))
    assert cost.query_gates(large, "network") > cost.query_gates(large, "multiset")


def test_metrics(spark):
    ans = spark.createDataFrame([(0, 1, 7), (1, 3, 8), (2, 1, 9)], "query_id long, rank int, item long")
    truth = spark.createDataFrame([(0, 7), (1, 8), (2, 5)], "query_id long, item long")
    r = metrics.ranking(ans, truth, truth).first()
    assert (r.hit, r.mrr, r.ndcg) == pytest.approx((2 / 3, (1 + 1 / 3) / 3, (1 + 0.5) / 3))


def test_registry_and_snapshot_files(spark, toy, q, tmp_path):
    v, reg = C.commit(toy), str(tmp_path / "registry")
    assert store.publish(spark, reg, 1, v, 7) and not store.publish(spark, reg, 1, v, 7)
    with pytest.raises(ValueError):
        store.publish(spark, reg, 1, C.Version("x", "y", "z"), 7)
    store.write_snapshot(toy, str(tmp_path / "snap"), bucket=1)
    again = store.read_snapshot(spark, str(tmp_path / "snap"))
    assert C.commit(again) == v == store.load_version(spark, reg, 1)
    plan = S.search_one([1, 1, 0, 0], again)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [" in plan and "list_bucket" in plan
    assert S.search_one([1, 1, 0, 0], again).count() == 3


def test_bad_configurations():
    for kw in ({"blocks": 3}, {"codes": 3}, {"n_probe": 3}, {"k": 5}):
        with pytest.raises(ValueError):
            Config(**({"dims": 4, "n_list": 2, "n_probe": 1, "slots": 4, "blocks": 2, "codes": 2, "k": 3} | kw)).validate()


def test_entries_in_runs_are_the_entries(spark, several, monkeypatch):
    """The inclusion query counts equal entries and never makes one row an entry."""
    st, ev = several
    first = ev.probes.filter(F.col("rank") <= st.cfg.n_probe)
    bag = ev.selected.groupBy("query_id", "list_id", "m", "code", "val", ((F.col("slot") == 0) & (F.col("m") == 0)).alias("marked")).agg(F.count("*").alias("n"))
    runs = S.selected_runs(ev.lut, first, ev.snap, (F.col("slot") == 0) & (F.col("m") == 0))
    assert sorted(map(tuple, bag.collect())) == sorted(map(tuple, runs.collect()))

    def rows_made(*_):
        raise AssertionError("one row an entry")

    monkeypatch.setattr(S, "selected_entries", rows_made)
    monkeypatch.setattr(G, "inclusion_witness", rows_made)
    got = catalogue._inclusion(ev.snap, st.queries, first).collect()
    assert len(got) == 3 and all(r.forged_fails and not r.fails for r in got)
    s = spark.createDataFrame([(0, 2, 3), (0, 5, 0)], "query_id long, x long, n long")
    t = spark.createDataFrame([(0, 2)], "query_id long, x long")
    assert G.not_included(s, t, ["x"], 999, 77, times="n").count() == 0 and G.not_included(s, t, ["x"], 999, 77).count() == 1


def test_rerun_makes_no_row_a_candidate(several, monkeypatch):
    """Padding and told items are judged as before, without a table of all scores; a repeated item is found out."""
    st, ev = several

    def rows_made(*_):
        raise AssertionError("one row a candidate")

    monkeypatch.setattr(S, "score_candidates", rows_made)
    whole = S.search(st.queries, ev.snap, k=st.cfg.scanned)
    assert whole.filter("is_padding").count() and A.verify_by_rerun(st.queries, ev.snap, whole, st.cfg.scanned).filter("ok").count() == 3
    first = F.first("item").over(Window.partitionBy("query_id").orderBy("rank"))
    twice = st.answers.withColumn("item", F.when(F.col("rank") == 2, first).otherwise(F.col("item")))
    assert A.verify_by_rerun(st.queries, ev.snap, twice).filter("ok").count() == 0


def test_least_keeps_the_order_of_equal_ones():
    rng = np.random.default_rng(3)
    d = rng.integers(0, 6, (9, 50)).astype(np.float64)
    d[0, 5:] = np.inf
    for k in (1, 3, 12, 40, 60):
        assert (kernels.least(d, k) == np.argsort(d, 1, kind="stable")[:, :k]).all()


def test_work_is_counted_by_keys(several, monkeypatch):
    """The same counts as of the steps' tables, which are not made."""
    st, ev = several
    want = {"distances": ev.dist.count(), "tables": ev.lut.count(), "lookups": ev.selected.count(), "scores": ev.cand.count(), "topk": st.answers.count(), "probes": 3 * st.cfg.n_probe}

    def rows_made(*_):
        raise AssertionError("a row for each lookup or score")

    for step in ("selected_entries", "score_candidates", "top_k"):
        monkeypatch.setattr(S, step, rows_made)
    assert {r["step"]: r["n_rows"] for r in cost.counted_work(st.queries, ev.snap).collect()} == want
    fewer = replace(ev.snap, slots=ev.snap.slots.filter("list_id <> 0 or slot > 2"))
    got = {r["step"]: r["n_rows"] for r in cost.counted_work(st.queries, fewer).collect()}
    lost = ev.cand.filter("list_id = 0 and slot <= 2").count()
    assert got["scores"] == want["scores"] - lost and got["lookups"] == want["lookups"] - lost * st.cfg.blocks


def test_few_candidates_are_admitted_without_windows(spark, monkeypatch):
    rng = np.random.default_rng(22)
    vec = spark.createDataFrame([(i, [int(x) for x in v]) for i, v in enumerate(rng.integers(-9, 9, (48, 2)))], "vec_id long, v array<bigint>").cache()
    cent = coarse.stride_centroids(vec, 6)
    assign = coarse.assign_coarse(vec, cent)
    moved = lambda: sorted(map(tuple, shaping.rebalance(vec, assign, cent, 6, 8)[1].collect()))
    with monkeypatch.context() as m:
        m.setattr(shaping, "ONE_TASK", 0)
        want = moved()
    monkeypatch.setattr(shaping, "_admit_by_windows", None)
    assert want and moved() == want


def test_word_counts_become_vectors_row_by_row(spark):
    """Dense vectors come from a kernel, once a row, and not from an expression that each use computes again."""
    rows = spark.createDataFrame([(3, "a b A"), (4, None), (5, "  "), (6, "c")], "doc_id long, text string")
    vec = tables.hash_vectors(rows, "doc_id", "text", 7)
    got = {r.doc_id: list(r.embedding) for r in vec.collect()}
    want = {}
    for key, words in ((3, "aba"), (6, "c")):
        want[key] = [0.0] * 7
        for w in words:
            h = int(hashlib.md5(w.encode()).hexdigest()[:8], 16)
            want[key][h % 7] += 1 if h // 7 % 2 == 0 else -1
    assert got == want and "MapInArrow" in vec._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("design,binding", [("multiset", "path"), ("network", "direct")])
def test_traces_judged_apart_give_the_verdicts_of_rows(spark, several, design, binding):
    from auditvec.operators import traces as T

    st, ev = several
    lean = A.prove(st.queries, ev.snap, later=True)[1]
    cols = ["query_id", "relation", "ok", "violations", "gates", "checked"]
    rows = lambda d: sorted(map(tuple, d.select(*cols).collect()))
    assert rows(A.verify_each(st, lean, [(design, binding)])) == rows(A.verify(st, ev, design, binding))
    first = ev.probes.filter(F.col("rank") <= st.cfg.n_probe).select("query_id", "list_id")
    turns = [(design, adversary.ON_ARRAYS[f.__name__], [*T.ON_TRACE]) for f in adversary.ON_TRACE]
    apart = {(r.query_id + 10 * (r.turn + 1), r.relation): r.violations for r in T.judge(st, ev.snap, first, turns, repeats=1).collect()}
    whole = A.verify(*adversary.together(st, ev, adversary.ON_TRACE, 10), design, binding, repeats=1).filter("query_id >= 10")
    for r in whole.collect():
        if r.relation in T.ON_TRACE:
            assert (apart[r.query_id, r.relation] == 0) == r.ok, (list(adversary.ON_TRACE)[r.query_id // 10 - 1], r)


def test_whole_audits_make_no_row_an_entry(spark, several, monkeypatch):
    made, keep = [], A.written
    monkeypatch.setattr(A, "written", lambda d, name: made.append(name) or keep(d, name))
    st, ev = several
    _, lean = A.prove(st.queries, ev.snap, later=True)
    assert A.verify_each(st, lean).filter("not ok").count() == 0
    for attack in (adversary.stale_version, adversary.mixed_snapshots):
        assert A.binding_checks(*attack(st, lean), "path")[adversary.ON_SNAPSHOT[attack]].filter("violations > 0").count()
    assert not {"selected", "scores", "order"} & set(made)
    none = replace(st, answers=st.answers.filter("query_id <> 1"))
    assert {r.query_id for r in A.verify_each(none, lean, A.WAYS[:1]).filter("not ok").collect()} == {1}


def test_bundles_come_row_by_row(spark, several, monkeypatch):
    import json

    st, ev = several
    pieces = list(A.bundle_pieces(ev, st.k))
    text = "".join(pieces)
    parts = json.loads(text)
    assert set(parts) == set(A.PARTS) and len(parts["slots"]) == ev.snap.slots.count() and len(parts["chosen"]) == 3 * st.k
    assert len(pieces) > sum(map(len, parts.values())) and text == json.dumps(parts, sort_keys=True)
    monkeypatch.setattr(A, "BUNDLE_CHARS", 500)
    made, keep = [], A.written
    monkeypatch.setattr(A, "written", lambda d, name: made.append(name) or keep(d, name))
    places = S.found(st.queries, ev.snap, st.k).select("query_id", "rank", "list_id", "slot")
    bundle = A.open_bundle(ev, st.k, places)
    assert A.verify_bundle(spark, bundle, st).filter("not ok").count() == 0
    assert made.count("bundle") > 1 and not {"selected", "scores", "order"} & set(made)
    first = next(c for c in parts["chosen"] if c["query_id"] == 1 and c["rank"] == 1)
    parts["chosen"].remove(first)
    assert set(failing(A.verify_bundle(spark, json.dumps(parts), st))) == {1}


def test_hashed_vectors_are_counted_where_texts_are_read(spark):
    texts = [(1, "a b  a\tC"), (2, None), (3, " "), (4, "c"), (1, "b d é"), (5, "x y z x")]
    df = spark.createDataFrame(texts, "doc_id long, text string")
    want = {}
    for i, t in texts:
        for w in (t or "").lower().split():
            h = int(hashlib.md5(w.encode()).hexdigest()[:8], 16)
            want.setdefault(i, [0.0] * 8)[h % 8] += 1 if h // 8 % 2 == 0 else -1
    got = tables.hash_vectors(df, "doc_id", "text", 8)
    assert {r.doc_id: r.embedding for r in got.collect()} == want
    plan = got._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[-1]
    assert "Generate" not in plan and plan.count("Exchange hashpartitioning") == 1
