"""The training-data operators on small tables with nulls, empty and long texts, ties, repeated rows and odd columns,
against brute force."""

import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from auditvec.llm import bitslice, decontam, linechunks, lshforest, mixing, quality, sharding, token_counts, toxicity, warc

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, rows, extra=False):
    df = spark.createDataFrame([(i, t, "en", s, len(t or "")) for i, t, s in rows], DOCS)
    return df.withColumn("slot", F.lit("mine")).withColumn("score", F.lit(7)) if extra else df


def text(rng, n, pool=400):
    return " ".join(f"w{rng.randrange(pool)}" for _ in range(n))


@pytest.fixture(scope="module")
def odd_docs(spark):
    rng = random.Random(4)
    rows = [(i, text(rng, rng.randrange(1, 60)), f"s{i % 4}") for i in range(60)]
    rows += [(60, None, "s0"), (61, "", "s1"), (62, " \t\n ", None), (None, "a b c", None), (63, text(rng, 5000), "s2")]
    rows += [rows[0], rows[0], (64, rows[5][1], "s3")]
    return docs_of(spark, rows, extra=True)


def empty(spark):
    return docs_of(spark, [])


# 1 sharding


def brute_table(names, size, seed):
    walks = {n: [(sharding.preference(n, size, seed)[0] + j * sharding.preference(n, size, seed)[1]) % size for j in range(size)] for n in names}
    owner, turn = {}, 0
    while len(owner) < size:
        name = names[turn % len(names)]
        owner[next(s for s in walks[name] if s not in owner)] = turn % len(names)
        turn += 1
    return [owner[i] for i in range(size)]


def test_table_is_filled_in_turns_and_moves_little():
    names = [f"n{i}" for i in range(7)]
    full = sharding.fill_table(names, 251)
    assert full == brute_table(names, 251, sharding.SEED)
    assert max(Counter(full).values()) - min(Counter(full).values()) <= 1
    less = sharding.fill_table(names[:-1], 251)
    moved = sum(a != b for a, b in zip(full, less) if a != 6)
    assert moved < 0.25 * 251
    with pytest.raises(ValueError):
        sharding.fill_table(names, 250)


def test_sharding_odd_rows(spark, odd_docs):
    got = sharding.assign_shards(odd_docs)
    assert got.count() == odd_docs.count() and got.columns[-2:] == ["slot", "shard_id"] and "score" in got.columns
    assert all(r.shard_id is not None for r in got.collect())
    assert len({r.shard_id for r in got.filter("doc_id = 0").collect()}) == 1
    assert sharding.assign_shards(empty(spark)).count() == 0


# 9 mixing


def brute_mix(rows):
    size = defaultdict(int)
    for _, t, s in rows:
        size[s] += len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    names = sorted(size, key=lambda s: (s is None, s or ""))
    weight = {s: mixing.WEIGHTS[i % 3] for i, s in enumerate(names)}
    full, total = set(), sum(size.values())
    while True:
        rest, w = total - sum(3 * size[s] for s in full), sum(weight[s] for s in names if s not in full)
        more = {s for s in names if s not in full and 3 * size[s] <= weight[s] * rest / w}
        if not more:
            return size, {s: 3.0 * size[s] if s in full else weight[s] * rest / w for s in names}
        full |= more


def test_mixing(spark, odd_docs):
    rows = [(r.doc_id, r.text, r.source) for r in odd_docs.collect()]
    size, target = brute_mix(rows)
    got = mixing.mix_plan(odd_docs).collect()
    assert len(got) == len(rows)
    assert sorted(map(tuple, mixing.mix_plan(odd_docs.repartition(5)).collect()), key=str) == sorted(map(tuple, got), key=str)
    by = defaultdict(int)
    goal = {}
    for r in got:
        assert 0 <= r.taken <= 3 * r["size"]
        by[(r.source_size, round(r.target, 6))] += r.taken
        goal[(r.source_size, round(r.target, 6))] = r.target
    assert sorted(goal.values()) == pytest.approx(sorted({round(t, 6): t for t in target.values()}.values()))
    for k, t in goal.items():
        n = sum(1 for s in target if (size[s], round(target[s], 6)) == k)
        assert abs(by[k] - n * t) <= n
    mixed = mixing.mix_documents(odd_docs)
    assert mixed.columns == odd_docs.columns
    assert mixing.mix_plan(empty(spark)).count() == 0 and mixing.mix_documents(empty(spark)).count() == 0


# 7 decontamination


def words(t):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate({i: i + 32 for i in range(65, 91)}))


def brute_hits(docs, bench):
    windows = defaultdict(set)
    for item, t in bench:
        w = words(t)
        n = min(13, len(w))
        for i in range(len(w) - n + 1 if n else 0):
            windows[tuple(w[i : i + n])].add(item)
    out = []
    for d, t in docs:
        w, hit, items = words(t), set(), set()
        for i in range(len(w)):
            for n in {len(x) for x in windows}:
                if (x := tuple(w[i : i + n])) in windows and len(x) == n:
                    hit |= set(range(i, i + n))
                    items |= {y for y in windows[x] if y is not None}
        out.append((d, len(w), len(hit), len(items)))
    return sorted(out, key=str)


def test_decontamination(spark):
    rng = random.Random(1)
    bench = [(1, text(rng, 30)), (2, text(rng, 14)), (3, "Ünï CØDE straße"), (4, None), (5, "!!"), (None, text(rng, 20)), (2, text(rng, 16))]
    docs = [(i, text(rng, 80, 50), "s") for i in range(20)]
    docs += [(20, text(rng, 9) + " " + bench[0][1].upper() + ", " + text(rng, 5), "s"), (21, "x,Ünï-cØde   straße!", "s"), (22, None, "s"), (23, "", "s"), (24, bench[1][1], "s"), (24, bench[1][1], "s"), (None, bench[5][1], "s"), (25, bench[1][1] + " " + text(rng, 2000), "s")]
    b = spark.createDataFrame(bench, "item_id long, text string")
    d = docs_of(spark, docs, extra=True)
    got = decontam.scan_documents(d, b)
    assert sorted(((r.doc_id, r.n_words, r.n_hit, r.n_items) for r in got.collect()), key=str) == brute_hits([x[:2] for x in docs], bench)
    bad = {r.doc_id for r in got.collect() if r.contaminated}
    assert bad == {20, 21, 24, None}
    kept = decontam.remove_contaminated(d, b)
    assert kept.columns == d.columns and {r.doc_id for r in kept.collect()} == {x[0] for x in docs} - bad
    cut = {r.doc_id: r.text for r in decontam.remove_contaminated(d, b, mode="spans").collect()}
    assert cut[20].split() == (docs[20][1].split()[:9] + docs[20][1].split()[-5:]) and cut[25] == docs[-1][1]
    assert decontam.scan_documents(d, b.limit(0)).filter("contaminated or n_hit > 0").count() == 0
    assert decontam.scan_documents(empty(spark), b).count() == 0


# 8 near duplicates


def shingles(t, k=3):
    w = [x for x in re.split(r"[\x20\x09-\x0D]+", (t or "").translate({i: i + 32 for i in range(65, 91)})) if x]
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def brute_groups(docs):
    sets = [shingles(t) for _, t, _ in docs]
    group = list(range(len(docs)))

    def find(i):
        while group[i] != i:
            i = group[i]
        return i

    for i in range(len(docs)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 85 * len(sets[i] | sets[j]):
                group[find(i)] = find(j)
    ids = defaultdict(list)
    for i, (d, _, _) in enumerate(docs):
        ids[find(i)].append(d)
    return sorted(((docs[i][0], len(sets[i]), min((x for x in ids[find(i)] if x is not None), default=None)) for i in range(len(docs))), key=str)


def test_near_duplicates(spark):
    rng = random.Random(2)
    base = text(rng, 120).split()
    docs = [(i, text(rng, 40), "s") for i in range(15)]
    for i in range(60):  # a crowded region around the threshold
        w = list(base)
        for _ in range(rng.randrange(0, 5)):
            w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
        docs.append((100 + i, " ".join(w), "s"))
    docs += [(200, docs[0][1].upper(), "s"), (201, None, "s"), (202, "", "s"), (203, "one two", "s"), (204, "ONE  two", "s"), (204, "ONE  two", "s"), (None, docs[1][1], "s"), (None, text(rng, 30), "s")]
    d = docs_of(spark, docs, extra=True)
    how = {"width": 3, "least": (85, 100)}
    got = lshforest.near_duplicates(d, **how)
    assert sorted(((r.doc_id, r.n_shingles, r.component_id) for r in got.collect()), key=str) == brute_groups(docs)
    kept = lshforest.keep_one(d, **how)
    assert kept.columns == d.columns and kept.filter("doc_id = 203").count() == 1 and kept.filter("doc_id in (200, 204)").count() == 0
    assert lshforest.near_duplicates(empty(spark)).count() == 0


def test_crowded_regions_lose_no_link(spark):
    """With no pair taken from runs, the prefix filter alone must find the links between the parts."""
    rng = random.Random(3)
    base = text(rng, 80).split()
    docs = []
    for i in range(50):
        w = list(base)
        for _ in range(rng.randrange(0, 4)):
            w[rng.randrange(len(w))] = f"y{rng.randrange(10**6)}"
        docs.append((i, " ".join(w), "s"))
    got = lshforest.near_duplicates(docs_of(spark, docs), width=3, least=(85, 100), few=0)
    assert sorted(((r.doc_id, r.n_shingles, r.component_id) for r in got.collect()), key=str) == brute_groups(docs)


# 5 top-k


def test_topk_is_exact_with_ties_and_bad_vectors(spark):
    rng = np.random.default_rng(0)
    rows = [(i, [float(x) for x in rng.normal(0, 0.3, 8)]) for i in range(300)]
    rows += [(300 + i, rows[7][1]) for i in range(40)] + [(400, None), (401, []), (402, [float("nan")] * 8), (450, [float("inf")] * 8), (7, rows[7][1]), (500, [0.0] * 8), (550, [0.5] * 3)]
    got = bitslice.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("rank", F.lit(1)))
    fine = [(i, np.floor(256 * np.array(v + [0.0] * (8 - len(v)))).astype(int)) for i, v in rows if v and np.isfinite(v).all()]
    want = []
    for qi, q in fine:
        if qi % 50 == 0:
            best = sorted(((-int(q @ v), i) for i, v in fine if i != qi))[:5]
            want += [(qi, r + 1, i, -s) for r, (s, i) in enumerate(best)]
    assert sorted(map(tuple, got.collect())) == sorted(want)
    few = spark.createDataFrame(rows[:3], "vec_id long, embedding array<double>")
    assert bitslice.top_k(few).count() == 2 and bitslice.top_k(few.limit(0)).count() == 0


def test_signed_digits():
    for x in range(-300, 300):
        assert sum(s << p for p, s in bitslice.signed_digits(x)) == x


# 6 WARC


def test_warc_round_trip(spark, tmp_path):
    html = ["<a>é\r\n\r\nWARC/1.1\r\n</a>", "", None, "x" * 100_000, "<b>"]
    rows = [(i, f"http://h/{i}", html[i % 5]) for i in range(25)] + [(24, "http://h/\r\nX: y", "<b>"), (None, None, "<b>"), (None, None, "only")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("payload", F.lit(1))
    got = warc.deduplicated_archives(pages, str(tmp_path / "w")).collect()
    top = defaultdict(lambda: None)
    for i, _, h in rows:
        if i is not None:
            top[h or ""] = max(i, top[h or ""] if top[h or ""] is not None else i)
    want = Counter((i, len((h or "").encode()), "revisit" if top[h or ""] is not None and i != top[h or ""] else "response", top[h or ""] if i != top[h or ""] and top[h or ""] is not None else None) for i, _, h in rows)
    assert Counter((r.page_id, r.payload_bytes, r.record_type, r.refers_to) for r in got) == want
    import base64
    import hashlib

    assert {r.payload_digest for r in got} == {base64.b32encode(hashlib.sha1((h or "").encode()).digest()).decode() for _, _, h in rows}
    assert warc.deduplicated_archives(pages.limit(0), str(tmp_path / "e")).count() == 0


# 4 token counts


def test_token_counts_equal_the_library(spark, tmp_path):
    P = pytest.importorskip("public_tokenizers")
    from tokenizers import Tokenizer

    path = P.path("byte_bpe_50k.json")
    lib = Tokenizer.from_file(path)
    texts = ["Hello  world's\n\n  tabs\t\tx", "<|endoftext|> in text", "naïve café 12345 $$$ %%%", "日本語 テキスト", "", None, "a" * 3000, "     odd \x1c\x85 spaces", "Hello  world's\n\n  tabs\t\tx", "'S 'll'Re"]
    docs = docs_of(spark, [(i, t, "s") for i, t in enumerate(texts)], extra=True)
    cache = str(tmp_path / "cache")
    got = {r.doc_id: r for r in token_counts.count_tokens(docs, path, cache).collect()}
    for i, t in enumerate(texts):
        n = len(lib.encode(t or "", add_special_tokens=False).ids)
        assert (got[i].n_bytes, got[i].n_tokens, got[i].over_limit) == (len((t or "").encode()), n, n > 512), t
    stored = spark.read.parquet(cache).count()
    assert stored == len({t or "" for t in texts})
    assert token_counts.count_tokens(docs, path, cache).count() == len(texts) and spark.read.parquet(cache).count() == stored
    assert token_counts.count_tokens(empty(spark), path, str(tmp_path / "none")).count() == 0
    words_ = P.path("word_bpe_49k.json")
    other = Tokenizer.from_file(words_)
    got = {r.doc_id: r.n_tokens for r in token_counts.count_tokens(docs, words_, cache).collect()}
    assert got == {i: len(other.encode(t or "", add_special_tokens=False).ids) for i, t in enumerate(texts)}


# 10 line dedup


def test_line_chunks(spark):
    rng = random.Random(5)
    shared = "\n".join(text(rng, 12) for _ in range(12))
    long = text(rng, 60)
    docs = [(i, "\n".join(text(rng, 8) for _ in range(6)), "s") for i in range(10)]
    docs += [(20 + i, text(rng, 6) + "\n" + shared + "\n" + text(rng, 7), "s") for i in range(5)] + [(30, long, "s"), (31, text(rng, 5) + "\n" + long, "s"), (32, None, "s"), (33, "", "s"), (33, "", "s"), (34, "\n\n\n", "s"), (35, "short\nline", "s"), (36, "x\nshort\ny", "s"), (None, long, "s")]
    d = docs_of(spark, docs, extra=True)
    got = {r.doc_id: r for r in linechunks.dedup_lines(d).collect()}
    for i, t, _ in docs:
        assert "\n".join(b.decode() for _, _, b in linechunks.chunks(t or "")) == (t or "")
    for i in range(10):
        assert got[i].text == docs[i][1] and got[i].removed_lines == 0
    assert got[20].text == docs[10][1]
    for i in range(21, 25):
        assert got[i].removed_lines >= 4 and len(got[i].text) < 0.7 * len(docs[i - 10][1])
    assert got[30].text == long and got[31].text == docs[16][1].split("\n")[0] and got[None].text == ""
    assert got[32].text == "" and got[34].text == "\n\n\n" and got[36].text == "x\nshort\ny"
    assert linechunks.dedup_lines(empty(spark)).count() == 0


def repeated_by_hand(texts, least=linechunks.LONG_WORDS):
    """Lines of each text that lie in a run of so many words which occurs at an earlier place, without overlap."""
    texts = [t.split("\n") for t in texts]
    size = lambda lines: sum(len(x.split()) for x in lines)
    gone = [set() for _ in texts]
    for a, x in enumerate(texts):
        for i in range(len(x)):
            for b, y in enumerate(texts[: a + 1]):
                for j in range(len(y) if b < a else i):
                    n = 0
                    while i + n < len(x) and j + n < (len(y) if b < a else i) and x[i + n] == y[j + n]:
                        n += 1
                    if size(x[i : i + n]) >= least:
                        gone[a].update(range(i, i + n))
    return gone


def test_repeated_runs_of_short_lines_go_whole(spark):
    rng = random.Random(8)
    runs = [[text(rng, -(-54 // n) + (k == 1) * 3, 10**9) for k in range(n)] for n in (2, 2, 3, 4, 5, 6)]
    runs += [[text(rng, 45, 10**9), text(rng, 4, 10**9), "", text(rng, 2, 10**9)]]
    texts = []
    for _ in range(5):
        for r in runs:
            own = [text(rng, rng.randrange(1, 9), 10**9) for _ in range(6)]
            at = rng.choice([0, 0, 2, 4, 6])
            texts.append("\n".join(own[:at] + r + own[at:]))
    texts.append("\n".join(runs[3][1:] + ["apart"] + runs[3][:2]))
    want = repeated_by_hand(texts)
    assert sum(map(len, want)) >= 4 * sum(map(len, runs))
    got = {r.doc_id: r for r in linechunks.dedup_lines(docs_of(spark, [(i, t, "s") for i, t in enumerate(texts)])).collect()}
    for i, t in enumerate(texts[:-1]):
        left = [x for j, x in enumerate(t.split("\n")) if j not in want[i]]
        assert got[i].text == "\n".join(left) and got[i].removed_lines == len(want[i]) and got[i].removed_chunks == bool(want[i]), i
    # The parts of a run of under LONG_WORDS words are no passage; a chunk of several lines may still go.
    assert "apart" in got[len(texts) - 1].text
    again = "\n".join([text(rng, 10, 10**9)] * 12)
    r = linechunks.dedup_lines(docs_of(spark, [(0, again, "s")])).first()
    assert r.text == "\n".join(again.split("\n")[:5]) and r.removed_lines == 7


# 2, 3 classifiers


def labelled(rng, n, kind):
    rows, labels = [], []
    for i in range(n):
        y = i % 3 == 0
        w = [f"word{rng.randrange(200)}" for _ in range(rng.randrange(5, 120))]
        if y and kind == "toxic":
            w[rng.randrange(len(w))] = rng.choice(["grumblax", "Snortik!", "vexohm"])
        if y and kind == "quality":
            w = [x + "." if rng.random() < 0.3 else x for x in w]
        rows.append((i, " ".join(w), "s"))
        labels.append((i, int(y)))
    return rows, labels


@pytest.mark.parametrize("module,kind", [(quality, "quality"), (toxicity, "toxic")])
def test_classifiers_on_held_out_rows(spark, module, kind):
    rows, labels = labelled(random.Random(6), 600, kind)
    rows += [(9000, None, "s"), (9001, "", "s"), (9002, "word1 " * 3000, "s"), (None, "x", "s")]
    docs = docs_of(spark, rows, extra=True)
    marks = spark.createDataFrame(labels + [(9000, None), (5, 1), (5, 0)], f"doc_id long, {kind} int")
    model = module.train(docs, marks)
    got = (module.score_quality if kind == "quality" else module.score_toxicity)(docs, model)
    assert got.columns[:4] == ["doc_id", "held_out", "score", "predicted"]
    out = {r.doc_id: r for r in got.collect()}
    assert len(out) == len(rows) and all(0 <= r.score <= 1 for r in out.values())
    held = [(out[i].score, y) for i, y in labels if out[i].held_out]
    good = np.mean([(s >= module.THRESHOLD) == y for s, y in held])
    assert len(held) > 100 and good > 0.85
    again = (module.score_quality if kind == "quality" else module.score_toxicity)(docs.repartition(7), model)
    assert {r.doc_id: r.score for r in again.collect()} == {i: r.score for i, r in out.items()}
    none = module.train(docs, marks.limit(0))
    assert (module.score_quality if kind == "quality" else module.score_toxicity)(docs, none).count() == len(rows)


def test_network_gradients_are_right():
    rng = np.random.default_rng(1)
    p = {k: v.astype(np.float64) for k, v in toxicity.new_parameters(rng).items()}
    words_ = toxicity.Words()
    win = np.stack([words_.ids([b"aa", b"bb", b"cc", b"dd"]), np.append(words_.ids([b"bb", b"ee"]), [-1, -1])])
    words_.close()
    logit, kept = toxicity._forward(win, words_, p, keep=True)
    grads = toxicity._backward(np.ones(2) / 2, kept, p)
    for name in ("wh", "wx", "wa", "va", "wo", "bo", "bx"):
        at = tuple(rng.integers(0, s) for s in p[name].shape)
        eps, q = 1e-3, {k: v.copy() for k, v in p.items()}
        q[name][at] += eps
        up = toxicity._forward(win, words_, q)[0].sum() / 2
        q[name][at] -= 2 * eps
        down = toxicity._forward(win, words_, q)[0].sum() / 2
        assert grads[name][at] == pytest.approx((up - down) / (2 * eps), abs=2e-3)


def test_components(spark):
    from auditvec.llm.components import connected_components

    rng = random.Random(9)
    edges = [(i, i + 1) for i in range(0, 200) if i % 40] + [(rng.randrange(300, 400), rng.randrange(300, 400)) for _ in range(80)] + [(500, 500)]
    label = {x: x for e in edges for x in e}
    for _ in range(300):
        for a, b in edges:
            label[a] = label[b] = min(label[a], label[b])
    got = connected_components(spark.createDataFrame(edges, "a long, b long")).collect()
    lone = {a for a, b in edges if a == b} - {x for a, b in edges if a != b for x in (a, b)}
    assert {r.node: r.label for r in got} == {k: v for k, v in label.items() if k not in lone}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0
