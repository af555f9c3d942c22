"""Operators against plain Python on small tables: whole texts, long words, several files, stages of the pipeline."""

import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_operators import brute_groups, brute_hits, brute_mix, docs_of, labelled, shingles, text

from auditvec.llm import bitslice, decontam, features, linechunks, lshforest, mixing, quality, sharding, token_counts, toxicity, warc

# Features -------------------------------------------------------------------------------------------------------------


def grams(words, sizes):
    return Counter((i, m[j : j + n]) for i, w in enumerate(words) for m in [b"<" + w + b">"] for n in sizes for j in range(len(m) - n + 1))


def test_all_n_grams_of_all_words_whatever_the_pieces(monkeypatch):
    rng = random.Random(1)
    words = [bytes(rng.choices(b"abc", k=rng.randrange(1, 9))) for _ in range(30)] + [b"x" * 300, bytes(rng.choices(b"abcdef", k=500))]
    whole = Counter(zip(*(np.concatenate(c).tolist() for c in zip(*features.gram_buckets(words, (3, 4), 1 << 30)))))
    assert sum(whole.values()) == sum(grams(words, (3, 4)).values())
    assert len({b for (b, i) in whole if i == 31}) == len({g for (i, g) in grams(words, (3, 4)) if i == 31})
    monkeypatch.setattr(features, "AT_ONCE", 7)
    assert Counter(zip(*(np.concatenate(c).tolist() for c in zip(*features.gram_buckets(words, (3, 4), 1 << 30))))) == whole


def test_long_words_differ_beyond_their_head():
    head = b"a" * 40
    tails = [head + bytes(random.Random(i).choices(b"bcdefgh", k=250)) for i in range(2)]
    a, b = ({int(x) for flat, _ in features.gram_buckets([w], (3, 4, 5), 1 << 20) for x in flat} for w in tails)
    assert len(a ^ b) > 100


def test_training_texts_come_whole(spark):
    rng = random.Random(2)
    ids = list(range(400))
    rows = [(i, text(rng, 20) if i % 50 else text(rng, 12_000), "s") for i in ids] + [(3, "again", "s")]
    docs, marks = docs_of(spark, rows, extra=True), spark.createDataFrame([(i, i % 2) for i in ids] + [(8, 1), (9, None)], "doc_id long, toxic int")
    got = features.training_rows(docs, marks, "toxic", (500, 500))
    held = {r.doc_id for r in docs.select("doc_id", features.held_out().alias("h")).filter("h").collect()}
    want = sorted((t, i % 2) for i, t, _ in rows if i not in held | {8})
    assert sorted(got) == want and any(len(t) > 40_000 for t, _ in got)
    few = features.training_rows(docs, marks, "toxic", (500, 500), most_bytes=50_000)
    assert 0 < sum(len(t) for t, _ in few) <= 50_000 and set(few) <= set(want)
    assert len(features.training_rows(docs, marks, "toxic", (7, 4))) <= 11 + 1
    assert features.training_rows(docs.limit(0), marks, "toxic", (7, 4)) == [] == features.training_rows(docs, marks.limit(0), "toxic", (7, 4))


# Classifiers ----------------------------------------------------------------------------------------------------------

ODD = ["", None, "one", " \t\n", "x" * 3000, "Word, word; wörd 日本語 " * 40]


def test_quality_scores_are_the_softmax_of_the_mean():
    rows, labels = labelled(random.Random(6), 200, "quality")
    data = [(t, y) for (_, t, _), (_, y) in zip(rows, labels)]
    vectors, out, bias = quality.fit_parts(data, steps=60)
    model = quality.fit(data, steps=60)
    texts = [t for _, t, _ in rows[:40]] + ODD + [text(random.Random(3), 15_000)]
    for t, s in zip(texts, quality.score_texts(texts, model)):
        ids, share = quality._features(t or "")
        z = share.astype(float) @ vectors[ids].astype(float) @ out.T.astype(float) + bias
        assert s == pytest.approx(np.exp(z[1]) / np.exp(z).sum(), abs=2e-5)


def slow_toxicity(t, p):
    """One window at a time through the training network."""
    words = toxicity.Words()
    ids = words.ids(toxicity._words(t))
    words.close()
    scores = []
    for a in toxicity.window_starts(len(ids)):
        win = ids[a : a + toxicity.WINDOW]
        if not len(win):
            return None
        scores.append(toxicity._sigmoid(toxicity._forward(win[None], words, p)[0][0]))
    return max(scores)


def test_toxicity_scores_are_the_networks():
    rows, labels = labelled(random.Random(6), 120, "toxic")
    p = toxicity.fit([(t, y) for (_, t, _), (_, y) in zip(rows, labels)], steps=40)
    texts = [t for _, t, _ in rows[:12]] + [o for o in ODD if (o or "").split()] + [text(random.Random(3), 400) + " grumblax"]
    for t, s in zip(texts, toxicity.score_texts(texts, p)):
        assert s == pytest.approx(slow_toxicity(t, p), abs=2e-5)
    assert np.allclose(toxicity.score_texts(texts, p), np.concatenate([toxicity.score_texts([t], p) for t in texts]), atol=1e-6)
    long = text(random.Random(4), 9000)
    assert len(long) > 40_000 and toxicity.score_texts([long + " grumblax snortik"], p)[0] > toxicity.score_texts([long], p)[0] - 1e-6


def test_short_statements_lie_whole_in_a_window():
    for n in (1, 16, 32, 33, 47, 48, 100):
        starts = toxicity.window_starts(n)
        for a in range(n):
            b = min(n, a + toxicity.WINDOW - toxicity.STRIDE + 1)
            assert any(s <= a and b <= s + toxicity.WINDOW for s in starts), (n, a)


def test_training_length_is_as_told(monkeypatch):
    """About `steps` steps, however few toxic rows there are."""
    rows, labels = labelled(random.Random(6), 90, "toxic")
    data, steps = [(t, y) for (_, t, _), (_, y) in zip(rows, labels)], []
    monkeypatch.setattr(toxicity, "_backward", lambda d, k, p, f=toxicity._backward: steps.append(1) or f(d, k, p))
    toxicity.fit(data, steps=60)
    assert 55 <= len(steps) <= 130


# Near duplicates ------------------------------------------------------------------------------------------------------


def test_dense_regions_lose_no_pair(spark):
    rng = random.Random(3)
    base = text(rng, 80).split()
    texts = []
    for _ in range(40):
        w = list(base)
        for _ in range(rng.randrange(0, 5)):
            w[rng.randrange(len(w))] = f"y{rng.randrange(10**6)}"
        texts.append(" ".join(w))
    sets = list(lshforest.shingle_sets(texts, 3))
    names = [f"{i:03}".encode() for i in range(len(sets))]
    kept = spark.createDataFrame([(n, s.tobytes()) for n, s in zip(names, sets)], "cls binary, items binary")
    dense = spark.createDataFrame([(n, f"{i % 7}".encode()) for i, n in enumerate(names)], "cls binary, label binary")
    found = {(bytes(r.a), bytes(r.b)) for r in lshforest.dense_pairs(dense, kept, (85, 100)).collect()}
    want = set()
    for i, x in enumerate(sets):
        for j in range(i):
            both = len(np.intersect1d(x, sets[j]))
            if i % 7 != j % 7 and 100 * both >= 85 * (len(x) + len(sets[j]) - both):
                want.add((names[j], names[i]))
    assert want and want <= found


def test_regions_choose_their_depth():
    levels = np.array([0, 4, 5, 0, 8, 8, 8, 5, 4, 2, 1])
    region, size = lshforest.regions(levels, 4, 8, 3)
    assert size.tolist() == [3, 3, 3, 6, 6, 6, 6, 6, 6, 1, 1]
    assert len(set(region[:3])) == 1 and (region[3:7] == -1).all() and region[7] >= 0 and region[8] >= 0


def test_one_row_of_each_group_stays(spark):
    rng = random.Random(12)
    same = text(rng, 60)
    near = same.split()
    near[30] = "other"
    rows = [(5, same, "a"), (3, " ".join(near), "b"), (None, same, "c"), (None, same.upper(), "d"), (3, " ".join(near), "e"), (9, text(rng, 30), "f"), (9, text(rng, 30), "g"), (None, text(rng, 20), "h"), (None, None, "i"), (7, "", "j"), (7, "", "k"), (4, text(rng, 15_000), "l")]
    d = docs_of(spark, rows, extra=True).withColumn("label", F.lit("x")).withColumn("row", F.lit(1))
    kept = lshforest.keep_one(d)
    left = sorted((str(r.doc_id), r.source) for r in kept.collect())
    assert kept.columns == d.columns
    assert [x for x in left if x[1] in "abcde"] in ([("3", "b")], [("3", "e")])
    assert {x[1] for x in left if x[1] not in "abcde"} == set("fghijkl")
    assert lshforest.keep_one(d.limit(0)).count() == 0
    lone = docs_of(spark, [(None, same, "a"), (None, same, "b")])
    assert lshforest.keep_one(lone).count() == 1


# Token counts, top-k, WARC --------------------------------------------------------------------------------------------


def test_token_counts_of_long_texts_and_of_many_copies(spark, tmp_path, monkeypatch):
    P = pytest.importorskip("public_tokenizers")
    from tokenizers import Tokenizer

    path, rng = P.path("byte_bpe_50k.json"), random.Random(5)
    lib = Tokenizer.from_file(path)
    texts = [text(rng, 20_000, 10**6), "z" * 5000 + " " + "q1" * 900] + ["copy of it"] * 300
    monkeypatch.setattr(token_counts, "REMEMBERED", 50)
    cache = str(tmp_path / "cache")
    d = docs_of(spark, [(i, t, "s") for i, t in enumerate(texts)])
    for _ in range(2):
        got = {r.doc_id: r.n_tokens for r in token_counts.count_tokens(d, path, cache).collect()}
        assert got == {i: len(lib.encode(t, add_special_tokens=False).ids) for i, t in enumerate(texts)}
    assert spark.read.parquet(cache).count() == 3


def test_topk_in_several_blocks_and_batches(spark, monkeypatch):
    rng = np.random.default_rng(4)
    x = rng.normal(0, 0.4, (400, 6))
    rows = spark.createDataFrame([(i, [float(f) for f in v]) for i, v in enumerate(x)], "vec_id int, embedding array<double>")
    monkeypatch.setattr(bitslice, "BLOCK_ROWS", 90)
    monkeypatch.setattr(bitslice, "BATCH_QUERIES", 11)
    got = sorted(map(tuple, bitslice.top_k(rows, every=10).collect()))
    q = np.floor(256 * x).astype(int)
    want = [(i, r + 1, j, -s) for i in range(0, 400, 10) for r, (s, j) in enumerate(sorted((-int(q[i] @ q[j]), j) for j in range(400) if j != i)[:5])]
    assert got == sorted(want)
    with pytest.raises(Exception, match="too large"):
        bitslice.top_k(spark.createDataFrame([(0, [1e300]), (1, [1.0])], "vec_id long, embedding array<double>")).collect()


def test_archives_of_several_files_and_large_payloads(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(warc, "FILE_BYTES", 2000)
    monkeypatch.setattr(warc, "CLASSES", (100, 500, 1000))
    html = ["s" * 50, "m" * 300, "l" * 900, "x" * 5000]
    rows = [(i, f"http://h/{i}", html[i % 4] + str(i // 8 * 8)) for i in range(64)]
    path = str(tmp_path / "w")
    got = warc.deduplicated_archives(spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1), path).collect()
    groups = defaultdict(list)
    for i, _, h in rows:
        groups[h].append(i)
    assert {(r.page_id, r.record_type, r.refers_to, r.payload_bytes) for r in got} == {(i, "response" if i == max(g) else "revisit", None if i == max(g) else max(g), len(h)) for h, g in groups.items() for i in g}
    import pathlib
    import zlib

    sizes = [len(zlib.decompress(f.read_bytes(), 31)) for f in pathlib.Path(path).glob("*.gz")]
    assert len(sizes) > 12 and max(sizes) < 30_000


# Line dedup -----------------------------------------------------------------------------------------------------------


def plain_dedup(texts):
    """Kept lines of each text: windows and chunks by their definition, first places in order of id and line."""
    import xxhash

    least, places = linechunks.LONG_WORDS, defaultdict(list)
    lines_of = [t.split("\n") for t in texts]
    for d, lines in enumerate(lines_of):
        size, spans = [len(x.split()) for x in lines], set()
        for i in range(len(lines)):
            e = next((e for e in range(i + 1, len(lines) + 1) if sum(size[i:e]) >= least), None)
            spans |= {(i, e)} if e else set()
            a = next((a for a in range(i, -1, -1) if sum(size[a : i + 1]) >= least), None)
            spans |= {(a, i + 1)} if a is not None else set()
        h, begin = [xxhash.xxh64_intdigest(x.encode()) for x in lines], 0
        for i in range(len(lines)):
            rolled = sum(x * pow(0x9E3779B97F4A7C15, k, 1 << 64) for k, x in enumerate(reversed(h[max(0, i - linechunks.ROLL + 1) : i + 1]))) % (1 << 64)
            if i + 1 == len(lines) or size[i] >= least or size[i + 1] >= least or (rolled >> 32) % linechunks.CUT == 0:
                if i + 1 - begin > 1 and 0 < sum(size[begin : i + 1]) < least:
                    spans.add((begin, i + 1))
                begin = i + 1
        for a, b in spans:
            places["\n".join(lines[a:b])].append((d, a, b))
    gone = [set() for _ in texts]
    for where in places.values():
        first = min(where)
        for d, a, b in where:
            if (d, a) != first[:2]:
                gone[d] |= set(range(max(a, first[2]) if d == first[0] else a, b))
    return ["\n".join(x for i, x in enumerate(lines) if i not in g) for lines, g in zip(lines_of, gone)], gone


def test_line_dedup_is_its_definition(spark):
    rng = random.Random(31)
    pool = [text(rng, rng.randrange(0, 14), 10**9) for _ in range(60)] + [text(rng, 55, 10**9) for _ in range(4)]
    texts = []
    for _ in range(40):
        parts = []
        for _ in range(rng.randrange(1, 5)):
            a = rng.randrange(len(pool))
            parts += pool[a : a + rng.randrange(1, 9)] + [text(rng, 6, 10**9)]
        texts.append("\n".join(parts))
    texts += ["", "\n\n", texts[3], "\n".join(text(rng, 3, 10**9) for _ in range(3000))]
    want, gone = plain_dedup(texts)
    d = docs_of(spark, [(i, t, "s") for i, t in enumerate(texts)]).withColumn("doc_id", F.format_string("%06d", F.col("doc_id")))
    got = {int(r.doc_id): r for r in linechunks.dedup_lines(d).collect()}
    assert sum(map(len, gone)) > 50
    for i in range(len(texts)):
        assert got[i].text == want[i] and got[i].removed_lines == len(gone[i]), i


# The pipeline's stages ------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def stage_input(spark, tmp_path_factory):
    folder = tmp_path_factory.mktemp("sf")
    rng = random.Random(17)
    rows, labels = labelled(rng, 150, "quality")
    rows = [(i, t, f"s{i % 3}") for i, t, _ in rows]
    item = text(rng, 40, 10**6)
    copy = rows[4][1].split()
    rows += [(500, " ".join([*copy[:-1], "end"]), "s1"), (501, rows[6][1], None), (502, item, "s0"), (503, text(rng, 30) + " " + item, "s2"), (504, None, "s0"), (505, "", "s1"), (None, "a few words", None), (506, text(rng, 9000), "s2"), rows[8], rows[8]]
    docs = docs_of(spark, rows, extra=True).withColumn("shard_id", F.lit("mine")).withColumn("taken", F.lit(2))
    spark.createDataFrame(labels, "doc_id long, quality int").write.parquet(str(folder / "labels.parquet"))
    spark.createDataFrame([(1, item), (2, None)], "item_id long, text string").write.parquet(str(folder / "benchmark.parquet"))
    docs.write.parquet(str(folder / "documents.parquet"))
    return spark.read.parquet(str(folder / "documents.parquet")), str(folder), rows


def ids(df):
    return Counter(r.doc_id for r in df.select("doc_id").collect())


def test_each_stage_against_plain_python(spark, stage_input):
    import corpus_pipeline as C

    docs, folder, rows = stage_input
    stage = dict(C.STAGES)

    good = stage["quality"](spark, docs, folder)
    model = quality.train(docs, spark.read.parquet(f"{folder}/labels.parquet"))
    scores = quality.score_texts([t for _, t, _ in rows], model)
    assert good.columns == docs.columns and ids(good) == Counter(i for (i, _, _), s in zip(rows, scores) if s >= quality.THRESHOLD)

    lone = stage["near_duplicates"](spark, docs, folder)
    sets = [shingles(t, 5) for _, t, _ in rows]
    group = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                old, new = group[i], group[j]
                group = [new if g == old else g for g in group]
    left = ids(lone)
    members = defaultdict(list)
    for (i, _, _), g, s in zip(rows, group, sets):
        members[g if s else ("empty", len(members))].append(i)
    assert sum(left.values()) == len(members) and lone.columns == docs.columns
    assert left == Counter(min(m, key=lambda i: (i is None, i or 0)) for m in members.values())

    clean = stage["decontamination"](spark, docs, folder)
    item = spark.read.parquet(f"{folder}/benchmark.parquet").filter("item_id = 1").first().text
    hits = brute_hits([(n, t) for n, (_, t, _) in enumerate(rows)], [(1, item)])
    bad = {n for n, w, h, _ in hits if h and 20 * h >= w}
    assert {rows[n][0] for n in bad} == {502, 503} and clean.columns == docs.columns
    assert ids(clean) == Counter(i for n, (i, _, _) in enumerate(rows) if n not in bad)

    mixed = stage["mixing"](spark, docs, folder)
    size, target = brute_mix(rows)
    words = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    took, most = Counter(), max(words(t) for _, t, _ in rows)
    for r in mixed.collect():
        took[r.source] += words(r.text)
    assert mixed.columns == docs.columns and max(ids(mixed).values()) <= 9
    assert all(target[s] - 1 <= took[s] < target[s] + most for s in size if size[s])

    placed = stage["sharding"](spark, docs, folder)
    assert ids(placed) == ids(docs) and {"slot", "shard_id"} <= set(placed.columns)
    assert {r.shard_id for r in placed.collect()} <= set(range(sharding.SHARDS))


def test_stages_on_an_empty_table(spark, stage_input):
    import corpus_pipeline as C

    docs, folder, _ = stage_input
    for name, stage in C.STAGES:
        assert stage(spark, docs.limit(0), folder).count() == 0, name


def test_operators_on_empty_tables_and_written_shards(spark, stage_input, tmp_path):
    docs, folder, rows = stage_input
    bench = spark.read.parquet(f"{folder}/benchmark.parquet")
    for mode in ("documents", "spans"):
        assert decontam.remove_contaminated(docs.limit(0), bench, mode=mode).count() == 0
        assert decontam.remove_contaminated(docs, bench.limit(0), mode=mode).count() == len(rows)
    sharding.write_shards(docs.drop("slot", "shard_id"), str(tmp_path / "shards"))
    back = spark.read.parquet(str(tmp_path / "shards"))
    assert back.count() == len(rows) and "shard_id" in back.columns
    assert mixing.mix_plan(docs).count() == len(rows) and brute_groups([r for r in rows[:3]])
