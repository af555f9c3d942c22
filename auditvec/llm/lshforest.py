"""Near-duplicate documents by an LSH forest.

A document is its set of word shingles; documents with equal sets form a class. Each of TREES trees orders the
classes by a signature of DEPTH min-hashes. A region of a tree is a run of neighbours with a common prefix of at
least SHALLOW of them. Its depth adapts to how crowded it is: the shallowest one at which at most FEW classes share
the prefix.

1. Candidates are all pairs of a region at its own depth, and all neighbours of a tree's order with a common prefix.
   They are confirmed on the full sets, and the links give components.
2. A region that is crowded at SHALLOW, or that a partition border cuts, has lost pairs by that. Where it holds several
   components, those pairs between components that are missing follow: all, if they are at most FEW squared, else
   those that an exact prefix filter over the classes of such regions finds. They are confirmed as well.

So of two sets with a common prefix in some tree none is lost, whatever the region's size; nothing is capped. Two sets
with similarity 0.85 miss a common prefix of 4 in all 24 trees with probability 2e-8 (0.48 to the 24th), with
similarity 0.8, 3e-6.

Trees are dealt by ranges of (tree, signature, class), so a group of near copies spreads over tasks however many
signatures are equal; joins on a region or a shingle are salted.

Defined results: null texts and texts without words have 0 shingles, are linked with nothing and are kept; rows that
repeat an id and text agree; a null doc_id is no candidate for component_id, and a group of null ids only has a null
component and near_duplicates keeps it; keep_one leaves one row of each group, of null ids and of repeated rows too
(the smallest id, ties by a digest of the text, null ids last); empty input gives an empty result; other columns are
ignored by near_duplicates and kept by keep_one.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .components import connected_components
from .shared import discard, row_key, slices, small, staged

TREES, DEPTH, SHALLOW, FEW, SKETCH = 24, 8, 4, 8, 1 << 18
WORDS, LEAST = 5, (80, 100)
#: Words, and bytes of a word, whose hashes a worker keeps; others are hashed again.
REMEMBERED, SHORT = 150_000, 48
#: Parts that the rows of one region or shingle are dealt to in joins.
SALTS = 16
#: Rows of one region that a task holds at once; a longer one goes on in the next part.
HELD = 1 << 16
_MIX = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9))


class _WordHashes(dict):
    def __missing__(self, word):
        h = xxhash.xxh64_intdigest(word)
        if len(word) <= SHORT and len(self) < REMEMBERED:
            self[word] = h
        return h


_KNOWN = _WordHashes()


def _finish(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * _MIX[0]
    return h ^ (h >> np.uint64(29))


def shingle_sets(texts: list, width: int = WORDS):
    """Sorted distinct 64-bit shingle hashes of each text; words are runs of non-blanks, A-Z in lower case."""
    if len(_KNOWN) >= REMEMBERED:
        _KNOWN.clear()
    for t in texts:
        words = (t or "").encode(errors="surrogatepass").lower().split()
        if not words:
            yield np.zeros(0, np.uint64)
            continue
        h = np.fromiter(map(_KNOWN.__getitem__, words), np.uint64, len(words))
        k = min(width, len(h))
        mixed = np.full(len(h) - k + 1, k, np.uint64)
        for i in range(k):
            mixed = _finish(mixed * _MIX[2] + h[i : i + len(mixed)] * _MIX[1])
        yield np.unique(mixed)


def _functions(n: int, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return rng.integers(0, 1 << 31, n, np.uint32) * np.uint32(2) + np.uint32(1), rng.integers(0, 1 << 32, n, np.uint32, endpoint=False)


def signature(shingles: np.ndarray, a: np.ndarray, b: np.ndarray) -> bytes:
    """Two bytes, most significant first, of each function's least value over the set."""
    x = (shingles >> np.uint64(32)).astype(np.uint32)
    least = np.full(len(a), 0xFFFFFFFF, np.uint32)
    for i in range(0, len(x), 1024):
        least = np.minimum(least, (a[:, None] * x[None, i : i + 1024] + b[:, None]).min(1))
    return ((least * np.uint32(0x9E3779B1)) >> np.uint32(16)).astype(">u2").tobytes()


def _digest(shingles: np.ndarray) -> bytes | None:
    return hashlib.blake2b(shingles.tobytes(), digest_size=16).digest() if len(shingles) else None


def _profiler(width: int, trees: int, depth: int):
    def run(batches):
        a, b = _functions(trees * depth)
        for batch in batches:
            for part in slices(batch, "text"):
                sizes, classes, signs = [], [], []
                for s in shingle_sets(part.column("text").to_pylist(), width):
                    sizes.append(len(s))
                    classes.append(_digest(s))
                    signs.append(signature(s, a, b) if len(s) else None)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("row"), pa.array(sizes, pa.int64()), pa.array(classes, pa.binary()), pa.array(signs, pa.binary())], names=["doc_id", "row", "n", "cls", "sig"])

    return run


def regions(levels: np.ndarray, shallow: int, depth: int, few: int) -> tuple[np.ndarray, np.ndarray]:
    """levels[i]: min-hashes that row i shares with the row before it. (region, size): a number for the rows that share
    a region at its own depth, -1 where even the full depth holds more than few; rows that share the shallow prefix."""
    region, size = np.full(len(levels), -1, np.int64), None
    for d in range(shallow, depth + 1):
        group = np.cumsum(levels < d)
        n = np.bincount(group)[group]
        size = n if size is None else size
        region = np.where((region < 0) & (n <= few), group + d * (len(levels) + 1), region)
    return region, size


WALK = "a binary, b binary, tree int, key binary, cls binary, n long, part int, edge int"


def _walker(depth: int, shallow: int, few: int):
    """Of a partition in order of (tree, key, cls): candidate pairs (a, b); rows of regions that are crowded or reach
    the partition's border (edge 0); its first row (edge 1) and its last (edge 2)."""
    kinds = [pa.binary(), pa.binary(), pa.int32(), pa.binary(), pa.binary(), pa.int64(), pa.int32(), pa.int32()]
    names = [x.split()[0] for x in WALK.split(", ")]

    def fixed(col, width: int) -> np.ndarray:
        return np.frombuffer(b"".join(col.to_pylist()), np.uint8).reshape(-1, width)

    def levels_of(tree, key) -> np.ndarray:
        words = key.reshape(len(key), depth, 2)
        same = (words[1:] == words[:-1]).all(2) & (tree[1:] == tree[:-1])[:, None]
        return np.concatenate([[0], np.cumprod(same, 1).sum(1)])

    def table(cols: list[list]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

    def run(batches):
        part = TaskContext.get().partitionId()

        def rows_out(rows, at, edge):
            tree, key, cls, n = rows
            none = [None] * len(at)
            return table([none, none, tree[at], [key[i].tobytes() for i in at], [cls[i].tobytes() for i in at], n[at], [part] * len(at), [edge] * len(at)])

        def done(rows, levels, cut_before: bool, cut_after: bool):
            """Pairs and open rows of whole regions, but for the first and last one, if they are cut."""
            tree, key, cls, n = rows
            region, size = regions(levels, shallow, depth, few)
            pairs = [np.flatnonzero(levels >= shallow)]
            offsets = [np.ones(len(pairs[0]), np.int64)]
            for k in range(2, min(few, len(levels))):
                at = np.flatnonzero((region[k:] >= 0) & (region[k:] == region[:-k])) + k
                pairs.append(at)
                offsets.append(np.full(len(at), k, np.int64))
            i, j = np.concatenate(pairs), np.concatenate(pairs) - np.concatenate(offsets)
            for lo in range(0, len(i), 50_000):
                ends = [sorted((cls[x].tobytes(), cls[y].tobytes())) for x, y in zip(i[lo : lo + 50_000], j[lo : lo + 50_000])]
                none = [None] * len(ends)
                yield table([[x for x, _ in ends], [y for _, y in ends], *[none] * 6])
            still = size > few
            if cut_before:
                still[: size[0]] = True
            if cut_after:
                still[len(size) - size[-1] :] = True
            at = np.flatnonzero(still)
            for lo in range(0, len(at), 50_000):
                yield rows_out(rows, at[lo : lo + 50_000], 0)

        held, first = None, True  # rows of the last region so far, whose end is not yet known
        for b in batches:
            if not b.num_rows:
                continue
            rows = [b.column("tree").to_numpy(), fixed(b.column("key"), 2 * depth), fixed(b.column("cls"), 16), b.column("n").to_numpy()]
            if held is None:
                yield rows_out(rows, [0], 1)
            else:
                rows = [np.concatenate([h, r]) for h, r in zip(held, rows)]
            levels = levels_of(rows[0], rows[1])
            starts = np.flatnonzero(levels < shallow)
            upto, cut = int(starts[-1]), False
            if len(levels) - upto > HELD:
                upto, cut = len(levels) - 1, True  # the last row is the first of the next part
            if upto:
                yield from done([r[:upto] for r in rows], levels[:upto], first, cut)
                if cut:
                    yield table([[x] for x in sorted((rows[2][upto - 1].tobytes(), rows[2][upto].tobytes()))] + [[None]] * 6)
                first = cut
            held = [r[upto:] for r in rows]
        if held is not None:
            yield from done(held, levels_of(held[0], held[1]), first, True)
            yield rows_out(held, [len(held[0]) - 1], 2)

    return run


def _over_borders(walked: DataFrame, shallow: int) -> DataFrame:
    """Pairs of a partition's last row and the next one's first, if they share a prefix. Two rows a partition."""
    place = F.struct("tree", _prefix(shallow).alias("p"), "cls")
    ends = walked.filter("edge > 0").groupBy("part").agg(F.max(F.when(F.col("edge") == 1, place)).alias("first"), F.max(F.when(F.col("edge") == 2, place)).alias("last"))
    ends = ends.withColumn("before", F.lag("last").over(Window.orderBy("part")))
    met = ends.filter((F.col("before.tree") == F.col("first.tree")) & (F.col("before.p") == F.col("first.p")))
    return met.select(F.least("before.cls", "first.cls").alias("a"), F.greatest("before.cls", "first.cls").alias("b"))


def _set_maker(width: int):
    def run(batches):
        for batch in batches:
            for part in slices(batch, "text", 256):
                sets = [s for s in shingle_sets(part.column("text").to_pylist(), width) if len(s)]
                yield pa.RecordBatch.from_arrays([pa.array([_digest(s) for s in sets], pa.binary()), pa.array([s.tobytes() for s in sets], pa.binary())], names=["cls", "items"])

    return run


def _confirmer(least: tuple[int, int]):
    def run(batches):
        for b in batches:
            keep = []
            for i, (x, y) in enumerate(zip(b.column("items_a"), b.column("items_b"))):
                s, t = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                both = np.concatenate([s, t])
                both.sort()
                common = int((both[1:] == both[:-1]).sum())
                if least[1] * common >= least[0] * (len(s) + len(t) - common):
                    keep.append(i)
            yield b.select(["a", "b"]).take(pa.array(keep, pa.int64()))

    return run


def _confirmed(pairs: DataFrame, sets: DataFrame, least: tuple[int, int]) -> DataFrame:
    """The pairs (a, b) whose full sets are similar enough."""
    side = lambda c: sets.select(F.col("cls").alias(c), F.col("items").alias(f"items_{c}"), F.octet_length("items").alias(f"n_{c}"))
    joined = pairs.join(side("a"), "a").join(side("b"), "b").filter(_close(least))
    return staged(joined.select("a", "b", "items_a", "items_b").mapInArrow(_confirmer(least), "a binary, b binary"), "confirmed")


def _close(least: tuple[int, int]):
    return (F.col("n_a") * least[1] >= F.col("n_b") * least[0]) & (F.col("n_b") * least[1] >= F.col("n_a") * least[0])


def _prefix(levels: int):
    return F.substring("key", 1, 2 * levels)


def _salted(rows: DataFrame, by: str, keyed: DataFrame, keys: list[str]) -> DataFrame:
    """rows join keyed on the keys, which are unique in keyed and may be hot in rows: a key's rows go to SALTS parts by
    a hash of another column, and keyed to each of them."""
    every = keyed.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return rows.withColumn("salt", F.pmod(F.xxhash64(by), F.lit(SALTS)).cast("int")).join(every, [*keys, "salt"])


def _across(opened: DataFrame, sets: DataFrame, few: int, least: tuple[int, int]) -> DataFrame | None:
    """Candidate pairs (a, b) between components in opened regions: (tree, p, cls, n, label)."""
    parts = opened.groupBy("tree", "p", "label").agg(F.count("*").alias("m")).groupBy("tree", "p").agg(F.sum("m").alias("m"), F.sum(F.col("m") * F.col("m")).alias("mm"), F.count("*").alias("labels"))
    mixed = staged(parts.filter("labels > 1").select("tree", "p", (F.col("m") * F.col("m") - F.col("mm") <= 2 * few * few).alias("easy")), "mixed-regions")
    if mixed.isEmpty():
        return None
    rows = staged(_salted(opened, "cls", mixed, ["tree", "p"]).drop("salt"), "mixed-rows")
    x, y = (rows.filter("easy").select("tree", "p", *[F.col(c).alias(f"{c}_{s}") for c in ("cls", "n", "label")]) for s in "ab")
    easy = x.join(y, ["tree", "p"]).filter((F.col("label_a") < F.col("label_b")) & _close(least)).select(F.col("cls_a").alias("a"), F.col("cls_b").alias("b"))
    dense = staged(rows.filter("not easy").select("cls", "label").distinct(), "dense")
    if not dense.isEmpty():
        found = dense_pairs(dense, sets, least)
        easy = easy if found is None else easy.union(found)
    out = staged(easy.distinct(), "across")
    discard(mixed, rows, dense)
    return out


def _frequencies(batches):
    counts = np.zeros(SKETCH, np.int64)
    for b in batches:
        for x in b.column("items"):
            np.add.at(counts, (np.frombuffer(x.as_buffer(), np.uint64) % np.uint64(SKETCH)).astype(np.int64), 1)
    at = np.flatnonzero(counts)
    yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(counts[at])], names=["at", "c"])


def _prefixes(shipped, least: tuple[int, int]):
    """Of each set, the rarest shingles that a set similar enough must share one of."""

    def run(batches):
        counts = shipped.value
        for b in batches:
            for part in slices(b, "items", 128, 4 << 20):
                out, rows, sizes, places = [], [], [], []
                for j, x in enumerate(part.column("items")):
                    s = np.frombuffer(x.as_buffer(), np.uint64)
                    keep = len(s) - -(-least[0] * len(s) // least[1]) + 1
                    order = np.lexsort((s, counts[(s % np.uint64(SKETCH)).astype(np.int64)]))[:keep]
                    out.append(s[order].view(np.int64))
                    rows.append(np.full(len(order), j))
                    sizes.append(np.full(len(order), len(s)))
                    places.append(np.arange(len(order)))
                at = pa.array(np.concatenate(rows))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(out)), part.column("cls").take(at), part.column("label").take(at), pa.array(np.concatenate(sizes)), pa.array(np.concatenate(places))], names=["s", "cls", "label", "n", "i"])

    return run


def dense_pairs(dense: DataFrame, sets: DataFrame, least: tuple[int, int]) -> DataFrame | None:
    """Candidate pairs between the components of dense (cls, label), without a miss: two sets that are similar enough
    share one of their rarest shingles (prefix filter). Any order of shingles is right; a sketch of counts makes it a
    good one. Of a shingle's classes, those of its largest component are not joined with each other."""
    spark = dense.sparkSession
    rows = staged(sets.join(dense, "cls"), "dense-sets")
    counts = np.zeros(SKETCH, np.int64)
    for r in rows.select("items").mapInArrow(_frequencies, "at long, c long").groupBy("at").agg(F.sum("c").alias("c")).collect():  # at most SKETCH rows
        counts[r["at"]] = r["c"]
    tokens = staged(rows.select("cls", "label", "items").mapInArrow(_prefixes(spark.sparkContext.broadcast(counts), least), "s long, cls binary, label binary, n long, i long"), "rare-shingles")
    shared = tokens.groupBy("s", "label").agg(F.count("*").alias("m")).groupBy("s").agg(F.max_by("label", "m").alias("top"), F.count("*").alias("labels")).filter("labels > 1").select("s", "top")
    ready = staged(_salted(tokens, "cls", shared, ["s"]), "shared-shingles")
    discard(rows, tokens)
    if ready.isEmpty():
        return None
    x, y = (ready.select("s", *[F.col(c).alias(f"{c}_{k}") for c in ("cls", "n", "label", "i", "top", "salt")]) for k in "ab")
    x = x.filter("label_a <> top_a").withColumn("salt_b", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    # The first shingle that both have leaves room for the overlap that they need; a later one need not.
    room = F.least(F.col("n_a") - F.col("i_a"), F.col("n_b") - F.col("i_b")) * (least[0] + least[1]) >= (F.col("n_a") + F.col("n_b")) * least[0]
    met = x.join(y, ["s", "salt_b"]).filter((F.col("label_a") != F.col("label_b")) & _close(least) & room)
    found = staged(met.select(F.least("cls_a", "cls_b").alias("a"), F.greatest("cls_a", "cls_b").alias("b")).distinct(), "dense-pairs")
    discard(ready)
    return found


def _joined(member: DataFrame, links: DataFrame) -> DataFrame:
    """member (node, label) after links between its labels."""
    to = connected_components(links).select(F.col("node").alias("label"), F.col("label").alias("to"))
    return staged(member.join(to, "label", "left").select("node", F.coalesce("to", "label").alias("label")), "member")


def _classified(docs: DataFrame, width: int, least: tuple[int, int], trees: int, depth: int, shallow: int, few: int) -> tuple[DataFrame, DataFrame]:
    """Rows (doc_id, row, n, cls) of docs, and (cls, label) of the classes, label naming the component."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = staged(docs.select("doc_id", row_key().alias("row"), "text").mapInArrow(_profiler(width, trees, depth), f"doc_id {kind}, row binary, n long, cls binary, sig binary"), "profiles")
    classes = staged(rows.filter("cls is not null").groupBy("cls").agg(F.min("doc_id").alias("rep"), F.any_value("n").alias("n"), F.any_value("sig").alias("sig")), "classes")
    tree = classes.select("cls", "n", "sig", F.explode(F.sequence(F.lit(0), F.lit(trees - 1))).alias("tree"))
    keys = tree.select("tree", F.expr(f"substring(sig, tree * {2 * depth} + 1, {2 * depth})").alias("key"), "cls", "n")
    ordered = keys.repartitionByRange("tree", "key", "cls").sortWithinPartitions("tree", "key", "cls")
    walked = staged(ordered.mapInArrow(_walker(depth, shallow, few), WALK), "walk")
    pairs = staged(walked.filter("a is not null").select("a", "b").union(_over_borders(walked, shallow)).distinct(), "pairs")

    near = staged(pairs.select(F.explode(F.array("a", "b")).alias("cls")).distinct(), "near")
    ids = staged(classes.join(near, "cls", "left_semi").filter("rep is not null").select(F.col("rep").alias("doc_id")).distinct(), "near-ids")
    texts = docs.select("doc_id", "text").join(small(ids), "doc_id", "left_semi").select("text").union(docs.filter("doc_id is null").select("text"))
    sets = texts.mapInArrow(_set_maker(width), "cls binary, items binary").join(near, "cls", "left_semi")
    sets = staged(sets.groupBy("cls").agg(F.any_value("items").alias("items")), "sets")

    links = _confirmed(pairs, sets, least)
    member = _joined(staged(near.select(F.col("cls").alias("node"), F.col("cls").alias("label")), "near-labels"), links)
    side = lambda c: member.select(F.col("node").alias(c), F.col("label").alias(f"label_{c}"))
    opened = walked.filter("edge = 0").select("tree", _prefix(shallow).alias("p"), "cls", "n")
    opened = staged(opened.join(side("cls"), "cls", "left").select("tree", "p", "cls", "n", F.coalesce("label_cls", "cls").alias("label")), "open-regions")
    across = _across(opened, sets, few, least)
    if across is not None:
        late = _confirmed(across, sets, least).join(side("a"), "a").join(side("b"), "b").select(F.col("label_a").alias("a"), F.col("label_b").alias("b"))
        member = _joined(member, late)
        discard(across)
    named = classes.select("cls", "rep").join(member.withColumnRenamed("node", "cls"), "cls", "left").select("cls", "rep", F.coalesce("label", "cls").alias("label"))
    named = staged(named, "members")
    discard(classes, walked, pairs, near, ids, sets, links, opened)
    return rows.drop("sig"), named


def near_duplicates(docs: DataFrame, width: int = WORDS, least: tuple[int, int] = LEAST, trees: int = TREES, depth: int = DEPTH, shallow: int = SHALLOW, few: int = FEW) -> DataFrame:
    """Per row of docs: doc_id, n_shingles, component_id, kept. least: similarity as a fraction (85, 100)."""
    rows, named = _classified(docs, width, least, trees, depth, shallow, few)
    first = named.groupBy("label").agg(F.min("rep").alias("component_id"))
    component = _salted(named, "cls", staged(first, "first-ids"), ["label"]).select("cls", "component_id", F.lit(True).alias("__in"))
    out = rows.join(component, "cls", "left").withColumn("component_id", F.when(F.col("__in"), F.col("component_id")).otherwise(F.col("doc_id")))
    return out.select("doc_id", F.col("n").alias("n_shingles"), "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def keep_one(docs: DataFrame, width: int = WORDS, least: tuple[int, int] = LEAST, **how) -> DataFrame:
    """One row of docs of each group of near duplicates, and the rows without words, with all their columns."""
    rows, named = _classified(docs, width, least, **({"trees": TREES, "depth": DEPTH, "shallow": SHALLOW, "few": FEW} | how))
    grouped = rows.filter("cls is not null").join(named.select("cls", "label"), "cls").select("label", "row", F.struct(F.col("doc_id").isNull().alias("a"), F.col("doc_id").alias("b"), F.col("row").alias("c")).alias("place"))
    best = grouped.groupBy("label").agg(F.min("place").alias("place"), F.count("*").alias("n")).filter("n > 1").select("label", F.col("place.c").alias("stays"))
    many = _salted(grouped.select("label", "row"), "row", staged(best, "stays"), ["label"]).select("row", (F.col("row") == F.col("stays")).alias("stays"))
    many = staged(many.groupBy("row", "stays").agg(F.count("*").alias("n")).filter("not stays or n > 1"), "copies")
    mark = "__row"
    while mark in (c.lower() for c in docs.columns):
        mark += "_"
    keyed = docs.withColumn(mark, row_key())
    out = keyed.join(small(many.select(F.col("row").alias(mark))), mark, "left_anti")
    again = staged(many.filter("stays").select(F.col("row").alias(mark)), "repeated")
    if not again.isEmpty():
        out = out.unionByName(keyed.join(small(again), mark, "left_semi").dropDuplicates([mark]))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])
