"""Benchmark decontamination by shared word windows, in DataFrame functions only.

A window is `span` consecutive words of a benchmark item (a shorter item is one window). Any window that occurs in
a document covers one chunk of half a window that starts at a multiple of that half. So a scan hashes each word
once, into aligned chunks, and tests them against a broadcast bit set of the items' half windows; only documents
with a hit build their full windows, test them against a second bit set, and verify by joining on the words.

Defined results: null and empty texts have no words and are clean; repeated rows are judged each; a null item_id
still marks hits but is not counted as an item; items repeated under one id count once; an empty benchmark leaves
every document clean; extra columns are ignored (scan_documents) or kept (remove_contaminated).
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import small, staged

SPAN = 13
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: The separators one by one: single characters are a table lookup to the pattern engine, ranges are not.
_NOT_WORD = "".join(rf"\x{c:02X}" for c in [*range(0x30), *range(0x3A, 0x41), *range(0x5B, 0x61), *range(0x7B, 0x80)])
ANY_CASE, SEPARATOR, SEPARATORS = f"[^{_NOT_WORD}]+", f"[{_NOT_WORD}]", f"[{_NOT_WORD}]+"
#: Most blocks of a bit set; it is bounded whatever the benchmark's size, and a full one only filters less.
MAX_BLOCKS = 1 << 17


def _words(text: Column) -> Column:
    lowered = F.translate(F.coalesce(text, F.lit("")), string.ascii_uppercase, string.ascii_lowercase)
    return F.regexp_extract_all(lowered, F.lit(WORD), F.lit(0))


def _rough_words(text: Column) -> Column:
    """The same words upper-cased throughout: quicker to make, and equal wherever the exact words are equal."""
    return F.array_remove(F.split(F.upper(F.coalesce(text, F.lit(""))), SEPARATORS), "")


def _grams(words: Column, length: int, step: int, make) -> Column:
    n = F.size(words)
    starts = F.sequence(F.lit(1), n - (length - 1), F.lit(step))
    return F.when(n >= length, F.transform(starts, lambda i: make(i, F.slice(words, i, length)))).otherwise(F.array())


class BitSet:
    """A blocked Bloom filter of hashed grams: a literal array of at most MAX_BLOCKS longs, three bits a gram in one."""

    def __init__(self, hashes: DataFrame, column: str):
        n = hashes.count()
        self.mask = min(MAX_BLOCKS, 1 << n.bit_length()) - 1
        block, bits = self._at(F.col(column))
        words = [0] * (self.mask + 1)
        for i, b in hashes.groupBy(block.alias("i")).agg(F.bit_or(bits)).collect():
            words[i] = b
        self.array = F.split(F.lit(",".join(map(str, words))), ",").cast("array<bigint>")

    def _at(self, h: Column) -> tuple[Column, Column]:
        bit = lambda k: F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftright(h, k).bitwiseAND(63).cast("int"))
        return F.shiftright(h, 20).bitwiseAND(self.mask).cast("int"), bit(0).bitwiseOR(bit(6)).bitwiseOR(bit(12))

    def has(self, h: Column) -> Column:
        block, bits = self._at(h)
        return F.get(self.array, block).bitwiseAND(bits) == bits


def benchmark_windows(bench: DataFrame, span: int = SPAN) -> DataFrame:
    """Distinct (item_id, n, gram, rough): the items' windows, and their words in upper case for the first test."""
    items = bench.select("item_id", _words(F.col("text")).alias("w"), _rough_words(F.col("text")).alias("u")).filter("size(w) > 0")
    n = F.least(F.size("w"), F.lit(span))
    rows = items.select("item_id", "w", "u", n.alias("n")).select(
        "item_id", "n", F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - F.col("n") + 1), lambda i: F.struct(F.array_join(F.slice("w", i, F.col("n")), " ").alias("gram"), F.slice("u", i, F.col("n")).alias("rough")))).alias("x")
    )
    return rows.select("item_id", "n", "x.gram", "x.rough").distinct()


def _scan(docs: DataFrame, windows: DataFrame, keep: list[str]) -> DataFrame:
    """Rows of docs with n_words and hits, an array of (pos, n, gram) that pass both bit sets; null if none can be."""
    lengths = sorted(r[0] for r in windows.select("n").distinct().collect())
    words, text = F.col("__w"), F.col("text")
    rows = docs.select(*[F.col(f"`{c}`") for c in keep], text.alias("text"), _rough_words(text).alias("__w"))
    n_words = F.size(words).cast("long").alias("n_words")
    if not lengths:
        return rows.select(*keep, n_words, F.lit(None).cast("array<struct<pos:int,n:int,gram:string>>").alias("hits"))
    half = {n: (n + 1) // 2 for n in lengths}
    parts = [windows.filter(F.col("n") == n).select(F.explode(_grams(F.col("rough"), k, 1, lambda _, g, n=n: F.xxhash64(F.lit(n), g))).alias("h")) for n, k in half.items()]
    halves = parts[0]
    for p in parts[1:]:
        halves = halves.union(p)
    first, second = BitSet(halves.distinct(), "h"), BitSet(windows.select(F.xxhash64("gram").alias("h")).distinct(), "h")
    near = None
    for n, k in half.items():
        found = F.exists(_grams(words, k, k, lambda _, g, n=n: F.xxhash64(F.lit(n), g)), first.has)
        near = found if near is None else near | found
    exact = _words(text)
    full = [_grams(F.col("__x"), n, 1, lambda i, g, n=n: F.struct(i.alias("pos"), F.lit(n).alias("n"), F.array_join(g, " ").alias("gram"))) for n in lengths]
    hits = F.filter(F.concat(*full) if len(full) > 1 else full[0], lambda s: second.has(F.xxhash64(s["gram"])))
    rows = rows.select(*keep, n_words, F.when(near, exact).alias("__x"))
    return rows.select(*keep, "n_words", F.when(F.col("__x").isNotNull(), hits).alias("hits"))


def _judged(docs: DataFrame, bench: DataFrame, span: int, keep: list[str]) -> DataFrame:
    windows = staged(benchmark_windows(bench, span), "bench-windows")
    scanned = _scan(docs, windows, keep).withColumn("__row", F.monotonically_increasing_id())
    grams = windows.groupBy("gram").agg(F.collect_set("item_id").alias("items"))
    hit = scanned.select("__row", *keep, "n_words", F.explode_outer("hits").alias("s"))
    hit = hit.join(small(grams), F.col("s.gram") == F.col("gram"), "left")
    real = F.when(F.col("gram").isNotNull(), F.struct("s.pos", "s.n"))
    out = hit.groupBy("__row").agg(*[F.first(c).alias(c) for c in keep], F.first("n_words").alias("n_words"), F.collect_set(real).alias("__spans"), F.array_distinct(F.flatten(F.collect_set("items"))).alias("__items"))
    covered = F.array_distinct(F.flatten(F.transform("__spans", lambda s: F.sequence(s["pos"], s["pos"] + s["n"] - 1))))
    names = F.array_sort(F.transform("__items", lambda x: x.cast("string")))
    out = out.select(*keep, "n_words", covered.alias("positions"), F.size(covered).cast("long").alias("n_hit"), F.size("__items").cast("long").alias("n_items"), F.sha2(F.array_join(names, ","), 256).alias("items_sha256"))
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (F.col("n_hit") * 20 >= F.col("n_words")))


def scan_documents(docs: DataFrame, bench: DataFrame, span: int = SPAN) -> DataFrame:
    """Per row of docs: doc_id, n_words, n_hit, n_items, items_sha256, contaminated."""
    return _judged(docs, bench, span, ["doc_id"]).drop("positions")


def remove_contaminated(docs: DataFrame, bench: DataFrame, span: int = SPAN, mode: str = "documents") -> DataFrame:
    """docs without contaminated documents (mode 'documents'), or with the hit words and what follows each up to the
    next word cut out of contaminated ones (mode 'spans'). Columns stay as they are."""
    if mode not in ("documents", "spans"):
        raise ValueError("mode is 'documents' or 'spans'")
    tag = F.xxhash64(F.col("text")).alias("__tag")
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__doc"), "doc_id", "text", tag)
    bad = staged(_judged(docs.select("doc_id", "text", tag), bench, span, ["doc_id", "__tag"]).filter("contaminated").select(F.col("doc_id").alias("__id"), F.col("__tag").alias("__t"), "positions").dropDuplicates(["__id", "__t"]), "contaminated")
    same = F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__tag") == F.col("__t"))
    if mode == "documents":
        return keyed.join(small(bad), same, "left_anti").select("__doc.*")
    pieces = F.regexp_extract_all("text", F.lit(f"{ANY_CASE}{SEPARATOR}*"), F.lit(0))
    head = F.regexp_extract("text", f"^{SEPARATOR}*", 0)
    cut = F.concat(head, F.array_join(F.filter(pieces, lambda p, i: ~F.array_contains(F.col("positions"), i + 1)), ""))
    mended = keyed.join(small(bad), same, "left").select("__doc", F.when(F.col("positions").isNull(), F.col("text")).otherwise(cut).alias("__text"))
    return mended.select(*[(F.col("__text") if c == "text" else F.col(f"__doc.`{c}`")).alias(c) for c in docs.columns])
