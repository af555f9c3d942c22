"""Hashed word and character n-gram features that both classifiers use."""

from __future__ import annotations

from zlib import crc32

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import small, staged

#: Of the ids' CRC-32 remainders by HOLD_OF, the one whose rows are kept out of training.
HOLD_OF, HOLD_AT = 4, 2
#: Bytes of all training texts together at most; a text that does not fit is left out whole, never cut.
MOST_BYTES = 32 << 20
#: Bytes of words whose n-grams are hashed at once.
AT_ONCE = 1 << 18


def held_out(doc_id="doc_id"):
    """Whether a row is kept from training; a null id is (its CRC is null), as it can carry no label either."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % HOLD_OF == HOLD_AT, F.lit(True))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, most: tuple[int, int], most_bytes: int = MOST_BYTES) -> list[tuple[str, int]]:
    """At most most[y] labelled texts of class y, first by a hash of their ids, without held-out rows.

    Texts come whole. In the order of the hash, a text that would take the sum beyond most_bytes is left out, so the
    driver's memory is bounded. Ids labelled both ways are left out; of rows that repeat an id, each counts.
    """
    marked = labels.filter(F.col(label).isin(0, 1) & ~held_out()).groupBy("doc_id").agg(F.min(label).alias("y"), F.max(label).alias("__y")).filter("y = __y").drop("__y")
    ids = None
    for y in (0, 1):
        part = marked.filter(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most[y])
        ids = part if ids is None else ids.union(part)
    text = F.coalesce(F.col("text"), F.lit(""))
    picked = docs.select("doc_id", text.alias("text")).join(small(staged(ids, "sampled")), "doc_id")
    picked = staged(picked.select("doc_id", "y", "text", F.octet_length("text").alias("bytes"), F.xxhash64("doc_id").alias("turn")).withColumn("row", F.monotonically_increasing_id()), "training")
    total, taken = 0, []
    for r in picked.select("row", "bytes", "turn", "doc_id").orderBy("turn", "doc_id", "bytes", "row").toLocalIterator():
        if total + r["bytes"] <= most_bytes:
            total += r["bytes"]
            taken.append(r["row"])
    got = picked.filter(F.col("row").isin(taken)).select("doc_id", "text", "y").toPandas().sort_values(["doc_id", "text"], kind="stable")
    return list(zip(got["text"], got["y"].astype(int)))


def word_buckets(words: list[bytes], buckets: int, seed: int) -> np.ndarray:
    return np.fromiter((crc32(w, seed) for w in words), np.int64, len(words)) % buckets


def _groups(sizes: np.ndarray):
    """(first, last + 1) of stretches of words with about AT_ONCE bytes; a longer word is one alone."""
    ends, at = np.cumsum(sizes), 0
    while at < len(sizes):
        upto = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + AT_ONCE, "right")))
        yield at, upto
        at = upto


def gram_buckets(words: list[bytes], sizes: tuple[int, ...], buckets: int):
    """Buckets of all character n-grams of all words (marked at both ends), and which word each is of, in pieces of
    about AT_ONCE n-grams of each size: a long word goes through whole, in several pieces."""
    for first, last in _groups(np.fromiter(map(len, words), np.int64, len(words)) + 2):
        marked = [b"<" + w + b">" for w in words[first:last]]
        ends = np.cumsum(np.fromiter(map(len, marked), np.int64, len(marked)))
        text = np.frombuffer(b"".join(marked), np.uint8)
        for lo in range(0, len(text), AT_ONCE):
            at = np.arange(lo, min(lo + AT_ONCE, len(text)))
            owner = np.searchsorted(ends, at, "right")
            flat, own = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for n in sizes:
                inside = at + n <= ends[owner]
                here = at[inside]
                h = np.full(len(here), n, np.uint64)
                for j in range(n):
                    h = (h ^ text[here + j]) * np.uint64(0x9E3779B97F4A7C15)
                    h ^= h >> np.uint64(29)
                flat.append(((h >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64))
                own.append(owner[inside] + first)
            yield np.concatenate(flat), np.concatenate(own)


class Vocabulary(dict):
    """Word -> row of arrays that grow with new words; starts anew beyond `most` words or `most_bytes` bytes of them, so
    memory is bounded."""

    def __init__(self, describe, most: int = 100_000, most_bytes: int = 8 << 20):
        super().__init__()
        self.describe, self.most, self.most_bytes, self.bytes, self.rows = describe, most, most_bytes, 0, {}

    def ids(self, words: list[bytes]) -> np.ndarray:
        """Rows of the words; the arrays in .rows hold them until the next call."""
        if len(self) > self.most or self.bytes > self.most_bytes:
            self.clear()
            self.rows, self.bytes = {}, 0
        new = [w for w in set(words) if w not in self]
        if new:
            self.bytes += sum(map(len, new))
            first, last = len(self), len(self) + len(new)
            for k, v in self.describe(new).items():
                a = self.rows.get(k)
                if a is None or last > len(a):
                    grown = np.empty((max(2 * last, 4096), *v.shape[1:]), v.dtype)
                    if first:
                        grown[:first] = a[:first]
                    a = self.rows[k] = grown
                a[first:last] = v
            self.update(zip(new, range(first, last)))
        return np.fromiter(map(self.__getitem__, words), np.int64, len(words))
