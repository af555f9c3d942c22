"""Exact top-k by inner product over a bit-sliced index.

Vectors are quantised to integers; a block of rows keeps, for each dimension, one bitmap a bit of (value - least).
A query adds the slices that its own digits select (shifted by the digit's place, complemented for a negative
digit) with carry-save adders on whole bitmaps, which gives the slices of all scores of the block at once. From the
most significant slice downward the best rows are told apart; rows that tie at the boundary are resolved by the
smaller vec_id. Blocks give their best k each, which a window ranks.

Defined results: a vector that is null, empty, or holds a null or a non-finite component takes no part, as query or
row; a component beyond the range of 53-bit integers when scaled is an error; vectors of other lengths are read as padded with 0; rows that repeat a vec_id are candidates each, and none of
them is a candidate of a query with that id; queries that repeat id and vector are one query; extra columns are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .shared import staged

SCALE, K, EVERY = 256, 5, 50
#: Rows of a block and queries of a batch: a task holds one of either. A block moves once a batch, so what moves is
#: some kilobytes a query and block, against milliseconds of work.
BLOCK_ROWS, BATCH_QUERIES = 32768, 512
INDEX = "block int, ids binary, least binary, widths binary, slices binary"


def quantised(vectors: DataFrame, id_col: str = "vec_id", col: str = "embedding", scale: int = SCALE) -> DataFrame:
    """(vec_id, q array<long>) of the vectors that take part."""
    e = F.col(col)
    fit = F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    good = vectors.select(F.col(id_col).cast("long").alias("vec_id"), e.alias("e")).filter(F.col("vec_id").isNotNull() & e.isNotNull() & (F.size(e) > 0) & fit)
    x = F.transform("e", lambda x: F.floor(x.cast("double") * scale).cast("long"))
    far = F.exists("e", lambda x: F.abs(x.cast("double") * scale) >= float(1 << 53))
    return good.select("vec_id", F.when(far, F.raise_error(F.lit("a component is too large for the index"))).otherwise(x).alias("q"))


def _slice(ids: np.ndarray, values: np.ndarray) -> dict[str, bytes]:
    order = np.argsort(ids, kind="stable")
    ids, values = ids[order], values[order]
    least = values.min(0)
    rest = (values - least).astype(np.uint64)
    widths = np.array([int(x).bit_length() for x in rest.max(0)], np.int64)
    pad = -len(ids) % 64
    rows = [np.packbits(np.pad((rest[:, d] >> np.uint64(b)) & np.uint64(1), (0, pad)).astype(np.uint8), bitorder="little") for d in range(values.shape[1]) for b in range(widths[d])]
    return {"ids": ids.tobytes(), "least": least.tobytes(), "widths": widths.tobytes(), "slices": b"".join(r.tobytes() for r in rows)}


def _blocks(batches):
    """One block of all rows of a partition."""
    ids, vals = [], []
    for b in batches:
        lists = b.column("q")
        sizes = np.diff(lists.offsets.to_numpy())
        flat, at = lists.flatten().to_numpy(), np.concatenate([[0], np.cumsum(sizes)])
        own = b.column("vec_id").to_numpy()
        for lo in range(0, len(own), 4096):
            hi = min(lo + 4096, len(own))
            if (sizes[lo:hi] == sizes[lo]).all():
                part = flat[at[lo] : at[hi]].reshape(hi - lo, -1)
            else:
                part = np.zeros((hi - lo, sizes[lo:hi].max()), np.int64)
                for i in range(lo, hi):
                    part[i - lo, : sizes[i]] = flat[at[i] : at[i + 1]]
            ids.append(own[lo:hi])
            vals.append(part)
    if ids:
        width = max(v.shape[1] for v in vals)
        out = _slice(np.concatenate(ids), np.concatenate([np.pad(v, ((0, 0), (0, width - v.shape[1]))) for v in vals]))
        yield pa.RecordBatch.from_pydict({"block": pa.array([TaskContext.get().partitionId()], pa.int32()), **{k: pa.array([v], pa.binary()) for k, v in out.items()}})


def build_index(rows: DataFrame, n_rows: int) -> DataFrame:
    """A written table with one row a block. Rows are dealt evenly, whatever their ids."""
    return staged(rows.repartition(max(1, -(-n_rows // BLOCK_ROWS))).mapInArrow(_blocks, INDEX), "bit-slices")


def signed_digits(x: int) -> list[tuple[int, int]]:
    """(place, sign) of the non-adjacent form, which has the fewest digits."""
    out, place = [], 0
    while x:
        if x & 1:
            d = 2 - (x & 3)
            out.append((place, d))
            x -= d
        x >>= 1
        place += 1
    return out


class Block:
    def __init__(self, row: dict):
        self.ids = np.frombuffer(row["ids"], np.int64)
        self.least, self.widths = np.frombuffer(row["least"], np.int64), np.frombuffer(row["widths"], np.int64)
        words = -(-len(self.ids) // 64)
        self.slices = np.frombuffer(row["slices"], np.uint64).reshape(-1, words)
        self.first = np.concatenate([[0], np.cumsum(self.widths)])
        self.all = np.zeros(words, np.uint64)
        self._put(self.all, 0, len(self.ids))

    @staticmethod
    def _put(bits: np.ndarray, lo: int, hi: int, value: int = 1) -> None:
        flags = np.unpackbits(bits.view(np.uint8), bitorder="little")
        flags[lo:hi] = value
        bits[:] = np.packbits(flags, bitorder="little").view(np.uint64)

    def scores(self, q: np.ndarray) -> tuple[list[np.ndarray], int]:
        """Slices of the sum over all rows, least significant first, and what to add to it for the score."""
        plus: dict[int, list[int]] = {}
        minus: dict[int, list[int]] = {}
        base = 0
        for d in range(min(len(q), len(self.widths))):
            x, w = int(q[d]), int(self.widths[d])
            base += x * int(self.least[d])
            for place, sign in signed_digits(x):
                side = plus if sign > 0 else minus
                for b in range(w):
                    side.setdefault(place + b, []).append(self.first[d] + b)
                if sign < 0:
                    base -= ((1 << w) - 1) << place
        out, carried, place = [], [], 0
        top = max([*plus, *minus], default=-1)
        while place <= top or carried:
            parts = [self.slices[plus[place]]] if place in plus else []
            if place in minus:
                parts.append(~self.slices[minus[place]])
            m = np.concatenate(parts + carried) if parts or carried else np.zeros((1, len(self.all)), np.uint64)
            carried = []
            while len(m) > 1:
                t = len(m) // 3
                if t:
                    a, b, c = m[:t], m[t : 2 * t], m[2 * t : 3 * t]
                    ab = a ^ b
                    carried.append((a & b) | (c & ab))
                    m = np.concatenate([ab ^ c, m[3 * t :]])
                else:
                    carried.append((m[0] & m[1])[None])
                    m = (m[0] ^ m[1])[None]
            out.append(m[0])
            place += 1
        return out, base

    def best(self, query_id: int, q: np.ndarray, k: int) -> tuple[np.ndarray, list[int]]:
        """Rows of the k highest scores (ties: smaller vec_id) and their scores."""
        slices, base = self.scores(q)
        tied, sure = self.all.copy(), np.zeros_like(self.all)
        lo, hi = np.searchsorted(self.ids, query_id, "left"), np.searchsorted(self.ids, query_id, "right")
        if hi > lo:
            self._put(tied, lo, hi, 0)
        for s in reversed(slices):
            more = sure | (tied & s)
            n = int(np.bitwise_count(more).sum())
            if n > k:
                tied &= s
            else:
                sure, tied = more, tied & ~s
                if n == k:
                    break
        rows = np.flatnonzero(np.unpackbits(sure.view(np.uint8), bitorder="little"))
        if len(rows) < k:
            rows = np.concatenate([rows, np.flatnonzero(np.unpackbits(tied.view(np.uint8), bitorder="little"))[: k - len(rows)]])
        word, bit = rows >> 6, (rows & 63).astype(np.uint64)
        total = [base] * len(rows)
        for p, s in enumerate(slices):
            for i in np.flatnonzero((s[word] >> bit) & np.uint64(1)):
                total[i] += 1 << p
        return rows, total


def _searcher(k: int):
    names = ("query_id", "query_key", "vec_id", "score")

    def run(batches):
        """Rows in order of (block, batch): a batch's queries, then the block."""
        at, asked = None, []
        for b in batches:
            for i in range(0, b.num_rows, 256):
                for row in b.slice(i, 256).to_pylist():
                    if (row["block"], row["batch"]) != at:
                        at, asked = (row["block"], row["batch"]), []
                    if row["ids"] is None:
                        asked.append((row["vec_id"], row["key"], np.array(row["q"], np.int64)))
                        continue
                    block, out = Block(row), []
                    for query, key, q in asked:
                        rows, scores = block.best(query, q, k)
                        out += [(query, key, int(block.ids[r]), x) for r, x in zip(rows, scores)]
                    cols = list(zip(*out)) or [[]] * 4
                    yield pa.RecordBatch.from_pydict({n: pa.array(list(c), pa.int64()) for n, c in zip(names, cols)})

    return run


def search_index(index: DataFrame, n_blocks: int, queries: DataFrame, n_queries: int, k: int = K) -> DataFrame:
    """queries (vec_id, q) against every block, in batches: a task takes a batch's queries and then the block."""
    n = max(1, -(-n_queries // BATCH_QUERIES))
    every = lambda m: F.explode(F.sequence(F.lit(0), F.lit(m - 1)))
    none = [F.lit(None).cast("binary").alias(c) for c in ("ids", "least", "widths", "slices")]
    batch = F.pmod(F.xxhash64("vec_id", "q"), F.lit(n)).cast("int").alias("batch")
    asked = queries.dropDuplicates(["vec_id", "q"]).select(every(n_blocks).alias("block"), batch, "vec_id", F.xxhash64("q").alias("key"), "q", *none)
    null = lambda kind, name: F.lit(None).cast(kind).alias(name)
    blocks = index.select("block", every(n).alias("batch"), null("long", "vec_id"), null("long", "key"), null("array<long>", "q"), "ids", "least", "widths", "slices")
    dealt = asked.unionByName(blocks).repartition(max(1, min(n * n_blocks, 10_000)), "block", "batch").sortWithinPartitions("block", "batch", F.col("ids").isNotNull())
    found = dealt.mapInArrow(_searcher(k), "query_id long, query_key long, vec_id long, score long")
    best = Window.partitionBy("query_id", "query_key").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def top_k(vectors: DataFrame, every: int = EVERY, k: int = K, is_query: Column | None = None) -> DataFrame:
    """The k best other rows of each query row: query_id, rank, vec_id, score."""
    rows = quantised(vectors)
    wanted = F.col("vec_id") % every == 0 if is_query is None else is_query
    n, n_queries = rows.agg(F.count("*"), F.count_if(wanted)).first()
    return search_index(build_index(rows, n), max(1, -(-n // BLOCK_ROWS)), rows.filter(wanted), n_queries, k)
