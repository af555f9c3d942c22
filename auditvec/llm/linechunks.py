"""Line dedup by content-defined chunks and windows.

A rolling hash over the last lines' hashes cuts a text into chunks where the hash says so, so an insertion shifts no
later boundary. Beside them stand windows: from each line on, and up to each line, the fewest whole lines with
LONG_WORDS words together. A run of lines of so many words that occurs at two places has equal windows there, and
these cover all its lines: up to the line that fills LONG_WORDS, the window from its first line; every later line, the
window up to it. So each line of each maximal repeated run is found, whatever stands beside the run.

Windows, and shorter chunks of several lines, that occur again anywhere are removed after their bytes are compared
with those of the first occurrence (the least doc_id, then position), which stays; where the two overlap in a text,
the lines of the first one stay. Of the repeated windows of a text, the fewest that cover the same lines are compared.

Defined results: null texts read as empty and stay empty; an empty text is one empty line; rows that repeat id and
text are one occurrence and are all treated alike; ties between rows without id go to the smaller text digest;
removed_chunks counts unbroken stretches of removed lines; other columns are ignored.
"""

from __future__ import annotations

from itertools import accumulate

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import row_key, slices, small, staged

#: Lines under the rolling hash; one line in CUT ends a chunk on average; words that make a line long.
ROLL, CUT, LONG_WORDS = 2, 3, 50
CHUNK = "row binary, doc_id {}, line int, n_lines int, hash binary"


def chunks(text: str, roll: int = ROLL, cut: int = CUT, long_words: int = LONG_WORDS) -> list[tuple[int, int, bytes]]:
    """(first line, lines, bytes) of the chunks of a text; they join to the text with line breaks between."""
    lines = text.encode(errors="surrogatepass").split(b"\n")
    long = [len(x.split()) >= long_words for x in lines]
    hashes = [xxhash.xxh64_intdigest(x) for x in lines]
    out, begin, mask = [], 0, (1 << 64) - 1
    for i in range(len(lines)):
        rolled = 0
        for j in range(max(0, i - roll + 1), i + 1):
            rolled = (rolled * 0x9E3779B97F4A7C15 + hashes[j]) & mask
        last = i + 1 == len(lines)
        if last or long[i] or long[i + 1] or (rolled >> 32) % cut == 0:
            out.append((begin, i + 1 - begin, b"\n".join(lines[begin : i + 1])))
            begin = i + 1
    return out


def windows(sizes: list[int], long_words: int = LONG_WORDS) -> set[tuple[int, int]]:
    """(first line, line after the last) of the fewest lines with long_words words, from each line and up to each line.
    sizes: words of each line."""
    out, end, total = set(), 0, 0
    for i, n in enumerate(sizes):
        while total < long_words and end < len(sizes):
            total += sizes[end]
            end += 1
        if total < long_words:
            break
        out.add((i, end))
        total -= n
    begin, total = 0, 0
    for j, n in enumerate(sizes):
        total += n
        while total - sizes[begin] >= long_words:
            total -= sizes[begin]
            begin += 1
        if total >= long_words:
            out.add((begin, j + 1))
    return out


def candidates(text: str, roll: int = ROLL, cut: int = CUT, long_words: int = LONG_WORDS):
    """(first line, lines, bytes) of what is removed if it occurs again, one after the other: windows, and shorter
    chunks of several lines with some word."""
    data = text.encode(errors="surrogatepass")
    lines = data.split(b"\n")
    ends = list(accumulate((len(x) + 1 for x in lines), initial=0))
    for i, e in windows([len(x.split()) for x in lines], long_words):
        yield i, e - i, data[ends[i] : ends[e] - 1]
    for i, n, body in chunks(text, roll, cut, long_words):
        if n > 1 and 0 < len(body.split()) < long_words:
            yield i, n, body


def _cutter(roll: int, cut: int, long_words: int):
    kinds = [pa.int32(), pa.int32(), pa.int32(), pa.binary()]

    def table(part, rows):
        at, *rest = (pa.array(list(c), k) for c, k in zip(zip(*rows), kinds))
        return pa.RecordBatch.from_arrays([part.column("row").take(at), part.column("doc_id").take(at), *rest], names=["row", "doc_id", "line", "n_lines", "hash"])

    def run(batches):
        for b in batches:
            for part in slices(b, "text", 1024):
                rows = []
                for i, text in enumerate(part.column("text")):
                    for line, n, body in candidates(text.as_py(), roll, cut, long_words):
                        rows.append((i, line, n, xxhash.xxh128_digest(body)))
                        if len(rows) == 100_000:
                            yield table(part, rows)
                            rows = []
                if rows:
                    yield table(part, rows)

    return run


def cover(parts: list[dict]) -> list[dict]:
    """The fewest parts (begin, end) whose lines are the lines of all parts."""
    out, upto, best = [], -1, None
    for x in sorted(parts, key=lambda x: x["begin"]):
        if best is not None and x["begin"] > upto:
            out.append(best)
            upto, best = best["end"], None
        if best is None:
            upto = max(upto, x["begin"])
        if x["end"] > upto and (best is None or x["end"] > best["end"]):
            best = x
    return out if best is None else [*out, best]


def _coverer(batches):
    for b in batches:
        yield pa.RecordBatch.from_arrays([b.column("row"), pa.array([cover(x) for x in b.column("parts").to_pylist()], b.column("parts").type)], names=["row", "parts"])


def _bodies(batches):
    """(hash, row, begin, end, body) of the parts of each text."""
    names = ["hash", "row", "begin", "end", "body"]
    kinds = [pa.binary(), pa.binary(), pa.int32(), pa.int32(), pa.binary()]
    for b in batches:
        rows, held = [], 0
        for row, text, parts in zip(b.column("row").to_pylist(), b.column("text"), b.column("parts")):
            data, parts = text.as_py().encode(errors="surrogatepass"), parts.as_py()
            ends = list(accumulate((len(x) + 1 for x in data.split(b"\n")), initial=0))
            for x in parts:
                body = data[ends[x["line"]] : ends[x["line"] + x["n_lines"]] - 1]
                rows.append((x["hash"], row, x["begin"], x["end"], body))
                held += len(body)
                if held > 8_000_000:
                    yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*rows), kinds)], names=names)
                    rows, held = [], 0
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*rows), kinds)], names=names)


def repeated_lines(docs: DataFrame, roll: int = ROLL, cut: int = CUT, long_words: int = LONG_WORDS) -> DataFrame:
    """Staged rows (row, lines): per text with repeats, the line numbers to remove in order."""
    rows = docs.select("row", "doc_id", "text")
    kind = docs.schema["doc_id"].dataType.simpleString()
    place = F.struct(F.col("doc_id").isNull().alias("a"), F.col("doc_id").alias("b"), F.col("row").alias("c"), F.col("line").alias("d"))
    every = rows.mapInArrow(_cutter(roll, cut, long_words), CHUNK.format(kind))
    # min and max over places tell a repeat from equal rows, without keeping the places.
    again = staged(every.groupBy("hash").agg(F.min(place).alias("first"), F.max(place).alias("last")).filter("first <> last").select("hash", "first"), "repeated-chunks")
    hit = every.join(small(again), "hash").filter(place != F.col("first"))
    begin = F.when(F.col("row") == F.col("first.c"), F.greatest("line", F.col("first.d") + F.col("n_lines"))).otherwise(F.col("line"))
    hit = hit.select("row", "hash", "line", "n_lines", begin.cast("int").alias("begin"), (F.col("line") + F.col("n_lines")).cast("int").alias("end"), F.col("first.c").alias("at"), F.col("first.d").alias("at_line")).filter("begin < end").distinct()
    part = F.struct("hash", "line", "n_lines", "begin", "end", "at", "at_line")
    shape = "array<struct<hash:binary,line:int,n_lines:int,begin:int,end:int,at:binary,at_line:int>>"
    chosen = staged(hit.groupBy("row").agg(F.collect_list(part).alias("parts")).mapInArrow(_coverer, f"row binary, parts {shape}"), "chosen")
    flat = chosen.select(F.explode("parts").alias("x")).select(F.col("x.at").alias("row"), F.col("x.hash").alias("hash"), F.col("x.at_line").alias("line"), F.col("x.n_lines").alias("n_lines")).distinct()
    part = F.struct("hash", "line", "n_lines", F.col("line").alias("begin"), F.col("line").alias("end"))
    first = staged(flat.groupBy("row").agg(F.collect_list(part).alias("parts")), "first-places")
    shape = "hash binary, row binary, begin int, end int, body binary"
    texts = rows.select("row", "text")
    owners = texts.join(small(first), "row").mapInArrow(_bodies, shape).groupBy("hash").agg(F.any_value("body").alias("kept"))
    copies = texts.join(small(chosen), "row").mapInArrow(_bodies, shape)
    same = copies.join(owners, "hash").filter(F.col("body") == F.col("kept")).select("row", "begin", "end").distinct()
    lines = F.array_sort(F.array_distinct(F.flatten(F.collect_list(F.sequence(F.col("begin"), F.col("end") - 1)))))
    return staged(same.groupBy("row").agg(lines.alias("lines")), "repeated-lines")


def dedup_lines(docs: DataFrame, roll: int = ROLL, cut: int = CUT, long_words: int = LONG_WORDS) -> DataFrame:
    """Per row: doc_id, n_lines, removed_lines, removed_chunks, text without the repeated chunks."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", text.alias("text"), row_key().alias("row"))
    gone = repeated_lines(rows, roll, cut, long_words)
    stretches = F.size(F.filter("lines", lambda x, i: (i == 0) | (F.get("lines", i - 1) != x - 1)))
    gone = gone.select("row", "lines", stretches.alias("chunks"))
    out = rows.join(small(gone), "row", "left").withColumn("all", F.split("text", "\n", -1))
    left = F.array_except(F.sequence(F.lit(0), F.size("all") - 1), F.col("lines"))
    cut_text = F.when(F.col("lines").isNull(), F.col("text")).otherwise(F.array_join(F.transform(left, lambda i: F.get("all", i)), "\n"))
    return out.select("doc_id", F.size("all").cast("long").alias("n_lines"), F.coalesce(F.size("lines"), F.lit(0)).cast("long").alias("removed_lines"), F.coalesce("chunks", F.lit(0)).cast("long").alias("removed_chunks"), cut_text.alias("text"))
