"""Arrow kernels for distances to a broadcast table of bounded size.

Integers are multiplied as doubles: all terms are below 2^53 for the fixed-point range, so results are exact.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bytes of a table (centroids, codebooks) that may be broadcast to the kernels.
TABLE_BYTES = 256 << 20


def checked(table: np.ndarray) -> np.ndarray:
    if table.nbytes > TABLE_BYTES:
        raise ValueError(f"{table.nbytes} bytes are too many to broadcast; use fewer lists or a two-level partition")
    return table


def matrix(col, dims: int) -> np.ndarray:
    col = col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col
    return col.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dims)


def distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return (x * x).sum(1)[:, None] + (c * c).sum(1)[None, :] - 2.0 * (x @ c.T)


def least(d: np.ndarray, k: int | None) -> np.ndarray:
    """Places of the k least of each row, equal ones in order; only what is at most the k-th least is sorted."""
    if k is None or 4 * k >= d.shape[1]:
        return np.argsort(d, 1, kind="stable")[:, :k]
    edge, out = np.partition(d, k - 1, 1)[:, k - 1], np.empty((len(d), k), np.int64)
    for i, row in enumerate(d):
        some = np.flatnonzero(row <= edge[i])
        out[i] = some[np.argsort(row[some], kind="stable")[:k]]
    return out


def nearest(df: DataFrame, col: str, table: np.ndarray, keep: list[str], exact: bool = True, step: int = 4096) -> DataFrame:
    """keep columns, list_id and dist of the nearest row of table (ties: the smaller index)."""
    shipped = df.sparkSession.sparkContext.broadcast(checked(table))
    dims = table.shape[1]
    kind = "long" if exact else "double"

    def run(batches):
        c = shipped.value
        for b in batches:
            for at in range(0, b.num_rows, step):
                part = b.slice(at, step)
                d = distances(matrix(part.column(col), dims), c)
                i = d.argmin(1)
                best = d[np.arange(len(i)), i]
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in keep), pa.array(i.astype(np.int32)), pa.array(best.astype(np.int64) if exact else np.maximum(best, 0))], names=[*keep, "list_id", "dist"])

    schema = ", ".join([*(f"`{k}` {df.schema[k].dataType.simpleString()}" for k in keep), "list_id int", f"dist {kind}"])
    return df.select(*dict.fromkeys([*keep, col])).mapInArrow(run, schema)


def all_distances(df: DataFrame, id_col: str, col: str, table: np.ndarray, exact: bool = True) -> DataFrame:
    """(id, list_id, dist) for every row of table."""
    shipped = df.sparkSession.sparkContext.broadcast(checked(table))
    dims, n = table.shape[1], table.shape[0]

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                d = distances(matrix(part.column(col), dims), shipped.value)
                ids = part.column(id_col).to_numpy()
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, n)), pa.array(np.tile(np.arange(n, dtype=np.int32), len(ids))), pa.array(d.ravel().astype(np.int64) if exact else d.ravel())], names=[id_col, "list_id", "dist"])

    return df.select(id_col, col).mapInArrow(run, f"{id_col} long, list_id int, dist {'long' if exact else 'double'}")


def nearest_lists(df: DataFrame, table: np.ndarray, n: int, exact: bool = True) -> DataFrame:
    """(query_id, rank, list_id, dist, q) of the n nearest rows of table, ties to the smaller index: only those leave
    the task. df: (query_id, q)."""
    shipped = df.sparkSession.sparkContext.broadcast(checked(table))
    dims, kind = table.shape[1], df.schema["q"].dataType.simpleString()

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                d = distances(matrix(part.column("q"), dims), shipped.value)
                i = np.argsort(d, 1, kind="stable")[:, :n]
                best = np.take_along_axis(d, i, 1).ravel()
                of = pa.array(np.repeat(np.arange(part.num_rows), i.shape[1]))
                rank = np.tile(np.arange(1, i.shape[1] + 1, dtype=np.int32), part.num_rows)
                yield pa.RecordBatch.from_arrays([part.column("query_id").take(of), pa.array(rank), pa.array(i.ravel().astype(np.int32)), pa.array(best.astype(np.int64) if exact else np.maximum(best, 0)), part.column("q").take(of)], names=["query_id", "rank", "list_id", "dist", "q"])

    return df.select("query_id", "q").mapInArrow(run, f"query_id {df.schema['query_id'].dataType.simpleString()}, rank int, list_id int, dist {'long' if exact else 'double'}, q {kind}")


def meet(probes: DataFrame, rows: DataFrame, prepare, score, schema: str, parts: int | None = None) -> DataFrame:
    """Let each probe (list_id, salt, query_id, q) meet the rows (list_id, salt, ...) of its list.

    Both are dealt by (list_id, salt) and come to a task in order, a list's rows first: prepare(table of the rows) is
    made once, then score(list_id, prepared, batch of probes) gives record batches. No row is copied per probe. parts:
    partitions that both are dealt to, where few rows make much work.
    """
    own = [c for c in rows.columns if c not in ("list_id", "salt")]
    asked = [c for c in probes.columns if c not in ("list_id", "salt")]
    null = lambda df, c: F.lit(None).cast(df.schema[c].dataType).alias(c)
    a = rows.select("list_id", "salt", F.lit(0).alias("kind"), *[null(probes, c) for c in asked], *own)
    b = probes.select("list_id", "salt", F.lit(1).alias("kind"), *asked, *[null(rows, c) for c in own])
    both = a.unionByName(b).repartition(*([] if parts is None else [parts]), "list_id", "salt").sortWithinPartitions("list_id", "salt", "kind")

    def run(batches):
        key, held, ready = None, [], None
        for b in batches:
            if not b.num_rows:
                continue
            place = np.stack([b.column(c).to_numpy() for c in ("list_id", "salt", "kind")]).astype(np.int64)
            cuts = np.flatnonzero((place[:, 1:] != place[:, :-1]).any(0)) + 1
            for lo, hi in zip([0, *cuts], [*cuts, b.num_rows]):
                if tuple(place[:2, lo]) != key:
                    key, held, ready = tuple(place[:2, lo]), [], None
                part = b.slice(lo, hi - lo)
                if place[2, lo] == 0:
                    held.append(part)
                elif held:
                    if ready is None:
                        ready = prepare(pa.Table.from_batches(held).select(own))
                    yield from score(int(key[0]), ready, part)

    return both.mapInArrow(run, schema)


def block_sums(df: DataFrame, col: str, words: np.ndarray) -> DataFrame:
    """partial_sums of every block at once; list_id is block * codes + code. words: (blocks, codes, width)."""
    shipped = df.sparkSession.sparkContext.broadcast(checked(words))
    blocks, codes, width = words.shape

    def run(batches):
        sums, n = np.zeros((blocks, codes, width)), np.zeros((blocks, codes), np.int64)
        for b in batches:
            for at in range(0, b.num_rows, 4096):
                x = matrix(b.slice(at, 4096).column(col), blocks * width).reshape(-1, blocks, width)
                for m in range(blocks):
                    i = distances(x[:, m], shipped.value[m]).argmin(1)
                    np.add.at(sums[m], i, x[:, m])
                    n[m] += np.bincount(i, minlength=codes)
        flat, n = sums.reshape(-1, width), n.ravel()
        for i in np.flatnonzero(n):
            yield pa.RecordBatch.from_arrays([pa.array([int(i)], pa.int32()), pa.array([int(n[i])], pa.int64()), pa.array([flat[i]], pa.list_(pa.float64()))], names=["list_id", "n", "sums"])

    return _summed(df.select(col).mapInArrow(run, SUMS))


SUMS = "list_id int, n long, sums array<double>"


def _summed(parts: DataFrame) -> DataFrame:
    by_place = parts.select("list_id", "n", F.posexplode("sums").alias("pos", "x")).groupBy("list_id", "pos").agg(F.sum("n").alias("n"), F.sum("x").alias("x"))
    return by_place.groupBy("list_id").agg(F.first("n").alias("n"), F.transform(F.array_sort(F.collect_list(F.struct("pos", "x"))), lambda s: s["x"]).alias("sums"))


def partial_sums(df: DataFrame, col: str, table: np.ndarray) -> DataFrame:
    """(list_id, n, sums) of the members nearest to each row of table: summed within a task, then over the tasks."""
    shipped = df.sparkSession.sparkContext.broadcast(checked(table))
    k, dims = table.shape

    def run(batches):
        sums, n = np.zeros((k, dims)), np.zeros(k, np.int64)
        for b in batches:
            for at in range(0, b.num_rows, 4096):
                x = matrix(b.slice(at, 4096).column(col), dims)
                i = distances(x, shipped.value).argmin(1)
                np.add.at(sums, i, x)
                n += np.bincount(i, minlength=k)
        for i in np.flatnonzero(n):
            yield pa.RecordBatch.from_arrays([pa.array([int(i)], pa.int32()), pa.array([int(n[i])], pa.int64()), pa.array([sums[i]], pa.list_(pa.float64()))], names=["list_id", "n", "sums"])

    return _summed(df.select(col).mapInArrow(run, SUMS))
