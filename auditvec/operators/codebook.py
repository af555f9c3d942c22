"""Product quantisation of residuals."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.vectors import split_blocks, sqdist
from ..session import rows_frame
from . import kernels


def stride_codebooks(resid: DataFrame, blocks: int, codes: int, width: int) -> DataFrame:
    """Codewords are the blocks of every t-th residual by vec_id, t = count div codes."""
    stride = max(1, resid.count() // codes)
    at = F.row_number().over(Window.orderBy("vec_id")) - 1
    ids = resid.select("vec_id", at.alias("i")).filter((F.col("i") % stride == 0) & (F.col("i") < stride * codes))
    rows = resid.join(F.broadcast(ids), "vec_id").select((F.col("i") / stride).cast("int").alias("code"), F.posexplode(split_blocks(F.col("resid"), blocks, width)).alias("m", "word"))
    return rows.select("m", "code", "word")


def hash_codebooks(resid: DataFrame, blocks: int, codes: int, width: int, seed: int = 0) -> DataFrame:
    """Codewords are the blocks of the residuals that come first by a hash of their ids: no global numbering."""
    picked = resid.select("vec_id", "resid").orderBy(F.xxhash64(F.lit(seed), F.col("vec_id")), "vec_id").limit(codes).collect()
    rows = [(m, c, list(r["resid"][m * width : (m + 1) * width])) for c, r in enumerate(picked) for m in range(blocks)]
    return rows_frame(resid.sparkSession, rows, f"m int, code int, word {resid.schema['resid'].dataType.simpleString()}")


def train_codebooks(resid: DataFrame, blocks: int, codes: int, width: int, iters: int = 5, exact: bool = True, init: str = "stride", seed: int = 0) -> DataFrame:
    """Lloyd's iterations in all blocks at once, one job each. init: hash, or stride, which numbers all residuals and
    exists for audits that SQL repeats. A codeword without members stays as it is."""
    start = hash_codebooks(resid, blocks, codes, width, seed) if init == "hash" else stride_codebooks(resid, blocks, codes, width)
    if not iters:
        return start
    words = as_words(start)
    for _ in range(iters):
        new = words.copy()
        for r in kernels.block_sums(resid, "resid", words).collect():
            mean = np.array(r["sums"]) / r["n"]
            new[divmod(r["list_id"], words.shape[1])] = np.floor(mean + 0.5) if exact else mean
        if (new == words).all():
            break
        words = new
    kind = int if exact else float
    out = [(m, c, [kind(x) for x in row]) for m, table in enumerate(words) for c, row in enumerate(table)]
    return rows_frame(resid.sparkSession, out, f"m int, code int, word array<{'bigint' if exact else 'double'}>")


def as_words(codebooks: DataFrame) -> np.ndarray:
    """(M, K, d) on the driver; configuration size, not data size. Missing codes repeat the last one."""
    rows = codebooks.orderBy("m", "code").collect()
    blocks = 1 + max(r["m"] for r in rows)
    per = [[r["word"] for r in rows if r["m"] == m] for m in range(blocks)]
    codes = max(map(len, per))
    return np.array([w + [w[-1]] * (codes - len(w)) for w in per], np.float64)


def encode_codes(resid: DataFrame, codebooks: DataFrame, keep: tuple[str, ...] = ("vec_id", "list_id")) -> DataFrame:
    """keep columns and codes: the nearest codeword of each block, ties to the smaller code."""
    words = resid.sparkSession.sparkContext.broadcast(kernels.checked(as_words(codebooks)))

    def run(batches):
        w = words.value
        for b in batches:
            x = kernels.matrix(b.column("resid"), w.shape[0] * w.shape[2]).reshape(-1, w.shape[0], w.shape[2])
            codes = np.stack([kernels.distances(x[:, m], w[m]).argmin(1) for m in range(len(w))], 1).astype(np.int32)
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keep), pa.array(list(codes), pa.list_(pa.int32()))], names=[*keep, "codes"])

    schema = ", ".join([*(f"{k} {resid.schema[k].dataType.simpleString()}" for k in keep), "codes array<int>"])
    return resid.select(*keep, "resid").mapInArrow(run, schema)


def decode_codes(codes: DataFrame, codebooks: DataFrame, key: str = "vec_id") -> DataFrame:
    """(key, resid): the codewords put together again."""
    rows = codes.select(key, F.posexplode("codes").alias("m", "code")).join(codebooks, ["m", "code"])
    return rows.groupBy(key).agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("m", "word"))), lambda s: s["word"])).alias("resid"))


def distortion(resid: DataFrame, codes: DataFrame, codebooks: DataFrame) -> DataFrame:
    """(vec_id, err): squared distance between a residual and its reconstruction."""
    back = decode_codes(codes, codebooks).withColumnRenamed("resid", "back")
    return resid.join(back, "vec_id").select("vec_id", sqdist(F.col("resid"), F.col("back")).alias("err"))
