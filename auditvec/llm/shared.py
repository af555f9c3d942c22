"""What the training-data operators share: staged tables, checked broadcasts, bounded slices, stable hash keys."""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes up to which the small side of a join is broadcast; beyond it the join shuffles.
BROADCAST_BYTES = 32 << 20


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a temporary one in local mode."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("auditvec.staging", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="auditvec-")
        spark.conf.set("auditvec.staging", base)
    return base.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write df as a Parquet table in the shared folder and read it back: cuts the lineage, survives lost executors."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(*tables: DataFrame) -> None:
    """Delete staged tables that nothing reads any more."""
    for df in tables:
        files, spark = df.inputFiles(), df.sparkSession
        if files:
            path = spark._jvm.org.apache.hadoop.fs.Path(files[0]).getParent()
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def _width(name: str, kind: T.DataType) -> Column:
    """Bytes of a value of a column, about."""
    c = F.col(f"`{name}`")
    if isinstance(kind, (T.StringType, T.BinaryType)):
        return F.coalesce(F.octet_length(c), F.lit(0)) + 8
    if isinstance(kind, T.ArrayType):
        return F.coalesce(F.octet_length(F.to_json(c)), F.lit(0)) + 16
    if isinstance(kind, T.StructType):
        return F.coalesce(F.octet_length(F.to_json(c)), F.lit(0)) + 16
    return F.lit(8)


def measured_bytes(df: DataFrame) -> int:
    """Bytes of all rows, about; df should be a staged table, as this reads it."""
    row = sum((_width(f.name, f.dataType) for f in df.schema.fields), F.lit(16))
    return df.agg(F.sum(row.cast("long"))).first()[0] or 0


def small(df: DataFrame, limit: int = BROADCAST_BYTES) -> DataFrame:
    """df with a broadcast hint if its rows measure at most `limit` bytes, else as it is (the join then shuffles)."""
    return F.broadcast(df) if measured_bytes(df) <= limit else df


def slices(batch: pa.RecordBatch, name: str, rows: int = 512, size: int = 8 << 20):
    """Parts of a batch with at most so many rows and, but for single longer rows, bytes of a column."""
    if not batch.num_rows:
        return
    n = np.concatenate([[0], np.cumsum(pc.fill_null(pc.binary_length(batch.column(name)), 0).to_numpy(zero_copy_only=False).astype(np.int64))])
    at = 0
    while at < batch.num_rows:
        upto = max(at + 1, min(at + rows, int(np.searchsorted(n, n[at] + size, "right")) - 1))
        yield batch.slice(at, upto - at)
        at = upto


def hash60(*parts: Column) -> Column:
    """First 60 bits of the MD5 of the parts joined by '|'; the same in any SQL engine. Nulls read as 'null'."""
    text = F.concat_ws("|", *[F.coalesce(p.cast("string"), F.lit("null")) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def row_key(doc_id: str = "doc_id", text: str = "text") -> Column:
    """16 bytes that rows share if their id and text agree (a null text reads as empty)."""
    known = F.coalesce(F.concat(F.lit("i"), F.col(doc_id).cast("string")), F.lit("n"))
    return F.unhex(F.md5(F.concat(known, F.lit("|"), F.coalesce(F.col(text), F.lit("")))))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
