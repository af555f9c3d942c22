"""WARC archives with revisit resolution.

Headers (page, digest, size) are shuffled by payload digest; of records with equal payloads the one with the largest
page_id stays a response and the others become revisit records that refer to it, with fresh headers and no payload.
Payloads stay where they are read, as long as the list of revisits is small enough to broadcast; beyond that, pages
move once, dealt by page and digest.

Archives are written by Spark's own text sink (a record is a value, the blank lines after it are the separator), so
its commit protocol covers lost executors and any file system works. Records are written by size class, each with as
many records a file as keep it below FILE_BYTES (one, if a record is larger); reading takes whole files and follows
each record's Content-Length.

Defined results: a null html is an empty payload; a null url has no target header; line breaks in a url are
escaped; rows that share the largest page_id are responses each; a null page_id is smaller than any other and, where
all ids of a payload are null, all are responses; empty input gives an archive without records; extra columns are
ignored.
"""

from __future__ import annotations

import base64
import hashlib
import zlib

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import small, staged

MIN_BYTES = 0
#: The date of fresh headers; a parameter, so that reruns agree.
DATE = "2024-01-01T00:00:00Z"
#: Uncompressed bytes of a file at most, and the payload sizes that part the size classes.
FILE_BYTES, CLASSES = 128 << 20, (32 << 10, 512 << 10, 8 << 20)
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: Digits of base 32 as number formatting has them, and as RFC 4648 has them (fixed values).
_FROM, _TO = "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
READ = "warc_type string, record_id string, refers_id string, page_id long, uri string, payload_digest string, computed_digest string, payload_bytes long"


def base32(h: Column) -> Column:
    """Base 32 of a SHA-1 in hex: 160 bits are eight groups of five hex digits, four base-32 digits each."""
    groups = [F.lpad(F.conv(F.substring(h, 5 * i + 1, 5), 16, 32), 4, "0") for i in range(8)]
    return F.translate(F.concat(*groups), _FROM, _TO)


def _uuid(*parts: Column) -> Column:
    h = F.md5(F.concat_ws("|", *parts))
    return F.concat(F.lit("<urn:uuid:"), F.regexp_replace(h, r"^(.{8})(.{4})(.{4})(.{4})(.{12})$", "$1-$2-$3-$4-$5"), F.lit(">"))


def resolve_pages(pages: DataFrame, min_bytes: int = MIN_BYTES) -> DataFrame:
    """pages with payload, payload_bytes, payload_digest, record_type and refers_to."""
    payload = F.coalesce(F.col("html"), F.lit(""))
    rows = pages.select("page_id", F.col("url").cast("string").alias("url"), payload.alias("payload")).withColumns({"payload_bytes": F.octet_length("payload").cast("long"), "__sha": F.unhex(F.sha1("payload"))})
    heads = staged(rows.select("page_id", "__sha", "payload_bytes"), "page-heads")
    first = heads.groupBy("__sha", "payload_bytes").agg(F.max("page_id").alias("__first"), F.count("*").alias("__n"))
    first = staged(first.filter((F.col("__n") > 1) & F.col("__first").isNotNull() & (F.col("payload_bytes") >= min_bytes)).drop("__n"), "page-groups")
    again = heads.join(small(first), ["__sha", "payload_bytes"]).filter(F.col("page_id").isNull() | (F.col("page_id") < F.col("__first")))
    again = staged(again.select(F.col("page_id").alias("__page"), F.col("__sha").alias("__of"), "__first").distinct(), "revisits")
    out = rows.join(small(again), F.col("page_id").eqNullSafe(F.col("__page")) & (F.col("__sha") == F.col("__of")), "left")
    kind = F.when(F.col("__of").isNotNull(), "revisit").otherwise("response")
    return out.select("page_id", "url", "payload", "payload_bytes", base32(F.lower(F.hex("__sha"))).alias("payload_digest"), kind.alias("record_type"), F.col("__first").alias("refers_to"))


def write_archives(resolved: DataFrame, path: str, date: str = DATE) -> None:
    """One record a row: response records carry the payload, revisit records only headers."""
    again = F.col("record_type") == "revisit"
    own = lambda page: _uuid(F.coalesce(page.cast("string"), F.lit("null")), F.col("payload_digest"))
    line = lambda name, value: F.coalesce(F.concat(F.lit(f"{name}: "), value.cast("string"), F.lit("\r\n")), F.lit(""))
    url = F.regexp_replace(F.regexp_replace("url", "\r", "%0D"), "\n", "%0A")
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.col("payload_bytes").cast("string"), F.lit("\r\n\r\n"))
    block_bytes = F.octet_length(http) + F.when(again, 0).otherwise(F.col("payload_bytes"))
    record = F.concat(
        F.lit("WARC/1.1\r\n"), line("WARC-Type", F.col("record_type")), line("WARC-Record-ID", own(F.col("page_id"))), line("WARC-Date", F.lit(date)), line("WARC-Target-URI", url),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("payload_digest"))), F.when(again, F.concat(line("WARC-Refers-To", own(F.col("refers_to"))), line("WARC-Profile", F.lit(PROFILE)))).otherwise(F.lit("")),
        line("X-Page-ID", F.col("page_id")), line("Content-Type", F.lit("application/http; msgtype=response")), line("Content-Length", block_bytes), F.lit("\r\n"), http, F.when(again, F.lit("")).otherwise(F.col("payload")),
    )
    stored = F.when(again, 0).otherwise(F.col("payload_bytes"))
    group = sum(((stored > c).cast("int") for c in CLASSES), F.lit(0))
    rows = resolved.select(record.alias("value"), group.alias("__group"))
    for i in sorted(r[0] for r in resolved.select(group).distinct().collect()) or [0]:
        many = 1 if i == len(CLASSES) else FILE_BYTES // CLASSES[i]
        rows.filter(F.col("__group") == i).select("value").write.mode("append").option("lineSep", "\r\n\r\n").option("compression", "gzip").option("maxRecordsPerFile", many).text(path)


def records(content: bytes):
    """(headers by lower-case name, HTTP payload) of each record of an archive's bytes."""
    if content[:2] == b"\x1f\x8b":
        whole, rest = [], content
        while rest:
            d = zlib.decompressobj(31)
            whole.append(d.decompress(rest))
            rest = d.unused_data
        content = b"".join(whole)
    at = 0
    while at < len(content):
        end = content.find(b"\r\n\r\n", at)
        head = content[at:end].split(b"\r\n")
        if not head[0].startswith(b"WARC/"):
            raise ValueError(f"no WARC record at byte {at}")
        headers = {k.strip().lower().decode(): v.strip().decode() for k, _, v in (x.partition(b":") for x in head[1:])}
        size = int(headers["content-length"])
        block = content[end + 4 : end + 4 + size]
        if len(block) < size or content[end + 4 + size : end + 8 + size] != b"\r\n\r\n":
            raise ValueError(f"the record at byte {at} is cut off")
        yield headers, block.partition(b"\r\n\r\n")[2] if headers.get("content-type", "").startswith("application/http") else block
        at = end + 8 + size


def _rows(h: dict, payload: bytes) -> tuple:
    again = h["warc-type"] == "revisit"
    digest = None if again else base64.b32encode(hashlib.sha1(payload).digest()).decode()
    page = h.get("x-page-id")
    return (h["warc-type"], h["warc-record-id"], h.get("warc-refers-to"), int(page) if page else None, h.get("warc-target-uri"), h.get("warc-payload-digest", "").removeprefix("sha1:"), digest, None if again else len(payload))


def _reader(batches):
    kinds = [pa.string(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64()]
    names = [x.split()[0] for x in READ.split(", ")]
    for b in batches:
        for content in b.column("content"):
            rows = [_rows(h, p) for h, p in records(content.as_py())]
            cols = list(zip(*rows)) if rows else [[] for _ in names]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(cols, kinds)], names=names)


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """Headers of all records, with digest and size of the payloads found."""
    return spark.read.format("binaryFile").option("pathGlobFilter", "*.gz").load(path).select("content").mapInArrow(_reader, READ)


def resolve_revisits(heads: DataFrame) -> DataFrame:
    """Per record of an archive: page_id, payload size and digest, record_type, refers_to; revisits are joined to the
    response that they refer to, by payload digest and record id."""
    responses = heads.filter("warc_type = 'response'")
    targets = responses.groupBy(F.col("computed_digest").alias("payload_digest"), F.col("record_id").alias("refers_id")).agg(F.max("page_id").alias("refers_to"), F.max("payload_bytes").alias("payload_bytes"))
    found = heads.filter("warc_type = 'revisit'").drop("payload_bytes").join(targets, ["payload_digest", "refers_id"], "left")
    a = responses.select("page_id", "payload_bytes", F.col("computed_digest").alias("payload_digest"), F.col("warc_type").alias("record_type"), F.lit(None).cast("long").alias("refers_to"))
    return a.unionByName(found.select("page_id", "payload_bytes", "payload_digest", F.col("warc_type").alias("record_type"), "refers_to"))


def deduplicated_archives(pages: DataFrame, path: str, min_bytes: int = MIN_BYTES) -> DataFrame:
    """Write the pages' archives below path and return what reading them back gives."""
    write_archives(resolve_pages(pages, min_bytes), path)
    return resolve_revisits(read_archives(pages.sparkSession, path)).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
