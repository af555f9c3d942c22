"""Token counts through a digest cache.

A text's digest and the tokenizer's digest look up stored counts; only distinct texts that the cache lacks are
encoded, and their counts are appended to it. Counts equal the tokenizer library's own for the whole text.

Texts are reduced to one a digest within each task before they move, so copies are not shuffled; the counts come back
by a join of two written tables, in which Spark splits the rows of a frequent digest.

Normalised content is the text itself, a null read as empty: any further change could change the count.

Defined results: null and empty texts have 0 bytes and 0 tokens; repeated texts are encoded once; a digest that is
stored twice (two runs at once) counts once; an empty table leaves the cache as it is; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
from importlib.metadata import version

import pyarrow as pa
import regex
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import slices, staged

LIMIT = 512
CACHE_SCHEMA = "content binary, tokenizer string, n_tokens long"
#: Words, and bytes of a word, whose counts a worker remembers; beyond it, it starts anew.
REMEMBERED, SHORT = 200_000, 64
#: The published split rule of byte-level BPE vocabularies (a fixed value).
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Texts with other characters go to the library whole: Unicode versions may class them differently.
UNSURE = r"[^\x09\x0A\x0D\x20-\x7E¡-ɏ‘-‟]"
_WORKER: dict = {}


class Counter:
    """Counts tokens with a tokenizers .json, a sentencepiece .model or nothing else, given the file's bytes."""

    def __init__(self, blob: bytes, kind: str):
        self.known: dict[str, int] = {}
        self.split = self.special = None
        if kind == "sentencepiece":
            import sentencepiece

            model = sentencepiece.SentencePieceProcessor(model_proto=blob)
            self.encode = lambda texts: [len(x) for x in model.encode(texts, num_threads=1)]
            return
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        rules = json.loads(blob)
        model = Tokenizer.from_str(blob.decode())
        model.no_padding()
        model.no_truncation()
        self.encode = lambda texts: [len(x.ids) for x in model.encode_batch(texts, add_special_tokens=False)]
        pre = rules.get("pre_tokenizer") or {}
        plain = pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space")
        if plain and not rules.get("normalizer") and not rules["model"].get("dropout"):
            self.split, self.unsure = regex.compile(SPLIT), regex.compile(UNSURE)
            self.special = [x["content"] for x in rules.get("added_tokens", [])]

    def counts(self, texts: list[str]) -> list[int]:
        if self.split is None:
            return self.encode(texts)
        if len(self.known) > REMEMBERED:
            self.known.clear()
        out, whole, known = [0] * len(texts), [], self.known
        pieces, new, long = {}, {}, {}
        for i, t in enumerate(texts):
            if self.unsure.search(t) or any(s in t for s in self.special):
                whole.append(i)
                continue
            pieces[i] = words = self.split.findall(t)
            new.update((w, 0) for w in set(words) if w not in known)
        if new:  # a word of the split rule splits into itself alone, so its count stands by itself
            for w, n in zip(new, self.encode(list(new))):
                (known if len(w) <= SHORT else long)[w] = n
        for i, words in pieces.items():
            out[i] = sum(known[w] if w in known else long[w] for w in words) if long else sum(map(known.__getitem__, words))
        for i, n in zip(whole, self.encode([texts[i] for i in whole]) if whole else []):
            out[i] = n
        return out


def read_tokenizer(path: str) -> tuple[bytes, str, str]:
    """File bytes, library, and a digest of both that changes with the file or the library's version."""
    with open(path, "rb") as f:
        blob = f.read()
    kind = "sentencepiece" if path.endswith(".model") else "tokenizers"
    return blob, kind, hashlib.sha256(blob + f"|{kind}|{version(kind)}".encode()).hexdigest()


def _encoder(shipped, kind: str, digest: str):
    def run(batches):
        if _WORKER.get("digest") != digest:  # kept between the tasks of a worker
            _WORKER.update(digest=digest, counter=Counter(shipped.value, kind))
        for b in batches:
            for part in slices(b, "text", 64, 4 << 20):
                n = _WORKER["counter"].counts(part.column("text").to_pylist())
                yield pa.RecordBatch.from_arrays([part.column("content"), pa.array([digest] * len(n)), pa.array(n, pa.int64())], names=["content", "tokenizer", "n_tokens"])

    return run


def _cached(spark, path: str, digest: str) -> DataFrame:
    try:
        known = spark.read.schema(CACHE_SCHEMA).parquet(path)
    except AnalysisException as e:
        if e.getCondition() != "PATH_NOT_FOUND":
            raise
        known = spark.createDataFrame([], CACHE_SCHEMA)
    return known.filter(F.col("tokenizer") == digest).groupBy("content").agg(F.min("n_tokens").alias("n_tokens"))


def count_tokens(docs: DataFrame, tokenizer: str, cache: str, limit: int = LIMIT) -> DataFrame:
    """Per row: doc_id, n_bytes, n_tokens, over_limit. tokenizer: a file's path; cache: a folder of Parquet files."""
    spark = docs.sparkSession
    blob, kind, digest = read_tokenizer(tokenizer)
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", text.alias("text"), F.unhex(F.sha2(text, 256)).alias("content"))
    missing = rows.groupBy("content").agg(F.any_value("text").alias("text")).join(_cached(spark, cache, digest), "content", "left_anti")
    missing.mapInArrow(_encoder(spark.sparkContext.broadcast(blob), kind, digest), CACHE_SCHEMA).write.mode("append").parquet(cache)
    sized = rows.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), "content")
    out = sized.join(staged(_cached(spark, cache, digest), "counts"), "content")
    return out.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
