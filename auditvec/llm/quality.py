"""Quality classifier: supervised subword embeddings.

A document is the mean of learned vectors of its words, their character 3- and 4-grams and its word pairs, all
hashed into buckets; a softmax layer on the mean gives the class. Training is stochastic gradient descent in numpy
on the driver over a bounded sample of labelled rows. For scoring, vectors and output layer fold into one number a
bucket, so a whole text costs one table lookup a word.

Defined results: null and empty texts have no features and get the output layer's bias alone; repeated rows are
scored each; with labelled rows of one class only, every score is the share of class 1 (0 or 1, to 1e-12), without any
0.5; extra columns are ignored by score_quality and kept by keep_quality.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .features import Vocabulary, gram_buckets, held_out, training_rows, word_buckets
from .shared import slices

#: Labelled rows of class 0 and 1 used for training at most.
MOST = (1500, 1500)
BUCKETS, DIM, STEPS, BATCH, RATE, SEED = 1 << 17, 10, 360, 32, 0.25, 5
THRESHOLD = 0.7
GRAMS = (3, 4)
#: Features a worker gathers before it adds them up.
CHUNK_WORDS = 200_000
_WORKER: dict = {}


@dataclass
class Model:
    weights: np.ndarray  # one number a bucket: its vector times the difference of the output layer's two rows
    bias: float


def _pieces(words: list[bytes]):
    """Buckets of words and of their character n-grams, and which word each is of, piece by piece."""
    yield word_buckets(words, BUCKETS, 1), np.arange(len(words))
    yield from gram_buckets(words, GRAMS, BUCKETS)


def _pairs(h: np.ndarray) -> np.ndarray:
    """Buckets of neighbouring words' pairs; a word after itself shares one bucket, whatever the word."""
    a, b = h[:-1].astype(np.uint64), h[1:].astype(np.uint64)
    mixed = (a * np.uint64(0x9E3779B97F4A7C15) + b) * np.uint64(0xC2B2AE3D27D4EB4F)
    return np.where(a == b, 0, (mixed >> np.uint64(40)) % np.uint64(BUCKETS)).astype(np.int64)


def _features(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct buckets of a text and their shares of all its features."""
    words = text.encode(errors="replace").split()
    if not words:
        return np.zeros(0, np.int64), np.zeros(0, np.float32)
    distinct, at, times = np.unique(np.array(words, object), return_inverse=True, return_counts=True)
    n = np.bincount(_pairs(word_buckets(list(distinct), 1 << 32, 3)[at]), minlength=BUCKETS).astype(np.float64)
    for flat, own in _pieces(list(distinct)):
        n += np.bincount(flat, times[own], BUCKETS)
    ids = np.flatnonzero(n)
    return ids.astype(np.int32), (n[ids] / n.sum()).astype(np.float32)


def fit(rows: list[tuple[str, int]], steps: int = STEPS, seed: int = SEED) -> Model:
    """The trained parts, folded: what a softmax over two classes gives for class 1 hangs on their difference alone."""
    vectors, out, bias = fit_parts(rows, steps, seed)
    return Model(vectors @ (out[1] - out[0]), float(bias[1] - bias[0]))


def fit_parts(rows: list[tuple[str, int]], steps: int = STEPS, seed: int = SEED) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(vectors, output layer, its bias)."""
    epochs = max(2, -(-steps * BATCH // max(1, len(rows))))
    y = np.array([r[1] for r in rows], np.float32)
    share = float(y.mean()) if len(y) else 0.5
    if not 0 < share < 1:
        return np.zeros((BUCKETS, DIM), np.float32), np.zeros((2, DIM), np.float32), np.array([0, np.log(max(share, 1e-12) / max(1 - share, 1e-12))])
    rng = np.random.default_rng(seed)
    docs = [_features(t) for t, _ in rows]
    vectors = rng.uniform(-1 / DIM, 1 / DIM, (BUCKETS, DIM)).astype(np.float32)
    seen = np.full(BUCKETS, 1e-6, np.float32)
    out, bias = rng.normal(0, 0.1, (2, DIM)).astype(np.float32), np.zeros(2, np.float32)
    for epoch in range(epochs):
        rate = RATE * (1 - epoch / epochs)
        order = rng.permutation(len(docs))
        for at in range(0, len(order), BATCH):
            batch = order[at : at + BATCH]
            ids = np.concatenate([docs[i][0] for i in batch])
            val = np.concatenate([docs[i][1] for i in batch])
            row = np.repeat(np.arange(len(batch)), [len(docs[i][0]) for i in batch])
            mean = np.stack([np.bincount(row, vectors[ids, d] * val, len(batch)) for d in range(DIM)], 1)
            logit = mean @ out.T + bias
            p = np.exp(logit - logit.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(batch)), y[batch].astype(int)] -= 1
            back = (p @ out).astype(np.float32)
            out -= rate * (p.T @ mean / len(batch) * 8).astype(np.float32)
            bias -= rate * p.mean(0).astype(np.float32)
            # What a step changes is scaled by each bucket's own past steps, so rare pieces learn as well.
            distinct, where = np.unique(ids, return_inverse=True)
            grad = np.stack([np.bincount(where, back[row, d] * val, len(distinct)) for d in range(DIM)], 1).astype(np.float32)
            seen[distinct] += (grad * grad).mean(1)
            vectors[distinct] -= rate * grad / np.sqrt(seen[distinct])[:, None]
    return vectors, out, bias


def _vocabulary(weights: np.ndarray) -> Vocabulary:
    def describe(words: list[bytes]) -> dict:
        total, n = np.zeros(len(words)), np.zeros(len(words))
        for flat, own in _pieces(words):
            total += np.bincount(own, weights[flat], len(words))
            n += np.bincount(own, minlength=len(words))
        return {"sum": total, "n": n, "h": word_buckets(words, 1 << 32, 3)}

    return Vocabulary(describe)


def score_texts(texts: list, model: Model, vocabulary: Vocabulary | None = None) -> np.ndarray:
    """Scores of whole texts, in chunks of about CHUNK_WORDS words; a longer text is one chunk."""
    vocab = vocabulary if vocabulary is not None else _vocabulary(model.weights)
    scores = np.empty(len(texts))
    words, ends, begin = [], [], 0

    def flush(stop: int) -> None:
        nonlocal words, ends, begin
        ids = vocab.ids(words)
        if not words:
            scores[begin:stop] = 1 / (1 + np.exp(-np.clip(model.bias, -30, 30)))
            ends, begin = [], stop
            return
        h = vocab.rows["h"][ids]
        total = np.concatenate([[0.0], np.cumsum(vocab.rows["sum"][ids])])
        count = np.concatenate([[0.0], np.cumsum(vocab.rows["n"][ids])])
        pair = np.concatenate([[0.0], np.cumsum(model.weights[_pairs(h)].astype(np.float64)) if len(h) > 1 else []])
        b = np.array(ends, np.int64)
        a = np.concatenate([[0], b[:-1]])
        n_pairs = np.maximum(b - a - 1, 0)
        p1 = np.minimum(np.maximum(b - 1, 0), len(pair) - 1)
        p0 = np.minimum(a, len(pair) - 1)
        num = total[b] - total[a] + np.where(n_pairs > 0, pair[p1] - pair[p0], 0)
        den = count[b] - count[a] + n_pairs
        scores[begin:stop] = 1 / (1 + np.exp(-np.clip(num / np.maximum(den, 1) + model.bias, -30, 30)))
        words, ends, begin = [], [], stop

    for i, t in enumerate(texts):
        words += (t or "").encode(errors="replace").split()
        ends.append(len(words))
        if len(words) >= CHUNK_WORDS:
            flush(i + 1)
    if begin < len(texts):
        flush(len(texts))
    return scores


def train(docs: DataFrame, labels: DataFrame, most: tuple[int, int] = MOST) -> Model:
    return fit(training_rows(docs, labels, "quality", most))


def _scorer(model: Model, cols: list[str], key: str):
    def run(batches):
        if _WORKER.get("key") != key:  # kept between the tasks of a worker
            _WORKER.update(key=key, vocabulary=_vocabulary(model.weights))
        for batch in batches:
            for b in slices(batch, "text", 2048):
                s = score_texts(b.column("text").to_pylist(), model, _WORKER["vocabulary"])
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in cols), pa.array(s, pa.float64())], names=[*cols, "score"])

    return run


def _key(model: Model) -> str:
    import hashlib

    return hashlib.sha256(model.weights.tobytes() + str(model.bias).encode()).hexdigest()


def score_quality(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """Per row: doc_id, held_out, score, predicted (1 if score >= threshold)."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", "text").mapInArrow(_scorer(model, ["doc_id"], _key(model)), f"doc_id {kind}, score double")
    return rows.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_quality(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of docs that score at least threshold, with all their columns, in one pass."""
    names = [f"c{i}" for i in range(len(docs.columns))]
    inner = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in zip(docs.columns, names)], F.col("text"))
    kinds = ", ".join(f"{n} {f.dataType.simpleString()}" for n, f in zip(names, docs.schema.fields))
    rows = inner.mapInArrow(_scorer(model, names, _key(model)), f"{kinds}, score double")
    return rows.filter(F.col("score") >= threshold).select(*[F.col(n).alias(c) for n, c in zip(names, docs.columns)])
