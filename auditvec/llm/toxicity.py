"""Toxicity: a bidirectional gated recurrent network with attention pooling over word and character inputs.

A text is cut into overlapping windows of WINDOW words, a new one every STRIDE. A word's input is its hashed word
vector beside the mean of its hashed character n-gram vectors. The network reads a window both ways, attention
pools the states, and a logistic unit scores the pool; a text scores as its worst window. Training is numpy back
propagation through time on the driver over a bounded sample of labelled texts: a toxic text teaches through its
worst window, a clean one through its worst and some random windows.

For scoring, whatever depends on a word alone (both directions' input products) is kept per distinct word, and
windows of many texts step together.

Every word of a text is read whole, in training and scoring; statements of up to WINDOW - STRIDE + 1 words lie whole in
some window.

Defined results: null and empty texts are one window without words and score as the network scores that; repeated
rows are scored each; without labelled rows of both classes every score is the share of class 1 (0 if none); other
columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .features import Vocabulary, gram_buckets, held_out, training_rows, word_buckets
from .shared import slices

#: Labelled rows of class 0 and 1 used for training at most.
MOST = (3000, 1000)
WINDOW, STRIDE = 32, 16
WORD_BUCKETS, GRAM_BUCKETS, HIDDEN, WIDTH, ATTEND = 1 << 14, 1 << 14, 8, 8, 8
STEPS, BATCH, RATE, SEED, CLEAN_PER_TOXIC, CLEAN_RATED = 240, 128, 0.01, 3, 3, 6
THRESHOLD = 0.3
GRAMS = (3, 4, 5)
#: Windows that step together when scoring.
TOGETHER = 512
_EDGE = b".,;:!?\"'()[]{}<>*#%&$|-_/\\"
_WORKER: dict = {}


def _words(text) -> list[bytes]:
    return (text or "").encode(errors="replace").lower().split()


def _pieces(words: list[bytes]):
    """Each word's bucket; buckets of all character n-grams, and which word each is of, piece by piece."""
    bare = [w.strip(_EDGE) or w for w in words]
    return word_buckets(bare, WORD_BUCKETS, 11), gram_buckets(bare, GRAMS, GRAM_BUCKETS)


def _sigmoid(x):
    y = np.tanh(0.5 * x)
    y *= 0.5
    y += 0.5
    return y


def window_starts(n_words: int) -> np.ndarray:
    """Starts of windows that cover all words, each overlapping the next by WINDOW - STRIDE."""
    return np.arange(max(1, -(-(n_words - (WINDOW - STRIDE)) // STRIDE))) * STRIDE


def new_parameters(rng) -> dict[str, np.ndarray]:
    g = lambda *s: (rng.normal(0, 1, s) / np.sqrt(s[-2] if len(s) > 1 else 1)).astype(np.float32)
    return {
        "word": g(WORD_BUCKETS, WIDTH) * 0.05 * np.sqrt(WORD_BUCKETS).astype(np.float32), "gram": g(GRAM_BUCKETS, WIDTH) * 0.05 * np.sqrt(GRAM_BUCKETS).astype(np.float32),
        "wx": g(2, 2 * WIDTH, 3 * HIDDEN), "bx": np.zeros((2, 3 * HIDDEN), np.float32), "wh": g(2, HIDDEN, 3 * HIDDEN),
        "wa": g(2 * HIDDEN, ATTEND), "va": g(ATTEND, 1), "wo": g(2 * HIDDEN, 1), "bo": np.zeros(1, np.float32),
    }


def _steps(px: np.ndarray, there: np.ndarray, p: dict, keep: bool):
    """px: (2, T, B, 3H) input products, direction 1 reversed in time; there: (2, T, B, 1) or None if
    no window has ended. States (2, T, B, H)."""
    two, t_max, b, _ = px.shape
    h, states, saved = np.zeros((two, b, HIDDEN), np.float32), np.empty((two, t_max, b, HIDDEN), np.float32), []
    for t in range(t_max):
        hw = h @ p["wh"]
        gates = _sigmoid(px[:, t, :, : 2 * HIDDEN] + hw[..., : 2 * HIDDEN])
        z, r = gates[..., :HIDDEN], gates[..., HIDDEN:]
        n = np.tanh(px[:, t, :, 2 * HIDDEN :] + r * hw[..., 2 * HIDDEN :])
        new = n + z * (h - n)
        if keep:
            saved.append((h, z, r, n, hw[..., 2 * HIDDEN :]))
        h = new if there is None else np.where(there[:, t] > 0, new, h)
        states[:, t] = h
    return states, saved


def _pool(states: np.ndarray, there: np.ndarray, p: dict):
    """Attention over words. states: (2, T, B, H) with direction 1 reversed; there: (T, B)."""
    s = np.concatenate([states[0], states[1, ::-1]], -1)
    a = np.tanh(s @ p["wa"])
    e = np.where(there, (a @ p["va"])[..., 0], -30)
    w = np.exp(e - e.max(0))
    w /= w.sum(0)
    c = (w[..., None] * s).sum(0)
    return s, a, w, c, (c @ p["wo"])[:, 0] + p["bo"][0]


class Words:
    """Training texts' distinct words with their hashed pieces."""

    def __init__(self):
        self.at: dict[bytes, int] = {}

    def ids(self, words: list[bytes]) -> np.ndarray:
        return np.array([self.at.setdefault(w, len(self.at)) for w in words], np.int64)

    def close(self) -> None:
        self.word, pieces = _pieces(list(self.at))
        self.grams = [np.zeros(0, np.int32)] * len(self.at)
        for flat, own in pieces:
            order = np.argsort(own, kind="stable")
            ids, first = np.unique(own[order], return_index=True)
            for i, some in zip(ids, np.split(flat[order].astype(np.int32), first[1:])):
                self.grams[i] = np.concatenate([self.grams[i], some]) if len(self.grams[i]) else some


def _inputs(ids: np.ndarray, words: Words, p: dict):
    grams = [words.grams[i] for i in ids]
    n = np.array([len(g) for g in grams])
    flat = np.concatenate(grams)
    means = np.add.reduceat(p["gram"][flat], np.concatenate([[0], np.cumsum(n)[:-1]])) / n[:, None]
    where = words.word[ids]
    return np.concatenate([p["word"][where], means], 1).astype(np.float32), where, flat, n


def _forward(win: np.ndarray, words: Words, p: dict, keep: bool = False):
    """win: (B, T) word rows, -1 where a window has ended."""
    there = (win >= 0).T
    ids, back = np.unique(np.where(win >= 0, win, win.max(initial=0)), return_inverse=True)
    back = back.reshape(win.shape).T
    x, where, flat, n = _inputs(ids, words, p)
    px = (x @ p["wx"] + p["bx"][:, None])[:, back]
    px[1] = px[1, ::-1]
    mask = np.stack([there, there[::-1]])[..., None].astype(np.float32)
    states, saved = _steps(px, mask, p, keep)
    pooled = _pool(states, there, p)
    return pooled[-1], (there, back, x, where, flat, n, mask, states, saved, pooled)


def _backward(dlogit: np.ndarray, kept, p: dict) -> dict[str, np.ndarray]:
    there, back, x, where, flat, n, mask, states, saved, (s, a, w, c, _) = kept
    d = {"wo": c.T @ dlogit[:, None], "bo": dlogit.sum(keepdims=True)}
    dc = dlogit[:, None] * p["wo"][:, 0]
    dw = (s * dc).sum(-1)
    de = w * (dw - (w * dw).sum(0))
    d["va"] = (a * de[..., None]).sum((0, 1))[:, None]
    da = de[..., None] * p["va"][:, 0] * (1 - a * a)
    d["wa"] = np.tensordot(s, da, ([0, 1], [0, 1]))
    ds = w[..., None] * dc + da @ p["wa"].T
    dstates = np.stack([ds[..., :HIDDEN], ds[::-1, :, HIDDEN:]])
    dh = np.zeros_like(states[:, 0])
    d["wh"], dpx = np.zeros_like(p["wh"]), np.empty((*states.shape[:3], 3 * HIDDEN), np.float32)
    for t in range(states.shape[1] - 1, -1, -1):
        h, z, r, m, hn = saved[t]
        dh = dh + dstates[:, t]
        dnew = dh * mask[:, t]
        dz = dnew * (h - m) * z * (1 - z)
        dm = dnew * (1 - z) * (1 - m * m)
        dr = dm * hn * r * (1 - r)
        dpx[:, t] = np.concatenate([dz, dr, dm], -1)
        dhw = np.concatenate([dz, dr, dm * r], -1)
        d["wh"] += np.swapaxes(h, 1, 2) @ dhw
        dh = dh * (1 - mask[:, t]) + dnew * z + dhw @ np.swapaxes(p["wh"], 1, 2)
    dpx[1] = dpx[1, ::-1].copy()
    d["bx"] = dpx.sum((1, 2))
    by_word = np.zeros((2, len(x), 3 * HIDDEN), np.float32)
    for k in range(2):
        np.add.at(by_word[k], back.ravel(), dpx[k].reshape(-1, 3 * HIDDEN))
    d["wx"] = np.stack([x.T @ by_word[k] for k in range(2)])
    dx = by_word[0] @ p["wx"][0].T + by_word[1] @ p["wx"][1].T
    d["word"], d["gram"] = np.zeros_like(p["word"]), np.zeros_like(p["gram"])
    np.add.at(d["word"], where, dx[:, :WIDTH])
    np.add.at(d["gram"], flat, np.repeat(dx[:, WIDTH:] / n[:, None], n, axis=0))
    return d


def _first_guess(windows: list[np.ndarray], y: np.ndarray, words: Words) -> np.ndarray:
    """A score of each word before there is a network: log-odds of its rarest telling piece over the texts."""
    share = np.zeros((2, WORD_BUCKETS + GRAM_BUCKETS))
    for win, label in zip(windows, y):
        ids = np.unique(win[win >= 0])
        if len(ids):
            pieces = np.unique(np.concatenate([words.word[ids], *[words.grams[i] + WORD_BUCKETS for i in ids]]))
            share[label, pieces] += 1
    total = np.bincount(y, minlength=2)[:, None]
    odds = np.log((share[1] + 0.5) / (total[1] + 1)) - np.log((share[0] + 0.5) / (total[0] + 1))
    odds *= np.minimum(1, share.sum(0) / 5)
    return np.array([max(odds[words.word[i]], odds[words.grams[i] + WORD_BUCKETS].max()) for i in range(len(words.word))])


def fit(rows: list[tuple[str, int]], steps: int = STEPS, seed: int = SEED) -> dict[str, np.ndarray]:
    """Parameters after about `steps` steps; with one class only, {'constant': its share}."""
    y = np.array([r[1] for r in rows], np.int64)
    epochs = max(4, -(-steps * BATCH // max(1, (2 + CLEAN_PER_TOXIC) * int(y.sum()))))
    if not 0 < y.sum() < len(y):
        return {"constant": np.array([float(y.mean()) if len(y) else 0.0])}
    rng, words, windows = np.random.default_rng(seed), Words(), []
    for text, _ in rows:
        ids = words.ids(_words(text))
        padded = np.concatenate([ids, np.full(WINDOW + STRIDE, -1)])
        windows.append(padded[window_starts(len(ids))[:, None] + np.arange(WINDOW)])
    words.close()
    of = np.repeat(np.arange(len(rows)), [len(w) for w in windows])
    win = np.concatenate(windows)
    full = (win >= 0).any(1)
    if not full.any():
        return {"constant": np.array([float(y.mean())])}
    guess = _first_guess(windows, y, words)
    score = np.where(win >= 0, guess[win], -9).max(1)
    p = new_parameters(rng)
    m, v, step = {k: np.zeros_like(a) for k, a in p.items()}, {k: np.zeros_like(a) for k, a in p.items()}, 0
    toxic, rated, n_windows = y[of] == 1, np.arange(len(win)), np.repeat([len(w) for w in windows], [len(w) for w in windows])
    for epoch in range(epochs):
        order = rated[np.lexsort((-score[rated], of[rated]))]
        worst = order[np.concatenate([[True], of[order][1:] != of[order][:-1]])]
        clean = np.flatnonzero(~toxic & full)
        pos = worst[toxic[worst] & full[worst]]
        hard = worst[~toxic[worst]]
        hard = hard[np.argsort(-score[hard], kind="stable")][: len(pos)]
        neg = np.concatenate([hard, rng.choice(clean, min(len(clean), CLEAN_PER_TOXIC * len(pos)), replace=False)]) if len(clean) else hard
        pick = rng.permutation(np.concatenate([pos, neg]))
        for at in range(0, len(pick), BATCH):
            b = pick[at : at + BATCH]
            logit, kept = _forward(win[b], words, p, keep=True)
            grads = _backward(((_sigmoid(logit) - toxic[b]) / len(b)).astype(np.float32), kept, p)
            step += 1
            rate = RATE * (1 - epoch / epochs) * np.sqrt(1 - 0.999**step) / (1 - 0.9**step)
            for k, g in grads.items():
                m[k] += 0.1 * (g - m[k])
                v[k] += 0.001 * (g * g - v[k])
                p[k] -= (rate * m[k] / (np.sqrt(v[k]) + 1e-6)).astype(np.float32)
        if epoch + 1 < epochs:  # all windows of toxic texts are rated again, and some of each clean text
            rated = np.flatnonzero(toxic | (rng.random(len(win)) < CLEAN_RATED / n_windows))
            for i in range(0, len(rated), 2048):
                score[rated[i : i + 2048]] = _forward(win[rated[i : i + 2048]], words, p)[0]
    return p


def _vocabulary(p: dict) -> Vocabulary:
    def describe(words: list[bytes]) -> dict:
        where, pieces = _pieces(words)
        n, total = np.zeros(len(words)), np.zeros((len(words), WIDTH))
        for flat, own in pieces:
            n += np.bincount(own, minlength=len(words))
            for d in range(WIDTH):
                total[:, d] += np.bincount(own, p["gram"][flat, d], len(words))
        x = np.concatenate([p["word"][where], total / n[:, None]], 1).astype(np.float32)
        return {"there": x @ p["wx"][0] + p["bx"][0], "back": x @ p["wx"][1] + p["bx"][1]}

    return Vocabulary(describe)


def _score_windows(ids: np.ndarray, starts: np.ndarray, ends: np.ndarray, vocab: Vocabulary, p: dict) -> np.ndarray:
    out = np.empty(len(starts), np.float32)
    for at in range(0, len(starts), TOGETHER):
        pos = starts[at : at + TOGETHER] + np.arange(WINDOW)[:, None]
        there = pos < ends[at : at + TOGETHER]
        px = np.zeros((2, *pos.shape, 3 * HIDDEN), np.float32)
        if len(ids):
            rows = ids[np.minimum(pos, len(ids) - 1)]
            np.take(vocab.rows["there"], rows, 0, out=px[0])
            np.take(vocab.rows["back"], rows[::-1], 0, out=px[1])
        mask = None if there.all() else np.stack([there, there[::-1]])[..., None].astype(np.float32)
        states, _ = _steps(px, mask, p, False)
        out[at : at + TOGETHER] = _sigmoid(_pool(states, there, p)[-1])
    return out


def score_texts(texts: list, p: dict, vocabulary: Vocabulary | None = None, together: int = 60_000) -> np.ndarray:
    """Scores of whole texts; texts are gathered until they have `together` words."""
    if "constant" in p:
        return np.full(len(texts), float(p["constant"][0]))
    vocab, scores, begin, words, bounds = vocabulary if vocabulary is not None else _vocabulary(p), np.empty(len(texts)), 0, [], []

    def flush(stop: int) -> None:
        nonlocal begin, words, bounds
        ids = vocab.ids(words)
        starts = [a + window_starts(b - a) for a, b in bounds]
        n = np.array([len(s) for s in starts])
        probs = _score_windows(ids, np.concatenate(starts), np.repeat([b for _, b in bounds], n), vocab, p)
        scores[begin:stop] = np.maximum.reduceat(probs, np.concatenate([[0], np.cumsum(n)[:-1]]))
        begin, words, bounds = stop, [], []

    for i, t in enumerate(texts):
        a = len(words)
        words += _words(t)
        bounds.append((a, len(words)))
        if len(words) >= together:
            flush(i + 1)
    if begin < len(texts):
        flush(len(texts))
    return scores


def train(docs: DataFrame, labels: DataFrame, most: tuple[int, int] = MOST) -> dict[str, np.ndarray]:
    return fit(training_rows(docs, labels, "toxic", most))


def _scorer(p: dict, key: str):
    def run(batches):
        if _WORKER.get("key") != key:  # kept between the tasks of a worker
            _WORKER.update(key=key, vocabulary=None if "constant" in p else _vocabulary(p))
        for batch in batches:
            for b in slices(batch, "text", 2048):
                s = score_texts(b.column("text").to_pylist(), p, _WORKER["vocabulary"])
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(s, pa.float64())], names=["doc_id", "score"])

    return run


def score_toxicity(docs: DataFrame, parameters: dict, threshold: float = THRESHOLD) -> DataFrame:
    """Per row: doc_id, held_out, score, predicted (1 if score >= threshold)."""
    key = hashlib.sha256(b"".join(parameters[k].tobytes() for k in sorted(parameters))).hexdigest()
    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", "text").mapInArrow(_scorer(parameters, key), f"doc_id {kind}, score double")
    return rows.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
