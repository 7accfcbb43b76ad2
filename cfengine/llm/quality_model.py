"""Document quality from random-indexing word vectors and a two-layer network.

Every token (a word's hash bucket, and the form of the word: case, signs and length) has a
fixed sparse random vector. A token's context vector is the sum of its neighbours' random
vectors over the whole corpus. A document is pooled to the means of its tokens' unit context
vectors, their squared lengths (texts that repeat themselves have long means) and its length.
The network is trained on the driver on about SAMPLE labelled rows, the ones with the smallest hashes of
their ids; a temperature is then fitted on a fifth of them that training did not use.

Defined cases: null and empty texts pool to zero vectors and get a score like any other.
Without labelled training rows every score is 0.5. Rows of labels with a null id or quality are
ignored, of several rows for one id the largest quality counts. Repeated rows stay repeated.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, about, fewer, fold, hash_words, mix64, text_or_empty

WORD_BUCKETS = 12288
FORM_BUCKETS = 4096
TOKENS = WORD_BUCKETS + FORM_BUCKETS
DIM = 32
ROWS = 256  # tokens of the context table that travel together
CHUNK = 1_500_000
#: Labelled rows that the network trains on, give or take a few per cent.
SAMPLE = 20_000
HIDDEN = 32
THRESHOLD = 0.3
FEATURES = 2 * DIM + 3

_rng = np.random.default_rng(5)
_AT = _rng.integers(0, DIM, size=(TOKENS, 2))
_SIGN = _rng.choice([-1.0, 1.0], size=(TOKENS, 2))
_UPPER = np.zeros(256, np.int64)
_UPPER[65:91] = 1
_LETTER = np.zeros(256, np.int64)
_LETTER[97:123] = 1
_LETTER[65:91] = 1
_LETTER[128:] = 1
_MARK = _rng.integers(0, 2**63, size=256, dtype=np.uint64)
_MARK[_LETTER == 1] = 0
_MARK[48:58] = _MARK[48]


def token_ids(texts: list) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(word bucket, form bucket) of each word, and offsets of texts."""
    data = [text_or_empty(t).encode("utf-8", "surrogatepass") for t in texts]
    buf = np.frombuffer(b"\n".join([*data, b""]), dtype=np.uint8)
    h, starts, ends = hash_words(buf)
    borders = np.cumsum([len(d) + 1 for d in data]) if data else np.zeros(0, np.int64)
    offsets = np.concatenate(([0], np.searchsorted(starts, borders))).astype(np.int64)
    if not len(h):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), offsets
    word = (h % np.uint64(WORD_BUCKETS)).astype(np.int64)
    upper = np.add.reduceat(_UPPER[buf], starts)  # blanks add nothing
    letters = np.add.reduceat(_LETTER[buf], starts)
    gaps = np.where(np.isin(buf, (0x20, 9, 10, 11, 12, 13)), np.uint64(0), _MARK[buf])
    marks = np.add.reduceat(gaps, starts)
    case = np.where(upper == 0, 0, np.where((upper == letters) & (letters > 1), 3, np.where(_UPPER[buf[starts]] == 1, 1, 2)))
    form = mix64(marks + (case * 8 + np.minimum(ends - starts, 28) // 4).astype(np.uint64))
    return word, WORD_BUCKETS + (form % np.uint64(FORM_BUCKETS)).astype(np.int64), offsets


def _blocks(texts: list) -> Iterator[list[int]]:
    at, size = 0, 0
    for k, t in enumerate(texts):
        size += len(text_or_empty(t))
        if size >= CHUNK:
            yield list(range(at, k + 1))
            at, size = k + 1, 0
    if at < len(texts):
        yield list(range(at, len(texts)))


def _contexts(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    total = np.zeros(TOKENS * DIM)
    for pdf in batches:
        texts = pdf["text"].tolist()
        for block in _blocks(texts):
            word, form, offsets = token_ids([texts[k] for k in block])
            n = len(word)
            if n < 2:
                continue
            joined = np.ones(n - 1, bool)  # whether word i and i + 1 are of one text
            cut = offsets[1:-1]
            joined[cut[(cut > 0) & (cut < n)] - 1] = False
            left = np.flatnonzero(joined)
            for a, b in ((left, left + 1), (left + 1, left)):  # each word gets its neighbour on either side
                for own in (word[a], form[a]):
                    for other in (word[b], form[b]):
                        for j in range(2):
                            total += np.bincount(own * DIM + _AT[other, j], weights=_SIGN[other, j], minlength=TOKENS * DIM)
    table = total.reshape(TOKENS, DIM)
    salt = TaskContext.get().partitionId() % 64
    yield pd.DataFrame({"block": range(TOKENS // ROWS), "part": salt, "sums": [table[k : k + ROWS].tobytes() for k in range(0, TOKENS, ROWS)]})


def _add(pdf: pd.DataFrame) -> pd.DataFrame:
    total = np.sum([np.frombuffer(b) for b in pdf["sums"]], axis=0)
    return pd.DataFrame({"block": pdf["block"].iloc[:1], "sums": [total.tobytes()]})


def context_vectors(docs: DataFrame) -> np.ndarray:
    """Unit context vector of every token (TOKENS x DIM), from all texts; partial sums are added in two steps."""
    parts = fewer(docs.select(F.col("text").cast("string").alias("text"))).mapInPandas(_contexts, "block int, part int, sums binary")
    first = parts.groupBy("block", "part").applyInPandas(_add, "block int, sums binary")
    rows = first.groupBy("block").applyInPandas(_add, "block int, sums binary").collect()  # TOKENS x DIM numbers
    table = np.zeros((TOKENS, DIM))
    for r in rows:
        table[r["block"] * ROWS : (r["block"] + 1) * ROWS] = np.frombuffer(r["sums"]).reshape(ROWS, DIM)
    table -= table.sum(0) / max(1.0, np.abs(table).sum()) * np.abs(table).sum(1, keepdims=True)  # what is common to all tokens says nothing
    return (table / np.maximum(np.linalg.norm(table, axis=1, keepdims=True), 1e-9)).astype(np.float32)


def pool(texts: list, table: np.ndarray) -> np.ndarray:
    out = np.zeros((len(texts), FEATURES), np.float32)
    for block in _blocks(texts):
        word, form, offsets = token_ids([texts[k] for k in block])
        n = np.diff(offsets)
        full = np.flatnonzero(n)
        rows = np.array(block)[full]
        for at, ids in ((0, word), (DIM, form)):
            if len(ids):
                mean = np.add.reduceat(table[ids], offsets[:-1][full], axis=0) / n[full, None]
                out[rows, at : at + DIM] = mean
                out[rows, 2 * DIM + at // DIM] = (mean * mean).sum(1)
        out[np.array(block), 2 * DIM + 2] = np.log1p(n) / 10
    return out


class Network:
    """x -> tanh layer -> one logit, with standardized inputs and a temperature."""

    def __init__(self, seed: int = 3):
        self.rng = np.random.default_rng(seed)
        self.ready = False

    def _forward(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        h = np.tanh(x @ self.w1 + self.b1)
        return h, h @ self.w2 + self.b2

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 60, batch: int = 128, lr: float = 0.003, decay: float = 1e-4) -> Network:
        order = self.rng.permutation(len(x))
        held, own = order[: len(x) // 5], order[len(x) // 5 :]
        self.mean, self.scale = x[own].mean(0), x[own].std(0) + 1e-6
        z = (x - self.mean) / self.scale
        self.w1 = self.rng.normal(0, 1 / np.sqrt(x.shape[1]), (x.shape[1], HIDDEN))
        self.b1 = np.zeros(HIDDEN)
        self.w2, self.b2 = self.rng.normal(0, 1 / np.sqrt(HIDDEN), HIDDEN), np.zeros(1)
        params = ["w1", "b1", "w2", "b2"]
        m = {p: np.zeros_like(getattr(self, p)) for p in params}
        v = {p: np.zeros_like(getattr(self, p)) for p in params}
        t = 0
        for _ in range(epochs):
            for at in range(0, len(own), batch):
                k = self.rng.choice(own, min(batch, len(own)), replace=False)
                h, logit = self._forward(z[k])
                d = (1 / (1 + np.exp(-np.clip(logit, -40, 40))) - y[k]) / len(k)
                dh = np.outer(d, self.w2) * (1 - h * h)
                g = {"w1": z[k].T @ dh + decay * self.w1, "b1": dh.sum(0), "w2": h.T @ d + decay * self.w2, "b2": np.array([d.sum()])}
                t += 1
                for p in params:
                    m[p] = 0.9 * m[p] + 0.1 * g[p]
                    v[p] = 0.999 * v[p] + 0.001 * g[p] ** 2
                    setattr(self, p, getattr(self, p) - lr * (m[p] / (1 - 0.9**t)) / (np.sqrt(v[p] / (1 - 0.999**t)) + 1e-8))
        self.temperature, self.ready = 1.0, True
        if len(held):
            logit = self._forward(z[held])[1]

            def loss(temp: float) -> float:
                s = logit / temp
                return float(np.mean(np.logaddexp(0, s) - y[held] * s))

            self.temperature = float(min(np.geomspace(0.25, 8, 81), key=loss))
        return self

    def predict(self, x: np.ndarray) -> np.ndarray:
        if not self.ready:
            return np.full(len(x), 0.5)
        logit = self._forward((x - self.mean) / self.scale)[1] / self.temperature
        return 1 / (1 + np.exp(-np.clip(logit, -40, 40)))


def quality_scores(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted of every row; learns from labelled rows outside fold 0 of 5."""
    spark = docs.sparkSession
    scratch = Scratch(spark)
    table = spark.sparkContext.broadcast(context_vectors(docs))

    def features(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            x = pool(pdf["text"].tolist(), table.value)
            yield pd.DataFrame({"doc_id": pdf["doc_id"].astype("Int64") if pdf["doc_id"].isna().any() else pdf["doc_id"], "x": [r.tobytes() for r in x]})

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    pooled = scratch.cut(rows.mapInPandas(features, "doc_id long, x binary"))
    known = labels.where("doc_id is not null and quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").alias("y"))
    train = pooled.join(known, "doc_id").where(fold(F.col("doc_id"), 5) != 0)
    picked = about(train, "doc_id", sample).collect()
    picked.sort(key=lambda r: r["doc_id"])
    net = Network()
    if picked:
        net.fit(np.array([np.frombuffer(r["x"], np.float32) for r in picked], np.float64), np.array([float(r["y"]) for r in picked]))
    held = spark.sparkContext.broadcast({k: v for k, v in net.__dict__.items() if k != "rng"})

    def score(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model = Network()
        model.__dict__.update(held.value)
        for pdf in batches:
            p = model.predict(np.array([np.frombuffer(b, np.float32) for b in pdf["x"]], np.float64).reshape(len(pdf), FEATURES))
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "held_out": pdf["held_out"], "score": p, "predicted": (p >= THRESHOLD).astype(np.int32)})

    tagged = pooled.select("doc_id", (fold(F.col("doc_id"), 5) == 0).alias("held_out"), "x")
    return tagged.mapInPandas(score, "doc_id long, held_out boolean, score double, predicted int")
