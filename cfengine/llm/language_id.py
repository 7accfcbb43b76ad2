"""Language identification by spans.

Script ranges narrow the languages a word can have; n-gram scores of each word under each
remaining language feed a Viterbi search whose penalty for switching keeps spans long. The
prediction is the language with most letters in its spans.

Training counts hashed character n-grams (1 to 4, over lower-cased words with their borders)
per language over all training rows; the table is BUCKETS rows whatever the corpus.

Defined cases: a null text, or one without a letter, is `und` with score 0. Without any
training row every text is `und`. Repeated rows stay repeated. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fewer, fold, mix64, text_or_empty

BUCKETS = 1 << 16
ORDERS = (1, 2, 3, 4)
SWITCH = 6.0  # nats
UNKNOWN = "und"
CHUNK = 500_000  # characters scored at once

#: First code point of each script range and its number: fixed values. 0 is no letter of a known script.
SCRIPT_STARTS = np.array([0x0, 0x41, 0x5B, 0x61, 0x7B, 0xAA, 0xAB, 0xB5, 0xB6, 0xBA, 0xBB, 0xC0, 0x250, 0x370, 0x400, 0x530, 0x590, 0x600, 0x700, 0x900, 0x980, 0xE00, 0xE80, 0x10A0, 0x1100, 0x1200, 0x1E00, 0x1F00, 0x2000, 0x3040, 0x3100, 0x3400, 0xA000, 0xAC00, 0xD7B0])
SCRIPT_KINDS = np.array([0, 1, 0, 1, 0, 1, 0, 1, 0, 1, 0, 1, 1, 2, 3, 4, 5, 6, 7, 8, 9, 10, 11, 12, 13, 14, 1, 2, 0, 15, 0, 16, 0, 13, 0])
SCRIPTS = 17
_LETTER = np.zeros(0x110000, dtype=bool)


def _letters() -> np.ndarray:
    if not _LETTER[97]:
        _LETTER[:] = np.fromiter((chr(c).isalpha() for c in range(0x110000)), dtype=bool, count=0x110000)
    return _LETTER


def _chunks(texts: list[str]) -> Iterator[tuple[list[int], np.ndarray]]:
    """Runs of texts as code points, each text followed by a blank; long texts come in parts that end at a blank."""
    owners: list[int] = []
    parts: list[str] = []
    size = 0
    for k, t in enumerate(texts):
        at = 0
        while at < len(t) or at == 0:
            end = min(len(t), at + CHUNK)
            while end < len(t) and not t[end].isspace():
                end += 1
            owners.append(k)
            parts.append(t[at:end])
            size += end - at + 1
            at = max(end, at + 1)
            if size >= CHUNK:
                yield owners, _points(parts)
                owners, parts, size = [], [], 0
            if end >= len(t):
                break
    if parts:
        yield owners, _points(parts)


def _points(parts: list[str]) -> np.ndarray:
    return np.frombuffer("\0".join([*parts, ""]).lower().encode("utf-32-le", "surrogatepass"), dtype=np.uint32)


def _features(points: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Word spans (runs of letters), script and letter count of each word, and its n-gram buckets by order."""
    letter = _letters()[points]
    edge = np.flatnonzero(np.diff(np.concatenate(([False], letter, [False])).astype(np.int8)))
    starts, ends = edge[0::2], edge[1::2]
    script = SCRIPT_KINDS[np.searchsorted(SCRIPT_STARTS, points[starts], side="right") - 1]
    c = np.where(letter, points, 0).astype(np.uint64)
    padded = np.concatenate((np.zeros(1, np.uint64), c, np.zeros(4, np.uint64)))
    grams = np.empty((len(ORDERS), len(c)), dtype=np.int32)
    h = np.zeros(len(c), np.uint64)
    for n in range(max(ORDERS)):
        h = h * np.uint64(1_000_003) + padded[n : n + len(c)] + np.uint64(7)
        if n + 1 in ORDERS:
            grams[ORDERS.index(n + 1)] = (mix64(h + np.uint64(n)) & np.uint64(BUCKETS - 1)).astype(np.int32)
    return starts, ends, script, letter, grams


def _count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    sums: dict[str, np.ndarray] = {}
    seen: dict[str, np.ndarray] = {}
    for pdf in batches:
        for lang, group in pdf.groupby("lang"):
            total = sums.setdefault(lang, np.zeros(BUCKETS, np.int64))
            scripts = seen.setdefault(lang, np.zeros(SCRIPTS, np.int64))
            for _, points in _chunks([text_or_empty(t) for t in group["text"]]):
                starts, ends, script, letter, grams = _features(points)
                for g in grams:
                    total += np.bincount(g[letter], minlength=BUCKETS)
                np.add.at(scripts, script, ends - starts)
    for lang, total in sums.items():
        at = np.flatnonzero(total)
        own = np.flatnonzero(seen[lang])
        yield pd.DataFrame({"lang": lang, "at": np.concatenate((at, -1 - own)), "n": np.concatenate((total[at], seen[lang][own]))})


def _viterbi(scores: np.ndarray, offsets: np.ndarray, penalty: float) -> np.ndarray:
    """Best language of each word of each text; texts advance side by side, longest first."""
    n, k = scores.shape
    best = np.zeros(n, dtype=np.int8)
    if k == 1 or not n:
        return best
    lens = np.diff(offsets)
    order = np.argsort(-lens, kind="stable")
    starts, lens = offsets[:-1][order], lens[order]
    stay = np.ones((n, k), dtype=bool)  # whether the best path into a state stayed in it
    via = np.zeros(n, dtype=np.int8)  # else the state it came from
    active = int(np.searchsorted(-lens, 0, side="left"))
    v = scores[starts[:active]].copy()
    final = np.zeros(len(lens), dtype=np.int8)
    t = 1
    while active:
        left = int(np.searchsorted(-lens, -t, side="left"))  # texts with more than t words
        if left < active:
            final[left:active] = v[left:active].argmax(1)
            v, active = v[:left], left
            if not active:
                break
        at = starts[:active] + t
        top = v.argmax(1)
        jump = v[np.arange(active), top] - penalty
        keep = v >= jump[:, None]
        via[at] = top
        stay[at] = keep
        v = np.where(keep, v, jump[:, None]) + scores[at]
        t += 1
    state = final.copy()
    active = 0
    for t in range(int(lens[0]) - 1 if len(lens) else -1, -1, -1):
        active = int(np.searchsorted(-lens, -t, side="left"))
        at = starts[:active] + t
        best[at] = state[:active]
        if t:
            held = stay[at, state[:active]]
            state[:active] = np.where(held, state[:active], via[at])
    return best


class LanguageModel:
    def __init__(self, langs: list[str], logp: np.ndarray, allowed: np.ndarray, penalty: float = SWITCH):
        self.langs, self.logp, self.allowed, self.penalty = langs, logp, allowed, penalty

    def word_scores(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Scores (word x language), letters and start of each word."""
        starts, ends, script, letter, grams = _features(points)
        if not len(starts):
            return np.zeros((0, len(self.langs)), np.float32), starts, starts
        per_char = self.logp[grams[0][letter]]
        for g in grams[1:]:
            per_char = per_char + self.logp[g[letter]]
        lens = ends - starts
        scores = np.add.reduceat(per_char, np.concatenate(([0], np.cumsum(lens)[:-1])), axis=0) / np.float32(len(ORDERS))
        return scores + np.where(self.allowed[script], np.float32(0), np.float32(-50)), lens, starts

    def label(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(language, letters) of each word and the offsets of texts."""
        scores, lens, counts = [], [], np.zeros(len(texts), np.int64)
        for owners, points in _chunks(texts):
            s, n, starts = self.word_scores(points)
            ends = np.flatnonzero(points == 0)[: len(owners)] if len(owners) == int((points == 0).sum()) else None
            if ends is None:  # a text holds NUL: find the borders by length
                raise ValueError("NUL must be replaced before scoring")
            per = np.diff(np.concatenate(([0], np.searchsorted(starts, ends))))
            np.add.at(counts, owners, per)
            scores.append(s)
            lens.append(n)
        offsets = np.concatenate(([0], np.cumsum(counts)))
        if not scores:
            return np.zeros(0, np.int8), np.zeros(0, np.int64), offsets
        return _viterbi(np.concatenate(scores), offsets, self.penalty), np.concatenate(lens), offsets

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray]:
        if not self.langs:
            return [UNKNOWN] * len(texts), np.zeros(len(texts))
        best, lens, offsets = self.label([t.replace("\0", " ") for t in texts])
        k = len(self.langs)
        owner = np.repeat(np.arange(len(texts)), np.diff(offsets))
        shares = np.bincount(owner * k + best, weights=lens, minlength=len(texts) * k).reshape(-1, k)
        total = shares.sum(1)
        score = np.divide(shares.max(1), total, out=np.zeros(len(texts)), where=total > 0)
        return [self.langs[j] if n else UNKNOWN for j, n in zip(shares.argmax(1), total, strict=True)], score

    def spans(self, text: str) -> list[tuple[int, int, str]]:
        """(first word, last word + 1, language) of each span of one text."""
        best, _, _ = self.label([text.replace("\0", " ")])
        cuts = np.flatnonzero(np.diff(best)) + 1
        edges = [0, *cuts.tolist(), len(best)]
        return [(a, b, self.langs[best[a]]) for a, b in zip(edges, edges[1:], strict=False) if b > a]


def fit_language_model(docs: DataFrame, penalty: float = SWITCH) -> LanguageModel:
    """docs: text, lang. Counts every row with a language; the driver gets at most BUCKETS rows a language."""
    rows = docs.where(F.col("lang").isNotNull()).select(F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    counts = fewer(rows).mapInPandas(_count, "lang string, at long, n long").groupBy("lang", "at").agg(F.sum("n").alias("n")).toPandas()
    langs = sorted(counts["lang"].unique())
    n = np.full((BUCKETS, len(langs)), 0.1)
    seen = np.zeros((SCRIPTS, len(langs)))
    for j, lang in enumerate(langs):
        own = counts[counts["lang"] == lang]
        at, c = own["at"].to_numpy(), own["n"].to_numpy()
        n[at[at >= 0], j] += c[at >= 0]
        seen[-1 - at[at < 0], j] += c[at < 0]
    logp = np.log(n / n.sum(0)) if langs else n
    allowed = seen > 0.001 * seen.sum(0, keepdims=True)
    allowed[~allowed.any(1)] = True
    return LanguageModel(langs, logp.astype(np.float32), allowed, penalty)


def identify_languages(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, lang_pred, score of every row, from its text alone. No shuffle."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            langs, score = held.value.predict([text_or_empty(t) for t in pdf["text"]])
            yield pd.DataFrame({"doc_id": pdf["doc_id"].to_numpy(), "held_out": pdf["held_out"].to_numpy(), "lang_pred": langs, "score": score})

    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", (fold(F.col("doc_id"), 5) == 0).alias("held_out"), F.col("text").cast("string").alias("text"))
    return rows.mapInPandas(run, f"doc_id {kind}, held_out boolean, lang_pred string, score double")


def language_id(docs: DataFrame) -> DataFrame:
    """Learns from rows outside fold 0 of 5, then predicts every row."""
    return identify_languages(docs, fit_language_model(docs.where(fold(F.col("doc_id"), 5) != 0)))
