"""A hidden Markov language model over words, trained and scored over partitions.

A word that is at least one in OWN of all training tokens has emission numbers of its own, one a state; there
cannot be more than OWN such words, so their table is sent to all tasks. All other words fall into
CLASSES classes by hash; a state emits a class, and a word of the class by its share of the class's training
tokens (with the base model's 0.1 for each word and for one unknown). So a text's likelihood is exact over
an open vocabulary, and what is counted for it, a number for every word, grows with the corpus.

Blocks: each task packs its texts into blocks of about BLOCK_CHARS characters, a row each, with the distinct
words of the block and the place of every token among them. Only distinct words travel: they are counted by
word, and counts of words that other blocks have too go back to their blocks. No vocabulary is ever
held whole by a machine, and no text is shuffled.

Training: Baum-Welch over whole texts, until an iteration gains less than SETTLED nats a token or ITERATIONS are
over; tasks' expected counts are added in two steps. Long texts are cut into segments that advance side by side; the
products of their transition matrices carry the exact forward and backward state across the cuts, so a start is counted
only where a text starts. Scoring: scaled forward recursion over each whole text, cut in the same way.

Defined cases: a null text is empty, its one token is the end. Repeated rows count as often as they occur; rows without an
id, or with the same, are rows like any other. With no training text all counts are 0 and every word is unknown.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, fewer, fold, mix64, text_or_empty, word_hashes

STATES = 6
CLASSES = 4096
OWN = 1 << 16
ITERATIONS = 5
SETTLED = 0.002
SEGMENT = 256
BLOCK_CHARS = 10_000_000
END_HASH = np.uint64(0x9E3779B97F4A7C15)
LOW = 0.1
SMOOTH = 0.01


def tokens(texts: list) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all tokens (each text's words, then the end) and offsets of texts."""
    h, offsets = word_hashes(texts)
    n = len(texts)
    out = np.full(len(h) + n, END_HASH, np.uint64)
    ends = offsets[1:] + np.arange(n)
    keep = np.ones(len(out), bool)
    keep[ends] = False
    out[keep] = h
    return out, offsets + np.arange(n + 1)


def class_of(h: np.ndarray) -> np.ndarray:
    return (mix64(h) & np.uint64(CLASSES - 1)).astype(np.int64)


# --- the recursions ----------------------------------------------------------


class Segments:
    """Texts cut into segments of at most SEGMENT tokens, longest first, so that those still live are a prefix."""

    def __init__(self, codes: np.ndarray, offsets: np.ndarray):
        lens = np.diff(offsets)
        per = -(-lens // SEGMENT)
        text = np.repeat(np.arange(len(lens)), per)
        turn = np.arange(len(text)) - np.repeat(np.cumsum(per) - per, per)
        first = offsets[:-1][text] + SEGMENT * turn
        size = np.minimum(offsets[1:][text] - first, SEGMENT)
        order = np.argsort(-size, kind="stable")
        self.text, self.turn, self.first, self.size = text[order], turn[order], first[order], size[order]
        self.n, self.width, self.turns = len(order), int(size.max(initial=0)), int(per.max(initial=0))
        self.live = [int(np.searchsorted(-self.size, -t, side="left")) for t in range(self.width + 1)]
        padded = np.concatenate((codes, np.zeros(SEGMENT, codes.dtype)))
        self.seqs = padded[self.first[:, None] + np.arange(self.width)] if self.n else np.zeros((0, 0), np.int64)
        place = np.full(len(text), -1, np.int64)
        place[order] = np.arange(len(order))
        self.places = [place[turn == k] for k in range(self.turns)]  # segments of turn k, in the order of their texts
        self.owners = [text[turn == k] for k in range(self.turns)]


def _unit(v: np.ndarray) -> np.ndarray:
    return v / np.maximum(v.sum(-1, keepdims=True), 1e-300 if v.dtype == np.float64 else 1e-30)


def _transfers(s: Segments, trans: np.ndarray, e: np.ndarray) -> np.ndarray:
    """For each segment after its text's first, the product of transition times emission over its tokens, up to a factor."""
    m = np.zeros((s.n, len(trans), len(trans)), e.dtype)
    later = np.flatnonzero(s.turn > 0)
    sizes = s.size[later]
    own = np.tile(np.eye(len(trans), dtype=e.dtype), (len(later), 1, 1))
    for t in range(int(sizes.max(initial=0))):
        k = int(np.searchsorted(-sizes, -t, side="left"))
        own[:k] = (own[:k] @ trans) * e[s.seqs[later[:k], t]][:, None, :]
        if t % 4 == 3:
            own[:k] /= own[:k].sum((1, 2), keepdims=True)
    m[later] = own / own.sum((1, 2), keepdims=True)
    return m


def _carried(s: Segments, start: np.ndarray, trans: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For every segment the state with which it is entered and, up to a factor, the backward vector at its end."""
    entry, leave = np.zeros((s.n, len(start)), e.dtype), np.ones((s.n, len(start)), e.dtype)
    if s.turns < 2:
        return entry, leave
    m = _transfers(s, trans, e)
    texts = s.owners[1]  # all that have a second segment; their first one is whole
    heads = s.places[0][np.searchsorted(s.owners[0], texts)]
    v = _unit(start * e[s.seqs[heads, 0]])
    for t in range(1, SEGMENT):
        v = _unit((v @ trans) * e[s.seqs[heads, t]])
    for k in range(1, s.turns):
        at = s.places[k]
        v = v[np.searchsorted(texts, s.owners[k])]
        texts = s.owners[k]
        entry[at] = v
        v = _unit(np.einsum("ni,nij->nj", v, m[at]))
    for k in range(s.turns - 1, 0, -1):
        at = s.places[k]
        before = s.places[k - 1][np.searchsorted(s.owners[k - 1], s.owners[k])]
        leave[before] = _unit(np.einsum("nij,nj->ni", m[at], leave[at]))
    return entry, leave


def _forward(s: Segments, start: np.ndarray, trans: np.ndarray, e: np.ndarray, entry: np.ndarray, keep: bool) -> tuple[np.ndarray, np.ndarray | None]:
    """Log likelihood of every segment given what came before it, and all scaled states if they are to be kept."""
    logs = np.zeros(s.n)
    alpha = np.zeros((s.width, s.n, len(start)), e.dtype) if keep else None
    v = np.where((s.turn == 0)[:, None], start, entry @ trans) * e[s.seqs[:, 0]] if s.n else entry
    for t in range(s.width):
        k = s.live[t]
        if t:
            v = (v[:k] @ trans) * e[s.seqs[:k, t]]
        total = v[:k].sum(1)
        logs[:k] += np.log(total)
        v = v[:k] / total[:, None]
        if keep:
            alpha[t, :k] = v
    return logs, alpha


def forward_log10(codes: np.ndarray, offsets: np.ndarray, start: np.ndarray, trans: np.ndarray, table: np.ndarray) -> np.ndarray:
    """log10 likelihood of each whole text. table: emission numbers by code and state."""
    s = Segments(codes, offsets)
    entry, _ = _carried(s, start, trans, table)
    logs, _ = _forward(s, start, trans, table, entry, False)
    return np.bincount(s.text, weights=logs, minlength=len(offsets) - 1) / np.log(10)


def expected_counts(codes: np.ndarray, offsets: np.ndarray, start: np.ndarray, trans: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Baum-Welch counts of whole texts: starts, transitions, emissions (by code and state), and the log likelihood."""
    s = Segments(codes, offsets)
    states = len(start)
    c_start, c_trans, c_emit = np.zeros(states), np.zeros((states, states)), np.zeros(table.shape)
    if not s.n:
        return c_start, c_trans, c_emit, 0.0
    a, e, begin = trans.astype(np.float32), table.astype(np.float32), start.astype(np.float32)
    entry, beta = _carried(s, begin, a, e)
    logs, alpha = _forward(s, begin, a, e, entry, True)
    gamma = np.zeros((int(offsets[-1]), states), np.float32)

    def pass_over(own: np.ndarray, ahead: np.ndarray) -> np.ndarray:
        """Counts the transitions between neighbouring tokens; ahead: emission times backward vector of the later one."""
        nonlocal c_trans
        back = ahead @ a.T
        share = np.maximum((own * back).sum(1, keepdims=True), np.float32(1e-30))
        c_trans += ((own / share).T @ ahead) * a
        return _unit(back)

    ahead = np.zeros((s.n, states), np.float32)
    for t in range(s.width - 1, -1, -1):
        later = s.live[t + 1]
        if later:
            beta[:later] = pass_over(alpha[t, :later], ahead[:later])
        k = s.live[t]
        gamma[s.first[:k] + t] = _unit(alpha[t, :k] * beta[:k])
        ahead[:k] = beta[:k] * e[s.seqs[:k, t]]
    for k in range(1, s.turns):
        before = s.places[k - 1][np.searchsorted(s.owners[k - 1], s.owners[k])]
        pass_over(alpha[SEGMENT - 1, before], ahead[s.places[k]])
    c_start = gamma[offsets[:-1]].sum(0, dtype=np.float64)
    for j in range(states):
        c_emit[:, j] = np.bincount(codes, weights=gamma[:, j], minlength=len(table))
    return c_start, c_trans, c_emit, float(logs.sum())


# --- blocks ------------------------------------------------------------------

PACKED = "block long, ids binary, none binary, held binary, offsets binary, at binary, words binary, n binary"


def _pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    part, count = TaskContext.get().partitionId(), 0
    ids, none, held, texts, size = [], [], [], [], 0

    def row() -> pd.DataFrame:
        h, offsets = tokens(texts)
        words, at = np.unique(h, return_inverse=True)
        learn = np.repeat(~np.array(held, bool), np.diff(offsets))
        n = np.bincount(at, weights=learn, minlength=len(words)).astype(np.int64)
        parts = (np.array(ids, np.int64), np.array(none, bool), np.array(held, bool), offsets, at.astype(np.int32), words, n)
        return pd.DataFrame([((part << 32) + count, *(zstandard.compress(x.tobytes()) for x in parts))], columns=[c.split()[0] for c in PACKED.split(", ")])

    for pdf in batches:
        for i, lacks, out, t in zip(pdf["doc_id"], pdf["no_id"], pdf["held_out"], pdf["text"], strict=True):
            ids.append(i)
            none.append(lacks)
            held.append(out)
            texts.append(text_or_empty(t))
            size += len(texts[-1])
            if size >= BLOCK_CHARS:
                yield row()
                count += 1
                ids, none, held, texts, size = [], [], [], [], 0
    if texts:
        yield row()


def _read(packed: bytes, kind) -> np.ndarray:
    return np.frombuffer(zstandard.decompress(packed), kind)


def _asked(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in batches:
        for block, words, n in zip(pdf["block"], pdf["words"], pdf["n"], strict=True):
            h, n = _read(words, np.int64), _read(n, np.int64)
            for lo in range(0, len(h), 200_000):
                part = slice(lo, lo + 200_000)
                yield pd.DataFrame({"block": block, "pos": np.arange(lo, lo + len(h[part]), dtype=np.int32), "h": h[part], "n": n[part]})


def _add(pdf: pd.DataFrame) -> pd.DataFrame:
    return pd.DataFrame({"part": [0], "sums": [np.sum([np.frombuffer(b) for b in pdf["sums"]], axis=0).tobytes()]})


class Model:
    """Start, transitions, words with emissions of their own (sorted hashes), and emissions by code: own words, then classes."""

    def __init__(self, own: np.ndarray, own_counts: np.ndarray, n_class: np.ndarray, n_all: int, seed: int = 11):
        rng = np.random.default_rng(seed)
        order = np.argsort(own)
        self.own = own[order]
        self.start = np.full(STATES, 1 / STATES)
        self.trans = np.full((STATES, STATES), 0.2 / (STATES - 1))
        np.fill_diagonal(self.trans, 0.8)
        first = np.concatenate((own_counts[order] / max(1, n_all), (n_class + 1) / (n_all + CLASSES)))
        self.table = first[:, None] * rng.uniform(0.5, 1.5, (len(first), STATES))

    def codes(self, h: np.ndarray) -> np.ndarray:
        """Code of each word hash."""
        out = len(self.own) + class_of(h)
        if len(self.own):
            at = np.minimum(np.searchsorted(self.own, h), len(self.own) - 1)
            mine = self.own[at] == h
            out[mine] = at[mine]
        return out


def _counting(held):
    """Expected counts of all training texts of a task, in one row."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model, total = held.value, None
        for pdf in batches:
            for r in pdf.itertuples(index=False):
                learn, lens = ~_read(r.held, bool), np.diff(_read(r.offsets, np.int64))
                code = model.codes(_read(r.words, np.uint64))
                codes = code[_read(r.at, np.int32)[np.repeat(learn, lens)]]
                offsets = np.concatenate(([0], np.cumsum(lens[learn]))).astype(np.int64)
                got = expected_counts(codes, offsets, model.start, model.trans, model.table)
                flat = np.concatenate((got[0], got[1].ravel(), got[2].ravel(), [got[3]]))
                total = flat if total is None else total + flat
        if total is not None:
            yield pd.DataFrame({"part": [TaskContext.get().partitionId() % 64], "sums": [total.tobytes()]})

    return count


def train(packed: DataFrame, model: Model, n_all: int, iterations: int = ITERATIONS) -> None:
    """Fits model in place."""
    before = None
    for _ in range(iterations if n_all else 0):
        held = packed.sparkSession.sparkContext.broadcast(model)
        parts = fewer(packed.select("held", "offsets", "at", "words")).mapInPandas(_counting(held), "part int, sums binary")
        rows = parts.groupBy("part").applyInPandas(_add, "part int, sums binary").groupBy("part").applyInPandas(_add, "part int, sums binary").collect()
        held.unpersist()
        if not rows:
            break
        start, trans, table, like = np.split(np.frombuffer(rows[0]["sums"]), np.cumsum([STATES, STATES * STATES, model.table.size]))
        start, trans, table = start + SMOOTH, trans.reshape(STATES, STATES) + SMOOTH, table.reshape(model.table.shape) + SMOOTH
        model.start, model.trans, model.table = start / start.sum(), trans / trans.sum(1, keepdims=True), table / table.sum(0)
        if before is not None and like[0] - before < SETTLED * n_all:
            break
        before = like[0]


def hmm_scores(docs: DataFrame, iterations: int = ITERATIONS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row; learns outside fold 0 of 10."""
    spark = docs.sparkSession
    scratch = Scratch(spark)
    doc_id = F.col("doc_id").cast("long")
    rows = docs.select(F.coalesce(doc_id, F.lit(0)).alias("doc_id"), doc_id.isNull().alias("no_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), (fold(F.col("doc_id"), 10) == 0).alias("held_out"))
    packed = scratch.cut(rows.mapInPandas(_pack, PACKED))
    asked = packed.select("block", "words", "n").mapInPandas(_asked, "block long, pos int, h long, n long")
    totals = scratch.cut(asked.groupBy("h").agg(F.sum("n").alias("c"), F.count(F.lit(1)).alias("k")).where("c > 0"))
    found = totals.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    n_all, v_all = int(found[0]), int(found[1])

    def per_class(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n, v = np.zeros(CLASSES, np.int64), np.zeros(CLASSES, np.int64)
        for pdf in batches:
            c = class_of(pdf["h"].to_numpy().view(np.uint64))
            n += np.bincount(c, weights=pdf["c"], minlength=CLASSES).astype(np.int64)
            v += np.bincount(c, minlength=CLASSES)
        yield pd.DataFrame({"class": range(CLASSES), "n": n, "v": v})

    frequent = F.col("c") * F.lit(OWN) >= F.lit(n_all)
    own = totals.where(frequent).select("h", "c").toPandas()  # at most OWN words can each be one in OWN
    by_class = fewer(totals.where(~frequent).select("h", "c")).mapInPandas(per_class, "class int, n long, v long").groupBy("class").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).toPandas()
    n_class, v_class = np.zeros(CLASSES), np.zeros(CLASSES)
    n_class[by_class["class"]], v_class[by_class["class"]] = by_class["n"], by_class["v"]
    model = Model(own["h"].to_numpy(np.int64).view(np.uint64), own["c"].to_numpy(float), n_class, n_all)
    train(packed, model, n_all, iterations)
    held = spark.sparkContext.broadcast((model, n_class + LOW * (v_class + 1)))

    def score(texts: pd.DataFrame, known: pd.DataFrame) -> pd.DataFrame:
        if not len(texts):
            return pd.DataFrame(columns=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])
        model, class_total = held.value
        r = texts.iloc[0]
        h, count = _read(r["words"], np.uint64), _read(r["n"], np.int64).astype(float)
        offsets, at = _read(r["offsets"], np.int64), _read(r["at"], np.int32)
        count[known["pos"]] = known["c"]
        code, mine = model.codes(h), len(model.own)
        inner = np.where(code < mine, 0.0, np.log10((count + LOW) / class_total[np.maximum(code - mine, 0)]))
        base = np.log10((count + LOW) / (n_all + LOW * (v_all + 1)))
        sums = lambda v: np.add.reduceat(v[at], offsets[:-1])
        ids = pd.array(_read(r["ids"], np.int64).copy(), "Int64")
        ids[_read(r["none"], bool)] = pd.NA
        return pd.DataFrame({
            "doc_id": ids, "held_out": _read(r["held"], bool), "n_tokens": np.diff(offsets), "n_known": sums((count > 0).astype(np.int64)),
            "train_tokens": n_all, "base_score": sums(base), "score": sums(inner) + forward_log10(code[at], offsets, model.start, model.trans, model.table),
        })

    # a word of one block has its count there already
    shared = scratch.cut(totals.where("k > 1").select("h", "c"))
    numbers = asked.select("block", "pos", "h").join(shared.hint("merge"), "h").select("block", "pos", "c")
    return packed.groupBy("block").cogroup(numbers.groupBy("block")).applyInPandas(
        score, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
