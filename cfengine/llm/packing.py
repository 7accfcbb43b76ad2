"""Packing token sequences: Martello-Toth dominance reduction, then best fit on what is left.

Only lengths matter to a packing, so all decisions run on the histogram of piece lengths
(at most capacity entries) and give bin patterns with multiplicities. Reduction fixes, for
the longest piece left, a set that dominates every other set with it: the piece alone if
nothing fits beside it, the pair that fills a bin exactly, and the pair with the largest fitting
partner if no two others fit beside the piece. The rest is packed by best fit, longest first.
Pieces then take the patterns' slots by their rank among pieces of their length.

Defined cases: a null text is empty and gives the one piece [end]. Only documents longer
than the capacity are cut. Repeated rows are separate documents. Other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from bisect import bisect_right
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, ranked, text_or_empty

CAPACITY = 4096
END = 1
TOKENIZER = "word_bpe_49k.json"
CACHE = 500_000  # units a worker remembers

_SPLIT = re.compile(r"[^\x20\x09-\x0D]+")
_LETTERS = "a-zA-Z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\xff"
_NUMBERS = "0-9\xb2\xb3\xb9\xbc-\xbe"
_BLANKS = "\x09-\x0d\x20\x85\xa0"
_UNIT = re.compile(f"[{_LETTERS}]+|[{_NUMBERS}]|[^{_BLANKS}{_LETTERS}{_NUMBERS}]+")
_ODD = ("\x1c", "\x1d", "\x1e", "\x1f")  # blanks to str.split, not to the tokenizer


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(TOKENIZER)


class WordEncoder:
    """Token ids of a text as bytes (little-endian, 32 bits each).

    The tokenizer drops blanks, and never joins across them or, without an apostrophe, across
    the borders of letters, digits and signs. So such units are encoded once and remembered.
    Texts of Latin-1 characters without an apostrophe are lower-cased and cut into these units;
    lower-casing and normalization commute there. Other texts are cut at blanks alone.
    """

    def __init__(self, path: str, limit: int = CACHE):
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        # for units, which are normalized and cut already: the same merges without those steps
        self.merger = Tokenizer.from_file(path)
        self.merger.normalizer = None
        self.merger.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        self.units: dict[str, bytes] = {}
        self.words: dict[str, bytes] = {}
        self.limit = limit
        vocab = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocab.values()) + 1, dtype=bool)
        self.ends[[k for w, k in vocab.items() if w.endswith("</w>")]] = True

    def _learn_units(self, units: list[str]) -> None:
        """Many units in one text: the last token of each, and no other, carries the mark of an end."""
        step = 200
        coded = self.merger.encode_batch_fast([" ".join(units[at : at + step]) for at in range(0, len(units), step)], add_special_tokens=False)
        for at, e in zip(range(0, len(units), step), coded, strict=True):
            part = units[at : at + step]
            ids = np.array(e.ids, dtype="<u4")
            cuts = np.flatnonzero(self.ends[ids]) + 1
            if len(cuts) != len(part):
                self.units.update((w, self._ids(w)) for w in part)
                continue
            data, last = ids.tobytes(), 0
            for w, c in zip(part, (4 * cuts).tolist(), strict=True):
                self.units[w] = data[last:c]
                last = c

    def _ids(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def _known(self, cut: list[list[str]], known: dict[str, bytes], learn) -> None:
        need: set[str] = set()
        need.update(*cut)
        new = need.difference(known)
        if len(known) + len(new) > self.limit:
            known.clear()
            new = need
        learn(list(new))

    def encode(self, texts: list[str]) -> Iterator[bytes]:
        plain = [_latin(t) for t in texts]
        cut = [_UNIT.findall(t.lower()) if p else (_SPLIT.findall(t) if any(c in t for c in _ODD) else t.split()) for t, p in zip(texts, plain, strict=True)]
        self._known([c for c, p in zip(cut, plain, strict=True) if p], self.units, self._learn_units)
        self._known([c for c, p in zip(cut, plain, strict=True) if not p], self.words, lambda new: self.words.update((w, self._ids(w)) for w in new))
        for c, p in zip(cut, plain, strict=True):
            yield b"".join(map((self.units if p else self.words).__getitem__, c))


def _latin(t: str) -> bool:
    if "'" in t or "<|" in t:
        return False
    try:
        t.encode("latin-1")
    except UnicodeEncodeError:
        return False
    return not any(c in t for c in _ODD)


_encoders: dict[str, WordEncoder] = {}


def _pieces_of(path: str, capacity: int, end: int):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        enc = _encoders.setdefault(path, None) or WordEncoder(path)
        _encoders[path] = enc
        last = np.array([end], dtype="<u4").tobytes()
        for pdf in batches:
            for lo in range(0, len(pdf), 1000):
                part = pdf.iloc[lo : lo + 1000]
                rows = []
                for doc, data in zip(part["doc_id"], enc.encode([text_or_empty(t) for t in part["text"]]), strict=True):
                    data += last
                    for k, at in enumerate(range(0, len(data), 4 * capacity)):
                        cut = data[at : at + 4 * capacity]
                        rows.append((doc, k, at // 4, len(cut) // 4, zlib.crc32(cut)))
                out = pd.DataFrame(rows, columns=["doc_id", "piece", "start", "length", "ids_crc32"])
                if out["doc_id"].isna().any():
                    out["doc_id"] = out["doc_id"].astype("Int64")
                yield out

    return run


def pieces(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every piece. One pass, no shuffle."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInPandas(_pieces_of(path or tokenizer_path(), capacity, end), "doc_id long, piece int, start long, length long, ids_crc32 long")


# --- packing of a histogram -------------------------------------------------


@dataclass
class Packing:
    """patterns: (lengths in a bin, how many such bins)."""

    patterns: list[tuple[tuple[int, ...], int]] = field(default_factory=list)
    fixed: int = 0  # bins that the reduction fixed

    @property
    def bins(self) -> int:
        return sum(n for _, n in self.patterns)


class _Lengths:
    """Distinct lengths with counts, and the largest present one that is no longer than a bound."""

    def __init__(self, counts: dict[int, int]):
        self.n = {w: c for w, c in counts.items() if c > 0}
        self.sorted = sorted(self.n)

    def take(self, w: int, c: int) -> None:
        self.n[w] -= c
        if not self.n[w]:
            del self.n[w]
            self.sorted.remove(w)

    def fit(self, room: int, without: int = 0) -> int:
        """Largest length that fits; without: a length of which one piece is already used."""
        k = bisect_right(self.sorted, room) - 1
        while k >= 0 and self.sorted[k] == without and self.n[without] < 2:
            k -= 1
        return self.sorted[k] if k >= 0 else 0


def reduce_by_dominance(counts: dict[int, int], capacity: int) -> tuple[list[tuple[tuple[int, ...], int]], dict[int, int]]:
    """(patterns fixed for good, counts of the remainder), by pieces from long to short until none dominates."""
    left = _Lengths(counts)
    done: list[tuple[tuple[int, ...], int]] = []
    k = len(left.sorted) - 1
    while k >= 0 and left.sorted:
        k = min(k, len(left.sorted) - 1)
        w = left.sorted[k]
        room = capacity - w
        partner = left.fit(room, without=w)
        if not partner:
            done.append(((w,), left.n[w]))
            left.take(w, left.n[w])
        else:
            small = left.sorted[0]
            two = 2 * small if left.n[small] > 1 + (small == w) else small + (left.sorted[1] if len(left.sorted) > 1 else capacity)
            if partner == room or two > room:
                c = left.n[w] // 2 if partner == w else min(left.n[w], left.n[partner])
                done.append(((w, partner), c))
                left.take(w, c)
                left.take(partner, c)
                if w in left.n:
                    continue
        k -= 1
    return done, dict(left.n)


def best_fit(counts: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Longest first, each into the fullest bin it fits. Equal bins are handled together, so the work follows
    the number of distinct lengths and fills, not of pieces."""
    by_room: dict[int, list[list]] = defaultdict(list)  # room -> [pattern, bins]
    rooms: list[int] = []

    def add(pattern: tuple[int, ...], room: int, n: int) -> None:
        if n:
            if room not in by_room or not by_room[room]:
                from bisect import insort

                insort(rooms, room)
            by_room[room].append([pattern, n])

    for w in sorted(counts, reverse=True):
        c = counts[w]
        k = bisect_right(rooms, w - 1)
        while c and k < len(rooms):
            room = rooms[k]
            per = room // w
            group = by_room[room][-1]
            pattern, n = group
            used = min(n, c // per)
            if used:
                group[1] -= used
                c -= used * per
                add(pattern + (w,) * per, room - per * w, used)
            elif c:  # one bin takes the last few
                group[1] -= 1
                add(pattern + (w,) * c, room - c * w, 1)
                c = 0
            if not group[1]:
                by_room[room].remove(group)
                if not by_room[room]:
                    rooms.remove(room)
            k = bisect_right(rooms, w - 1)
        per = capacity // w
        if c // per:
            add((w,) * per, capacity - per * w, c // per)
        if c % per:
            add((w,) * (c % per), capacity - (c % per) * w, 1)
    return [(tuple(p), n) for room in sorted(by_room) for p, n in by_room[room] if n]


def pack_lengths(counts: dict[int, int], capacity: int = CAPACITY) -> Packing:
    done, rest = reduce_by_dominance(counts, capacity)
    return Packing(done + best_fit(rest, capacity), sum(n for _, n in done))


def lower_bound(counts: dict[int, int], capacity: int = CAPACITY) -> int:
    """Bins that any packing needs: the largest Martello-Toth L2 bound over the distinct lengths."""
    ws = sorted(counts)
    best = -(-sum(w * counts[w] for w in ws) // capacity)
    for k in [0, *[w for w in ws if 2 * w <= capacity]]:
        big = sum(counts[w] for w in ws if w > capacity - k)
        mid = sum(counts[w] for w in ws if capacity - k >= w > capacity / 2)
        free = mid * capacity - sum(w * counts[w] for w in ws if capacity - k >= w > capacity / 2)
        small = sum(w * counts[w] for w in ws if capacity / 2 >= w >= k)
        best = max(best, big + mid + max(0, -(-(small - free) // capacity)))
    return best


def slots(packing: Packing) -> tuple[np.ndarray, ...]:
    """Runs of slots, sorted by length and first rank: length, first rank, first sequence, offset."""
    rank: dict[int, int] = defaultdict(int)
    rows, first = [], 0
    for pattern, n in packing.patterns:
        offset = 0
        for w in pattern:
            rows.append((w, rank[w], first, offset))
            rank[w] += n
            offset += w
        first += n
    rows.sort()
    a = np.array(rows, dtype=np.int64).reshape(-1, 4)
    return a[:, 0], a[:, 1], a[:, 2], a[:, 3]


def pack(piece_rows: DataFrame, scratch: Scratch, capacity: int = CAPACITY) -> tuple[DataFrame, Packing]:
    """Adds sequence_id and offset. The driver sees one row a length; the slot table it sends has a few runs a length."""
    counts = {int(r["length"]): int(r["n"]) for r in piece_rows.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    packing = pack_lengths(counts, capacity)
    table = piece_rows.sparkSession.sparkContext.broadcast(slots(packing))
    hashed = piece_rows.withColumn("_h", F.xxhash64("doc_id", "piece", "ids_crc32"))
    placed = ranked(hashed, ["length"], F.struct("doc_id", "piece", "ids_crc32"), F.lit(1), scratch, share=1024)
    shift = 1 << 44

    def seat(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        lengths, ranks, firsts, offsets = table.value
        keys = lengths * shift + ranks
        for pdf in batches:
            k = np.searchsorted(keys, pdf["length"].to_numpy() * shift + pdf["place"].to_numpy(), side="right") - 1
            pdf["sequence_id"] = firsts[k] + pdf["place"].to_numpy() - ranks[k]
            pdf["offset"] = offsets[k]
            yield pdf.drop(columns="place")

    cols = ["doc_id", "piece", "start", "length", "ids_crc32"]
    types = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
    return placed.select(*cols, F.col("place").cast("long").alias("place")).mapInPandas(seat, types), packing


def best_fit_packing(docs: DataFrame, path: str | None = None) -> DataFrame:
    scratch = Scratch(docs.sparkSession)
    return pack(scratch.cut(pieces(docs, path)), scratch)[0]
