"""Approximate nearest neighbours by a permutation index.

Each vector is represented by its NEAREST closest pivots in order. The index is a table that is written once: vectors
are dealt into blocks of about BLOCK, and a block's row holds its vectors and an inverted file for each pivot, with
the place of the pivot in each vector's order. A query reads the lists of its SEEK closest pivots alone and adds up how
far places agree, which ranks candidates by the footrule distance of the two orders (a pivot that is missing counts as
place NEAREST). The best RERANK share of a block's distinct vectors is scored exactly, in
double precision on the original vectors, and blocks' best are merged. Blocks hold parts of every list, so a pivot
that is close to very many vectors is no hot key; a block meets queries QUERY_BLOCK at a time.

Pivots are about SAMPLE vectors with the smallest hashes of their ids, thinned to PIVOTS that lie far apart; every
vector is indexed. Equal vectors share one entry, so crowds of copies neither fill the
candidates nor hide smaller ids.

Defined cases: vectors that are null, of another length than most, zero, or hold a null or
non-finite component take no part, as query or candidate. An id that repeats is a row each time; a query
excludes every row of its own id. No usable vector gives no row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import Scratch, about

PIVOTS = 256
NEAREST = 48
SEEK = 32
SAMPLE = 2048
RERANK = 0.2
LEAST = 256  # candidates reranked in a block at least
BLOCK = 4096
QUERY_BLOCK = 2048
TOP = 5


def choose_pivots(sample: np.ndarray, count: int = PIVOTS) -> np.ndarray:
    """Farthest-first from the first row: each next pivot is the one least like those chosen."""
    unit = sample / np.linalg.norm(sample, axis=1, keepdims=True)
    chosen = [0]
    close = unit @ unit[0]
    while len(chosen) < min(count, len(unit)):
        k = int(close.argmin())
        if close[k] > 1 - 1e-9:
            break
        chosen.append(k)
        close = np.maximum(close, unit @ unit[k])
    return unit[chosen]


def permutations(vectors: np.ndarray, pivots: np.ndarray, nearest: int = NEAREST) -> np.ndarray:
    """Closest pivots of each vector, in order; ties to the smaller pivot."""
    near = -(vectors @ pivots.T)
    return np.argsort(near, axis=1, kind="stable")[:, : min(nearest, len(pivots))]


class InvertedFiles:
    """Posting lists of a block: for each pivot, the entries that have it and its place there."""

    def __init__(self, orders: np.ndarray, pivots: int):
        n, k = orders.shape
        self.n, self.k = n, k
        flat = orders.ravel()
        by_pivot = np.argsort(flat, kind="stable")
        self.entries = (by_pivot // k).astype(np.int64)
        self.places = (by_pivot % k).astype(np.int64)
        self.bounds = np.searchsorted(flat[by_pivot], np.arange(pivots + 1))

    def pack(self) -> tuple[bytes, bytes, bytes]:
        return self.entries.astype(np.int32).tobytes(), self.places.astype(np.int16).tobytes(), self.bounds.astype(np.int64).tobytes()

    @classmethod
    def unpack(cls, n: int, k: int, entries: bytes, places: bytes, bounds: bytes) -> InvertedFiles:
        out = cls.__new__(cls)
        out.n, out.k = n, k
        out.entries, out.places, out.bounds = np.frombuffer(entries, np.int32), np.frombuffer(places, np.int16).astype(np.int64), np.frombuffer(bounds, np.int64)
        return out

    def agreement(self, order: np.ndarray) -> np.ndarray:
        """For each entry a sum over the given pivots' lists that falls as the footrule distance to their order rises:
        distance = constant + sum over pivots of both of (|difference| - 2k + both places)."""
        lists = [slice(self.bounds[p], self.bounds[p + 1]) for p in order]
        entries = np.concatenate([self.entries[s] for s in lists])
        gain = np.concatenate([2 * self.k - q - self.places[s] - np.abs(self.places[s] - q) for q, s in enumerate(lists)])
        return np.bincount(entries, weights=gain, minlength=self.n)


class Block:
    """A block of the index: its distinct vectors, the ids of each, and the inverted files."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, pivots: np.ndarray, nearest: int = NEAREST):
        order = np.argsort(ids, kind="stable")
        ids, vectors = ids[order], np.ascontiguousarray(vectors[order])
        keys = vectors.view(f"V{vectors.shape[1] * vectors.itemsize}").ravel()
        _, first, owner = np.unique(keys, return_index=True, return_inverse=True)
        members = np.argsort(owner, kind="stable")  # ids of an entry stay in order
        self.own, self.ids = vectors[first].astype(np.float64), ids[members]
        self.starts = np.searchsorted(owner[members], np.arange(len(first) + 1))
        self.files = InvertedFiles(permutations(self.own, pivots, nearest), len(pivots))

    def pack(self) -> tuple:
        return (self.own.shape[1], self.files.k, self.own.tobytes(), self.ids.astype(np.int64).tobytes(), self.starts.astype(np.int64).tobytes(), *self.files.pack())

    @classmethod
    def unpack(cls, width: int, k: int, own: bytes, ids: bytes, starts: bytes, entries: bytes, places: bytes, bounds: bytes) -> Block:
        out = cls.__new__(cls)
        out.own, out.ids, out.starts = np.frombuffer(own).reshape(-1, width), np.frombuffer(ids, np.int64), np.frombuffer(starts, np.int64)
        out.files = InvertedFiles.unpack(len(out.own), k, entries, places, bounds)
        return out

    def search(self, query_ids: np.ndarray, queries: np.ndarray, pivots: np.ndarray, top: int, share: float = RERANK, least: int = LEAST, seek: int = SEEK) -> pd.DataFrame:
        """The best top rows of the block for each query."""
        n = len(self.own)
        norms = np.sqrt((self.own * self.own).sum(1))
        keep = min(n, max(least, int(np.ceil(share * n))))
        q = queries.astype(np.float64)
        q_norms = np.sqrt((q * q).sum(1))
        out_q, out_v, out_s = [], [], []
        for k, order in enumerate(permutations(q, pivots, self.files.k)):
            near = np.argpartition(-self.files.agreement(order[:seek]), keep - 1)[:keep] if keep < n else np.arange(n)
            score = self.own[near] @ q[k] / (norms[near] * q_norms[k])
            if len(near) > top + 1:
                cut = np.partition(score, -(top + 1))[-(top + 1)]  # one entry may be the query itself
                near, score = near[score >= cut], score[score >= cut]
            found = []
            for e, s in zip(near, score, strict=True):
                some = self.ids[self.starts[e] : min(self.starts[e + 1], self.starts[e] + top + 64)]
                some = some[some != query_ids[k]]
                if len(some) < top:
                    some = self.ids[self.starts[e] : self.starts[e + 1]]
                    some = some[some != query_ids[k]]
                found += [(-s, v) for v in some[:top]]
            for s, v in sorted(found)[:top]:
                out_q.append(query_ids[k])
                out_v.append(v)
                out_s.append(-s)
        return pd.DataFrame({"query_id": np.array(out_q, np.int64), "vec_id": np.array(out_v, np.int64), "score": np.array(out_s, np.float64)})


def search_block(ids: np.ndarray, vectors: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, pivots: np.ndarray, top: int) -> pd.DataFrame:
    """Index and search of one block at once."""
    return Block(ids, vectors, pivots).search(query_ids, queries, pivots, top)


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id, v (array of double): rows that take part."""
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    rows = rows.where(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & fine & F.exists("v", lambda x: x != 0))
    size = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").first()
    return rows.where(F.size("v") == F.lit(size["n"] if size else 0))


def _packed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in batches:
        yield pd.DataFrame({"vec_id": pdf["vec_id"], "v": [np.asarray(v, np.float64).tobytes() for v in pdf["v"]]})


INDEX = "block int, width int, k int, own binary, ids binary, starts binary, entries binary, places binary, bounds binary"


def build_index(rows: DataFrame, n: int, pivots: np.ndarray, scratch: Scratch, block: int = BLOCK) -> DataFrame:
    """One row a block of about block vectors. rows: vec_id, v (packed doubles)."""
    held = rows.sparkSession.sparkContext.broadcast(pivots)
    blocks = max(1, -(-n // block))

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        made = Block(pdf["vec_id"].to_numpy(), np.frombuffer(b"".join(pdf["v"])).reshape(len(pdf), -1), held.value)
        return pd.DataFrame([(pdf["block"].iloc[0], *made.pack())], columns=[c.split()[0] for c in INDEX.split(", ")])

    dealt = rows.withColumn("block", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(blocks)).cast("int"))
    return scratch.cut(dealt.groupBy("block").applyInPandas(build, INDEX))


def search_index(index: DataFrame, queries: DataFrame, n_queries: int, pivots: np.ndarray, top: int) -> DataFrame:
    """query_id, vec_id, score: the best top rows of every block for each query (vec_id, v)."""
    held = index.sparkSession.sparkContext.broadcast(pivots)
    q_blocks = max(1, -(-n_queries // QUERY_BLOCK))
    blocks = (index.agg(F.max("block")).first()[0] or 0) + 1
    own = index.withColumn("q_block", F.explode(F.sequence(F.lit(0), F.lit(q_blocks - 1))))
    asked = queries.withColumn("q_block", F.pmod(F.xxhash64("vec_id", F.lit(2)), F.lit(q_blocks)).cast("int")).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))

    def cell(made: pd.DataFrame, pdf: pd.DataFrame) -> pd.DataFrame:
        if not len(made) or not len(pdf):
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype({"query_id": "int64", "vec_id": "int64", "score": "float64"})
        row = made.iloc[0]
        block = Block.unpack(*(row[c.split()[0]] for c in INDEX.split(", ")[1:]))
        ids, at = np.unique(pdf["vec_id"].to_numpy(), return_index=True)
        return block.search(ids, np.frombuffer(b"".join(pdf["v"].iloc[at])).reshape(len(ids), -1), held.value, top)

    return own.groupBy("block", "q_block").cogroup(asked.groupBy("block", "q_block")).applyInPandas(cell, "query_id long, vec_id long, score double")


def nearest_neighbours(vectors: DataFrame, every: int = 50, top: int = TOP, block: int = BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score: queries are the ids divisible by every."""
    spark = vectors.sparkSession
    scratch = Scratch(spark)
    rows = scratch.cut(usable(vectors).mapInPandas(_packed, "vec_id long, v binary"))
    n = rows.count()
    sample = about(rows, "vec_id", SAMPLE).collect()
    sample.sort(key=lambda r: (r["vec_id"], r["v"]))
    if not sample:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    pivots = choose_pivots(np.array([np.frombuffer(r["v"]) for r in sample]))
    index = build_index(rows, n, pivots, scratch, block)
    queries = rows.where(F.col("vec_id") % every == 0)
    found = search_index(index, queries, queries.count(), pivots, top)
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= top).select("query_id", "rank", "vec_id", "score")
