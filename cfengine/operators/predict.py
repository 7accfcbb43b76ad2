"""Scores and top-k lists."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..shipping import ship
from .blocks import TrainConfig


def score_pairs(pairs: DataFrame, users: DataFrame, items: DataFrame, similarity: str = "cosine") -> DataFrame:
    j = pairs.join(users.select(F.col("id").alias("user_id"), F.col("vec").alias("s")), "user_id").join(items.select(F.col("id").alias("item_id"), F.col("vec").alias("t")), "item_id")
    f = V.cosine if similarity == "cosine" else V.dot
    return j.select("user_id", "item_id", f(F.col("s"), F.col("t")).alias("score"))


def predict_block(users: DataFrame, items: DataFrame, similarity: str = "dot") -> DataFrame:
    """user_id, item_id, score of every cell of a chosen slice of the predicted matrix. users, items: id, vec of
    the slice; the smaller side is sent to all tasks only if Spark's own size check allows it."""
    f = V.cosine if similarity == "cosine" else V.dot
    cells = users.select(F.col("id").alias("user_id"), F.col("vec").alias("s")).crossJoin(items.select(F.col("id").alias("item_id"), F.col("vec").alias("t")))
    return cells.select("user_id", "item_id", f(F.col("s"), F.col("t")).alias("score"))


def history_sums(rows: DataFrame, keys: list[str], users: DataFrame, items: DataFrame, params: np.ndarray, cfg: TrainConfig) -> DataFrame:
    """keys, num, den, off of history rows (user_id, item_id, keys, counts): sums of weight x row and of weights, and the
    exponent taken off each weight, all of a user alike. Rows that do not count add nothing but keep their keys.
    Sums have map-side partial sums, so no history is gathered."""
    k, rest = cfg.dim, params[cfg.dim :]
    rows = rows.join(items.select(F.col("id").alias("item_id"), F.col("vec").alias("t")), "item_id")
    if cfg.aggregator == "average":
        rows = rows.select(*keys, "counts", "t", F.struct(F.lit(1.0).alias("e"), F.lit(0.0).alias("off")).alias("w"))
    else:
        asks = cfg.aggregator == "user_attention"
        rows = rows.join(users.select(F.col("id").alias("user_id"), F.col("vec").alias("s")), "user_id") if asks else rows.withColumn("s", F.array().cast("array<double>"))

        @F.pandas_udf("e double, off double")
        def weight(t: pd.Series, s: pd.Series) -> pd.DataFrame:
            act = np.tanh(np.stack(t) @ rest[:k].T + rest[k])
            q = np.stack(s) if asks else np.broadcast_to(rest[k + 1], act.shape)
            off = np.abs(q).sum(1)  # tanh bounds the exponent
            return pd.DataFrame({"e": np.exp((act * q).sum(1) - off), "off": off})

        rows = V.carry(rows, *keys, "counts", "t", weight("t", "s").alias("w"))
    e = F.when(F.col("counts"), F.col("w.e")).otherwise(0.0)
    sums = rows.groupBy(*keys).agg(F.sum(e).alias("den"), F.max("w.off").alias("off"), *[F.sum(e * F.col("t")[d]).alias(f"_{d}") for d in range(k)])
    return sums.select(*keys, F.array(*[F.col(f"_{d}") for d in range(k)]).alias("num"), "den", "off")


def pooled_rows(rows: DataFrame, users: DataFrame, items: DataFrame, params: np.ndarray, cfg: TrainConfig) -> DataFrame:
    """user_id, vec: the pooled row of every user in rows (user_id, item_id, counts)."""
    return history_sums(rows, ["user_id"], users, items, params, cfg).select("user_id", F.transform("num", lambda v: v / F.col("den")).alias("vec"))


def aggregated_users(users: DataFrame, items: DataFrame, history: DataFrame, params: np.ndarray, cfg: TrainConfig) -> DataFrame:
    """id, vec of every user: the row that training scored with, over the whole history (user_id, hist).
    Pooled rows are ratios of sums, so no history is gathered. A user without one keeps its gated row."""
    ship(users.sparkSession)
    k, gate = cfg.dim, cfg.gate
    layer = params[:k]
    rows = history.select("user_id", F.explode("hist").alias("item_id"), F.lit(True).alias("counts"))
    pooled = pooled_rows(rows, users, items, params, cfg).select(F.col("user_id").alias("id"), F.col("vec").alias("p"))

    @F.pandas_udf("array<double>")
    def mixed(s: pd.Series, p: pd.Series) -> pd.Series:
        return pd.Series(list(gate * np.stack(s) + (1 - gate) * (np.stack(p) @ layer)))

    return users.join(pooled, "id", "left").select("id", mixed("vec", F.coalesce("p", F.array_repeat(F.lit(0.0), k))).alias("vec"))


#: Users and bytes of item rows that a cell holds; items of a leaf; leaves and users that meet before any other; users' leaves and
#: candidates that wait at a time.
CELL_USERS, CELL_BYTES = 1 << 16, 40 << 20
LEAF, FIRST, CHUNK, WAITING = 256, 8, 512, 1 << 19


def _deal(rows: np.ndarray, n: int, rng: np.random.Generator) -> np.ndarray:
    """Groups of near directions: each row goes to the nearest of n rows, moved to the middle of what a sample gives them."""
    sample = rows[rng.choice(len(rows), min(len(rows), 48 * n), replace=False)]
    mid = sample[rng.choice(len(sample), min(len(sample), n), replace=False)]
    for _ in range(3):
        of = np.argmax(sample @ mid.T, axis=1)
        moved = np.stack([np.bincount(of, weights=sample[:, d], minlength=len(mid)) for d in range(rows.shape[1])], axis=1)
        size = np.linalg.norm(moved, axis=1, keepdims=True)
        mid = np.where(size > 0, moved / np.maximum(size, 1e-30), mid).astype(rows.dtype)
    return np.concatenate([np.argmax(rows[lo : lo + (1 << 14)] @ mid.T, axis=1) for lo in range(0, len(rows), 1 << 14)])


def _leaves(units: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order of rows of length 1 in which leaves of about LEAF near ones lie together, and where these begin and end."""
    rng = np.random.default_rng(1)
    n = max(1, round((len(units) / LEAF) ** 0.5))
    of = _deal(units, n, rng).astype(np.int64) * (4 * n)
    for g in np.unique(of):
        own = np.flatnonzero(of == g)
        of[own] += _deal(units[own], min(2 * n, -(-len(own) // LEAF)), rng)
    order = np.argsort(of, kind="stable")
    first = np.flatnonzero(np.concatenate(([True], np.diff(of[order]) > 0)))
    return order, np.append(first, len(order))


class _Lists:
    """The k best unseen items of every user of a cell. Items lie in leaves of near directions, and a user meets the leaves whose
    bound reaches its k-th score: an angle for cosine, a distance for dot. Screened in single precision with a margin; scores
    and order are those of double precision, so the lists are exact."""

    def __init__(self, users: np.ndarray, items: np.ndarray, item_ids: np.ndarray, seen: tuple[np.ndarray, np.ndarray], k: int, cosine: bool):
        self.k, self.ids = k, item_ids
        size = [np.maximum(np.sqrt(np.einsum("rk,rk->r", v, v)), 1e-300) for v in (users, items)]
        most = float(size[1].max())
        unit, directions = (np.divide(v, n[:, None], out=np.empty(v.shape, np.float32), casting="same_kind") for v, n in zip((users, items), size, strict=True))
        order, ends = _leaves(directions)
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        self.ends, self.order = ends, order
        self.s, self.t, self.size = users, items, size
        self.unit, self.scale = unit, np.ones(len(users)) if cosine else size[0] * most
        self.held = (directions if cosine else np.divide(items, most, out=directions, casting="same_kind"))[order]
        self.tol = 1e-6 * (users.shape[1] + 8)
        self.seen = np.sort(seen[0] * len(item_ids) + place[seen[1]])
        self.cosine = cosine
        lens = np.diff(ends)
        mid = np.add.reduceat(self.held, ends[:-1], axis=0, dtype=float) / lens[:, None]
        leaf = np.repeat(np.arange(len(lens)), lens)
        by_part = lambda f: np.concatenate([f(self.held[lo : lo + (1 << 16)], mid[leaf[lo : lo + (1 << 16)]]) for lo in range(0, len(leaf), 1 << 16)])
        if cosine:
            mid = mid / np.maximum(np.linalg.norm(mid, axis=1, keepdims=True), 1e-300)
            empty = ~self.held.any(axis=1)  # of length 0: its score is 0 for all
            near = np.where(empty, 1.0, by_part(lambda v, m: np.einsum("rk,rk->r", v, m)))
            wide = np.arccos(np.clip(np.minimum.reduceat(near, ends[:-1]), -1, 1)) + 1e-3
            wide[np.logical_or.reduceat(empty, ends[:-1])] = np.pi
            self.widest = float(wide[wide < np.pi].max(initial=0.0))
            self.bound = np.column_stack((mid, np.cos(wide), np.sin(wide)))
            self.always = np.flatnonzero(wide >= np.pi)
        else:
            far = by_part(lambda v, m: np.linalg.norm(v - m, axis=1))
            self.bound = np.column_stack((mid, np.maximum.reduceat(far, ends[:-1]), np.ones(len(lens))))
            self.always = np.zeros(0, np.int64)
        self.bound = self.bound.astype(np.float32)
        self.floor = np.full(len(users), -np.inf)  # what a user's k-th score reaches for certain, in units of scale
        self.best = np.full((len(users), k), -np.inf)
        self.item = np.full((len(users), k), -1, np.int64)  # places
        self.pile: list[tuple[np.ndarray, np.ndarray]] = []
        self.piled = 0

    def _by_leaf(self, u: np.ndarray, leaf: np.ndarray):
        order = np.argsort(leaf, kind="stable")
        cut = np.flatnonzero(np.diff(leaf[order])) + 1
        for own in np.split(order, cut):
            if len(own):
                lo, hi = self.ends[leaf[own[0]]], self.ends[leaf[own[0]] + 1]
                for at in range(0, len(own), CHUNK):
                    who = u[own[at : at + CHUNK]]
                    yield who, lo, hi, self.unit[who] @ self.held[lo:hi].T

    def meet(self, u: np.ndarray, leaf: np.ndarray) -> None:
        """Every item of these leaves that may be on the list of the user beside it becomes a candidate."""
        for who, lo, _, x in self._by_leaf(u, leaf):
            r, c = np.divmod(np.flatnonzero(x >= (self.floor[who] - self.tol).astype(np.float32)[:, None]), x.shape[1])
            self.pile.append((who[r], lo + c))
            self.piled += len(r)
            if self.piled > WAITING:
                self.settle()

    def settle(self) -> None:
        """Candidates that wait are scored and go to the lists."""
        if not self.pile:
            return
        u, at = (np.concatenate(v) for v in zip(*self.pile, strict=True))
        self.pile, self.piled = [], 0
        key = u * len(self.ids) + at
        if len(self.seen):
            new = self.seen[np.minimum(np.searchsorted(self.seen, key), len(self.seen) - 1)] != key
            u, at = u[new], at[new]
        rows, score = self.order[at], np.zeros(len(u))
        for d in range(self.s.shape[1]):
            score += self.s[u, d] / self.size[0][u] * (self.t[rows, d] / self.size[1][rows]) if self.cosine else self.s[u, d] * self.t[rows, d]
        some = np.flatnonzero(np.isfinite(score) & (score >= self.best[u, -1]))
        u, at, score = u[some], at[some], score[some]
        who = np.unique(u)
        old = self.item[who] >= 0
        u = np.concatenate((u, np.repeat(who, old.sum(1))))
        at, score = np.concatenate((at, self.item[who][old])), np.concatenate((score, self.best[who][old]))
        order = np.lexsort((self.ids[self.order[at]], -score, u))
        u, at, score = u[order], at[order], score[order]
        first = np.searchsorted(u, who)
        rank = np.arange(len(u)) - np.repeat(first, np.diff(np.append(first, len(u))))
        top = rank < self.k
        self.best[who], self.item[who] = -np.inf, -1
        self.best[u[top], rank[top]], self.item[u[top], rank[top]] = score[top], at[top]
        self.floor[who] = np.maximum(self.floor[who], self.best[who, -1] / self.scale[who])

    def _reach(self, who: np.ndarray) -> np.ndarray:
        """By user and leaf, by how much the leaf's bound is above the user's k-th score (at least its sign)."""
        floor = self.floor[who]
        if self.cosine:
            a = np.arccos(np.clip(floor, -1, 1))
            row = np.column_stack((self.unit[who], -np.cos(a), np.sin(a)))
            row[a + self.widest >= np.pi] = 0.0  # any leaf
        else:
            row = np.column_stack((self.unit[who], np.ones(len(who)), -np.maximum(floor, -4.0)))
        out = row.astype(np.float32) @ self.bound.T
        out[:, self.always] = 0.0
        return out

    def run(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Users, ranks, items and scores."""
        n, lens = len(self.unit), np.diff(self.ends)
        dim, some = self.unit.shape[1], min(FIRST, len(lens))
        near, nearest = np.empty((n, some), np.int64), np.empty(n, np.int64)
        large = np.flatnonzero(lens >= min(2 * self.k, lens.max()))
        for lo in range(0, n, CHUNK):
            p = self.unit[lo : lo + CHUNK] @ self.bound[:, :dim].T
            near[lo : lo + CHUNK] = np.argpartition(-p, some - 1, axis=1)[:, :some]
            nearest[lo : lo + CHUNK] = large[np.argmax(p[:, large], axis=1)]
        every = np.arange(n)
        for who, lo, hi, x in self._by_leaf(every, nearest):  # the k-th unseen one of the nearest leaf is a first floor
            if hi - lo >= self.k:
                if len(self.seen):
                    first, last = (np.searchsorted(self.seen, who * len(self.ids) + v) for v in (lo, hi))
                    r = np.repeat(np.arange(len(who)), last - first)
                    at = np.repeat(first - (np.cumsum(last - first) - (last - first)), last - first) + np.arange(len(r))
                    x[r, self.seen[at] % len(self.ids) - lo] = -np.inf
                self.floor[who] = np.partition(x, hi - lo - self.k, axis=1)[:, hi - lo - self.k] - self.tol
        self.meet(np.repeat(every, some), near.ravel())
        self.settle()
        found, waits = [], 0
        for lo in range(0, n, CHUNK):
            reach = self._reach(every[lo : lo + CHUNK])
            reach[np.arange(len(reach))[:, None], near[lo : lo + CHUNK]] = -np.inf
            r, leaf = np.divmod(np.flatnonzero(reach >= -self.tol), len(lens))
            found.append((r + lo, leaf))
            waits += len(r)
            if waits > WAITING or lo + CHUNK >= n:
                self.meet(*(np.concatenate(v) for v in zip(*found, strict=True)))
                found, waits = [], 0
        self.settle()
        u, r = np.nonzero(self.item >= 0)
        return u, r + 1, self.order[self.item[u, r]], self.best[u, r]


def _matrix(rows: pa.Table, side: str) -> tuple[np.ndarray, np.ndarray]:
    """ids in order and their rows; a row that holds what is no number takes no part."""
    at = np.flatnonzero(pc.equal(rows["side"], side).to_numpy())
    if not len(at):
        return np.zeros(0, np.int64), np.zeros((0, 1))
    ids = rows["id"].to_numpy()[at]
    order = np.argsort(ids, kind="stable")
    place = np.empty(len(at), np.int64)
    place[order] = np.arange(len(at))
    vec, base = None, 0
    for part in rows.to_batches():  # no copy of the whole beside the one that is asked for
        here = np.flatnonzero((at >= base) & (at < base + part.num_rows))
        lists, own = part["vec"], at[here] - base
        flat, first = lists.values.to_numpy(zero_copy_only=False), lists.offsets.to_numpy()
        if len(here):
            vec = np.empty((len(at), first[own[0] + 1] - first[own[0]])) if vec is None else vec
            for d in range(vec.shape[1]):
                vec[place[here], d] = flat[first[own] + d]
        base += part.num_rows
    fine = np.isfinite(vec.sum(axis=1))
    return (ids[order], vec) if fine.all() else (ids[order][fine], vec[fine])


def _known(ids: np.ndarray, asked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.minimum(np.searchsorted(ids, asked), len(ids) - 1)
    return at, ids[at] == asked


def recommend(users: DataFrame, items: DataFrame, seen: DataFrame | None, k: int = 20, similarity: str = "cosine") -> DataFrame:
    """user_id, rank, item_id, score: seen items are left out. Cells of users meet items, in as few parts as memory allows; a cell
    returns k rows a user and part."""
    spark = ship(users.sparkSession)
    n_u = max(1, -(-users.count() // CELL_USERS), min(spark.sparkContext.defaultParallelism, users.count() // CHUNK))
    size = items.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("vec")).alias("dim")).first()
    n_i = max(1, -(-size.n * 8 * max(1, size.dim or 1) // CELL_BYTES))
    ub, ib = (lambda c, n=n: F.pmod(F.xxhash64(c), F.lit(n)).cast("int") for n in (n_u, n_i))
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    u = users.select(F.lit("user").alias("side"), "id", "vec", ub("id").alias("ub")).withColumn("ib", every(n_i))
    i = items.select(F.lit("item").alias("side"), "id", "vec", ib("id").alias("ib")).withColumn("ub", every(n_u))
    rows = u.unionByName(i)
    if seen is None:
        seen = users.select(F.col("id").alias("user_id")).limit(0).withColumn("item_id", F.lit(0).cast("long"))
    marks = seen.select("user_id", "item_id", ub("user_id").alias("ub"), ib("item_id").alias("ib"))

    def cell(vecs: pa.Table, known: pa.Table) -> pa.Table:
        pa.default_memory_pool().release_unused()  # of the worker's last cell
        (ui, s), (ii, t) = _matrix(vecs, "user"), _matrix(vecs, "item")
        out = [np.zeros(0, np.int64)] * 3 + [np.zeros(0)]
        if len(ui) and len(ii):
            (a, has_a), (b, has_b) = _known(ui, known["user_id"].to_numpy()), _known(ii, known["item_id"].to_numpy())
            both = has_a & has_b
            at, rank, item, score = _Lists(s, t, ii, (a[both], b[both]), k, similarity == "cosine").run()
            out = [ui[at], rank, ii[item], score]
        return pa.table({"user_id": out[0], "rank": pa.array(out[1].astype(np.int32)), "item_id": out[2], "score": out[3]})

    found = rows.groupBy("ub", "ib").cogroup(marks.groupBy("ub", "ib")).applyInArrow(cell, "user_id long, rank int, item_id long, score double")
    if n_i == 1:
        return found
    rank = F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("score"), "item_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("user_id", "rank", "item_id", "score")
