"""Distributed training: block rotation, independent workers with merged deltas, one block, and the relational loop.

rotate: users and items are dealt into blocks by a hash of their id (never by id range or
community: a positive would then meet only negatives of its own kind). In sub-epoch r user block b
trains with item block (b + r) mod blocks, so no two tasks share a row. The number of blocks follows
from pairs and factor bytes alone (plans.planner), so a cell has a bounded size whatever the input.
A step over a whole cell (a batch of all its pairs, plain updates) is a sum over examples: its users are dealt into
parts, each with all the item rows it may draw, and the parts' moves are summed. So no task holds all pairs. A part's rows
come and go batch by batch: no Arrow table of them stands beside the arrays that the kernel reads.
merge: each worker trains on a private copy of the rows it touches; deltas are summed.
A worker of merge, and a single block, may have any number of pairs. Without aggregation they come in their seeded order, which Spark
makes, and are trained as they come, so that it holds its rows and one stretch of pairs.
Every cell starts from the same aggregation parameters; their deltas are summed after each
sub-epoch, and the next one starts from there. These are at most 2 K + 2 rows, held by the driver.
A history reaches over all item blocks: before each epoch a user's pooled sums are taken for every block,
and a cell gets those of the blocks it does not hold, as constants of that epoch.
Snapshots are written to the shared folder after every sub-epoch, so a lost executor costs one; with a
folder of its own (snapshots) a stopped run goes on after its last whole epoch.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.mix import mix
from ..functions.vectors import init_vector
from ..plans.cuts import Cuts
from ..plans.files import exists, listed
from ..sources.feedback import index_ids
from . import relational, sampling
from .aggregate import SummedLayer, first_params, make_layer
from .blocks import PHASES, Counts, Histories, Pass, TrainConfig, _mix_np, block_epoch, with_options
from .predict import history_sums

#: state is the optimizer's, null before the first update.
FACTORS = "side string, id long, vec array<double>, state double"
#: What kernels count: whole numbers, then sums and seconds by phase.
WHOLE = ("examples", "reads", "tile_hits", "tile_loads", "active", "rows_written", "copied_bytes", "weight_writes")
REAL = ("loss_sum", *(f"s_{p}" for p in PHASES))
#: Pairs of a part of a step over a whole cell.
PART_PAIRS = 1_000_000
#: Rows that a cell gives back at a time: the executor holds as many of them outside its heap.
GIVEN_ROWS = 1 << 14
#: Parts whose rows are dealt out at a time.
ROUND_PARTS = 6
#: Pairs that a worker takes from its stream at a time, and what stands before them in it.
STRETCH_PAIRS, USER_KEY, ITEM_KEY = 1 << 16, -2, -1
#: Bytes of the rows of pairs that are summed to pooled histories at a time.
AWAY_BYTES = 1 << 30


@dataclass
class Model:
    factors: DataFrame  # side, id, vec
    cfg: TrainConfig
    weights: np.ndarray | None = None  # of the aggregation, if there is one
    history: list[dict] = field(default_factory=list)
    cuts: Cuts | None = None  # the run's tables

    def drop(self) -> None:
        """Deletes the run's tables, where nothing reads the factors any more."""
        self.cuts.close()

    @property
    def user_factors(self) -> DataFrame:
        return self.factors.where("side = 'user'").select("id", "vec")

    @property
    def item_factors(self) -> DataFrame:
        return self.factors.where("side = 'item'").select("id", "vec")

    def save(self, path: str) -> None:
        rows = self.factors.select("side", "id", "vec")
        if self.weights is not None:
            own = [("layer", k, [float(v) for v in r]) for k, r in enumerate(self.weights)]
            rows = rows.unionByName(rows.sparkSession.createDataFrame(own, "side string, id long, vec array<double>"))
        rows.write.mode("overwrite").partitionBy("side").parquet(path)

    @staticmethod
    def load(spark, path: str, cfg: TrainConfig) -> Model:
        rows = spark.read.parquet(path).select("side", "id", "vec")
        weights = None
        if cfg.aggregator:
            weights = np.array([r.vec for r in rows.where("side = 'layer'").orderBy("id").collect()])
        return Model(rows.where("side <> 'layer'"), cfg, weights)


def init_factors(pairs: DataFrame, cfg: TrainConfig, warm: DataFrame | None = None) -> DataFrame:
    """side, id, vec of every user and item; rows of warm (side, id, vec) are kept."""
    parts = [pairs.select(F.lit(s).alias("side"), F.col(f"{s}_id").alias("id")).distinct().withColumn("vec", init_vector(cfg.seed + k, "id", cfg.dim, "uniform", cfg.init)) for k, s in enumerate(("user", "item"))]
    both = parts[0].unionByName(parts[1])
    if warm is not None:
        both = both.alias("n").join(warm.alias("w"), ["side", "id"], "full").select("side", "id", F.coalesce("w.vec", "n.vec").alias("vec"))
    return both.withColumn("state", F.lit(None).cast("double"))


def _lists(rows: np.ndarray) -> pa.Array:
    ends = np.arange(len(rows) + 1, dtype=np.int64) * rows.shape[1]
    return pa.LargeListArray.from_arrays(ends, pa.array(np.ascontiguousarray(rows, float).ravel())).cast(pa.list_(pa.float64()))


def _side(rows: pa.Table, name: str, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """ids in order, their rows and states."""
    at = np.flatnonzero(pc.equal(rows["side"], name).to_numpy())
    ids = rows["id"].to_numpy()[at]
    order = np.argsort(ids, kind="stable")
    at, ids = at[order], ids[order]
    vec, state, base = np.empty((len(at), width)), np.empty(len(at)), 0
    for part in rows.to_batches():  # no copy of the whole beside the one that is asked for
        here = np.flatnonzero((at >= base) & (at < base + part.num_rows))
        lists, own = part["vec"], at[here] - base
        flat, first = lists.values.to_numpy(zero_copy_only=False), lists.offsets.to_numpy()[own]
        for d in range(width):
            vec[here, d] = flat[first + d]
        state[here] = pc.fill_null(part["state"].cast(pa.float64()), 0.0).to_numpy(zero_copy_only=False)[own]
        base += part.num_rows
    return ids, vec, state


class _Stream:
    """A cell's factor rows and pairs, as they come: rows of side pair have the user in id and the item in other."""

    def __init__(self, batches: Iterator[pa.RecordBatch], width: int):
        self.width, self.piles, pairs = width, {"user": [], "item": []}, []
        for b in batches:
            for side in ("user", "item", "pair"):
                at = np.flatnonzero(pc.equal(b["side"], side).to_numpy(zero_copy_only=False))
                if not len(at):
                    continue
                ids = b["id"].to_numpy()[at]
                if side == "pair":
                    pairs.append([ids] + [pc.take(b[c], pa.array(at)).to_numpy(zero_copy_only=False) for c in ("other", "at", "recent") if c in b.schema.names])
                    continue
                lists = b["vec"]
                flat, first = lists.values.to_numpy(zero_copy_only=False), lists.offsets.to_numpy()[at]
                state = pc.fill_null(b["state"].cast(pa.float64()), 0.0).to_numpy(zero_copy_only=False)[at]
                self.piles[side].append((ids, flat[first[:, None] + np.arange(width)], state))
        columns = zip(*pairs, strict=True) if pairs else [[np.zeros(0, np.int64)]] * 2
        self.pairs = {n: np.concatenate(c) for n, c in zip(("user_id", "item_id", "at", "recent"), columns, strict=False)}

    def side(self, name: str, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """ids in order, their rows and states; batches are let go one by one."""
        pile = self.piles.pop(name, [])
        ids = np.concatenate([p[0] for p in pile]) if pile else np.zeros(0, np.int64)
        order = np.argsort(ids, kind="stable")
        place = np.empty(len(ids), np.int64)
        place[order] = np.arange(len(ids))
        vec, state, base = np.empty((len(ids), width)), np.empty(len(ids)), 0
        pile.reverse()
        while pile:
            _, v, s = pile.pop()
            here = place[base : base + len(v)]
            vec[here], state[here] = v, s
            base += len(v)
        return ids[order], vec, state


#: The same for Arrow.
FACTOR_COLUMNS = pa.schema([("side", pa.string()), ("id", pa.int64()), ("vec", pa.list_(pa.float64())), ("state", pa.float64())])


def _stats(c: Counts, cfg: TrainConfig) -> np.ndarray:
    """What a kernel counted, as rows of a factor's width."""
    counted = np.array([float(getattr(c, n)) for n in WHOLE] + [c.loss, *(c.seconds[p] for p in PHASES)])
    stats = np.zeros((-(-len(counted) // cfg.dim), cfg.dim))
    stats.ravel()[: len(counted)] = counted
    return stats


def _tagged(side: str, ids: np.ndarray, vec: np.ndarray, state: np.ndarray) -> list[pa.RecordBatch]:
    name = pa.DictionaryArray.from_arrays(pa.array(np.zeros(len(ids), np.int32)), pa.array([side])).cast(pa.string())
    return pa.table([name, pa.array(ids.astype(np.int64)), _lists(vec), pa.array(state)], FACTOR_COLUMNS).to_batches(max_chunksize=GIVEN_ROWS)


def _train_cell(pairs: pa.Table, rows: pa.Table, cfg: TrainConfig, epoch: int, params: np.ndarray | None = None) -> pa.Table:
    columns = {n: pairs[n].to_numpy() for n in _needed(params)}
    return _train(columns, lambda name, width: _side(rows, name, width), cfg, epoch, params=params)


def _train(pairs: dict[str, np.ndarray], side_of: Callable, cfg: TrainConfig, epoch: int, delta: bool = False, params: np.ndarray | None = None, groups: tuple | None = None, whole: bool = True) -> pa.Table:
    """Kernel of one cell: pairs and tagged factor rows in, tagged rows out (changed ones, or deltas where there are any;
    always deltas for the rows of the aggregation). Rows of side away hold what a user's history elsewhere adds; those of
    side stats, what the kernel counted. whole: false for a part of a step, which leaves its rows as they are;
    groups: what _groups says of the whole step."""
    pa.default_memory_pool().release_unused()  # of the worker's last cell, or of the batches that rows came in
    u_ids, first_users, u_state = side_of("user", cfg.dim)
    i_ids, first_items, i_state = side_of("item", cfg.dim)
    users, items = (v.astype(cfg.precision, copy=delta and whole) for v in (first_users, first_items))
    moves = None if whole else []
    states = (u_state, i_state)
    c = Counts()
    moved = np.zeros((0, cfg.dim))
    if len(pairs["user_id"]) and len(users) and len(items):
        pu, pi = pairs.pop("user_id"), pairs.pop("item_id")
        if params is not None:
            newest = np.lexsort((pi, -pairs.pop("at"), pu))
            pu, pi = pu[newest], pi[newest]
        u, i = (np.searchsorted(a, v).astype(np.int32) for a, v in ((u_ids, pu), (i_ids, pi)))
        layer = hist = away = None
        if params is not None:
            layer = make_layer(params.copy(), cfg) if groups is None else SummedLayer(params.copy(), cfg.lr, _shares(pu, pi, cfg, epoch, groups))
            new = pairs.pop("recent")[newest]
            del newest
            hist = Histories(i[new], np.searchsorted(u[new], np.arange(len(users) + 1)))
            off_ids, off, _ = side_of("away", cfg.dim + 2)
            if len(off_ids):
                away = np.zeros((len(users), cfg.dim + 2))
                away[np.searchsorted(u_ids, off_ids)] = off
        c = block_epoch(users, items, u, i, pu, pi, cfg, epoch, layer, hist, away, states, moves)
        if layer is not None:
            moved = layer.w - params
    stats = _stats(c, cfg)
    if not whole:  # a part leaves its rows as they are, and gives only moves
        users, items = moves or (users[:0], items[:0])
        first_users = first_items = None
    out = []
    for side, ids, vec, first, state in (("user", u_ids, users, first_users, u_state), ("item", i_ids, items, first_items, i_state)):
        if delta:
            vec = vec if not whole else np.subtract(vec, first, out=vec, casting="same_kind")
            ids, state = ids[: len(vec)], state[: len(vec)]
            some = vec.any(axis=1) | (state > 0)
            if some.mean() < 0.9 if len(some) else False:  # a few rows that did not move cost less than a copy of the others
                ids, vec, state = ids[some], vec[some], state[some]
        out.append((side, ids, vec, state))
    out += [(side, np.arange(len(vec)), vec, np.zeros(len(vec))) for side, vec in (("layer", moved), ("stats", stats))]
    return pa.Table.from_batches([b for side in out for b in _tagged(*side)], FACTOR_COLUMNS)


def _cell(cfg: TrainConfig, epoch: int, params: np.ndarray | None = None):
    def run(pairs: pa.Table, rows: pa.Table) -> pa.Table:
        return _train_cell(pairs, rows, cfg, epoch, params)

    return run


def _part(cfg: TrainConfig, epoch: int, params: np.ndarray | None, groups: tuple | None, whole: bool):
    """The same for what moved, from one stream of pairs and rows."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pa.default_memory_pool().release_unused()  # of the worker's last cell
        got = _Stream(rows, cfg.dim)
        yield from _train(got.pairs, got.side, cfg, epoch, True, params, groups, whole).to_batches()

    return run


class _Held:
    """A side's rows as they come in order of their ids, in arrays that grow where they are."""

    def __init__(self, cfg: TrainConfig):
        self.dim, self.n = cfg.dim, 0
        self.ids, self.vec, self.state = np.empty(1024, np.int64), np.empty(1024 * cfg.dim, cfg.precision), np.empty(1024)

    def size(self, rows: int) -> None:
        for a, width in ((self.ids, 1), (self.vec, self.dim), (self.state, 1)):
            a.resize(rows * width, refcheck=False)

    def add(self, b: pa.RecordBatch) -> None:
        n = self.n + b.num_rows
        if n > len(self.ids):
            self.size(n + n // 8)
        lists = b["vec"]
        first, end = lists.offsets[0].as_py(), lists.offsets[b.num_rows].as_py()
        self.ids[self.n : n] = b["id"].to_numpy()
        self.vec[self.n * self.dim : n * self.dim] = lists.values[first:end].to_numpy(zero_copy_only=False)
        self.state[self.n : n] = pc.fill_null(b["state"].cast(pa.float64()), 0.0).to_numpy(zero_copy_only=False)
        self.n = n

    def rows(self) -> np.ndarray:
        self.size(self.n)
        return self.vec.reshape(-1, self.dim)


def _in_order(batches: Iterator[pa.RecordBatch], cfg: TrainConfig, epoch: int, alone: bool = False) -> Iterator[pa.RecordBatch]:
    """A cell's rows after an epoch without aggregation. Its stream has users, items and then pairs in their seeded order, which are
    trained as they come: a worker holds factor rows and one stretch of pairs, however many pairs it has. alone: no other cell trains."""
    pa.default_memory_pool().release_unused()  # of the worker's last cell
    users, items, run, c = _Held(cfg), _Held(cfg), None, Counts()
    waiting: list[pa.RecordBatch] = []
    held = most = 0

    def train(n: int) -> None:
        nonlocal waiting, held
        pairs = pa.Table.from_batches(waiting)
        u_ids, i_ids = (pairs[k][:n].to_numpy() for k in ("id", "other"))
        run.go(*(np.searchsorted(own.ids, ids).astype(np.int32) for own, ids in ((users, u_ids), (items, i_ids))), u_ids, i_ids)
        waiting, held = pairs.slice(n).to_batches(), held - n

    for b in batches:
        ends = np.searchsorted(b["key"].to_numpy(), (ITEM_KEY, 0))
        for own, lo, hi in ((users, 0, ends[0]), (items, ends[0], ends[1])):
            if lo < hi:
                own.add(b.slice(lo, hi - lo))
        if ends[1] == b.num_rows:
            continue
        if run is None:
            run = Pass(users.rows(), items.rows(), cfg, epoch, states=(users.state, items.state), helped=alone)
            most = -(-STRETCH_PAIRS // run.stretch()) * run.stretch()
        waiting.append(b.slice(ends[1]).select(["id", "other"]))
        held += b.num_rows - ends[1]
        if held >= most:
            train(held // most * most)
    if run is not None:
        if held:
            train(held)
        c = run.finish()
    stats = _stats(c, cfg)
    yield from _tagged("stats", np.arange(len(stats)), stats, np.zeros(len(stats)))
    for side, own in (("user", users), ("item", items)):
        yield from _tagged(side, own.ids[: own.n], own.rows(), own.state[: own.n])


def _ordered_cells(pairs: DataFrame, rows: DataFrame, cells: int, cfg: TrainConfig, epoch: int) -> DataFrame:
    """side, id, vec, state after an epoch of cells without aggregation. pairs: cell, user_id, item_id; rows: cell, side, id, vec,
    state. A cell is a partition of its own, and Spark sorts it, on disk where it has to; by key first, since rows are compared by eight
    bytes of the first column and only where these agree as a whole."""
    key = F.when(F.col("side") == "user", F.lit(USER_KEY)).otherwise(F.lit(ITEM_KEY))
    seeded = mix(cfg.seed + 101 * epoch, "user_id", "item_id")
    stream = rows.select("cell", key.cast("long").alias("key"), "id", F.lit(None).cast("long").alias("other"), "vec", "state").unionByName(
        pairs.select("cell", seeded.cast("long").alias("key"), F.col("user_id").alias("id"), F.col("item_id").alias("other"), F.lit(None).cast("array<double>").alias("vec"), F.lit(None).cast("double").alias("state"))
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _in_order(batches, cfg, epoch, cells == 1)

    dealt = stream.repartitionById(cells, F.col("cell")).sortWithinPartitions("key", "id", "other")
    return dealt.select("key", "id", "other", "vec", "state").mapInArrow(run, FACTORS)


def _groups(pairs: DataFrame, cfg: TrainConfig, epoch: int, n: int) -> tuple:
    """m, the size of the last group, and the place in the seeded order at which it starts (None: at the first), where
    parameters of an aggregation are moved by the means of groups of m examples in that order."""
    m = 1 if cfg.sync_mode == "shared" else cfg.sync
    rest = n % m
    if not rest or m > n:
        return m, rest, None
    key = F.struct(mix(cfg.seed + 101 * epoch, "user_id", "item_id").alias("h"), "user_id", "item_id")
    r = pairs.select(key.alias("key")).orderBy(F.desc("key")).limit(rest).agg(F.min("key")).first()[0]
    return m, rest, tuple(r)


def _shares(users: np.ndarray, items: np.ndarray, cfg: TrainConfig, epoch: int, groups: tuple) -> np.ndarray:
    """By how much each pair's gradient of the parameters counts."""
    m, rest, start = groups
    if not rest:
        return np.full(len(users), 1.0 / m)
    last = 1.0 / rest if cfg.flush_tail else 0.0
    if start is None:
        return np.full(len(users), last)
    h = _mix_np(cfg.seed + 101 * epoch, users, items)
    late = (h > start[0]) | ((h == start[0]) & ((users > start[1]) | ((users == start[1]) & (items >= start[2]))))
    return np.where(late, last, 1.0 / m)


def parts_of(pairs: int, cfg: TrainConfig) -> int:
    """Parts of a cell of so many pairs: more than one only where its epoch is one plain step over all of them."""
    one_step = cfg.batch >= pairs and cfg.optimizer == "sgd" and not cfg.l2 and not cfg.tile
    return max(1, -(-pairs // PART_PAIRS)) if one_step else 1


def block_of(side: str, ident: str | F.Column, cfg: TrainConfig) -> F.Column:
    return (mix(cfg.seed + (31 if side == "user" else 37), ident) % cfg.blocks).cast("int")


def rotation(pairs: DataFrame, cfg: TrainConfig) -> DataFrame:
    """Adds cell (the user block) and turn (the sub-epoch in which the pair trains)."""
    ub, ib = block_of("user", "user_id", cfg), block_of("item", "item_id", cfg)
    return pairs.withColumn("cell", ub).withColumn("turn", F.pmod(ib - ub, F.lit(cfg.blocks)))


def mark_recent(pairs: DataFrame, most: int) -> DataFrame:
    """Adds recent: the pair is among its user's newest. Ranks stop at most before any user is gathered."""
    rank = F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("at"), F.desc("item_id")))
    newest = pairs.withColumn("_n", rank).where(F.col("_n") <= most).select("user_id", "item_id", F.lit(True).alias("recent"))
    return pairs.join(newest, ["user_id", "item_id"], "left").withColumn("recent", F.coalesce("recent", F.lit(False)))


def _totals(history: list[dict], out: DataFrame, epoch: int, dim: int) -> None:
    summed = relational.combine_gradients(out.where("side = 'stats'").select("side", "id", F.col("vec").alias("g")), dim)
    rows = {r.id: r.g for r in summed.collect()}
    values = [v for k in sorted(rows) for v in rows[k]] or [0.0] * (len(WHOLE) + len(REAL))
    history.append({"epoch": epoch} | {n: round(v) for n, v in zip(WHOLE, values, strict=False)} | dict(zip(REAL, values[len(WHOLE) :], strict=False)))


def _merged(params: np.ndarray | None, out: DataFrame, dim: int) -> np.ndarray | None:
    """Parameters moved by the summed deltas of all cells."""
    if params is None:
        return None
    summed = relational.combine_gradients(out.where("side = 'layer'").select("side", "id", F.col("vec").alias("g")), dim)
    params = params.copy()
    for r in summed.collect():
        params[r.id] += r.g
    return params


def away_sums(dealt: DataFrame, factors: DataFrame, params: np.ndarray, cfg: TrainConfig) -> DataFrame:
    """turn, side, id, vec: for each user and sub-epoch in which it trains, the sums over its history in
    all other item blocks, as the row num, den, off that pooling reads. A row a user and block it has pairs in."""
    users, items = (factors.where(F.col("side") == s).select("id", "vec") for s in ("user", "item"))
    parts = history_sums(dealt.select("user_id", "item_id", "turn", F.col("recent").alias("counts")), ["user_id", "turn"], users, items, params, cfg)
    sums = parts.groupBy("user_id").agg(F.sum("den").alias("_den"), *[F.sum(F.col("num")[d]).alias(f"_{d}") for d in range(cfg.dim)])
    return _rest(parts, sums.select("user_id", "_den", F.array(*[F.col(f"_{d}") for d in range(cfg.dim)]).alias("_num")), cfg)


def _rest(parts: DataFrame, total: DataFrame, cfg: TrainConfig) -> DataFrame:
    """turn, side, id, vec: what remains of a user's sums over its whole history without those of a block."""
    both = parts.join(total, "user_id")
    rest = [F.col("_num")[d] - F.col("num")[d] for d in range(cfg.dim)]
    return both.select("turn", F.lit("away").alias("side"), F.col("user_id").alias("id"), F.array(*rest, F.greatest(F.col("_den") - F.col("den"), F.lit(0.0)), F.col("off")).alias("vec"))


class Away:
    """The rows of away_sums sub-epoch by sub-epoch, from rows as they were before the epoch. A row a user and block is more than
    disks should hold, and so is a row a pair; so users take turns for the sums over whole histories, and a sub-epoch sums its own."""

    def __init__(self, dealt: DataFrame, factors: DataFrame, params: np.ndarray, cfg: TrainConfig, cuts: Cuts):
        self.params, self.cfg, self.cuts = params, cfg, cuts
        self.rows = dealt.select("user_id", "item_id", "turn", F.col("recent").alias("counts"))
        sides = factors if cfg.aggregator == "user_attention" else factors.where("side = 'item'")
        self.first = cuts.cut(sides.select("side", "id", "vec"))
        rounds = -(-dealt.count() * 8 * (cfg.dim + 2) // AWAY_BYTES) or 1
        turns = [F.pmod(F.xxhash64("user_id"), F.lit(rounds)) == r for r in range(rounds)]
        self.made = [cuts.cut(self.sums(self.rows.where(t), "user_id").select("user_id", F.col("den").alias("_den"), F.col("num").alias("_num"))) for t in turns]
        self.total = reduce(DataFrame.union, self.made)

    def sums(self, rows: DataFrame, *keys: str) -> DataFrame:
        users, items = (self.first.where(F.col("side") == s).select("id", "vec") for s in ("user", "item"))
        return history_sums(rows, list(keys), users, items, self.params, self.cfg)

    def turn(self, number: int) -> DataFrame:
        return _rest(self.sums(self.rows.where(F.col("turn") == number), "user_id", "turn"), self.total, self.cfg)

    def close(self) -> None:
        self.cuts.drop(self.first, *self.made)


class Progress:
    """What epochs leave behind: counts, and whole snapshots in a folder of the caller's, if there is one."""

    def __init__(self, cfg: TrainConfig, folder: str | None):
        self.cfg, self.folder, self.history = cfg, folder, []

    def first(self, spark, factors: DataFrame, params: np.ndarray | None) -> tuple[int, DataFrame, np.ndarray | None]:
        """The epoch to begin with, and factors and parameters as they were before it."""
        done = [int(n.removeprefix("epoch=")) for n in listed(spark, self.folder) if n.startswith("epoch=") and exists(spark, f"{self.folder}/{n}/_SUCCESS")] if self.folder else []
        if not done:
            return 0, factors, params
        rows = spark.read.parquet(f"{self.folder}/epoch={max(done)}")
        if params is not None:
            params = np.array([r.vec for r in rows.where("side = 'layer'").orderBy("id").collect()])
        return max(done) + 1, rows.where("side <> 'layer'"), params

    def epoch(self, number: int, factors: DataFrame, params: np.ndarray | None) -> bool:
        """Keeps a snapshot; true if training has to go on."""
        if self.folder:
            rows = factors.select("side", "id", "vec", "state")
            if params is not None:
                rows = rows.unionByName(factors.sparkSession.createDataFrame([("layer", k, [float(v) for v in r], None) for k, r in enumerate(params)], FACTORS))
            rows.write.mode("overwrite").parquet(f"{self.folder}/epoch={number}")
        losses = {}
        for h in self.history:
            losses[h["epoch"]] = losses.get(h["epoch"], 0.0) + (h["loss_sum"] or 0.0)
        if not self.cfg.patience or len(losses) <= self.cfg.patience:
            return True
        values = [losses[k] for k in sorted(losses)]
        return min(values[-self.cfg.patience :]) < min(values[: -self.cfg.patience])


def fit_rotate(pairs: DataFrame, cfg: TrainConfig, factors: DataFrame, cuts: Cuts, params: np.ndarray | None = None, folder: str | None = None, made: DataFrame | None = None) -> Model:
    """made: the table that pairs are read from, deleted when they are dealt."""
    dealt = rotation(pairs.select("user_id", "item_id", "at", "recent"), cfg)
    dealt = cuts.cut(dealt.repartition("turn", "cell"), "turn")  # a sub-epoch reads its own pairs alone
    if made is not None:
        cuts.drop(made)
    progress = Progress(cfg, folder)
    start, factors, params = progress.first(pairs.sparkSession, factors, params)
    for epoch in range(start, cfg.epochs):
        away = Away(dealt, factors, params, cfg, cuts) if params is not None and cfg.blocks > 1 else None
        for turn in range(cfg.blocks):
            block = F.when(F.col("side") != "item", block_of("user", "id", cfg)).otherwise(F.pmod(block_of("item", "id", cfg) - turn, F.lit(cfg.blocks)))
            rows = factors.select("side", "id", "vec", "state")
            if away is not None:
                rows = rows.unionByName(away.turn(turn).select("side", "id", "vec", F.lit(None).cast("double").alias("state")))
            right = rows.withColumn("cell", block.cast("int")).groupBy("cell")
            left = dealt.where(F.col("turn") == turn).groupBy("cell")
            out = cuts.cut(left.cogroup(right).applyInArrow(_cell(cfg, epoch, params=params), FACTORS))
            _totals(progress.history, out, epoch, cfg.dim)
            params = _merged(params, out, cfg.dim)
            factors = cuts.follow(out.where("side IN ('user', 'item')").select("side", "id", "vec", "state"), out)
        if away is not None:
            away.close()
        if not progress.epoch(epoch, factors, params):
            break
    return Model(factors, cfg, params, progress.history)


def _needed(params: np.ndarray | None) -> list[str]:
    return ["user_id", "item_id"] if params is None else ["user_id", "item_id", "at", "recent"]


def _sums(out: DataFrame, dim: int, *more: F.Column) -> DataFrame:
    """side, id, vec, state: the sums of all cells' rows and the most of their state."""
    sums = out.groupBy("side", "id").agg(*[F.sum(F.col("vec")[d]).alias(f"_{d}") for d in range(dim)], F.max("state").alias("state"), *more)
    return sums.select("side", "id", F.array(*[F.col(f"_{d}") for d in range(dim)]).alias("vec"), *sums.columns[2 + dim :])


def _summed_moves(dealt: DataFrame, right: DataFrame, cfg: TrainConfig, epoch: int, params: np.ndarray | None, groups: tuple | None, cells: int, parts: int, cuts: Cuts) -> DataFrame:
    """side, id, vec, state: what all cells moved a row by, and the most of its state. dealt, right: pairs and factor rows,
    by cell. Many parts take turns, so that only some of the copied rows are on disk at a time."""
    rounds = -(-cells // ROUND_PARTS) if parts > 1 else 1
    turn = lambda rows, r: rows.where(F.col("cell") % rounds == r) if rounds > 1 else rows

    def summed(out: DataFrame) -> DataFrame:
        return cuts.cut(_sums(out, cfg.dim))

    extra = {n: t for n, t in (("at", "long"), ("recent", "boolean")) if n in _needed(params)}
    none = lambda n, t: F.lit(None).cast(t).alias(n)
    pairs = dealt.select("cell", F.lit("pair").alias("side"), F.col("user_id").alias("id"), F.col("item_id").alias("other"), *extra, none("vec", "array<double>"), none("state", "double"))
    stream = pairs.unionByName(right.select("cell", "side", "id", none("other", "long"), *[none(n, t) for n, t in extra.items()], "vec", "state"))
    found = [summed(turn(stream, r).groupBy("cell").applyInArrow(_part(cfg, epoch, params, groups, parts == 1), FACTORS)) for r in range(rounds)]
    return found[0] if rounds == 1 else summed(reduce(DataFrame.union, found))


def _from_workers(factors: DataFrame, sums: DataFrame) -> DataFrame:
    """Rows moved by the summed deltas of the n workers that had them. sums has the sums of their new rows, so no worker keeps old ones."""
    both = factors.select("side", "id", "vec").join(sums.select("side", "id", F.col("vec").alias("total"), "n", "state"), ["side", "id"], "left")
    moved = F.zip_with("vec", "total", lambda v, t: v + (t - F.col("n") * v))
    return both.select("side", "id", F.when(F.col("n").isNull(), F.col("vec")).otherwise(moved).alias("vec"), "state")


def _apply_moves(factors: DataFrame, moves: DataFrame) -> DataFrame:
    moved = relational.apply_sparse(factors.select("side", "id", "vec"), moves.select("side", "id", F.col("vec").alias("g")), -1.0)
    return moved.join(moves.select("side", "id", "state"), ["side", "id"], "left").select("side", "id", "vec", "state")


def fit_block(pairs: DataFrame, cfg: TrainConfig, factors: DataFrame, cuts: Cuts, folder: str | None = None) -> Model:
    """One block without aggregation, whose pairs are trained as they come."""
    progress = Progress(cfg, folder)
    start, factors, _ = progress.first(pairs.sparkSession, factors, None)
    cell = F.lit(0).alias("cell")
    for epoch in range(start, cfg.epochs):
        out = cuts.cut(_ordered_cells(pairs.select(cell, "user_id", "item_id"), factors.select(cell, "side", "id", "vec", "state"), 1, cfg, epoch))
        _totals(progress.history, out, epoch, cfg.dim)
        factors = cuts.follow(out.where("side IN ('user', 'item')").select("side", "id", "vec", "state"), out)
        if not progress.epoch(epoch, factors, None):
            break
    return Model(factors, cfg, None, progress.history)


def fit_parts(pairs: DataFrame, cfg: TrainConfig, factors: DataFrame, cuts: Cuts, parts: int, n: int, params: np.ndarray | None = None, folder: str | None = None) -> Model:
    """One block whose epoch is one step: a part has the pairs of its users and all items."""
    progress = Progress(cfg, folder)
    start, factors, params = progress.first(pairs.sparkSession, factors, params)
    of = lambda c: (mix(cfg.seed + 47, c) % parts).cast("int")
    dealt = pairs.select(of("user_id").alias("cell"), *_needed(params))
    every = F.when(F.col("side") == "user", F.array(of("id"))).otherwise(F.sequence(F.lit(0), F.lit(parts - 1)))
    for epoch in range(start, cfg.epochs):
        right = factors.select(F.explode(every).alias("cell"), "side", "id", "vec", "state")
        groups = _groups(pairs, cfg, epoch, n) if params is not None else None
        moves = _summed_moves(dealt, right, cfg, epoch, params, groups, parts, parts, cuts)
        _totals(progress.history, moves, epoch, cfg.dim)
        params = _merged(params, moves, cfg.dim)
        factors = cuts.cut(_apply_moves(factors, moves))
        if not progress.epoch(epoch, factors, params):
            break
    return Model(factors, cfg, params, progress.history)


def fit_merge(pairs: DataFrame, cfg: TrainConfig, factors: DataFrame, cuts: Cuts, params: np.ndarray | None = None, folder: str | None = None, extra: int = 256) -> Model:
    """Workers read the rows of their pairs and a drawn tile of extra further items; summed deltas give the
    next snapshot. A tile is a list of drawn places in the item index, joined to it: its cost is that of its rows.
    A worker whose epoch is one step works in parts, each with the pairs of its users and all of the worker's items."""
    spark = pairs.sparkSession
    progress = Progress(cfg, folder)
    worker = lambda c: (mix(cfg.seed + 41, c) % cfg.blocks).cast("int")
    most = pairs.groupBy(worker("user_id").alias("worker")).agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    parts = parts_of(most, cfg) if params is None else 1
    cell = lambda c: (worker(c) * parts + mix(cfg.seed + 47, c) % parts).cast("int")
    dealt = pairs.select(cell("user_id").alias("cell"), *_needed(params))
    own = cuts.cut(pairs.select(worker("user_id").alias("worker"), F.lit("item").alias("side"), F.col("item_id").alias("id")).distinct())
    index = cuts.cut(index_ids(factors.where("side = 'item'").select("id"), "id"))
    n_items = index.count()
    start, factors, params = progress.first(spark, factors, params)
    for epoch in range(start, cfg.epochs):
        slots = spark.range(cfg.blocks * extra).select((F.col("id") / extra).cast("int").alias("worker"), (mix(cfg.seed + 43 + epoch, F.col("id")) % max(1, n_items)).alias("idx"))
        need = own.union(slots.join(index, "idx").select("worker", F.lit("item").alias("side"), "id")).distinct()
        every = F.explode(F.sequence(F.col("worker") * parts, F.col("worker") * parts + (parts - 1)))
        right = need.join(factors, ["side", "id"]).select(every.alias("cell"), "side", "id", "vec", "state")
        right = right.union(factors.where("side = 'user'").select(cell("id").alias("cell"), "side", "id", "vec", "state"))
        if params is None and parts == 1:
            sums = cuts.cut(_sums(_ordered_cells(dealt, right, cfg.blocks, cfg, epoch), cfg.dim, F.count(F.lit(1)).alias("n")))
            _totals(progress.history, sums, epoch, cfg.dim)
            factors = cuts.cut(_from_workers(factors, sums))
        else:
            moves = _summed_moves(dealt, right, cfg, epoch, params, None, cfg.blocks * parts, parts, cuts)
            _totals(progress.history, moves, epoch, cfg.dim)
            params = _merged(params, moves, cfg.dim)
            factors = cuts.cut(_apply_moves(factors, moves))
        if not progress.epoch(epoch, factors, params):
            break
    return Model(factors, cfg, params, progress.history)


def fit_relational(pairs: DataFrame, cfg: TrainConfig, factors: DataFrame, cuts: Cuts, params: np.ndarray | None = None, folder: str | None = None) -> Model:
    """All examples of an epoch in one synchronous step, without aggregation; for checking and small data."""
    if params is not None:
        raise ValueError("the relational plan has no aggregation")
    items = cuts.cut(index_ids(pairs, "item_id"))
    step_cfg = relational.StepConfig(cfg.dim, cfg.negatives, cfg.lr, cfg.mu, cfg.theta, cfg.loss, cfg.similarity, l2=cfg.l2)
    progress = Progress(cfg, folder)
    start, factors, params = progress.first(pairs.sparkSession, factors, params)
    for epoch in range(start, cfg.epochs):
        negs = cuts.cut(sampling.sample_uniform(pairs, items, cfg.negatives, cfg.seed + 13 + epoch))
        new = relational.step(pairs, negs, factors.select("side", "id", "vec"), step_cfg)
        factors = cuts.cut(new.withColumn("state", F.lit(None).cast("double")))
        if not progress.epoch(epoch, factors, params):
            break
    return Model(factors, cfg)


def fit(pairs: DataFrame, cfg: TrainConfig, warm: DataFrame | None = None, weights: np.ndarray | None = None, snapshots: str | None = None) -> Model:
    """plan: auto (rotate), reference (one block, one pair at a time), block (one block), rotate, merge, relational.
    A column ts of pairs orders histories; warm and weights are an earlier model's. snapshots: a folder of whole
    epochs; where it holds some of the same run, training goes on after the last."""
    from ..plans.planner import settle

    cuts = Cuts(pairs.sparkSession)
    at = F.max(F.unix_micros(F.col("ts").cast("timestamp"))) if "ts" in pairs.columns and cfg.aggregator else F.lit(0).cast("long")
    made = pairs = cuts.cut(pairs.where("user_id is not null and item_id is not null").groupBy("user_id", "item_id").agg(F.coalesce(at, F.lit(0).cast("long")).alias("at")))
    if cfg.aggregator:
        made = cuts.cut(mark_recent(pairs, cfg.history))
        cuts.drop(pairs)
        pairs = made
    else:
        pairs = pairs.withColumn("recent", F.lit(False))
    cfg = settle(pairs, cfg)
    factors = cuts.cut(init_factors(pairs, cfg, warm))
    params = None
    if cfg.aggregator:
        params = first_params(cfg.aggregator, cfg.dim, cfg.seed) if weights is None else weights
    n = pairs.count() if cfg.plan == "block" else 0
    if (parts := parts_of(n, cfg)) > 1:
        model = fit_parts(pairs, cfg, factors, cuts, parts, n, params, snapshots)
    elif cfg.plan in ("reference", "block") and params is None:
        model = fit_block(pairs, with_options(cfg, blocks=1, batch=1 if cfg.plan == "reference" else cfg.batch), factors, cuts, snapshots)
    elif cfg.plan in ("reference", "block"):
        model = fit_rotate(pairs, with_options(cfg, blocks=1, batch=1 if cfg.plan == "reference" else cfg.batch), factors, cuts, params, snapshots, made)
    elif cfg.plan == "rotate":
        model = fit_rotate(pairs, cfg, factors, cuts, params, snapshots, made)
    else:
        model = {"merge": fit_merge, "relational": fit_relational}[cfg.plan](pairs, cfg, factors, cuts, params, snapshots)
    model.cuts = cuts
    return model
