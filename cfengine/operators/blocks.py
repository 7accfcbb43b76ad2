"""Fused kernel: forward, loss, gradient and update of one block in numpy, over rows that no other task holds.

One call takes the block's pairs and its user and item rows. Pairs run in a seeded order in
batches of cfg.batch; batch 1 is sequential. The three sums are kept for the gradients, only
rows of the batch are written, and inactive negatives cost nothing after the forward pass.
A batch is worked off in slices whose rows stay in cache. The gradient of an item row is a sum of
mixed user rows less a multiple of the row itself, so no gradient is stored for a single draw.

With a tile the worker holds a buffer of item rows: negatives are read and changed there, positives and
histories too where the tile has them, and rows go back to the matrix when the tile is redrawn (or
after every batch). All similarities to a small tile are one matrix product.

The engines dense, sparse and jagged are the baselines: they copy rows into a tensor, write a
normalized tensor, compute the sums again for the gradients and merge updates their own way. The engine dense moves every row
in every batch; draws do not depend on rows, so those that a run of batches does not draw take all its steps one after another, in cache.
Behaviour aggregation pools resident history rows with a snapshot of the others; its gradients are summed over m iterations before they are applied.
"""

from __future__ import annotations

import math
import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace

import numpy as np

from ..functions.mix import P, multipliers
from .aggregate import Layer, SummedLayer, backward, pool

PHASES = ("sample", "read_user", "read_item", "user_norm", "item_norm", "copy", "aggregate", "similarity", "loss", "backward", "update")
ENGINES = ("fused", "dense", "sparse", "jagged")
#: Rows and bytes of one slice of a batch.
SLICE_ROWS, SLICE_BYTES = 64, 2 << 20
#: Bytes of draws, or of copied rows, that a piece of a large batch takes at most.
PIECE_BYTES = 4 << 20
#: Rows of gradients that wait one by one before they are summed.
FOLD_ROWS = 1 << 17
#: A tile of up to so many times the negatives is multiplied as a whole; rows are gathered from a larger one.
WHOLE_TILE = 8
#: Batches of the engine dense that are worked off on a table of their own rows, from the outside in; rows that need none; and bytes of
#: rows that take such a run of steps together.
RUNS, NEAR_BYTES, STILL_BYTES = (64, 8), 1 << 19, 1 << 20
#: Rows of a table that a helping thread takes at a time.
HELP_ROWS = 1 << 16


@dataclass(frozen=True)
class TrainConfig:
    dim: int = 16
    negatives: int = 8
    epochs: int = 1
    lr: float = 0.05
    decay: float = 1.0
    l2: float = 0.0
    optimizer: str = "sgd"  # sgd; adagrad (one state a row: mean squares of its gradients)
    mu: float = 1.0
    theta: float = 0.0
    loss: str = "ccl"  # ccl, mse, bce, bpr, metric
    similarity: str = "cosine"  # cosine, dot
    batch: int = 64
    tile: int = 0  # 0: uniform over the block's items; -1: from the machine (plans.planner)
    refresh: int = 256
    tile_replace: bool = False
    writeback: str = "refresh"  # refresh, step
    aggregator: str | None = None  # None, average, self_attention, user_attention
    gate: float = 0.8
    history: int = 100
    update_history: bool = True  # history rows get their share of the pooled row's gradient
    leave_out: bool = True  # an example's positive is no part of its own pooled history
    sync: int = 32
    sync_mode: str = "local"  # local (every sync iterations), server (stale replicas), shared (every iteration)
    stale: int = 1  # mini-batches after which a server's replica shows a gradient
    flush_tail: bool = True
    init: float = 0.1
    seed: int = 1
    plan: str = "auto"
    blocks: int = 0  # 0: from the sizes of pairs and factors
    engine: str = "fused"
    precision: str = "float64"  # float64, float32
    patience: int = 0  # epochs without a better loss after which training ends; 0: never

    def __post_init__(self):
        if self.negatives < 1 or self.dim < 1 or self.batch < 1 or self.refresh < 1 or self.sync < 1 or self.tile < -1 or self.blocks < 0:
            raise ValueError("sizes must be positive")
        if not -1 <= self.theta <= 1 or self.mu < 0:
            raise ValueError("theta is in [-1, 1] and mu is not negative")
        for name, value, known in (("engine", self.engine, ENGINES), ("optimizer", self.optimizer, ("sgd", "adagrad")), ("writeback", self.writeback, ("refresh", "step")), ("sync_mode", self.sync_mode, ("local", "server", "shared")), ("precision", self.precision, ("float64", "float32")), ("loss", self.loss, ("ccl", "mse", "bce", "bpr", "metric"))):
            if value not in known:
                raise ValueError(f"unknown {name} {value}")


#: The paper's settings, by name: fixed values.
PRESETS = {
    "default": TrainConfig(dim=128, negatives=64, history=100),
    "pointwise": TrainConfig(dim=128, negatives=1, loss="mse", similarity="dot"),
    "profile": TrainConfig(dim=128, negatives=64, batch=1024),
    "pair_sgd": TrainConfig(dim=128, negatives=1, loss="mse", similarity="dot", plan="rotate", batch=1),
    "bpr": TrainConfig(dim=128, negatives=1, loss="bpr", similarity="dot"),
    "bce": TrainConfig(dim=128, negatives=1, loss="bce", similarity="dot"),
    "metric": TrainConfig(dim=128, negatives=1, loss="metric", similarity="dot"),
}


@dataclass
class Counts:
    loss: float = 0.0
    examples: int = 0
    reads: int = 0
    tile_hits: int = 0
    active: int = 0
    weight_writes: int = 0
    copied_bytes: int = 0
    rows_written: int = 0
    tile_loads: int = 0
    seconds: dict[str, float] = field(default_factory=lambda: dict.fromkeys(PHASES, 0.0))


def _mix_np(seed: int, *keys: np.ndarray) -> np.ndarray:
    h = np.int64(seed)  # grows to the keys' common shape as they come
    for k in (*keys, np.int64(7919)):
        g = (48271 * h + np.asarray(k, np.int64) % P + 1) % P
        h = (g * g + 1234567) % P
    return h


def scatter_add(target: np.ndarray, rows: np.ndarray, values: np.ndarray) -> int:
    """target[rows] += values with repeats; sorted segments, one write a distinct row."""
    ids, sums = summed(rows, values)
    if len(ids):
        target[ids] += sums
    return len(ids)


def summed(rows: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct rows and the sums of their values."""
    if not len(rows):
        return rows, values
    order = np.argsort(rows, kind="stable")
    r = rows[order]
    first = np.flatnonzero(np.concatenate(([True], r[1:] != r[:-1])))
    return r[first], np.add.reduceat(values[order], first, axis=0)


def tile_indices(seed: int, keys: tuple[int, ...], tile: int, items: int, replacement: bool, steps: np.ndarray | None = None) -> np.ndarray:
    """Row numbers of a tile. Without replacement slots walk around the items from a drawn start
    in a drawn step that shares no factor with their number, so no row comes twice."""
    tile = min(tile, items)
    if replacement:
        return _mix_np(seed, *(np.int64(k) for k in keys[:2]), np.arange(tile), *(np.int64(k) for k in keys[2:])) % items
    steps = multipliers(seed, items) if steps is None else steps
    start, pick = (int(_mix_np(seed + d, *(np.int64(k) for k in keys))) for d in (1, 2))
    return (start % items + steps[pick % len(steps)] * np.arange(tile, dtype=np.int64)) % items


class Histories:
    """Row numbers of every user's past items, one after another."""

    def __init__(self, rows: np.ndarray, ends: np.ndarray):
        self.rows, self.ends = rows.astype(np.int64), ends.astype(np.int64)

    def of(self, users: np.ndarray, skip: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
        """Rows of these users' histories and their lengths; skip: a row that an example's history leaves out."""
        first, lens = self.ends[users], self.ends[users + 1] - self.ends[users]
        at = np.repeat(first - (np.cumsum(lens) - lens), lens) + np.arange(int(lens.sum()))
        rows = self.rows[at]
        if skip is not None:
            keep = rows != np.repeat(skip, lens)
            of = np.repeat(np.arange(len(users)), lens)[keep]
            rows, lens = rows[keep], np.bincount(of, minlength=len(users))
        return rows, lens


class Buffer:
    """The item rows of a tile, held together while it lasts."""

    def __init__(self, items: np.ndarray, state: np.ndarray | None, rows: np.ndarray, slot_of: np.ndarray, cfg: TrainConfig):
        self.items, self.state, self.rows, self.slot_of = items, state, rows, slot_of
        self.updates = Updates(items[rows], None if state is None else state[rows], cfg)
        self.first = self.vec.copy()
        slot_of[rows] = np.arange(len(rows))

    @property
    def vec(self) -> np.ndarray:
        return self.updates.rows

    def write_back(self) -> int:
        """What the tile's life added goes to the matrix; repeated rows add up."""
        written = scatter_add(self.items, self.rows, self.vec - self.first)
        self.vec[:] = self.items[self.rows]
        self.first = self.vec.copy()
        if self.state is not None:
            self.state[self.rows] = self.updates.state
        return written

    def close(self) -> int:
        written = self.write_back()
        self.slot_of[self.rows] = -1
        return written


def _loss(cfg: TrainConfig, x: np.ndarray, st: np.ndarray, ss: np.ndarray, tt: np.ndarray) -> tuple[float, np.ndarray]:
    """Summed loss and its derivative by each similarity (metric: by each squared distance). Column 0 is the positive."""
    n = x.shape[1] - 1
    coef = np.zeros_like(x)
    if cfg.loss == "ccl":
        hinge = np.maximum(0, x[:, 1:] - cfg.theta)
        coef[:, 0], coef[:, 1:] = -1, np.where(x[:, 1:] > cfg.theta, cfg.mu / n, 0)
        return float((1 - x[:, 0]).sum() + cfg.mu / n * hinge.sum()), coef
    if cfg.loss == "bpr":
        d = x[:, :1] - x[:, 1:]
        p = 1 / (1 + np.exp(d)) / n
        coef[:, 0], coef[:, 1:] = -p.sum(1), p
        return float(np.logaddexp(0, -d).mean(1).sum()), coef
    if cfg.loss == "metric":
        dist = ss + tt - 2 * st
        hinge = np.maximum(0, 1 + dist[:, :1] - dist[:, 1:]) / n
        on = (hinge > 0) / n
        coef[:, 0], coef[:, 1:] = on.sum(1), -on
        return float(hinge.sum()), coef
    y = np.zeros_like(x)
    y[:, 0] = 1
    if cfg.loss == "mse":
        return float(((y - x) ** 2).sum()), 2 * (x - y)
    return float((np.logaddexp(0, x) - y * x).sum()), 1 / (1 + np.exp(-x)) - y


def _reciprocal(v: np.ndarray) -> np.ndarray:
    return np.divide(1.0, v, out=np.zeros_like(v), where=v > 0)


def _pulls(cfg: TrainConfig, coef: np.ndarray, x: np.ndarray, inv: np.ndarray | None, ss: np.ndarray, tt: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Weights a, b, c of the gradients: a user row gets sum(a t) - sum(b) s, an item row a s - c t."""
    if cfg.loss == "metric":
        return -2 * coef, -2 * coef, -2 * coef
    if cfg.similarity == "cosine":
        pulled = coef * x
        return coef * inv, pulled * _reciprocal(ss), pulled * _reciprocal(tt)
    zero = np.zeros_like(coef)
    return coef, zero, zero


def _table(rows: np.ndarray, owner: np.ndarray, weight: np.ndarray, source: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct rows, the summed weight of each row for each owner, and each entry's place among the rows."""
    ids, at = np.unique(rows, return_inverse=True)
    b = len(source)
    table = np.bincount(at * b + owner, weights=weight, minlength=len(ids) * b).reshape(len(ids), b)
    return ids, table.astype(source.dtype), at


class Updates:
    """Gradients of one side's rows over a batch, applied together."""

    def __init__(self, rows: np.ndarray, state: np.ndarray | None, cfg: TrainConfig):
        self.rows, self.state, self.cfg = rows, state, cfg
        self.ids: list[np.ndarray] = []
        self.grads: list[np.ndarray] = []
        self.waiting, self.total, self.touched = 0, None, None
        self.hold = False  # gradients are summed, and rows stay as they are

    def add(self, ids: np.ndarray, grads: np.ndarray) -> None:
        if len(ids):
            self.ids.append(ids)
            self.grads.append(grads)
            self.waiting += len(ids)
            if self.waiting > FOLD_ROWS:
                self.fold()

    def fold(self) -> None:
        """What waits goes into one sum a row, so that a batch of any size takes no more than its rows."""
        if self.total is None:
            self.total, self.touched = np.zeros_like(self.rows), np.zeros(len(self.rows), bool)
        for ids, g in zip(self.ids, self.grads, strict=True):
            self.total[ids] += g
            self.touched[ids] = True
        self.ids, self.grads, self.waiting = [], [], 0

    def apply(self, lr: float) -> int:
        if self.hold or self.total is not None:
            self.fold()
            if self.hold:
                return int(self.touched.sum())
            ids = np.flatnonzero(self.touched)
            step(self.rows, self.state, ids, self.total[ids], lr, self.cfg)
            self.total = self.touched = None
            return len(ids)
        if not self.ids:
            return 0
        written = 0
        if self.state is None and not self.cfg.l2:  # plain steps add up in any order
            for ids, g in zip(self.ids, self.grads, strict=True):
                self.rows[ids] -= lr * g
                written += len(ids)
        else:
            ids, g = (self.ids[0], self.grads[0]) if len(self.ids) == 1 else summed(np.concatenate(self.ids), np.concatenate(self.grads))
            step(self.rows, self.state, ids, g, lr, self.cfg)
            written = len(ids)
        self.ids, self.grads, self.waiting = [], [], 0
        return written


def step(rows: np.ndarray, state: np.ndarray | None, ids: np.ndarray | slice, g: np.ndarray, lr: float, cfg: TrainConfig) -> None:
    """One update of distinct rows, with L2 and the optimizer's state."""
    if cfg.l2:
        g = g + cfg.l2 * rows[ids]
    if state is None:
        rows[ids] -= lr * g
    else:
        state[ids] += (g * g).mean(1)
        rows[ids] -= (lr / np.sqrt(state[ids] + 1e-10))[:, None].astype(rows.dtype) * g


def still_steps(rows: np.ndarray, state: np.ndarray | None, lr: float, cfg: TrainConfig, times: int) -> None:
    """So many updates of rows whose gradient is zero, a piece of rows after another, so that a piece stays in cache."""
    n = max(1, STILL_BYTES // (rows.shape[1] * rows.itemsize))
    zero = np.zeros((min(n, len(rows)), rows.shape[1]), rows.dtype)
    moved = lr * zero
    for lo in range(0, len(rows), n):
        own, by = rows[lo : lo + n], moved[: len(rows) - lo]
        for _ in range(times):
            if state is None and not cfg.l2:
                np.subtract(own, by, out=own)
            else:
                step(own, None if state is None else state[lo : lo + n], slice(None), zero[: len(own)], lr, cfg)


class _Clock:
    """Adds the time since the last mark to a phase."""

    def __init__(self, seconds: dict[str, float]):
        self.seconds, self.at = seconds, time.perf_counter()

    def __call__(self, phase: str) -> None:
        now = time.perf_counter()
        self.seconds[phase] += now - self.at
        self.at = now


def block_epoch(users: np.ndarray, items: np.ndarray, u: np.ndarray, i: np.ndarray, u_ids: np.ndarray, i_ids: np.ndarray, cfg: TrainConfig, epoch: int = 0, layer: Layer | None = None, hist: Histories | None = None, away: np.ndarray | None = None, states: tuple[np.ndarray, np.ndarray] | None = None, moves: list | None = None) -> Counts:
    """Trains users and items in place. u, i: row numbers of the block's pairs; u_ids, i_ids: their ids, which seed all draws.
    hist, away: a user's history rows here, and what those elsewhere add to its pooled row. states: the optimizer's, of users and items.
    moves: gets what one plain step over all pairs adds to users and to items, which then stay as they are."""
    if not len(u):
        return Counts()
    order = None  # a sum over all pairs has none, and makes no arrays for it
    if moves is None or cfg.tile:
        order = np.lexsort((i_ids, u_ids, _mix_np(cfg.seed + 101 * epoch, u_ids, i_ids)))
        u, i = u[order], i[order]
        if isinstance(layer, SummedLayer):
            layer.shares = layer.shares[order]
    run = Pass(users, items, cfg, epoch, layer, hist, away, states, moves is not None)
    run.go(u, i, u_ids, i_ids, order)
    return run.finish(moves)


class Pass:
    """One epoch over pairs in their order, all at once or stretch by stretch. All but the last have a multiple of stretch() pairs,
    so that batches and tiles end where they do in a single one."""

    def __init__(self, users: np.ndarray, items: np.ndarray, cfg: TrainConfig, epoch: int, layer: Layer | None = None, hist: Histories | None = None, away: np.ndarray | None = None, states: tuple[np.ndarray, np.ndarray] | None = None, hold: bool = False, helped: bool = False):
        """helped: a second thread works on rows that a dense batch does not draw, where other cores have nothing to do."""
        self.c, self.cfg, self.epoch, self.layer = Counts(), cfg, epoch, layer
        self.lr = cfg.lr * cfg.decay**epoch
        states = (None, None) if cfg.optimizer == "sgd" or states is None else states
        self.run = (_Fused if cfg.engine == "fused" else _Copying)(self.c, users, items, cfg, self.lr, layer, hist, away, states)
        self.run.user_updates.hold = self.run.item_updates.hold = hold
        self.run.helper = ThreadPoolExecutor(1) if helped and cfg.engine == "dense" else None
        self.items = len(items)
        self.steps = multipliers(cfg.seed + 7, len(items)) if cfg.tile and not cfg.tile_replace else None
        self.tile_no, self.tile, self.first = -1, np.zeros(0, np.int64), None
        self.done = 0
        self.tick = _Clock(self.c.seconds)

    def stretch(self) -> int:
        return self.cfg.refresh if self.cfg.tile else self.cfg.batch

    def go(self, u: np.ndarray, i: np.ndarray, u_ids: np.ndarray, i_ids: np.ndarray, order: np.ndarray | None = None) -> None:
        """u, i: row numbers, in order; u_ids, i_ids: ids, whose places order has (None: in order themselves)."""
        cfg, run, tick = self.cfg, self.run, self.tick
        tick = self.tick = _Clock(self.c.seconds)  # what happens between two stretches is no part of the kernel
        size = min(cfg.tile, self.items)

        def draws(lo: int, hi: int) -> np.ndarray:
            at = slice(lo, hi) if order is None else order[lo:hi]
            return _mix_np(cfg.seed + 13 + self.epoch, u_ids[at, None], i_ids[at, None], np.arange(cfg.negatives)[None, :])

        bounds, last, at, most = [], [], 0, run.piece()
        while at < len(u):
            end = min(len(u), at + cfg.batch)
            if cfg.tile:
                end = min(end, (at // cfg.refresh + 1) * cfg.refresh)  # a batch never spans two tiles
            for lo in range(at, end, most):
                bounds.append((lo, min(end, lo + most)))
                last.append(lo + most >= end)
            at = end
        if self.first is None:
            self.first = int(u_ids[0 if order is None else order[0]])
        ahead = ThreadPoolExecutor(1) if cfg.engine == "jagged" else None  # the ragged library prepares its next input meanwhile
        waiting = ahead.submit(draws, *bounds[0]) if ahead else None
        for k, (at, end) in enumerate(bounds):
            if cfg.tile and (self.done + at) // cfg.refresh != self.tile_no:
                self.tile_no = (self.done + at) // cfg.refresh
                self.tile = tile_indices(cfg.seed + 7, (self.epoch, self.tile_no, self.first), cfg.tile, self.items, cfg.tile_replace, self.steps)
                run.new_tile(self.tile)
            if ahead:
                draw = waiting.result()
                waiting = ahead.submit(draws, *bounds[k + 1]) if k + 1 < len(bounds) else None
            else:
                draw = draws(at, end)
            tick("sample")
            run.batch(u[at:end], i[at:end], draw % size if cfg.tile else draw % self.items, self.tile, tick, last[k])
            self.c.examples += end - at
        run.settle(tick)
        if ahead:
            ahead.shutdown()
        self.done += len(u)

    def finish(self, moves: list | None = None) -> Counts:
        self.run.finish()
        if self.run.helper:
            self.run.helper.shutdown()
        if moves is not None:
            moves += [np.multiply(g, -self.lr, out=g) for g in self.run.totals()]
        self.tick("update")
        if self.layer is not None:
            self.layer.finish()
            self.c.weight_writes = self.layer.writes
        return self.c


class _Fused:
    """Slices of a batch from cached rows to summed gradients."""

    def __init__(self, c: Counts, users: np.ndarray, items: np.ndarray, cfg: TrainConfig, lr: float, layer: Layer | None, hist: Histories | None, away: np.ndarray | None, states: tuple):
        self.c, self.users, self.items, self.cfg, self.lr = c, users, items, cfg, lr
        self.layer, self.hist, self.away = layer, hist, away
        self.user_updates, self.item_updates = Updates(users, states[0], cfg), Updates(items, states[1], cfg)
        self.state = states[1]
        self.waiting: list[tuple] = []
        self.helper: ThreadPoolExecutor | None = None
        self.sums: list[tuple] | None = None
        self.buffer: Buffer | None = None
        self.slot_of = np.full(len(items), -1, np.int64) if cfg.tile else None
        width = (cfg.negatives + 1) * cfg.dim * users.itemsize
        self.rows = max(1, min(SLICE_ROWS, SLICE_BYTES // width))

    def piece(self) -> int:
        """Examples that are drawn at a time; a batch of more is one step all the same."""
        return max(self.rows, PIECE_BYTES // (8 * self.cfg.negatives))

    def new_tile(self, tile: np.ndarray) -> None:
        if self.buffer is not None:
            self.c.rows_written += self.buffer.close()
        self.buffer = Buffer(self.items, self.state, tile, self.slot_of, self.cfg)
        self.c.tile_loads += len(tile)

    def totals(self) -> tuple[np.ndarray, np.ndarray]:
        return self.user_updates.total, self.item_updates.total

    def settle(self, tick: _Clock) -> None:
        """Batches that wait are worked off."""

    def finish(self) -> None:
        if self.buffer is not None:
            self.c.rows_written += self.buffer.close()
            self.buffer = None

    def read(self, rows: np.ndarray) -> np.ndarray:
        """Item rows, from the tile where it has them."""
        out = self.items[rows]
        self.c.reads += len(rows)
        if self.buffer is not None:
            slot = self.slot_of[rows]
            hit = np.flatnonzero(slot >= 0)
            out[hit] = self.buffer.vec[slot[hit]]
            self.c.tile_hits += len(hit)
        return out

    def give(self, ids: np.ndarray, grads: np.ndarray) -> None:
        """Gradients of distinct rows, to the tile where it has them."""
        if self.buffer is None:
            self.item_updates.add(ids, grads)
            return
        slot = self.slot_of[ids]
        hit = slot >= 0
        self.buffer.updates.add(slot[hit], grads[hit])
        self.item_updates.add(ids[~hit], grads[~hit])

    def batch(self, uu: np.ndarray, ii: np.ndarray, neg: np.ndarray, tile: np.ndarray, tick: _Clock, last: bool = True) -> None:
        for lo in range(0, len(uu), self.rows):
            part = slice(lo, lo + self.rows)
            self.slice(uu[part], ii[part], neg[part], tick)
        if not last:
            return
        self.c.rows_written += self.user_updates.apply(self.lr) + self.item_updates.apply(self.lr)
        if self.buffer is not None:
            self.buffer.updates.apply(self.lr)
            if self.cfg.writeback == "step":
                self.c.rows_written += self.buffer.write_back()
        for rows in self.waiting:  # a batch reads one state of the layer, however it is sliced
            self.layer.add(*rows)
        self.waiting = []
        tick("update")

    def slice(self, uu: np.ndarray, ii: np.ndarray, neg: np.ndarray, tick: _Clock) -> None:
        cfg, c = self.cfg, self.c
        b, n = neg.shape
        s = self.users[uu]
        tick("read_user")
        held = self.items if self.buffer is None else self.buffer.vec  # what negatives are drawn from
        whole = self.buffer is not None and len(held) <= WHOLE_TILE * n
        tp = self.read(ii)
        t = None if whole else held[neg]
        c.reads += neg.size
        c.tile_hits += neg.size if self.buffer is not None else 0
        tick("read_item")
        mixed, pooled = s, None
        if self.layer is not None:
            past, lens = self.hist.of(uu, ii if cfg.leave_out else None)
            pooled = pool(self.read(past), past, lens, cfg.aggregator, s, self.layer.w, None if self.away is None else self.away[uu])
            mixed = (cfg.gate * s + (1 - cfg.gate) * (pooled.vec @ self.layer.w[: cfg.dim])).astype(s.dtype)
        tick("aggregate")
        ss = np.einsum("bk,bk->b", mixed, mixed)[:, None]
        st = (mixed @ held.T)[np.arange(b)[:, None], neg] if whole else np.matmul(t, mixed[:, :, None])[:, :, 0]
        tt = np.einsum("bnk,bnk->bn", t, t) if self.buffer is None else np.einsum("rk,rk->r", held, held)[neg]
        st = np.concatenate((np.einsum("bk,bk->b", mixed, tp)[:, None], st), axis=1)
        tt = np.concatenate((np.einsum("bk,bk->b", tp, tp)[:, None], tt), axis=1)
        inv = _reciprocal(np.sqrt(ss * tt)) if cfg.similarity == "cosine" else None
        x = st if inv is None else st * inv
        tick("similarity")
        loss, coef = _loss(cfg, x, st, ss, tt)
        c.loss += loss
        live = np.flatnonzero(coef[:, 1:])
        c.active += len(live)
        tick("loss")
        a, pull, own = _pulls(cfg, coef, x, inv, ss, tt)
        # active negatives: a table of distinct rows by examples serves both sides' gradients
        ids, table, at = _table(neg.ravel()[live], live // n, a[:, 1:].ravel()[live], mixed)
        rows = held[ids]
        gs = table.T @ rows + a[:, :1] * tp - pull.sum(1)[:, None] * mixed
        gu = gs
        if pooled is not None:
            out = (1 - cfg.gate) * gs
            g_past, g_user, g_att = backward(pooled, cfg.aggregator, out @ self.layer.w[: cfg.dim].T, self.layer.w)
            gu = cfg.gate * gs if g_user is None else cfg.gate * gs + g_user
        tick("backward")
        g = table @ mixed - np.bincount(at, weights=own[:, 1:].ravel()[live], minlength=len(ids)).astype(rows.dtype)[:, None] * rows
        (self.item_updates if self.buffer is None else self.buffer.updates).add(ids, g)
        self.give(*summed(ii, a[:, :1] * mixed - own[:, :1] * tp))
        self.user_updates.add(*summed(uu, gu))
        if pooled is not None:
            if not cfg.update_history:
                pass
            elif cfg.aggregator == "average":
                ids, table, _ = _table(pooled.rows, np.repeat(np.arange(b), pooled.lens), pooled.share, s)
                self.give(ids, table @ (out @ self.layer.w[: cfg.dim].T).astype(s.dtype))
            else:
                self.give(*summed(pooled.rows, g_past))
            if isinstance(self.layer, SummedLayer):  # its rows stand still meanwhile
                self.layer.add(pooled.vec, out, g_att)
            else:
                self.waiting.append((pooled.vec, out, g_att))
        tick("update")


class _Copying(_Fused):
    """The baselines: a batch's rows are copied into one tensor, normalized into another, and multiplied."""

    def piece(self) -> int:
        if self.layer is not None and not isinstance(self.layer, SummedLayer):
            return 1 << 62  # a batch reads one state of the layer
        return max(1024, PIECE_BYTES // ((self.cfg.negatives + 1) * self.cfg.dim * 8))

    def new_tile(self, tile: np.ndarray) -> None:
        self.tile = tile
        self.c.tile_loads += len(tile)

    def batch(self, uu: np.ndarray, ii: np.ndarray, neg: np.ndarray, tile: np.ndarray, tick: _Clock, last: bool = True) -> None:
        rows = np.concatenate((ii[:, None], tile[neg] if self.cfg.tile else neg), axis=1)
        tables = ((self.users, self.user_updates.state), (self.items, self.state))
        if self.cfg.engine != "dense" or self.layer is not None or self.item_updates.hold or self.sums is not None or not last:
            self.settle(tick)
            self.train(tables, uu, rows, tick, last)
            return
        self.waiting.append((uu, rows))
        if len(self.waiting) == RUNS[0]:
            self.settle(tick)

    def settle(self, tick: _Clock) -> None:
        if self.waiting:
            self.work_off(((self.users, self.user_updates.state), (self.items, self.state)), self.waiting, RUNS, tick)
            self.c.rows_written += (len(self.users) + len(self.items)) * len(self.waiting)
            self.waiting = []

    def work_off(self, tables: tuple, batches: list[tuple], runs: tuple[int, ...], tick: _Clock) -> None:
        """Dense batches one after another. What a run of them draws is moved in a table of its own, by runs of fewer; all other rows
        take as many steps without a gradient. Every row is written in every batch."""
        if not runs or sum(rows.nbytes for rows, _ in tables) <= NEAR_BYTES:
            for uu, rows in batches:
                self.train(tables, uu, rows, tick)
            return
        for lo in range(0, len(batches), runs[0]):
            run, own = batches[lo : lo + runs[0]], []
            for k, (rows, state) in enumerate(tables):
                ids, at = np.unique(np.concatenate([b[k].ravel() for b in run]), return_inverse=True)
                ends = np.cumsum([b[k].size for b in run])[:-1]
                own.append((ids, rows[ids], None if state is None else state[ids], [a.reshape(b[k].shape) for a, b in zip(np.split(at, ends), run, strict=True)]))
            tick("read_item")
            still = [(v[at : at + HELP_ROWS], None if st is None else st[at : at + HELP_ROWS], self.lr, self.cfg, len(run)) for v, st in tables for at in range(0, len(v), HELP_ROWS)]
            helped = [self.helper.submit(still_steps, *x) for x in still] if self.helper else []
            self.work_off(tuple((v, st) for _, v, st, _ in own), [*zip(*(at for *_, at in own), strict=True)], runs[1:], tick)
            for k, x in reversed([*enumerate(still)]):
                if not helped or helped[k].cancel():
                    still_steps(*x)
            for x in helped:
                x.cancelled() or x.result()
            for (rows, state), (ids, vec, st, _) in zip(tables, own, strict=True):
                rows[ids] = vec
                if state is not None:
                    state[ids] = st
            tick("update")

    def train(self, tables: tuple, uu: np.ndarray, rows: np.ndarray, tick: _Clock, last: bool = True) -> None:
        """One batch or a piece of it, of users uu with the item rows of their positives and negatives."""
        cfg, c, lr, ((users, user_state), (items, item_state)) = self.cfg, self.c, self.lr, tables
        (b, n), ii = rows.shape, rows[:, 0]
        n -= 1
        s = users[uu]
        tick("read_user")
        t = items[rows]
        c.reads += rows.size
        tick("read_item")
        mixed, pooled = s, None
        if self.layer is not None:
            past, lens = self.hist.of(uu, ii if cfg.leave_out else None)
            pooled = pool(self.read(past), past, lens, cfg.aggregator, s, self.layer.w, None if self.away is None else self.away[uu])
            mixed = cfg.gate * s + (1 - cfg.gate) * (pooled.vec @ self.layer.w[: cfg.dim])
        tick("aggregate")
        wide = np.repeat(mixed[:, None, :], n + 1, axis=1)
        flat = t.reshape(-1, cfg.dim).copy() if cfg.engine == "jagged" else t.copy()
        c.copied_bytes += wide.nbytes + flat.nbytes
        flat = flat.reshape(b, n + 1, cfg.dim)
        tick("copy")
        inv = None
        if cfg.similarity == "cosine":
            r_user = _reciprocal(np.sqrt((wide**2).sum(2)))
            wide = wide * r_user[:, :, None]
            tick("user_norm")
            r_item = _reciprocal(np.sqrt((flat**2).sum(2)))
            flat = flat * r_item[:, :, None]
            c.copied_bytes += flat.nbytes + wide.nbytes
            tick("item_norm")
        x = (flat * wide).sum(2) if cfg.engine == "jagged" else np.matmul(flat, wide[:, 0, :, None])[:, :, 0]
        tick("similarity")
        st, ss, tt = x, np.zeros((b, 1)), np.zeros_like(x)
        if cfg.loss == "metric":
            st, ss, tt = np.matmul(t, mixed[:, :, None])[:, :, 0], (mixed**2).sum(1)[:, None], (t**2).sum(2)
        loss, coef = _loss(cfg, x, st, ss, tt)
        c.loss += loss
        c.active += int((coef[:, 1:] != 0).sum())
        tick("loss")
        ss, tt = (mixed**2).sum(1)[:, None], (t**2).sum(2)  # nothing of the forward pass is reused
        if cfg.similarity == "cosine":
            inv = _reciprocal(np.sqrt(ss * tt))
        a, pull, own = _pulls(cfg, coef, x, inv, ss, tt)
        gs = np.einsum("bn,bnk->bk", a, t) - pull.sum(1)[:, None] * mixed
        gt = (a[:, :, None] * mixed[:, None, :] - own[:, :, None] * t).reshape(-1, cfg.dim)
        gu = gs
        if pooled is not None:
            out = (1 - cfg.gate) * gs
            g_past, g_user, g_att = backward(pooled, cfg.aggregator, out @ self.layer.w[: cfg.dim].T, self.layer.w)
            gu = cfg.gate * gs if g_user is None else cfg.gate * gs + g_user
            if cfg.update_history:
                rows, gt = np.concatenate((rows.ravel(), pooled.rows)), np.concatenate((gt, g_past))
            self.layer.add(pooled.vec, out, g_att)
        tick("backward")
        rows = rows.ravel()
        if not last or self.sums is not None or self.item_updates.hold:
            self.sum_pieces(((items, item_state, rows, gt), (users, user_state, uu, gu)), last)
        elif cfg.engine == "dense":
            for own_rows, state, at, g in ((items, item_state, rows, gt), (users, user_state, uu, gu)):
                cells = at[:, None] * cfg.dim + np.arange(cfg.dim)
                full = np.bincount(cells.ravel(), weights=g.ravel(), minlength=own_rows.size).reshape(own_rows.shape)
                step(own_rows, state, slice(None), full.astype(own_rows.dtype, copy=False), lr, cfg)
                if self.layer is not None:
                    c.rows_written += len(own_rows)  # else settle counts them
        else:
            for own_rows, state, at, g in ((items, item_state, rows, gt), (users, user_state, uu, gu)):
                ids, place = np.unique(at, return_inverse=True)
                merged = np.zeros((len(ids), cfg.dim), own_rows.dtype)
                np.add.at(merged, place, g)
                step(own_rows, state, ids, merged, lr, cfg)
                c.rows_written += len(ids)
        tick("update")

    def sum_pieces(self, sides: tuple, last: bool) -> None:
        """A batch in pieces: gradients are summed over all, and applied with the last."""
        if self.sums is None:
            self.sums = [(np.zeros_like(own_rows), np.zeros(len(own_rows), bool)) for own_rows, *_ in sides]
        for (total, touched), (own_rows, state, at, g) in zip(self.sums, sides, strict=True):
            ids, place = np.unique(at, return_inverse=True)
            cells = place[:, None] * self.cfg.dim + np.arange(self.cfg.dim)
            total[ids] += np.bincount(cells.ravel(), weights=g.ravel(), minlength=len(ids) * self.cfg.dim).reshape(len(ids), -1)
            touched[ids] = True
            if last and not self.item_updates.hold:
                ids = slice(None) if self.cfg.engine == "dense" else np.flatnonzero(touched)
                step(own_rows, state, ids, total[ids], self.lr, self.cfg)
                self.c.rows_written += len(own_rows) if self.cfg.engine == "dense" else len(ids)
        if last and not self.item_updates.hold:
            self.sums = None

    def totals(self) -> tuple[np.ndarray, np.ndarray]:
        return self.sums[1][0], self.sums[0][0]


def init_rows(ids: np.ndarray, side: int, cfg: TrainConfig) -> np.ndarray:
    """The same rows as init_vector(seed + side, id, ...) gives."""
    h = _mix_np(cfg.seed + side, ids[:, None], np.arange(cfg.dim)[None, :])
    return (2 * h / P - 1) * cfg.init


def with_options(cfg: TrainConfig, **changes) -> TrainConfig:
    return replace(cfg, **changes)


def cell_bytes(rows: int, cfg: TrainConfig) -> int:
    """What the factor rows of a cell take in a worker, with a copy."""
    return 2 * rows * cfg.dim * (8 if cfg.precision == "float64" else 4)


def blocks_for(pairs: int, users: int, items: int, cfg: TrainConfig, pairs_a_cell: int, bytes_a_cell: int) -> int:
    """Blocks a side so that no cell of blocks x blocks exceeds either size."""
    by_pairs = math.isqrt(max(0, -(-pairs // pairs_a_cell) - 1)) + 1
    return max(1, by_pairs, -(-cell_bytes(users + items, cfg) // bytes_a_cell))
