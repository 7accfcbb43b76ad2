"""Behaviour aggregation: pooled rows of past items pass a dense layer and are mixed with the user row.

All parameters are rows of one matrix: the K x K layer, and for attention also a K x K
projection, its offset and a query (the last row; user attention asks with the user row).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

KINDS = ("average", "self_attention", "user_attention")


def first_params(kind: str, dim: int, seed: int) -> np.ndarray:
    if kind not in KINDS:
        raise ValueError(f"aggregator is one of {KINDS}")
    layer = np.eye(dim) * 0.5
    if kind == "average":
        return layer
    rng = np.random.default_rng(seed)
    return np.concatenate((layer, rng.normal(0, 0.1, (dim, dim)), np.zeros((1, dim)), rng.normal(0, 0.1, (1, dim))))


def _segment_sums(values: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """Sums of consecutive runs; an empty run sums to zero."""
    out = np.zeros((len(lens), *values.shape[1:]))
    full = lens > 0
    if full.any():
        out[full] = np.add.reduceat(values, (np.cumsum(lens) - lens)[full], axis=0)
    return out


@dataclass
class Pooled:
    vec: np.ndarray  # one pooled row an example
    rows: np.ndarray  # item row numbers of all histories, one after another
    lens: np.ndarray
    t: np.ndarray
    share: np.ndarray  # weight of each history row
    act: np.ndarray | None
    query: np.ndarray | None


def pool(t: np.ndarray, rows: np.ndarray, lens: np.ndarray, kind: str, user: np.ndarray, params: np.ndarray, away: np.ndarray | None = None) -> Pooled:
    """average: equal weights; self_attention: softmax(q . tanh(W1 t + b)); user_attention: the user row for q.
    t: the history rows of all examples, one after another, rows their numbers, lens how many an example has.
    away, a row an example: what history rows that are not in t add, as constants: the weighted sum, the
    sum of the weights, and the exponent that was taken off each weight."""
    dim, n = params.shape[1], len(lens)
    num, den, off = (np.zeros((n, dim)), np.zeros(n), np.full(n, -np.inf)) if away is None else (away[:, :dim], away[:, dim], away[:, dim + 1])
    of = np.repeat(np.arange(n), lens)
    act = query = None
    if kind == "average":
        e = np.ones(len(rows))
    else:
        act = np.tanh(t @ params[dim : 2 * dim].T + params[2 * dim])
        query = np.broadcast_to(params[2 * dim + 1], t.shape) if kind == "self_attention" else user[of]
        z = np.einsum("rk,rk->r", act, query)
        top = np.where(den > 0, off, -np.inf)
        np.maximum.at(top, of, z)
        e = np.exp(z - top[of])
        shrink = np.exp(np.subtract(off, top, out=np.zeros_like(den), where=den > 0))
        num, den = num * shrink[:, None], den * shrink
    total = _segment_sums(e, lens) + den
    total[total == 0] = 1.0
    share = e / total[of]
    return Pooled(_segment_sums(share[:, None] * t, lens) + num / total[:, None], rows, lens, t, share, act, query)


def backward(p: Pooled, kind: str, g: np.ndarray, params: np.ndarray) -> tuple[np.ndarray, np.ndarray | None, Callable[[int, int], np.ndarray] | None]:
    """From the gradient of the pooled rows: gradients of the history rows, of the user rows (user
    attention) and, for a run of examples, of the attention parameters."""
    of = np.repeat(np.arange(len(p.lens)), p.lens)
    direct = p.share[:, None] * g[of]
    if kind == "average":
        return direct, None, None
    dim = g.shape[1]
    gain = np.einsum("rk,rk->r", g[of], p.t)
    dz = p.share * (gain - np.einsum("bk,bk->b", g, p.vec)[of])
    inner = dz[:, None] * p.query * (1 - p.act**2)
    asked = dz[:, None] * p.act
    ends = np.concatenate(([0], np.cumsum(p.lens)))

    def attention(lo: int, hi: int) -> np.ndarray:
        r = slice(ends[lo], ends[hi])
        q = asked[r].sum(0) if kind == "self_attention" else np.zeros(dim)
        return np.concatenate((inner[r].T @ p.t[r], inner[r].sum(0)[None], q[None]))

    return direct + inner @ params[dim : 2 * dim], _segment_sums(asked, p.lens) if kind == "user_attention" else None, attention


class Layer:
    """Parameters with locally accumulated gradients: every m iterations the mean of the sum is applied.
    m = 1 is the shared copy that every iteration writes."""

    def __init__(self, w: np.ndarray, m: int, lr: float, flush_tail: bool = True):
        self.w, self.m, self.lr, self.flush_tail = w, m, lr, flush_tail
        self.sum, self.n, self.writes = np.zeros_like(w), 0, 0

    def add(self, pooled: np.ndarray, g: np.ndarray, attention: Callable[[int, int], np.ndarray] | None = None) -> None:
        """Row by row counts as iterations; whole groups of m are one matrix product."""
        at = 0
        while at < len(pooled):
            k = min(self.m - self.n, len(pooled) - at)
            part = pooled[at : at + k].T @ g[at : at + k]
            self.sum += part if attention is None else np.concatenate((part, attention(at, at + k)))
            self.n += k
            at += k
            if self.n == self.m:
                self._apply()

    def _apply(self) -> None:
        self.w -= self.lr * self.sum / self.n
        self.sum[:] = 0
        self.n = 0
        self.writes += 1

    def finish(self) -> None:
        if self.n and self.flush_tail:
            self._apply()


class ServerLayer(Layer):
    """A parameter server without barriers: a worker reads a replica, sends the mean gradient of m
    iterations, and sees it in a replica only after age more of its mini-batches."""

    def __init__(self, w: np.ndarray, m: int, lr: float, flush_tail: bool = True, age: int = 1):
        super().__init__(w, m, lr, flush_tail)
        self.server, self.age, self.sent = w.copy(), age, []

    def _apply(self) -> None:
        self.sent.append(self.lr * self.sum / self.n)
        self.sum[:] = 0
        self.n = 0
        if len(self.sent) > self.age:
            self.server -= self.sent.pop(0)
            self.writes += 1
        self.w[:] = self.server

    def finish(self) -> None:
        super().finish()
        for g in self.sent:
            self.server -= g
            self.writes += 1
        self.sent = []
        self.w[:] = self.server


class SummedLayer(Layer):
    """Some examples of one batch: parameters stand still, and each example counts by its share, one over the size of
    its group of m iterations; the groups are dealt over all parts of the batch."""

    def __init__(self, w: np.ndarray, lr: float, shares: np.ndarray):
        super().__init__(w, 1, lr)
        self.shares, self.at, self.writes = shares, 0, float(shares.sum())

    def add(self, pooled: np.ndarray, g: np.ndarray, attention: Callable[[int, int], np.ndarray] | None = None) -> None:
        s = self.shares[self.at : self.at + len(pooled)]
        self.at += len(pooled)
        ends = [0, *(np.flatnonzero(s[1:] != s[:-1]) + 1), len(s)]
        for lo, hi in zip(ends, ends[1:], strict=False):
            part = pooled[lo:hi].T @ g[lo:hi]
            self.sum += (part if attention is None else np.concatenate((part, attention(lo, hi)))) * s[lo]

    def finish(self) -> None:
        self.w -= self.lr * self.sum


def make_layer(params: np.ndarray, cfg) -> Layer:
    """The way of updating that cfg.sync_mode names: local, server or shared."""
    if cfg.sync_mode == "server":
        return ServerLayer(params, cfg.sync, cfg.lr, cfg.flush_tail, cfg.stale)
    return Layer(params, cfg.sync if cfg.sync_mode == "local" else 1, cfg.lr, cfg.flush_tail)
