"""Portable draws: a fold of integer keys modulo 2^31 - 1, equal in Spark, SQL and Python."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P = 2147483647
_MUL, _ADD, _LAST = 48271, 1234567, 7919


def _long(x) -> Column:
    return (F.lit(x) if isinstance(x, int) else F.col(x) if isinstance(x, str) else x).cast("long")


def mix(seed: int, *keys) -> Column:
    """0 <= mix < P. Keys are column names, columns or ints; negative keys wrap."""
    step = lambda h, k: F.transform(F.array((F.lit(_MUL) * h + F.pmod(k, F.lit(P)) + 1) % P), lambda g: (g * g + _ADD) % P)[0]
    return F.aggregate(F.array(*[_long(k) for k in keys], _long(_LAST)), F.lit(seed).cast("long"), step)


def mix_py(seed: int, *keys: int) -> int:
    h = seed
    for k in (*keys, _LAST):
        g = (_MUL * h + k % P + 1) % P
        h = (g * g + _ADD) % P
    return h


def mix_sql(seed: int, *keys: str) -> str:
    """The same fold as a DuckDB expression; keys are SQL of non-negative integers."""
    items = ", ".join(f"CAST({k} AS BIGINT)" for k in (seed, *keys, _LAST))
    g = f"(({_MUL} * h + (k % {P}) + 1) % {P})"
    return f"list_reduce([{items}], lambda h, k: ({g} * {g} + {_ADD}) % {P})"


def unit(seed: int, *keys) -> Column:
    return mix(seed, *keys) / F.lit(float(P))


def multipliers(seed: int, n: int, count: int = 64) -> np.ndarray:
    """Numbers that share no factor with n: from each of count draws, the first one at or after it."""
    out = []
    for k in range(count):
        c = 1 + mix_py(seed, k) % n
        while math.gcd(c, n) != 1:
            c += 1
        out.append(c)
    return np.array(out, np.int64)


def multiplier_sql(seed: int, n: str, pick: str, count: int = 64) -> str:
    """The number that multipliers(seed, n)[pick % count] is, as a DuckDB expression."""
    first = f"(1 + {mix_sql(seed, f'({pick} % {count})')} % {n})"
    return f"list_filter(range({first}, {first} + 400), lambda c: gcd(c, {n}) = 1)[1]"
