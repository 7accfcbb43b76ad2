"""Tile size and refresh interval from cache capacity and a latency model.

The functions take numbers; plan_frame does the same for a frame of settings.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Machine:
    l2: float
    l3: float
    workers: int
    t_l2: float = 4.0
    t_l3: float = 40.0
    t_mem: float = 100.0
    price: float = 0.0


MIB = 1 << 20
#: Published profiles: fixed values.
EPYC = Machine(32 * MIB, 256 * MIB, 64, price=2.46)
A64FX = Machine(32 * MIB, 0, 48)


@dataclass(frozen=True)
class TilePlan:
    n1: int
    n2: int
    n2_cover: float
    n2_speed: float
    neg_speedup: float
    pos_speedup: float
    level: str
    achieved_alpha: float
    achieved_beta: float


def tile_from_capacity(m: Machine, dim: int, width: int = 4) -> int:
    return max(1, int(m.l2 // (m.workers * dim * width)))


def read_latency(total: float, m: Machine) -> tuple[float, str]:
    """Latency and level of tiles of all workers together: a level holds what is strictly smaller."""
    if total < m.l2:
        return m.t_l2, "l2"
    return (m.t_l3, "l3") if total < m.l3 else (m.t_mem, "memory")


def neg_time_random(iterations: float, n: int, t_mem: float) -> float:
    return iterations * n * t_mem


def neg_time_tiled(iterations: float, n: int, n1: int, n2: int, t_cache: float, t_mem: float, model: str = "paper") -> float:
    """model: paper counts a refresh's misses once a negative; load_once once a refresh."""
    n2 = max(n1, n2)
    if model == "load_once":
        return iterations / n2 * (n1 * t_mem + n * n2 * t_cache)
    return n * iterations / n2 * ((n2 - n1) * t_cache + n1 * t_mem)


def neg_speedup(n1: int, n2: int, t_cache: float, t_mem: float, form: str = "exact") -> float:
    n2 = max(n1, n2)
    if form == "approx":
        return n2 / n1
    spread = t_mem - (t_cache if form == "exact" else 1)
    return t_mem / (t_cache + spread * n1 / n2)


def pos_speedup(hit: float, t_cache: float, t_mem: float) -> float:
    return t_mem / (hit * t_cache + (1 - hit) * t_mem)


def refresh_candidates(items: float, iterations: float, n1: int, target: float, beta: float, form: str = "derived") -> tuple[float, float]:
    """(interval whose tiles draw as many rows as there are items, interval that reaches beta of the target speedup)."""
    return iterations * n1 / items, n1 * beta * target if form == "derived" else n1 / (beta * target)


def plan_tiles(items: int, iterations: int, dim: int, machine: Machine, hit: float = 0.0, target: float = 4.0, beta: float = 0.85, form: str = "derived") -> TilePlan:
    n1 = min(items, tile_from_capacity(machine, dim))
    cover, speed = refresh_candidates(items, iterations, n1, target, beta, form)
    n2 = max(1, math.floor(min(cover, speed)))
    t, level = read_latency(n1 * dim * 4 * machine.workers, machine)
    neg, pos = neg_speedup(n1, n2, t, machine.t_mem), pos_speedup(hit, t, machine.t_mem)
    return TilePlan(n1, n2, cover, speed, neg, pos, level, pos / target, neg / target)


def plan_frame(settings: DataFrame, target: float = 4.0, beta: float = 0.85) -> DataFrame:
    """settings with the tuner's figures. settings: items, iterations, negatives, dim, hit, l2, l3, workers, t_l2, t_l3, t_mem."""
    n1 = F.least(F.col("items"), F.greatest(F.lit(1), F.floor(F.col("l2") / (F.col("workers") * F.col("dim") * 4)))).cast("long")
    sized = settings.withColumn("n1", n1).withColumn("held", F.col("n1") * F.col("dim") * 4 * F.col("workers"))
    level = F.when(F.col("held") < F.col("l2"), "l2").when(F.col("held") < F.col("l3"), "l3").otherwise("memory")
    sized = sized.withColumns({
        "level": level,
        "t_cache": F.when(level == "l2", F.col("t_l2")).when(level == "l3", F.col("t_l3")).otherwise(F.col("t_mem")),
        "n2_cover": F.col("iterations") * F.col("n1") / F.col("items"),
        "n2_speed": F.col("n1") * beta * target,
    })
    sized = sized.withColumn("n2", F.greatest(F.lit(1), F.floor(F.least("n2_cover", "n2_speed"))).cast("long"))
    long = F.greatest("n1", "n2")
    t_c, t_m = F.col("t_cache"), F.col("t_mem")
    return sized.withColumns({
        "neg_time_random": F.col("iterations") * F.col("negatives") * t_m,
        "neg_time_tiled": F.col("negatives") * F.col("iterations") / long * ((long - F.col("n1")) * t_c + F.col("n1") * t_m),
        "neg_speedup": t_m / (t_c + (t_m - t_c) * F.col("n1") / long),
        "pos_speedup": t_m / (F.col("hit") * t_c + (1 - F.col("hit")) * t_m),
    }).drop("held")


def spark_machine(task_bytes: float, cores: int, tasks: int, executor_bytes: float) -> Machine:
    """The same model one level up: what a task keeps at hand for L2, what an executor's tasks share for L3, a
    read from elsewhere for memory; latencies relative to a row at hand."""
    return Machine(task_bytes, executor_bytes, tasks, 1.0, 3.0, 60.0 / max(1, cores))
