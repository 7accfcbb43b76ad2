"""Settles what a training run leaves open, from the sizes of pairs and factors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.blocks import TrainConfig, blocks_for, with_options
from ..operators.tuning import plan_tiles, spark_machine

#: Most pairs and factor bytes of a cell; the number of blocks a side follows from them.
CELL_PAIRS, CELL_BYTES = 100_000, 256 << 20
#: A task's cache for a tile, in bytes, and the latencies of a cached and an uncached row.
TASK_CACHE = 1 << 20


def settle(pairs: DataFrame, cfg: TrainConfig) -> TrainConfig:
    """cfg with a plan, a number of blocks and a tile. The plan is rotation at every size; blocks grow with the input."""
    plan = "rotate" if cfg.plan == "auto" else cfg.plan
    cfg = with_options(cfg, plan=plan)
    if cfg.blocks and cfg.tile >= 0:
        return cfg
    r = pairs.agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct("user_id").alias("u"), F.approx_count_distinct("item_id").alias("i")).first()
    if not cfg.blocks:
        cfg = with_options(cfg, blocks=blocks_for(r["n"], r["u"], r["i"], cfg, CELL_PAIRS, CELL_BYTES))
    if cfg.tile < 0:
        m = spark_machine(TASK_CACHE, 1, 1, 16 * TASK_CACHE)
        own = max(1, r["i"] // cfg.blocks)
        tuned = plan_tiles(own, max(1, r["n"] // cfg.blocks**2), cfg.dim, m)
        cfg = with_options(cfg, tile=tuned.n1, refresh=tuned.n2)
    return cfg


def explain_plan(pairs: DataFrame, cfg: TrainConfig) -> str:
    cfg = settle(pairs, cfg)
    sampler = f"tiles of {cfg.tile}, redrawn every {cfg.refresh}" if cfg.tile else "uniform"
    return f"plan={cfg.plan} blocks={cfg.blocks} sampler={sampler} aggregator={cfg.aggregator or 'none'} engine={cfg.engine}"
