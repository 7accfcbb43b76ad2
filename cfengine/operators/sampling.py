"""Negative samplers: uniform over all items, and uniform inside a tile that is redrawn at intervals.

Draws are functions of keys alone, so a retried or repartitioned task draws the same.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.mix import P, mix, multipliers
from ..plans.cuts import Cuts


def sample_uniform(pairs: DataFrame, items: DataFrame, n: int, seed: int = 7, exclude_seen: bool = False, redraws: int = 8) -> DataFrame:
    """user_id, pos_id, j, item_id: n draws with replacement a pair. items: id, idx (dense).
    exclude_seen: a draw that its user has seen is drawn again, at most redraws times; one
    that has hit a seen item every time is left out, so only users who have seen nearly all get fewer than n."""
    if n < 1:
        raise ValueError("n must be at least 1")
    count = items.count()
    wanted = pairs.select("user_id", F.col("item_id").alias("pos_id"), F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("j"))

    def drawn(rows: DataFrame, attempt: int) -> DataFrame:
        idx = mix(seed + 1000 * attempt, "user_id", "pos_id", "j") % count
        return rows.withColumn("idx", idx).join(items, "idx").select("user_id", "pos_id", "j", F.col("id").alias("item_id"))

    if not exclude_seen:
        return drawn(wanted, 0)
    cuts, seen, on = Cuts(pairs.sparkSession), pairs.select("user_id", "item_id"), ["user_id", "item_id"]
    kept = None
    for attempt in range(redraws + 1):
        out = drawn(wanted, attempt)
        fresh = out.join(seen, on, "left_anti").select("user_id", "pos_id", "j", "item_id")
        kept = fresh if kept is None else kept.unionByName(fresh)
        wanted = cuts.cut(out.join(seen, on, "left_semi").select("user_id", "pos_id", "j"))  # few: those that hit
        if wanted.isEmpty():
            break
    return kept


def tile_slot(worker: Column, refresh: Column, slot: Column, items: int, seed: int, replacement: bool = False) -> Column:
    """Item index in a slot of a tile. Without replacement slots walk around the items from a drawn start in a
    drawn step that shares no factor with their number."""
    if replacement:
        return mix(seed, worker, refresh, slot) % items
    steps = F.array(*[F.lit(int(m)) for m in multipliers(seed, items)])
    step = F.get(steps, (mix(seed + 2, worker, refresh) % 64).cast("int"))
    return (mix(seed + 1, worker, refresh) % items + step * slot) % items


def tile_rows(items: DataFrame, workers: int, refreshes: int, tile: int, seed: int = 9, replacement: bool = False) -> DataFrame:
    """worker, refresh, slot, item_id: all tiles of a run."""
    n = items.count()
    tile = tile if replacement else min(tile, n)
    grid = items.sparkSession.range(workers * refreshes * tile).select(
        (F.col("id") / (refreshes * tile)).cast("int").alias("worker"), ((F.col("id") / tile).cast("long") % refreshes).alias("refresh"), (F.col("id") % tile).cast("int").alias("slot"))
    drawn = grid.withColumn("idx", tile_slot(F.col("worker"), F.col("refresh"), F.col("slot"), n, seed, replacement))
    return drawn.join(items, "idx").select("worker", "refresh", "slot", F.col("id").alias("item_id"))


def with_steps(pairs: DataFrame, workers: int, refresh: int, seed: int = 9, share: int = 1 << 16) -> DataFrame:
    """Adds worker, step (the pair's turn in its worker's seeded order) and refresh (its tile's number).
    A worker's order is dealt into ranges of the seeded hash, about share rows each; ranges are counted
    first and only a range is ordered as a whole."""
    cuts = Cuts(pairs.sparkSession)
    dealt = cuts.cut(pairs.withColumn("worker", (mix(seed + 1, "user_id") % workers).cast("int")).withColumn("_h", mix(seed + 2, "user_id", "item_id")))
    ranges = max(1, -(-dealt.count() // (workers * share)))
    dealt = dealt.withColumn("_range", F.floor(F.col("_h") * ranges / P).cast("long"))
    sizes = dealt.groupBy("worker", "_range").agg(F.count(F.lit(1)).alias("_n"))
    before = F.coalesce(F.sum("_n").over(W.partitionBy("worker").orderBy("_range").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    bases = cuts.cut(sizes.select("worker", "_range", before.alias("_base")))
    turn = F.row_number().over(W.partitionBy("worker", "_range").orderBy("_h", "user_id", "item_id")) - 1
    placed = dealt.withColumn("_turn", turn).join(bases, ["worker", "_range"])
    out = placed.withColumn("step", (F.col("_base") + F.col("_turn")).cast("long")).withColumn("refresh", F.floor(F.col("step") / refresh).cast("long"))
    return out.select(*[F.col(f"`{c}`") for c in pairs.columns], "worker", "step", "refresh")


def sample_tiled(pairs: DataFrame, items: DataFrame, n: int, tile: int, refresh: int, workers: int, seed: int = 9, replacement: bool = False) -> DataFrame:
    """user_id, pos_id, worker, refresh, j, item_id: n draws from the tile that the pair's worker holds at its turn.
    A draw is a slot of the tile and a slot is a function of keys, so no tile is stored or joined."""
    count = items.count()
    tile = tile if replacement else min(tile, count)
    drawn = with_steps(pairs, workers, refresh, seed).select("user_id", F.col("item_id").alias("pos_id"), "worker", "refresh", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("j"))
    slot = mix(seed + 3, "user_id", "pos_id", "j") % tile
    drawn = drawn.withColumn("idx", tile_slot(F.col("worker"), F.col("refresh"), slot, count, seed, replacement))
    return drawn.join(items, "idx").select("user_id", "pos_id", "worker", "refresh", "j", F.col("id").alias("item_id"))


def tiles_used(steps: DataFrame) -> int:
    """How often the busiest worker draws a tile."""
    return (steps.agg(F.max("refresh")).first()[0] or 0) + 1


def sampling_space(iterations: int, tile: int, refresh: int, items: int) -> tuple[float, float]:
    """(draws into tiles, distinct items expected among them)."""
    draws = iterations / refresh * tile
    return draws, items * (1 - (1 - 1 / items) ** draws)


def hit_ratio(reads: DataFrame, tiles: DataFrame) -> DataFrame:
    """Share of reads (worker, refresh, item_id) that the worker's tile holds at that time."""
    own = tiles.select("worker", "refresh", "item_id").distinct().withColumn("_hit", F.lit(1))
    return reads.join(own, ["worker", "refresh", "item_id"], "left").agg(F.round(F.avg(F.coalesce("_hit", F.lit(0))), 6).alias("hit_ratio"))
