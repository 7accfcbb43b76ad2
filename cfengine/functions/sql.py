"""SQL names for the engine's methods: similarities, draws, tiles and top-k lists.

    register(spark)
    SELECT user_id, cosine_vec(s, t) FROM pairs_with_rows
    SELECT p.user_id, d.j, d.idx FROM pairs p, LATERAL negative_draws(7, user_id, item_id, 8, 2000) d
    SELECT * FROM tile_slots(9, 0, 3, 1024, 2000)

Draws agree with sampling.sample_uniform and sampling.tile_rows: both are functions of keys alone.
The similarity functions are SQL functions over built-in ones, so they
stay in generated code.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from ..shipping import ship
from .mix import P

_DOT = "aggregate(zip_with(a, b, (x, y) -> cast(x AS double) * cast(y AS double)), 0D, (s, x) -> s + x)"
_SQ = "aggregate(transform({v}, x -> cast(x AS double) * cast(x AS double)), 0D, (s, x) -> s + x)"
MACROS = {
    "dot_vec": f"(a array<double>, b array<double>) RETURNS double RETURN {_DOT}",
    "cosine_vec": f"(a array<double>, b array<double>) RETURNS double RETURN coalesce(try_divide({_DOT}, sqrt({_SQ.format(v='a')} * {_SQ.format(v='b')})), 0D)",
    "ccl_loss": "(x_pos double, x_negs array<double>, mu double, theta double) RETURNS double RETURN 1 - x_pos + coalesce(try_divide(mu * aggregate(x_negs, 0D, (s, x) -> s + greatest(0D, x - theta)), size(x_negs)), 0D)",
}


def fold(seed: int, *keys: int) -> int:
    h = seed
    for k in (*keys, 7919):
        g = (48271 * h + k % P + 1) % P
        h = (g * g + 1234567) % P
    return h


@udtf(returnType="j int, idx long")
class NegativeDraws:
    """j, idx: n draws of a pair from items dense indexes; no row where an argument is null or n < 1."""

    def eval(self, seed: int, user_id: int, pos_id: int, n: int, items: int):
        if None in (seed, user_id, pos_id, n, items) or items < 1:
            return
        for j in range(n):
            yield j, fold(seed, user_id, pos_id, j) % items


@udtf(returnType="slot int, idx long")
class TileSlots:
    """slot, idx: the tile that a worker holds after a number of refreshes, without repeats."""

    def eval(self, seed: int, worker: int, refresh: int, tile: int, items: int):
        if None in (seed, worker, refresh, tile, items) or items < 1:
            return
        step = 1 + fold(seed, fold(seed + 2, worker, refresh) % 64) % items
        while math.gcd(step, items) != 1:
            step += 1
        first = fold(seed + 1, worker, refresh) % items
        for slot in range(min(tile, items)):
            yield slot, (first + step * slot) % items


def cosine_arrow(a: pd.Series, b: pd.Series) -> pd.Series:
    """The cosine of whole batches of vectors of one length, for plans that are in Python anyway."""
    x, y = np.stack(a.to_numpy()).astype(float), np.stack(b.to_numpy()).astype(float)
    under = np.sqrt((x * x).sum(1) * (y * y).sum(1))
    return pd.Series(np.divide((x * y).sum(1), under, out=np.zeros(len(x)), where=under > 0))


def sum_vec(v: pd.Series) -> np.ndarray:
    """Element-wise sum of a group's vectors. A group is gathered; relational.combine_gradients adds up before the shuffle."""
    return np.sum(np.stack(v.to_numpy()).astype(float), axis=0).tolist()


def register(spark: SparkSession) -> None:
    """Adds the functions to the session, under the names above, and the data source planted."""
    from ..sources.tables import PlantedSource

    ship(spark)
    spark.dataSource.register(PlantedSource)
    spark.udf.register("cosine_arrow", pandas_udf(cosine_arrow, "double"))
    spark.udf.register("sum_vec", pandas_udf(sum_vec, "array<double>"))
    for name, body in MACROS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("negative_draws", NegativeDraws)
    spark.udtf.register("tile_slots", TileSlots)


def expose(model, pairs: DataFrame, k: int = 20) -> None:
    """Temporary views of a model: user_factors, item_factors, recommendations (user_id, rank, item_id, score)."""
    from ..operators.predict import aggregated_users, recommend
    from ..sources.feedback import user_history

    users = model.user_factors
    if model.weights is not None:
        timed = pairs if "ts" in pairs.columns else pairs.selectExpr("*", "cast(null AS timestamp) AS ts")
        users = aggregated_users(users, model.item_factors, user_history(timed, model.cfg.history), model.weights, model.cfg)
    model.user_factors.createOrReplaceTempView("user_factors")
    model.item_factors.createOrReplaceTempView("item_factors")
    recommend(users, model.item_factors, pairs, k, model.cfg.similarity).createOrReplaceTempView("recommendations")
