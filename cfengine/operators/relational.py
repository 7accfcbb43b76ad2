"""One training step as a plan of joins: sample, forward, loss, gradient, update. The truth for the kernels."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import vectors as V


@dataclass(frozen=True)
class StepConfig:
    dim: int = 8
    negatives: int = 4
    lr: float = 0.05
    mu: float = 1.0
    theta: float = 0.0
    loss: str = "ccl"
    similarity: str = "cosine"
    reuse: bool = True
    l2: float = 0.0
    margin: float = 1.0


def examples(pairs: DataFrame, negatives: DataFrame) -> DataFrame:
    """user_id, pos_id, j (-1 for the positive), item_id."""
    pos = pairs.select("user_id", F.col("item_id").alias("pos_id"), F.lit(-1).alias("j"), "item_id")
    return pos.unionByName(negatives.select("user_id", "pos_id", F.col("j").cast("int").alias("j"), "item_id"))


def forward(rows: DataFrame, users: DataFrame, items: DataFrame, cfg: StepConfig) -> DataFrame:
    """Adds s, t, sums and x. users, items: id, vec."""
    joined = rows.join(users.select(F.col("id").alias("user_id"), F.col("vec").alias("s")), "user_id").join(items.select(F.col("id").alias("item_id"), F.col("vec").alias("t")), "item_id")
    summed = V.carry(joined, "user_id", "pos_id", "j", "item_id", "s", "t", V.sums(F.col("s"), F.col("t")).alias("sums"))
    x = V.cosine_from_sums(F.col("sums.st"), F.col("sums.ss"), F.col("sums.tt")) if cfg.similarity == "cosine" else F.col("sums.st")
    return V.carry(summed, *summed.columns, x.alias("x"))


def example_loss(scored: DataFrame, cfg: StepConfig) -> DataFrame:
    """user_id, pos_id, loss: one row an example."""
    negs = F.collect_list(F.when(F.col("j") >= 0, F.col("x")))
    return scored.groupBy("user_id", "pos_id").agg(F.max(F.when(F.col("j") < 0, F.col("x"))).alias("xp"), negs.alias("xn")).select("user_id", "pos_id", V.ccl(F.col("xp"), F.col("xn"), cfg.mu, cfg.theta).alias("loss"))


def coefficients(scored: DataFrame, cfg: StepConfig) -> DataFrame:
    """Adds c: the loss's derivative by x; for metric, by the squared distance. Losses that compare a negative
    with its positive bring both into one window of their example."""
    if cfg.loss not in ("bpr", "metric"):
        return scored.withColumn("c", V.dloss_dx(cfg.loss, F.col("x"), F.col("j") < 0, cfg.negatives, cfg.mu, cfg.theta))
    value = F.col("x") if cfg.loss == "bpr" else F.col("sums.ss") + F.col("sums.tt") - 2 * F.col("sums.st")
    example = W.partitionBy("user_id", "pos_id")
    rows = scored.withColumn("_v", value).withColumn("_p", F.max(F.when(F.col("j") < 0, F.col("_v"))).over(example))
    if cfg.loss == "bpr":
        one = 1 / (1 + F.exp(F.col("_p") - F.col("_v"))) / cfg.negatives
    else:
        one = F.when(cfg.margin + F.col("_p") - F.col("_v") > 0, F.lit(-1.0 / cfg.negatives)).otherwise(F.lit(0.0))
    rows = rows.withColumn("_c", F.when(F.col("j") >= 0, one).otherwise(F.lit(0.0)))
    return rows.withColumn("c", F.when(F.col("j") < 0, -F.sum("_c").over(example)).otherwise(F.col("_c"))).drop("_v", "_p", "_c")


def gradients(scored: DataFrame, cfg: StepConfig) -> DataFrame:
    """side, id, g: a row a touched vector and example. Inactive negatives are dropped before any shuffle."""
    sums = F.col("sums") if cfg.reuse else V.sums(F.col("s"), F.col("t"))
    active = V.carry(coefficients(scored, cfg), "user_id", "item_id", "s", "t", "x", sums.alias("sums"), "c").where("c <> 0")
    ss, tt, s, t, x = F.col("sums.ss"), F.col("sums.tt"), F.col("s"), F.col("t"), F.col("x")
    if cfg.loss == "metric":
        two = F.lit(-2.0)
        gu, gi = V.combine(two, t, two, s), V.combine(two, s, two, t)
    elif cfg.similarity == "cosine":
        gu, gi = V.grad_cosine(s, t, x, ss, ss, tt), V.grad_cosine(t, s, x, tt, ss, tt)
    else:
        gu, gi = F.transform(t, lambda v: v.cast("double")), F.transform(s, lambda v: v.cast("double"))
    scale = lambda g: F.transform(g, lambda v: F.col("c") * v)
    both = F.array(F.struct(F.lit("user").alias("side"), F.col("user_id").alias("id"), scale(gu).alias("g")), F.struct(F.lit("item").alias("side"), F.col("item_id").alias("id"), scale(gi).alias("g")))
    return active.select(F.inline(both))


def combine_gradients(grads: DataFrame, dim: int) -> DataFrame:
    """side, id, g: element-wise sums with map-side partial sums, one column a dimension."""
    parts = grads.groupBy("side", "id").agg(*[F.sum(F.col("g")[d]).alias(f"_{d}") for d in range(dim)])
    return parts.select("side", "id", F.array(*[F.col(f"_{d}") for d in range(dim)]).alias("g"))


def apply_sparse(factors: DataFrame, grads: DataFrame, lr: float, l2: float = 0.0) -> DataFrame:
    """Touched rows change, all others pass as they are. factors: side, id, vec. l2 shrinks touched rows of both sides."""
    j = factors.join(grads, ["side", "id"], "left")
    return j.select("side", "id", F.when(F.col("g").isNull(), F.col("vec")).otherwise(V.combine(F.lit(1.0 - lr * l2), F.col("vec"), F.lit(lr), F.col("g"))).alias("vec"))


def apply_dense(factors: DataFrame, grads: DataFrame, lr: float, dim: int) -> DataFrame:
    """Every row is rewritten, with a zero gradient where there is none."""
    zero = F.array(*[F.lit(0.0)] * dim)
    j = factors.join(grads, ["side", "id"], "full")
    return j.select("side", "id", V.combine(F.lit(1.0), F.col("vec"), F.lit(lr), F.coalesce("g", zero)).alias("vec"))


def apply_coalesced(factors: DataFrame, grads: DataFrame, lr: float, dim: int) -> DataFrame:
    """The slow baseline: gradients stay in long form, are sorted, and are merged at the end."""
    long = grads.select("side", "id", F.posexplode("g")).groupBy("side", "id", "pos").agg(F.sum("col").alias("v")).orderBy("side", "id", "pos")
    merged = long.groupBy("side", "id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "v"))), lambda e: e["v"]).alias("g"))
    return apply_sparse(factors, merged, lr)


def step(pairs: DataFrame, negatives: DataFrame, factors: DataFrame, cfg: StepConfig, update: str = "sparse") -> DataFrame:
    """factors after one summed step over all examples. factors: side, id, vec (materialized)."""
    users, items = (factors.where(F.col("side") == s).select("id", "vec") for s in ("user", "item"))
    grads = gradients(forward(examples(pairs, negatives), users, items, cfg), cfg)
    if update == "coalesced":
        return apply_coalesced(factors, grads, cfg.lr, cfg.dim)
    summed = combine_gradients(grads, cfg.dim)
    return apply_sparse(factors, summed, cfg.lr, cfg.l2) if update == "sparse" else apply_dense(factors, summed, cfg.lr, cfg.dim)
