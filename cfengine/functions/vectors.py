"""Similarities, losses and gradients of two rows as column expressions.

The three sums ss, tt and st are computed once in the forward pass and carried as a struct;
gradients read the struct. carry() puts a generator between the passes, since the optimizer
would otherwise copy the sums into every later use.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    """Sum of products in double; vectors of unequal length or with a null give null."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def sq_norm(a: Column) -> Column:
    return dot(a, a)


def sums(s: Column, t: Column) -> Column:
    return F.struct(sq_norm(s).alias("ss"), sq_norm(t).alias("tt"), dot(s, t).alias("st"))


def cosine_from_sums(st: Column, ss: Column, tt: Column) -> Column:
    """0 if either norm is 0."""
    return F.coalesce(F.try_divide(st, F.sqrt(ss * tt)), F.lit(0.0))


def cosine(a: Column, b: Column) -> Column:
    return cosine_from_sums(dot(a, b), sq_norm(a), sq_norm(b))


def carry(df: DataFrame, *exprs: Column) -> DataFrame:
    """select() whose results later projections read and do not recompute."""
    return df.select(F.inline(F.array(F.struct(*exprs))))


def normalize_rows(df: DataFrame, vec: str = "vec") -> DataFrame:
    """The dense baseline's normalization: the inverse norm of every row (0 for a zero row) and the rows
    times it, both written out as columns of their own."""
    inverse = F.coalesce(F.try_divide(F.lit(1.0), F.sqrt(sq_norm(F.col(vec)))), F.lit(0.0))
    rows = carry(df, *df.columns, inverse.alias("inverse_norm"))
    return rows.withColumn("unit", F.transform(vec, lambda v: v.cast("double") * F.col("inverse_norm")))


def combine(a: Column, x: Column, b: Column, y: Column) -> Column:
    """a * x - b * y for vectors x, y."""
    return F.zip_with(x, y, lambda p, q: a * p.cast("double") - b * q.cast("double"))


def grad_cosine(own: Column, other: Column, x: Column, own_sq: Column, ss: Column, tt: Column) -> Column:
    """Gradient of the cosine with respect to own: other / sqrt(ss tt) - (x / own_sq) own; zero for a zero row."""
    return combine(F.coalesce(F.try_divide(F.lit(1.0), F.sqrt(ss * tt)), F.lit(0.0)), other, F.coalesce(F.try_divide(x, own_sq), F.lit(0.0)), own)


def ccl(x_pos: Column, x_negs: Column, mu: float, theta: float) -> Column:
    hinge = F.aggregate(x_negs, F.lit(0.0), lambda a, x: a + F.greatest(F.lit(0.0), x - theta))
    return (1 - x_pos) + F.coalesce(F.try_divide(F.lit(float(mu)) * hinge, F.size(x_negs)), F.lit(0.0))


def mse(x: Column, y: Column) -> Column:
    return (y - x) * (y - x)


def _softplus(z: Column) -> Column:
    return F.greatest(z, F.lit(0.0)) + F.log1p(F.exp(-F.abs(z)))


def bce(x: Column, y: Column) -> Column:
    return _softplus(x) - y * x


def bpr(x_pos: Column, x_neg: Column) -> Column:
    return _softplus(x_neg - x_pos)


def metric_hinge(d_pos: Column, d_neg: Column, margin: float) -> Column:
    """Squared distances; d = ss + tt - 2 st from the same three sums."""
    return F.greatest(F.lit(0.0), F.lit(margin) + d_pos - d_neg)


def dloss_dx(kind: str, x: Column, positive: Column, n: int, mu: float = 1.0, theta: float = 0.0) -> Column:
    """Derivative of a loss with respect to one similarity. kind: ccl, mse or bce."""
    if kind == "ccl":
        return F.when(positive, F.lit(-1.0)).when(x > theta, F.lit(mu / n)).otherwise(F.lit(0.0))
    y = F.when(positive, F.lit(1.0)).otherwise(F.lit(0.0))
    if kind == "mse":
        return 2 * (x - y)
    if kind == "bce":
        return 1 / (1 + F.exp(-x)) - y
    raise ValueError(kind)


def init_vector(seed: int, ident, dim: int, scheme: str = "uniform", scale: float = 0.1, fan_in: int = 0) -> Column:
    """A row drawn from keys alone. uniform: +-scale; normal: Irwin-Hall of 12 times scale;
    xavier_uniform, xavier_normal: by fan_in + dim."""
    from .mix import unit

    ident = F.col(ident) if isinstance(ident, str) else ident
    if scheme.startswith("xavier"):
        scale = (6.0 if scheme == "xavier_uniform" else 2.0) ** 0.5 / (fan_in + dim) ** 0.5
    if scheme in ("uniform", "xavier_uniform"):
        one = lambda d: (2 * unit(seed, ident, d) - 1) * scale
    else:
        one = lambda d: (F.aggregate(F.sequence(F.lit(0), F.lit(11)), F.lit(0.0), lambda a, k: a + unit(seed, ident, d, k)) - 6) * scale
    return F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), one)
