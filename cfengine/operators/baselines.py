"""Neighbour, probabilistic, content, popularity and library baselines."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.mix import mix
from ..functions.vectors import init_vector
from ..plans.cuts import Cuts
from ..plans.skew import SHARE, meetings, split_join
from ..shipping import ship
from ..sources.feedback import dense_index


def _common(pairs: DataFrame, own: str, other: str) -> DataFrame:
    """a, b, c: how many columns two different rows share, in both orders. Half of it is counted."""
    met = meetings(pairs, own, other, Cuts(pairs.sparkSession)).groupBy("a", "b").agg(F.count(F.lit(1)).alias("c"))
    return met.select(F.inline(F.array(F.struct("a", "b", "c"), F.struct(F.col("b").alias("a"), F.col("a").alias("b"), "c"))))


#: Meetings that a block of rows counts in memory, and rows of lists that are sent to blocks at a time.
BLOCK_MEETINGS, SENT = 4_000_000, 60_000_000
#: By how much similarities before rounding to nine digits may differ and still change places.
NEAR = 2e-9


def _nearest(own: pa.Table, lists: pa.Table, k: int, sim: str) -> pa.Table:
    """a, b, c, na, nb: of every row a of a block all that can be among its k nearest after rounding. own: a, o, n.
    lists: o, and b and n of its members. Meetings are counted by sorting, and nothing is kept of a pair that is too far."""
    o_of, at = np.unique(lists["o"].to_numpy(), return_inverse=True)
    order = np.argsort(at, kind="stable")
    members, numbers = (lists[c].combine_chunks() for c in ("b", "n"))
    first, size = members.offsets.to_numpy()[:-1][order].astype(np.int64), members.value_lengths().to_numpy()[order].astype(np.int64)
    starts = np.searchsorted(at[order], np.arange(len(o_of) + 1))  # a value of o may have its list in several parts
    b_ids, b_of = np.unique(members.values.to_numpy(), return_inverse=True)
    nb_of = np.zeros(len(b_ids), np.int64)
    nb_of[b_of] = numbers.values.to_numpy()
    a_ids, a_of = np.unique(own["a"].to_numpy(), return_inverse=True)
    na_of = np.zeros(len(a_ids), np.int64)
    na_of[a_of] = own["n"].to_numpy()
    o = np.searchsorted(o_of, own["o"].to_numpy())
    reps = starts[o + 1] - starts[o]
    part = np.repeat(starts[o] - (np.cumsum(reps) - reps), reps) + np.arange(int(reps.sum()))
    lens, a_rows = size[part], np.repeat(a_of, reps)
    place = np.repeat(first[part] - (np.cumsum(lens) - lens), lens) + np.arange(int(lens.sum()))
    keys = np.repeat(a_rows, lens) * len(b_ids) + b_of[place]
    del place
    keys.sort()
    new = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    c = np.diff(np.append(new, len(keys)))
    a, b = np.divmod(keys[new], len(b_ids))
    other = a_ids[a] != b_ids[b]
    a, b, c = a[other], b[other], c[other]
    na, nb = na_of[a], nb_of[b]
    value = c / (np.sqrt((na * nb).astype(float)) if sim == "cosine" else na + nb - c)
    # a row's own stretch of places, and in it the k-th value
    ends = np.searchsorted(a, np.arange(len(a_ids) + 1))
    ranked = np.sort(a * 4.0 - value)
    edge = ranked[np.minimum(ends[:-1] + k, ends[1:])[a] - 1]
    some = np.flatnonzero(a * 4.0 - value <= edge + 1e-6)
    a, b, c, na, nb, value = (v[some] for v in (a, b, c, na, nb, value))
    order = np.lexsort((b, -value, a))
    a, b, c, na, nb, value = (v[order] for v in (a, b, c, na, nb, value))
    ends = np.searchsorted(a, np.arange(len(a_ids) + 1))
    kth = value[np.minimum(ends[:-1] + k, ends[1:])[a] - 1]
    run = np.flatnonzero(np.concatenate(([True], (a[1:] != a[:-1]) | (value[1:] != value[:-1])))) if len(a) else np.zeros(0, int)
    tie = np.arange(len(a)) - np.repeat(run, np.diff(np.append(run, len(a))))  # equal values keep the order of b
    keep = (value >= kth - NEAR) & (tie < k)
    return pa.table({"a": a_ids[a[keep]], "b": b_ids[b[keep]], "c": c[keep], "na": na[keep], "nb": nb[keep]})


def _knn(pairs: DataFrame, own: str, other: str, k: int, sim: str) -> DataFrame:
    """sim: cosine of the 0/1 rows of own, common / sqrt(n n'), or jaccard, common / (n + n' - common). Rows are dealt into
    ranges of about as many meetings; a range gets the lists of what its rows have, and counts in memory. So no meeting is
    shuffled, and the copied lists go out in turns. A table is deleted as soon as the next one is made from it."""
    spark = ship(pairs.sparkSession)
    cuts = Cuts(spark)
    rows = pairs.select(F.col(own).alias("a"), F.col(other).alias("o"))
    first = cuts.cut(rows)
    counted = cuts.cut(first.join(first.groupBy("o").agg(F.count(F.lit(1)).alias("no")), "o"))
    cuts.drop(first)
    sized = counted.groupBy("a").agg(F.count(F.lit(1)).alias("n"), F.sum("no").alias("w"))
    placed = cuts.cut(sized.repartitionByRange("a").sortWithinPartitions("a").withColumn("_p", F.spark_partition_id()))
    before = F.sum("w").over(W.partitionBy("_p").orderBy("a").rowsBetween(W.unboundedPreceding, W.currentRow))
    blocks = cuts.cut(placed.select("a", "n", (F.shiftleft(F.col("_p").cast("long"), 40) + F.floor(before / BLOCK_MEETINGS)).alias("block")))
    rows = cuts.cut(counted.join(blocks, "a"))
    cuts.drop(counted, placed, blocks)
    part = F.pmod(F.xxhash64("a"), F.ceil(F.col("no") / F.lit(SHARE)).cast("int"))
    members = rows.groupBy("o", part.alias("part")).agg(F.collect_list(F.struct("a", "n")).alias("m"))
    lists = cuts.cut(members.select("o", F.col("m.a").alias("b"), F.col("m.n").alias("n")))  # half as wide as lists of structs
    asks = cuts.cut(rows.select("block", "o", "no").distinct())
    rounds = -(-(asks.agg(F.sum("no")).first()[0] or 0) // SENT) or 1
    turn = F.pmod(F.xxhash64("block"), F.lit(rounds))

    def cell(left: pa.Table, right: pa.Table) -> pa.Table:
        if not len(left) or not len(right):
            return pa.table({n: pa.array([], pa.int64()) for n in ("a", "b", "c", "na", "nb")})
        return _nearest(left, right, k, sim)

    found = []
    for r in range(rounds):
        left = rows.where(turn == r).select("block", "a", "o", "n")
        right = asks.where(turn == r).select("block", "o").join(lists, "o").select("block", "o", "b", "n")
        found.append(cuts.cut(left.groupBy("block").cogroup(right.groupBy("block")).applyInArrow(cell, "a long, b long, c long, na long, nb long")))
    cuts.drop(rows, lists, asks)
    j = reduce(DataFrame.union, found)
    under = F.sqrt((F.col("na") * F.col("nb")).cast("double")) if sim == "cosine" else F.col("na") + F.col("nb") - F.col("c")
    near = j.select("a", "b", F.round(F.col("c") / under, 9).alias("sim"))
    rank = F.row_number().over(W.partitionBy("a").orderBy(F.desc("sim"), "b"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k)


def user_knn(pairs: DataFrame, k: int = 10, sim: str = "cosine") -> DataFrame:
    return _knn(pairs, "user_id", "item_id", k, sim)


def item_knn(pairs: DataFrame, k: int = 10, sim: str = "cosine") -> DataFrame:
    return _knn(pairs, "item_id", "user_id", k, sim)


#: Votes that are shuffled at a time.
VOTES = 60_000_000


def _voted(votes: Callable[[F.Column], DataFrame], many: DataFrame, pairs: DataFrame, k: int, cuts: Cuts) -> DataFrame:
    """votes: of the users that a condition on user_id takes. many: n, numbers that sum to all votes. Users take turns, so that
    only some of the votes are on disk at a time."""
    rounds = -(-(many.agg(F.sum("n")).first()[0] or 0) // VOTES) or 1
    rank = F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("score"), "item_id"))
    found = []
    for r in range(rounds):
        turn = F.pmod(F.xxhash64("user_id"), F.lit(rounds)) == r
        scored = votes(turn).groupBy("user_id", "item_id").agg(F.round(F.sum("sim"), 9).alias("score")).join(pairs.where(turn).select("user_id", "item_id"), ["user_id", "item_id"], "left_anti")
        top = scored.withColumn("rank", rank).where(F.col("rank") <= k)
        found.append(top if rounds == 1 else cuts.cut(top))
    return reduce(DataFrame.union, found)


def user_knn_votes(pairs: DataFrame, neighbours: DataFrame, k: int = 20) -> DataFrame:
    """user_id, item_id, score, rank: unseen items by the summed similarity of the neighbours that have them."""
    cuts = Cuts(pairs.sparkSession)
    pairs = cuts.cut(pairs.select("user_id", "item_id"))
    near = neighbours.select(F.col("a").alias("user_id"), F.col("b").alias("_b"), "sim")
    has = pairs.select(F.col("user_id").alias("_b"), "item_id")
    many = near.groupBy("_b").agg(F.count(F.lit(1)).alias("m")).join(has.groupBy("_b").agg(F.count(F.lit(1)).alias("d")), "_b").select((F.col("m") * F.col("d")).alias("n"))
    return _voted(lambda turn: near.where(turn).join(has, "_b"), many, pairs, k, cuts)


def item_knn_votes(pairs: DataFrame, neighbours: DataFrame, k: int = 20) -> DataFrame:
    """The same from item neighbours: an item collects its similarity to each of the user's items that has it for a neighbour."""
    cuts = Cuts(pairs.sparkSession)
    pairs = cuts.cut(pairs.select("user_id", "item_id"))
    near = neighbours.select(F.col("a").alias("_a"), F.col("b").alias("item_id"), "sim")
    own = pairs.select("user_id", F.col("item_id").alias("_a"))
    many = own.groupBy("_a").agg(F.count(F.lit(1)).alias("d")).join(near.groupBy("_a").agg(F.count(F.lit(1)).alias("m")), "_a").select((F.col("m") * F.col("d")).alias("n"))
    return _voted(lambda turn: split_join(own.where(turn), near, "_a", "user_id", cuts), many, pairs, k, cuts)


def item_cond_prob(pairs: DataFrame, k: int = 10) -> DataFrame:
    """given, item, p: share of the given item's users who also have the item."""
    n = pairs.groupBy("item_id").agg(F.count(F.lit(1)).alias("n"))
    c = _common(pairs, "item_id", "user_id").select(F.col("a").alias("given"), F.col("b").alias("item"), "c")
    prob = c.join(n.withColumnRenamed("item_id", "given"), "given").select("given", "item", F.round(F.col("c") / F.col("n"), 9).alias("p"))
    rank = F.row_number().over(W.partitionBy("given").orderBy(F.desc("p"), "item"))
    return prob.withColumn("rank", rank).where(F.col("rank") <= k)


def row_sums(pairs: DataFrame, vectors: DataFrame, side: str, dim: int) -> DataFrame:
    """id, vec of every row of side: the sum of the other side's vectors (id, vec) over its pairs, that is
    the 0/1 matrix (or its transpose) times vectors. Sums have map-side partial sums."""
    other = "item_id" if side == "user_id" else "user_id"
    joined = pairs.select(F.col(side).alias("_row"), F.col(other).alias("id")).join(vectors, "id")
    sums = joined.groupBy("_row").agg(*[F.sum(F.col("vec")[d]).alias(f"_{d}") for d in range(dim)])
    return sums.select(F.col("_row").alias("id"), F.array(*[F.col(f"_{d}") for d in range(dim)]).alias("vec"))


def _gram(rows: DataFrame, dim: int) -> np.ndarray:
    """Sum of v v^T over all rows: dim x dim numbers."""
    cells = [(a, b) for a in range(dim) for b in range(a, dim)]
    r = rows.agg(*[F.sum(F.col("vec")[a] * F.col("vec")[b]).alias(f"_{a}_{b}") for a, b in cells]).first()
    g = np.zeros((dim, dim))
    for a, b in cells:
        g[a, b] = g[b, a] = r[f"_{a}_{b}"] or 0.0
    return g


def _times(rows: DataFrame, m: np.ndarray) -> DataFrame:
    """Each row times a small matrix."""
    columns = [F.aggregate(F.zip_with("vec", F.array(*[F.lit(float(v)) for v in m[:, k]]), lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x) for k in range(m.shape[1])]
    return rows.select("id", F.array(*columns).alias("vec"))


def truncated_factors(pairs: DataFrame, rank: int = 8, rounds: int = 8, seed: int = 1) -> tuple[DataFrame, DataFrame, np.ndarray]:
    """(users, items, singular values) of the best rank-rank product for the 0/1 matrix, by subspace iteration:
    users x items gives the prediction. Each round is two sums over the pairs; only rank x rank numbers reach the driver."""
    cuts = Cuts(pairs.sparkSession)
    items = cuts.cut(pairs.select(F.col("item_id").alias("id")).distinct().withColumn("vec", init_vector(seed, "id", rank, "uniform", 1.0)))
    for _ in range(rounds):
        users = cuts.cut(row_sums(pairs, items, "user_id", rank))
        items = cuts.cut(row_sums(pairs, users, "item_id", rank))
        values, vectors = np.linalg.eigh(_gram(items, rank))
        items = cuts.cut(_times(items, vectors[:, ::-1] / np.sqrt(np.maximum(values[::-1], 1e-300))))
    users = cuts.cut(row_sums(pairs, items, "user_id", rank))
    values, vectors = np.linalg.eigh(_gram(users, rank))
    turn = vectors[:, ::-1]
    return cuts.cut(_times(users, turn)), cuts.cut(_times(items, turn)), np.sqrt(np.maximum(values[::-1], 0.0))


def content_profile(pairs: DataFrame, attrs: DataFrame) -> DataFrame:
    """user_id, attr, share: what part of a user's items has an attribute. attrs: item_id, attr."""
    c = pairs.join(attrs, "item_id").groupBy("user_id", "attr").agg(F.count(F.lit(1)).alias("c"))
    total = pairs.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    return c.join(total, "user_id").select("user_id", "attr", F.round(F.col("c") / F.col("n"), 6).alias("share"))


def content_recs(pairs: DataFrame, attrs: DataFrame, k: int = 20) -> DataFrame:
    """Unseen items by their attributes' share in the user's items. Where no item has two attributes a user meets, of each
    attribute, only the first k items he has not seen, and no attribute below those whose unseen items make k already."""
    cuts = Cuts(pairs.sparkSession)
    attrs = cuts.cut(attrs.where("attr is not null and item_id is not null"))
    pairs = cuts.cut(pairs.select("user_id", "item_id"))
    profile = content_profile(pairs, attrs)
    if attrs.groupBy("item_id").count().where("count > 1").isEmpty():
        scored = _first_of_attributes(pairs, attrs, profile, k, cuts)
    else:
        met = split_join(profile, attrs, "attr", "user_id", cuts)
        scored = met.groupBy("user_id", "item_id").agg(F.round(F.sum("share"), 6).alias("score"))
    scored = scored.join(pairs, ["user_id", "item_id"], "left_anti")
    rank = F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("score"), "item_id"))
    return scored.withColumn("rank", rank).where(F.col("rank") <= k)


def _first_of_attributes(pairs: DataFrame, attrs: DataFrame, profile: DataFrame, k: int, cuts: Cuts) -> DataFrame:
    """user_id, item_id, score: a user who has d items of an attribute finds k unseen ones among its first k + d."""
    placed = cuts.cut(dense_index(attrs, "attr", "item_id"))
    sizes = cuts.cut(placed.groupBy("attr").agg(F.min("idx").alias("first"), F.count(F.lit(1)).alias("size")))
    seen = pairs.join(attrs, "item_id").groupBy("user_id", "attr").agg(F.count(F.lit(1)).alias("d"))
    known = profile.join(seen, ["user_id", "attr"]).join(sizes, "attr")
    # unseen items of all attributes with a larger share
    above = F.sum(F.col("size") - F.col("d")).over(W.partitionBy("user_id").orderBy(F.desc("share")).rangeBetween(W.unboundedPreceding, W.currentRow))
    level = F.sum(F.col("size") - F.col("d")).over(W.partitionBy("user_id", "share"))
    kept = known.withColumn("_above", above - level).where(F.col("_above") < k)
    last = F.col("first") + F.least(F.col("size"), F.col("d") + k) - 1
    cand = kept.select("user_id", F.round("share", 6).alias("score"), F.explode(F.sequence(F.col("first"), last)).alias("idx"))
    return cand.join(placed.select("idx", "item_id"), "idx").select("user_id", "item_id", "score")


def popularity(pairs: DataFrame, k: int = 100) -> DataFrame:
    return pairs.groupBy("item_id").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "item_id").limit(k)


def popularity_recs(pairs: DataFrame, k: int = 20) -> DataFrame:
    """The most popular unseen items. A user that has seen d items finds k unseen ones among the k + d most
    popular, so it meets only these: rows grow with pairs, not with users times items."""
    ranked = dense_index(pairs.groupBy("item_id").agg(F.count(F.lit(1)).alias("n")), F.desc("n"), F.col("item_id"))
    seen = pairs.groupBy("user_id").agg(F.count(F.lit(1)).alias("d"))
    cand = seen.select("user_id", F.explode(F.sequence(F.lit(0).cast("long"), F.col("d") + (k - 1))).alias("idx")).join(ranked, "idx")
    cand = cand.join(pairs.select("user_id", "item_id"), ["user_id", "item_id"], "left_anti")
    rank = F.row_number().over(W.partitionBy("user_id").orderBy("idx"))
    return cand.withColumn("rank", rank).where(F.col("rank") <= k).select("user_id", "rank", "item_id")


def random_recs(users: DataFrame, items: DataFrame, k: int = 20, seed: int = 17) -> DataFrame:
    """users: id. items: id, idx."""
    n = items.count()
    drawn = users.select(F.col("id").alias("user_id"), F.explode(F.sequence(F.lit(1), F.lit(k))).alias("rank"))
    return drawn.withColumn("idx", mix(seed, "user_id", "rank") % n).join(items, "idx").select("user_id", "rank", F.col("id").alias("item_id"))


def als_baseline(pairs: DataFrame, rank: int = 8, iterations: int = 3, seed: int = 1):
    """Implicit ALS of the ML library; ids have to fit an int."""
    from pyspark.ml.recommendation import ALS

    rows = pairs.select(F.col("user_id").cast("int").alias("user"), F.col("item_id").cast("int").alias("item"), F.lit(1.0).alias("rating"))
    return ALS(rank=rank, maxIter=iterations, implicitPrefs=True, seed=seed, userCol="user", itemCol="item", ratingCol="rating").fit(rows)
