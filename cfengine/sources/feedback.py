"""Implicit feedback from tables: pairs of a user and an item, distinct, no null."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.mix import P, mix
from ..plans.cuts import Cuts


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def implicit_pairs(df: DataFrame, user: str | Column, item: str | Column, ts: str | Column | None = None) -> DataFrame:
    """user_id, item_id (, ts: the latest): one partial and one final aggregation."""
    col = lambda c: F.col(c) if isinstance(c, str) else c
    rows = df.select(col(user).cast("long").alias("user_id"), col(item).cast("long").alias("item_id"), *([col(ts).alias("ts")] if ts is not None else []))
    rows = rows.where("user_id is not null and item_id is not null")
    return rows.distinct() if ts is None else rows.groupBy("user_id", "item_id").agg(F.max("ts").alias("ts"))


def from_explicit(df: DataFrame, user: str, item: str, rating: str, min_rating: float | None = None, keep: list | None = None) -> DataFrame:
    """Pairs whose rating reaches a threshold, or is one of keep."""
    cond = F.lit(True)
    if min_rating is not None:
        cond = cond & (F.col(rating) >= min_rating)
    if keep is not None:
        cond = cond & F.col(rating).isin(keep)
    return implicit_pairs(df.where(cond), user, item)


def from_events(df: DataFrame, types: tuple[str, ...] = ("view", "click", "purchase"), weights: dict[str, float] | None = None) -> DataFrame:
    """Pairs of the chosen signals with their latest time; with weights also weight, the sum over a pair's events
    of what their type counts (a type without one counts 1)."""
    rows = df.where(F.col("event_type").isin(*types))
    pairs = implicit_pairs(rows, "user_id", F.get_json_object("props", "$.k"), "ts")
    if weights is None:
        return pairs
    one = F.lit(1.0)
    for name, value in weights.items():
        one = F.when(F.col("event_type") == name, F.lit(float(value))).otherwise(one)
    sums = rows.select(F.col("user_id").cast("long").alias("user_id"), F.get_json_object("props", "$.k").cast("long").alias("item_id"), one.alias("w"))
    return pairs.join(sums.groupBy("user_id", "item_id").agg(F.sum("w").alias("weight")), ["user_id", "item_id"])


def terms(df: DataFrame, ident: str, text: str = "text") -> DataFrame:
    """user_id, term: distinct words of three or more ASCII letters, lower-cased."""
    words = F.regexp_extract_all(F.lower(text), F.lit("[a-z]{3,}"), F.lit(0))
    return df.select(F.col(ident).cast("long").alias("user_id"), F.explode(F.array_distinct(words)).alias("term")).distinct()


def term_pairs(df: DataFrame, ident: str, min_df: int, max_share: float) -> DataFrame:
    """user_id, item_id, term of terms that occur in at least min_df rows and in at most max_share of all rows.
    item_id is a hash of the term, checked nowhere for collisions but 63 bits wide."""
    t = terms(df, ident)
    most = df.count() * max_share
    common = t.groupBy("term").agg(F.count(F.lit(1)).alias("df")).where((F.col("df") >= min_df) & (F.col("df") <= F.lit(most)))
    return t.join(common, "term", "left_semi").select("user_id", F.shiftrightunsigned(F.xxhash64("term"), 1).alias("item_id"), "term")


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity")
    return lines.join(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))


def workload(spark: SparkSession, sf_dir: str, name: str, **opts) -> DataFrame:
    """Orders, suppliers, events, docterms, talkterms, brands."""
    if name == "orders":
        return implicit_pairs(purchases(spark, sf_dir), "o_custkey", "l_partkey", "o_orderdate")
    if name == "suppliers":
        return implicit_pairs(purchases(spark, sf_dir), "o_custkey", "l_suppkey", "o_orderdate")
    if name == "events":
        return from_events(table(spark, sf_dir, "events"), **opts)
    if name == "docterms":
        return term_pairs(table(spark, sf_dir, "documents"), "doc_id", **({"min_df": 5, "max_share": 0.1} | opts))
    if name == "talkterms":
        return term_pairs(table(spark, sf_dir, "conversations"), "conv_id", **({"min_df": 1, "max_share": 1.0} | opts))
    if name == "brands":
        part = table(spark, sf_dir, "part").select("p_partkey", F.regexp_extract("p_brand", "([0-9]+)$", 1).cast("long").alias("brand"))
        return implicit_pairs(purchases(spark, sf_dir).join(part, F.col("l_partkey") == F.col("p_partkey")), "o_custkey", "brand")
    raise ValueError(name)


def planted(spark: SparkSession, users: int = 1000, items: int = 500, blocks: int = 10, inside: float = 0.4, outside: float = 0.004, seed: int = 5) -> DataFrame:
    """Pairs with known communities: a user likes items of its own block."""
    cell = spark.range(users * items).select((F.col("id") / items).cast("long").alias("user_id"), (F.col("id") % items).alias("item_id"))
    return planted_among(cell, blocks, inside, outside, seed)


def planted_among(pairs: DataFrame, blocks: int = 10, inside: float = 0.4, outside: float = 0.004, seed: int = 5) -> DataFrame:
    """Those of pairs that planted communities keep."""
    same = F.col("user_id") % blocks == F.col("item_id") % blocks
    return pairs.where(mix(seed, "user_id", "item_id") < F.when(same, F.lit(int(inside * P))).otherwise(F.lit(int(outside * P))))


def dense_index(rows: DataFrame, *order: str | Column) -> DataFrame:
    """rows with idx, dense from 0 in the given total order. Rows are range-sorted and written once, so that
    a row's partition and place in it are fixed; then only counts of partitions are ordered as a whole."""
    placed = rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id())
    placed = Cuts(rows.sparkSession).cut(placed)
    part = F.shiftright("_at", 33)
    sizes = placed.groupBy(part.alias("_p")).agg(F.count(F.lit(1)).alias("_n"))
    base = sizes.select("_p", F.coalesce(F.sum("_n").over(W.orderBy("_p").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_base"))
    kept = placed.withColumn("_p", part).join(F.broadcast(base), "_p")  # a row a partition
    return kept.withColumn("idx", (F.col("_base") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))).cast("long")).drop("_p", "_at", "_base")


def index_ids(pairs: DataFrame, column: str) -> DataFrame:
    """id, idx: dense from 0 in id order."""
    return dense_index(pairs.select(F.col(column).alias("id")).distinct(), "id")


def kcore(pairs: DataFrame, min_user: int, min_item: int, max_rounds: int | None = None) -> DataFrame:
    """Drops rare users, then rare items, until nothing changes or max_rounds are over. Every step reads a
    written table, so the plan does not grow with the rounds."""
    cuts = Cuts(pairs.sparkSession)
    pairs = cuts.follow(*[cuts.cut(pairs)] * 2)
    size, done = pairs.count(), 0
    while max_rounds is None or done < max_rounds:
        for side, least in (("user_id", min_user), ("item_id", min_item)):
            keep = pairs.groupBy(side).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= least)
            pairs = cuts.follow(*[cuts.cut(pairs.join(keep, side, "left_semi"))] * 2)
        before, size, done = size, pairs.count(), done + 1
        if size == before:
            break
    return pairs


def split_holdout(pairs: DataFrame, mode: str = "hash", frac: float = 0.2, seed: int = 3) -> tuple[DataFrame, DataFrame]:
    """(train, test). hash: by keys alone; last: each user's latest item (needs ts); random: Bernoulli."""
    if mode == "hash":
        out = mix(seed, "user_id", "item_id") % 1000 < int(frac * 1000)
        return pairs.where(~out), pairs.where(out)
    if mode == "last":
        n = F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("ts"), F.desc("item_id")))
        ranked = pairs.withColumn("_n", n)
        return ranked.where("_n > 1").drop("_n"), ranked.where("_n = 1").drop("_n")
    if mode == "random":
        train, test = pairs.randomSplit([1 - frac, frac], seed)
        return train, test
    raise ValueError(mode)


def stratified(rows: DataFrame, column: str, shares: dict, keys: list[str], seed: int = 3) -> DataFrame:
    """A share of the rows of each stratum, drawn from keys alone; strata without a share give none."""
    share = F.lit(0)
    for value, part in shares.items():
        share = F.when(F.col(column) == value, F.lit(int(part * 1_000_000))).otherwise(share)
    return rows.where(mix(seed, *keys) % 1_000_000 < share)


def user_history(pairs: DataFrame, max_len: int = 100) -> DataFrame:
    """user_id, hist: items newest first, at most max_len; the cut comes before items are gathered."""
    n = F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("ts"), F.desc("item_id")))
    return pairs.withColumn("_n", n).where(F.col("_n") <= max_len).groupBy("user_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("_n", "item_id"))), lambda x: x["item_id"]).alias("hist"))


def profile(pairs: DataFrame, at: tuple[float, ...] = (0.5, 0.9, 0.99)) -> DataFrame:
    """users, items, pairs, density, and for each side quantiles of the degrees and skew, the largest over the mean.
    Quantiles are taken over the histogram of degrees, so no side is gathered."""
    out = pairs.agg(F.countDistinct("user_id").alias("users"), F.countDistinct("item_id").alias("items"), F.count(F.lit(1)).alias("pairs")).withColumn("density", F.round(F.col("pairs") / F.col("users") / F.col("items"), 6))
    for side in ("user_id", "item_id"):
        h, name = degree_hist(pairs, side), side.removesuffix("_id")
        q = [F.percentile("degree", F.lit(p), F.col("n")).alias(f"{name}_p{round(100 * p)}") for p in at]
        skew = F.round(F.max("degree") * F.sum("n") / F.sum(F.col("degree") * F.col("n")), 6).alias(f"{name}_skew")
        out = out.join(h.agg(*q, skew), F.lit(True))
    return out


def degree_hist(pairs: DataFrame, side: str) -> DataFrame:
    return pairs.groupBy(side).agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("n"))


def as_sparse_vectors(pairs: DataFrame, side: str, width: int = 1 << 16) -> DataFrame:
    """side, part, members: the other side's ids of each row, sorted; a row with more than about width of them
    has several parts, dealt by a hash."""
    from ..plans.skew import parted

    other = "item_id" if side == "user_id" else "user_id"
    rows = parted(pairs.select(side, other).distinct(), side, other, Cuts(pairs.sparkSession), width)
    return rows.groupBy(side, F.col("_part").alias("part")).agg(F.array_sort(F.collect_list(other)).alias("members"))
