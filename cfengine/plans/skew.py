"""Joins on keys of which a few may hold a large part of all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .cuts import Cuts

#: Rows of one key that a task takes at most, on the side that is split.
SHARE = 1 << 14


def parted(rows: DataFrame, key: str, by: str, cuts: Cuts, share: int = SHARE) -> DataFrame:
    """rows with _parts, the number of parts their key is dealt into, and _part, the row's own by a hash of by."""
    sizes = cuts.cut(rows.groupBy(key).agg(F.ceil(F.count(F.lit(1)) / F.lit(share)).cast("int").alias("_parts")))
    joined = rows.join(sizes, key)
    return cuts.cut(joined.withColumn("_part", F.pmod(F.xxhash64(by), F.col("_parts")).cast("int")))


def split_join(left: DataFrame, right: DataFrame, key: str, by: str, cuts: Cuts, share: int = SHARE) -> DataFrame:
    """Inner join on key; rows of left are dealt into parts of about share, rows of right are copied to each."""
    dealt = parted(left, key, by, cuts, share)
    sizes = dealt.groupBy(key).agg(F.first("_parts").alias("_parts"))
    copies = right.join(cuts.cut(sizes), key).withColumn("_part", F.explode(F.sequence(F.lit(0), F.col("_parts") - 1))).drop("_parts")
    return dealt.drop("_parts").join(copies, [key, "_part"]).drop("_part")


def meetings(rows: DataFrame, own: str, on: str, cuts: Cuts, share: int = SHARE) -> DataFrame:
    """a, b: one row for each value of on that two values a < b of own share. A value of on with many rows is dealt
    into parts, and each pair of its parts is a key of its own."""
    dealt = parted(rows.select(own, on), on, own, cuts, share)
    every = F.sequence(F.lit(0), F.col("_parts") - 1)
    left = dealt.select(on, F.col(own).alias("a"), F.col("_part").alias("_l"), F.explode(every).alias("_r"))
    right = dealt.select(on, F.col(own).alias("b"), F.col("_part").alias("_r"), F.explode(every).alias("_l"))
    return left.join(right, [on, "_l", "_r"]).where("a < b").select("a", "b")
