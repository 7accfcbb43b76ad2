"""Reading feedback from files and catalog tables, and writing models and lists."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.mix import P, mix, mix_py
from .feedback import implicit_pairs

FORMATS = ("parquet", "orc", "json", "csv")


def read_text_pairs(spark: SparkSession, at: str, separator: str = "\t") -> DataFrame:
    """Implicit pairs from text lines of a user and an item; lines that are not two whole numbers are left out."""
    parts = F.split("value", separator, 2)
    rows = spark.read.text(at).select(parts.alias("p")).select(F.expr("try_cast(trim(p[0]) AS bigint)").alias("u"), F.expr("try_cast(trim(get(p, 1)) AS bigint)").alias("i"))
    return implicit_pairs(rows, "u", "i")


def rate_pairs(spark: SparkSession, rows_a_second: int, users: int, items: int, seed: int = 3) -> DataFrame:
    """A stream of drawn pairs with their times, for load tests."""
    source = spark.readStream.format("rate").option("rowsPerSecond", rows_a_second).load()
    return source.select((mix(seed, "value") % users).alias("user_id"), (mix(seed + 1, "value") % items).alias("item_id"), F.col("timestamp").alias("ts"))


class PlantedSource(DataSource):
    """spark.read.format('planted'): pairs with known communities, one partition a range of users.
    Options: users, items, blocks, inside, outside, seed, partitions. The rows are those of feedback.planted."""

    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return "user_id long, item_id long"

    def reader(self, schema) -> DataSourceReader:
        return PlantedReader({k: float(self.options.get(k, v)) for k, v in (("users", 1000), ("items", 500), ("blocks", 10), ("inside", 0.4), ("outside", 0.004), ("seed", 5), ("partitions", 4))})


class PlantedReader(DataSourceReader):
    def __init__(self, options: dict[str, float]):
        self.o = options

    def partitions(self):
        n, users = max(1, int(self.o["partitions"])), int(self.o["users"])
        return [InputPartition((users * k // n, users * (k + 1) // n)) for k in range(n)]

    def read(self, partition):
        lo, hi = partition.value
        items, blocks, seed = int(self.o["items"]), int(self.o["blocks"]), int(self.o["seed"])
        near, far = int(self.o["inside"] * P), int(self.o["outside"] * P)
        for u in range(lo, hi):
            for i in range(items):
                if mix_py(seed, u, i) < (near if u % blocks == i % blocks else far):
                    yield u, i


def read_pairs(spark: SparkSession, at: str, user: str, item: str, ts: str | None = None, fmt: str = "parquet") -> DataFrame:
    """Implicit pairs from a path, or from a catalog table with fmt='table'. Text formats get a schema of
    just the named columns, so nothing is inferred; ids that are no numbers are an error."""
    if fmt == "table":
        rows = spark.table(at)
    elif fmt not in FORMATS:
        raise ValueError(f"format is table or one of {FORMATS}")
    elif fmt == "csv":
        rows = spark.read.option("header", True).option("enforceSchema", False).csv(at)
    elif fmt == "json":
        rows = spark.read.schema(", ".join(f"`{c}` {t}" for c, t in ((user, "long"), (item, "long"), (ts, "timestamp_ntz")) if c)).json(at)
    else:
        rows = spark.read.format(fmt).load(at)
    when = F.col(ts).cast("timestamp_ntz") if ts else None
    return implicit_pairs(rows, user, item, when)


def bucket_factors(factors: DataFrame, table: str, buckets: int) -> DataFrame:
    """factors (side, id, vec) as a catalog table bucketed and sorted by id: joins on id of two tables with
    as many buckets need no exchange of either."""
    factors.write.mode("overwrite").bucketBy(buckets, "id").sortBy("id").format("parquet").saveAsTable(table)
    return factors.sparkSession.table(table)


def write_lists(recs: DataFrame, path: str, fmt: str = "parquet") -> None:
    """user_id, rank, item_id, score; one directory, any of the file formats."""
    if fmt not in FORMATS:
        raise ValueError(f"format is one of {FORMATS}")
    w = recs.select("user_id", "rank", "item_id", "score").write.mode("overwrite")
    (w.option("header", True) if fmt == "csv" else w).format(fmt).save(path)
