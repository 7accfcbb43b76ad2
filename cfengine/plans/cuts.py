"""Snapshots in the folder that the cluster shares; lineage ends there."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from .files import remove, shared_dir


class Cuts:
    """Tables of one run. Those that follow() replaces are deleted; close() deletes the rest."""

    def __init__(self, spark: SparkSession):
        self.spark, self.base, self.n = spark, f"{shared_dir(spark)}/snap-{uuid.uuid4().hex}", 0
        self.last: str | None = None

    def cut(self, df: DataFrame, by: str | None = None) -> DataFrame:
        """df, written and read again; by: a column whose values get folders of their own."""
        self.n += 1
        path = f"{self.base}/{self.n}"
        (df.write.partitionBy(by) if by else df.write).parquet(path)
        self.spark._jvm.System.gc()  # shuffles behind a cut are deleted only when the driver forgets their plans
        out = self.spark.read.schema(df.schema).parquet(path)
        out._cut_path = path
        return out

    def follow(self, df: DataFrame, made: DataFrame) -> DataFrame:
        """df, read from the table made; the table that was made in this way before is deleted."""
        if self.last:
            remove(self.spark, self.last)
        self.last = made._cut_path
        return df

    def drop(self, *made: DataFrame) -> None:
        """Deletes tables that nothing reads any more."""
        for df in made:
            remove(self.spark, df._cut_path)

    def close(self) -> None:
        remove(self.spark, self.base)
