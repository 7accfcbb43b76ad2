"""Files of the shared folder, through the file system that Spark itself uses."""

from __future__ import annotations

import tempfile

from pyspark.sql import SparkSession


def _path(spark: SparkSession, at: str):
    path = spark._jvm.org.apache.hadoop.fs.Path(at)
    return path.getFileSystem(spark._jsc.hadoopConfiguration()), path


def exists(spark: SparkSession, at: str) -> bool:
    fs, path = _path(spark, at)
    return fs.exists(path)


def listed(spark: SparkSession, at: str) -> list[str]:
    """Names in a folder; none if there is no such folder."""
    fs, path = _path(spark, at)
    return sorted(s.getPath().getName() for s in fs.listStatus(path)) if fs.exists(path) else []


def remove(spark: SparkSession, at: str) -> None:
    fs, path = _path(spark, at)
    fs.delete(path, True)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Where the session names none, a local one will do only
    for a local master: elsewhere each executor would write to its own disk."""
    sc = spark.sparkContext
    at = sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not at:
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir has to name a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="cfengine-"))
        at = sc.getCheckpointDir()
    return at.rstrip("/")
