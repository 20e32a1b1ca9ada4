"""The shared folder: written tables that cut lineage and survive lost executors."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

#: Used only where the session names no spark.checkpoint.dir and runs on one machine.
LOCAL_SHARED = "file:///tmp/checkpoints/rangegraph"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, as the cluster names it; a cluster must name one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return (named or LOCAL_SHARED).rstrip("/")


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


def stash(df: DataFrame, tag: str) -> DataFrame:
    path = new_path(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _at(spark: SparkSession, path: str):
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p


def exists(spark: SparkSession, path: str) -> bool:
    fs, p = _at(spark, path)
    return fs.exists(p)


def drop_path(spark: SparkSession, path: str) -> None:
    fs, p = _at(spark, path)
    fs.delete(p, True)


class Steps:
    """Written versions of a table that is replaced again and again: each step is read, and the one before the last is deleted."""

    def __init__(self, spark: SparkSession, tag: str):
        self.spark, self.tag, self.paths = spark, tag, []

    def write(self, df: DataFrame) -> DataFrame:
        path = new_path(self.spark, self.tag)
        df.write.parquet(path)
        self.paths.append(path)
        if len(self.paths) > 2:  # the last but one may still be read by a frame that makes the next
            drop_path(self.spark, self.paths.pop(0))
        return self.spark.read.schema(df.schema).parquet(path)
