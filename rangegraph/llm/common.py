"""Shared pieces of the corpus operators: tables, the shared folder, column hygiene."""

from __future__ import annotations

import ctypes
import gc
import time
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Used only where the session names no spark.checkpoint.dir (tests on one machine).
LOCAL_SHARED = "file:///tmp/checkpoints/rangegraph"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, as the cluster names it; a cluster must name one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return (named or LOCAL_SHARED).rstrip("/")


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


def stash(df: DataFrame, tag: str) -> DataFrame:
    """Cut the lineage: write to the shared folder and read again. Survives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Lets Spark's cleaner find shuffles whose frames are gone, so that their files leave the executors' disks.

    The events of a query that has just ended hold its plan for a moment, so the collector runs again after a pause.
    """
    for _ in range(3):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.4)


def drop_path(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


class Scratch:
    """Written intermediate tables by tag, and their deletion once nothing reads them any more."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def stash(self, df: DataFrame, tag: str) -> DataFrame:
        path = new_path(self.spark, tag)
        df.write.parquet(path)
        self.paths.append((tag, path))
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, tag: str, keep: int = 0) -> None:
        """Deletes the tables of a tag, but for the last `keep`."""
        old = [x for x in self.paths if x[0] == tag]
        for x in old[: len(old) - keep]:
            drop_path(self.spark, x[1])
            self.paths.remove(x)


def texts(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id, text (null becomes empty), and the named further columns."""
    return docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("text"), *more)


def text_bytes(batch: pa.RecordBatch, name: str = "text") -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a text column without copies: (buffer, offsets); nulls count as empty."""
    col = batch.column(name)
    if pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type):
        col, width = col.cast(pa.large_binary()), np.int64
    else:
        col, width = col.cast(pa.binary()), np.int32
    if col.null_count:
        col = col.fill_null(b"")
    _, offsets, data = col.buffers()
    off = np.frombuffer(offsets, width)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    buf = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return buf[off[0] : off[-1]], off - off[0]


def fresh(taken: list[str], name: str) -> str:
    """A column name that a table does not have."""
    name = f"_{name}"
    while name.lower() in {c.lower() for c in taken}:
        name = "_" + name
    return name


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on uint64."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def merge_iter(batches, schema: pa.Schema, build, rows: int = 20_000):
    """Yield record batches of `schema` from build(batch) -> dict of columns."""
    for batch in batches:
        for i in range(0, max(batch.num_rows, 1), rows):
            part = batch.slice(i, rows)
            if part.num_rows:
                yield pa.RecordBatch.from_pydict(build(part), schema=schema)


def lean(fn):
    """fn over batches that gives freed memory back at its end: Python workers stay, and others need room."""

    def run(batches):
        try:
            yield from fn(batches)
        finally:
            pa.default_memory_pool().release_unused()
            if (trim := getattr(ctypes.CDLL(None), "malloc_trim", None)) is not None:
                trim(0)

    return run
