"""Windows, lateness, deduplication and joins over the event stream; insertion and search of arriving objects.

Files of a directory are the stream; each call runs the query to the end of what is there and returns a
batch frame of its output, so that results can be compared with batch queries.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import exact, index, seeds
from ..schema import BuildParams, Norm, SearchParams, ShardParams
from ..sources import tables
from ..storage import drop_path, exists, new_path, stash

OUT_SCHEMA_SEEDS = "id long, de double, ds double"


def replay(spark: SparkSession, sf_dir: str, files: int = 4, shuffle: bool = False, twice: bool = False) -> str:
    """The events as a directory of files in the order of time (or out of order, or each file twice)."""
    e = tables.load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    n = e.count()
    part = F.least(F.floor(F.col("event_id") * files / n), F.lit(files - 1)).cast("int")
    if shuffle:  # one event in ten comes with the next file but one
        part = F.when(F.col("event_id") % 10 == 3, F.least(part + 2, F.lit(files - 1))).otherwise(part)
    path = new_path(spark, "replay")
    for k in range(files):
        for _ in range(2 if twice else 1):
            e.where(part == k).coalesce(1).write.mode("append").parquet(path)
    return path


def _stream(spark: SparkSession, path: str, per_batch: int = 1) -> DataFrame:
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_batch).parquet(path)


def run_to_end(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All output rows of a stream until its input is used up; the sink and its state are in the shared folder."""
    spark, out = stream.sparkSession, new_path(stream.sparkSession, "stream-out")

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("append").parquet(out)

    stream.writeStream.outputMode(mode).option("checkpointLocation", new_path(spark, "stream-state")).trigger(availableNow=True).foreachBatch(keep).start().awaitTermination()
    if not exists(spark, out):
        from pyspark.sql.types import IntegerType, StructType

        return spark.createDataFrame([], StructType([*stream.schema.fields]).add("batch", IntegerType()))
    return spark.read.parquet(out)


def _counts(df: DataFrame, window) -> DataFrame:
    return df.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 6).alias("mean")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n", "mean")


def tumbling(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(from the stream, from the batch): counts and mean values per day and type."""
    path = replay(spark, sf_dir)
    win = F.window("ts", "1 day")
    # complete mode: every window is there at the end; the last batch has them all
    got = run_to_end(_counts(_stream(spark, path), win), "complete")
    return got.where(F.col("batch") == got.agg(F.max("batch")).first()[0]).drop("batch"), _counts(spark.read.parquet(path), win)


def sliding(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    path = replay(spark, sf_dir)
    win = F.window("ts", "1 day", "6 hours")
    got = run_to_end(_counts(_stream(spark, path), win), "complete")
    return got.where(F.col("batch") == got.agg(F.max("batch")).first()[0]).drop("batch"), _counts(spark.read.parquet(path), win)


def sessions(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Sessions of users, closed after eight hours without an event; the watermark decides when they are complete."""
    path = replay(spark, sf_dir)

    def count(df: DataFrame) -> DataFrame:
        return df.groupBy(F.session_window("ts", "8 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")

    end = spark.read.parquet(path).agg(F.max("ts")).first()[0]
    # written before it is filtered: a filter on the end of a window would be pushed below the merging of sessions
    batch = stash(count(spark.read.parquet(path)), "sessions").where(F.col("end") < F.lit(end) - F.expr("INTERVAL 1 HOUR"))
    return run_to_end(count(_stream(spark, path).withWatermark("ts", "1 hour"))).drop("batch"), batch


def late(spark: SparkSession, sf_dir: str, delay: str = "2 hours") -> DataFrame:
    """side ('counted' or 'late'), events: out-of-order replay under a watermark; what it leaves out goes to a side table."""
    path = replay(spark, sf_dir, shuffle=True)
    spark_rows = spark.read.parquet(path)
    counted = run_to_end(_stream(spark, path).withWatermark("ts", delay).groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n"))
    batch = spark_rows.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("all")).select(F.col("w.start").alias("start"), "all")
    both = counted.join(batch, "start")
    return both.agg(F.sum("n").alias("n"), F.sum(F.col("all") - F.col("n")).alias("late")).select(F.explode(F.array(F.struct(F.lit("counted").alias("side"), F.col("n").alias("events")), F.struct(F.lit("late").alias("side"), F.col("late").alias("events")))).alias("x")).select("x.*")


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events once each, from files that come twice."""
    path = replay(spark, sf_dir, twice=True)
    s = _stream(spark, path).withWatermark("ts", "30 days").dropDuplicatesWithinWatermark(["event_id"])
    return run_to_end(s.select("event_id", "event_type")).drop("batch")


def view_to_click(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Clicks within an hour after a view of the same user: a join of two streams, and of two batches."""
    path = replay(spark, sf_dir)

    def pair(df: DataFrame, mark) -> DataFrame:
        v = mark(df.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("vu"), F.col("ts").alias("vt")), "vt")
        c = mark(df.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("cu"), F.col("ts").alias("ct")), "ct")
        return v.join(c, F.expr("vu = cu AND ct >= vt AND ct <= vt + INTERVAL 1 HOUR")).select("view_id", "click_id")

    return run_to_end(pair(_stream(spark, path), lambda d, c: d.withWatermark(c, "1 hour"))).drop("batch"), pair(spark.read.parquet(path), lambda d, c: d)


def search_arrivals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries that arrive as files, searched against a fixed index, micro-batch by micro-batch."""
    from ..workloads import case

    c = case(spark, sf_dir)
    ix = c.index()
    path, out = new_path(spark, "arrivals"), new_path(spark, "answers")
    for b in range(5):
        c.queries.where(F.col("band") == b).coalesce(1).write.mode("append").parquet(path)

    def answer(batch: DataFrame, number: int) -> None:
        index.topk(ix, batch, SearchParams(10, 50)).withColumn("batch", F.lit(number)).write.mode("append").parquet(out)

    _stream(spark, path).writeStream.option("checkpointLocation", new_path(spark, "stream-state")).trigger(availableNow=True).foreachBatch(answer).start().awaitTermination()
    return spark.read.parquet(out)


STATE = "ids binary, de binary, ds binary"


def _rim_state(key, frames, state):
    """The rim of all rows so far: the old rim is the state, new rows come reduced to the rims of their batches."""
    old = [np.frombuffer(x, t) for x, t in zip(state.get, (np.int64, float, float))] if state.exists else [np.zeros(0, np.int64), np.zeros(0), np.zeros(0)]
    for f in frames:
        old = [np.concatenate([o, f[c].to_numpy()]) for o, c in zip(old, ("id", "de", "ds"))]
        keep = np.sort(seeds.rim_block(old[1], old[2], old[0]))
        old = [o[keep] for o in old]
    state.update(tuple(np.ascontiguousarray(o).tobytes() for o in old))
    yield pd.DataFrame({"id": old[0], "de": old[1], "ds": old[2]})


def seeds_as_state(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(rim seeds kept as the state of a streaming operator, rim of all): events as objects, a fixed centroid.

    Tasks reduce their batches to rims first, so the one group of the operator gets few rows. The state lives in the
    stream's checkpoint and survives a restart.
    """
    rows = tables.event_stream(spark, sf_dir)
    ce, cs = seeds.centroid(rows)
    norm = Norm(1.0, 1.0)

    def reduce(batches):
        for b in batches:
            if b.num_rows:
                yield b.take(pa.array(np.sort(seeds.rim_block(*(b.column(c).to_numpy() for c in ("de", "ds", "id"))))))

    new = seeds.from_centroid(tables.event_features(_stream(spark, replay(spark, sf_dir))), ce, cs, norm).mapInArrow(reduce, OUT_SCHEMA_SEEDS)
    grown = new.withColumn("all", F.lit(0)).groupBy("all").applyInPandasWithState(_rim_state, OUT_SCHEMA_SEEDS, STATE, "update", "NoTimeout")
    got = run_to_end(grown, "update")
    return got.where(F.col("batch") == got.agg(F.max("batch")).first()[0]).drop("batch"), seeds.rim_of(seeds.from_centroid(rows, ce, cs, norm))


def insert_waves(spark: SparkSession, sf_dir: str, params: BuildParams = BuildParams(M=10, ef_c=50), shards: int = 8, max_rows: int = 100_000) -> index.Index:
    """An index that grows by micro-batches of events: each batch is inserted into the graphs of its shards.

    Version n of the index is made from version n - 1 and batch n, and is found by its number in the shared folder. So
    a restarted stream goes on from what is written, a repeated batch replaces its own version, and readers of earlier
    versions are not disturbed.
    """
    norm, root = Norm(1.0, 30.0), new_path(spark, "grown")

    def insert(batch: DataFrame, number: int) -> None:
        objects = tables.event_features(batch).dropDuplicates(["id"])
        if number == 0:
            now = index.build_index(objects, params, norm, ShardParams(shards, max_rows=max_rows), "wave")
        else:
            now = index.insert(index.read_index(spark, f"{root}/v{number - 1}"), objects, max_rows)
        drop_path(spark, f"{root}/v{number}")
        index.write_index(now, f"{root}/v{number}")
        if number > 1:
            drop_path(spark, f"{root}/v{number - 2}")

    query = _stream(spark, replay(spark, sf_dir)).writeStream.option("checkpointLocation", new_path(spark, "stream-state")).trigger(availableNow=True).foreachBatch(insert).start()
    query.awaitTermination()
    last = 0
    while exists(spark, f"{root}/v{last + 1}/meta") or not exists(spark, f"{root}/v{last}/meta"):
        last += 1
    return index.read_index(spark, f"{root}/v{last}")


def grown_queries(objects: DataFrame) -> DataFrame:
    """The objects with id % 20 = 7 (the rows that other workloads hold out), five weights each."""
    return objects.where("id % 20 = 7").select(F.col("id").alias("qid"), "e", "s").withColumn("band", F.explode(F.sequence(F.lit(0), F.lit(4)))).withColumn("alpha", tables.alpha_of(F.col("qid"), F.col("band"))).select("qid", "band", "alpha", "e", "s")


def grown_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """band, recall of the grown index against an exact scan of all events."""
    from ..operators import metrics

    ix = insert_waves(spark, sf_dir)
    objects = ix.nodes.where("level = 0").select("id", "e", "s")
    q = grown_queries(objects)
    truth = exact.topk(objects, q, ix.norm, 10)
    return metrics.by_band(metrics.recall(index.topk(ix, q, SearchParams(10, 50)), truth))
