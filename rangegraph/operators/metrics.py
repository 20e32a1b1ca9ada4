"""Measures of accuracy and cost."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..schema import SCALE
from .index import Index


def recall(result: DataFrame, truth: DataFrame, k: int = 10) -> DataFrame:
    """qid, band, recall: share of the true top-k among the results."""
    hit = result.where(F.col("rank") <= k).select("qid", "band", "id", F.lit(1).alias("hit"))
    return truth.where(F.col("rank") <= k).join(hit, ["qid", "band", "id"], "left").groupBy("qid", "band").agg((F.count("hit") / F.lit(k)).alias("recall"))


def by_band(per_query: DataFrame, column: str = "recall") -> DataFrame:
    """band (null: all), mean, queries."""
    return per_query.rollup("band").agg(F.avg(column).alias(column), F.count(F.lit(1)).alias("queries"))


def timed(df: DataFrame) -> float:
    """Seconds to compute all rows, without keeping them."""
    began = time.time()
    df.write.format("noop").mode("overwrite").save()
    return time.time() - began


def qps(n: int, seconds: float) -> float:
    return n / max(seconds, 1e-9)


def tradeoff(runs: DataFrame) -> DataFrame:
    """runs (method, ef, recall, qps) -> the points that no other of the method beats in both."""
    w = Window.partitionBy("method").orderBy(F.desc("qps"), F.desc("recall")).rowsBetween(Window.unboundedPreceding, -1)
    return runs.withColumn("before", F.max("recall").over(w)).where(F.col("before").isNull() | (F.col("recall") > F.col("before"))).drop("before")


def qps_at(runs: DataFrame, wanted: float) -> DataFrame:
    """method, qps at a recall, between the two neighbouring points of the curve."""
    w = Window.partitionBy("method").orderBy("recall", "qps")
    steps = tradeoff(runs).withColumn("r2", F.lead("recall").over(w)).withColumn("q2", F.lead("qps").over(w))
    share = (F.lit(wanted) - F.col("recall")) / (F.col("r2") - F.col("recall"))
    inside = steps.where((F.col("recall") <= wanted) & (F.col("r2") >= wanted)).select("method", (F.col("qps") + share * (F.col("q2") - F.col("qps"))).alias("qps"))
    return inside.groupBy("method").agg(F.max("qps").alias("qps"))


def degree(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """One row: nodes, edges, mean and largest number of edges per node."""
    per = edges.select("src", "dst").distinct().groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    return nodes.select(F.col("id").alias("src")).distinct().join(per, "src", "left").agg(F.count(F.lit(1)).alias("nodes"), F.sum(F.coalesce("n", F.lit(0))).alias("edges"), F.avg(F.coalesce("n", F.lit(0))).alias("avg_edges"), F.max(F.coalesce("n", F.lit(0))).alias("max_edges"))


def range_stats(edges: DataFrame) -> DataFrame:
    """One row: edges, mean active share of [0, 1], mean pieces, share of edges that are always active."""
    per = edges.groupBy("src", "dst").agg((F.sum(F.col("hi") - F.col("lo")) / SCALE).alias("length"), F.count(F.lit(1)).alias("pieces"))
    return per.agg(F.count(F.lit(1)).alias("edges"), F.avg("length").alias("avg_length"), F.avg("pieces").alias("avg_pieces"), F.avg(F.when(F.col("length") >= 1, 1.0).otherwise(0.0)).alias("always"))


def active_degree(edges: DataFrame, alphas: DataFrame) -> DataFrame:
    """alpha, active edges per alpha, for alphas (band, alpha): the join goes over 20 cells of the weight."""
    cell = F.explode(F.sequence(F.floor(F.col("lo") / 500), F.floor(F.least(F.col("hi"), F.lit(SCALE - 1)) / 500))).alias("cell")
    e = edges.select("src", "dst", "lo", "hi", cell)
    a = alphas.withColumn("at", F.round(F.col("alpha") * SCALE)).withColumn("cell", F.floor(F.least(F.col("at"), F.lit(SCALE - 1)) / 500))
    return a.join(e, "cell").where("lo <= at and at <= hi").select("band", "alpha", "src", "dst").distinct().groupBy("band", "alpha").agg(F.count(F.lit(1)).alias("active_edges"))


def index_size(index: Index) -> DataFrame:
    """One row: bytes of vectors, of edges (8 each) and of ranges (4 per interval)."""
    pieces = F.aggregate("lo", F.lit(0), lambda acc, x: acc + F.size(x))
    return index.nodes.agg(F.sum(4 * (F.size("e") + F.size("s"))).alias("vector_bytes"), F.sum(8 * F.size("dst")).alias("edge_bytes"), F.sum(4 * pieces).alias("range_bytes"))


def work(result: DataFrame, width: int = 0) -> DataFrame:
    """band, mean distance evaluations, hops, edges scanned and gated, early stops, shards, seconds per query, and the
    bytes of vectors (of `width` numbers in both) that its shards were sent."""
    columns = ("n_dist", "hops", "scanned", "gated", "stopped", "probed", "seconds")
    per = result.groupBy("qid", "band").agg(*[F.first(c).alias(c) for c in columns])
    return per.groupBy("band").agg(*[F.avg(c).alias(c) for c in columns], (F.avg("probed") * 4 * width).alias("bytes_sent"))


def reachability(index: Index) -> DataFrame:
    """One row: nodes, reached from the seeds over any edges, by semi-joins to a fixpoint."""
    from ..storage import Steps

    edges = index.edges().select("shard", "src", "dst").distinct()
    steps = Steps(index.nodes.sparkSession, "reached")
    reached = steps.write(index.seeds().distinct())
    n = reached.count()
    while True:
        step = reached.join(edges, (reached.shard == edges.shard) & (reached.id == edges.src)).select(edges.shard, F.col("dst").alias("id"))
        reached = steps.write(reached.unionByName(step).distinct())
        now = reached.count()
        if now == n:
            break
        n = now
    return index.nodes.where("level = 0").agg(F.count(F.lit(1)).alias("nodes")).withColumn("reached", F.lit(n).cast("long"))
