"""Streams: state and insertion end where a batch over all rows ends."""

from __future__ import annotations

from pyspark.sql import functions as F

from rangegraph.operators import exact, index, metrics
from rangegraph.schema import SearchParams
from rangegraph.streaming import events


def test_seeds_as_state_are_the_rim_of_all(spark, small):
    got, want = events.seeds_as_state(spark, small)
    key = lambda df: sorted((r.id, round(r.de, 9), round(r.ds, 9)) for r in df.collect())
    assert key(got) == key(want) and key(want)


def test_sessions_of_the_stream_are_those_of_the_batch(spark, small):
    got, want = events.sessions(spark, small)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_late_rows_are_counted_once(spark, small):
    rows = {r.side: r.events for r in events.late(spark, small).collect()}
    assert rows["counted"] > 0 and rows["late"] > 0


def test_index_that_grows_by_batches(spark, small):
    ix = events.insert_waves(spark, small, shards=2)
    objects = ix.nodes.where("level = 0").select("id", "e", "s")
    n = objects.count()
    assert n == objects.select("id").distinct().count() == spark.read.parquet(f"{small}/events.parquet").count()
    q = events.grown_queries(objects)
    hits = index.topk(ix, q, SearchParams(10, 50))
    assert metrics.recall(hits, exact.topk(objects, q, ix.norm, 10)).agg(F.avg("recall")).first()[0] >= 0.9
