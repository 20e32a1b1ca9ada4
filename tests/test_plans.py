"""The planner's choices and the index source."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from rangegraph.operators import exact, index
from rangegraph.plans import planner
from rangegraph.schema import ShardParams
from rangegraph.sources import range_index
from rangegraph.storage import new_path
from rangegraph.workloads import case


def test_choices():
    assert planner.choose(10**6, 10**6, "exact").method == "scan"
    assert planner.choose(10**8, 10**8, "exact").method == "scan"
    assert planner.choose(10**3, 10**3, "approximate").method == "graph"
    assert planner.choose(10**8, 10**6, "approximate").method == "scan"
    with pytest.raises(ValueError):
        planner.choose(1, 1, "fast")


def test_both_ways_agree(spark, small):
    c = case(spark, small)
    condition = F.col("attrs.lang") == "en"
    scan, how = planner.topk(c.objects, c.queries, c.norm, 10, condition, c.index())
    assert how.method == "scan"
    graph, how = planner.topk(c.objects, c.queries, c.norm, 10, condition, c.index(), guarantee="approximate")
    assert how.method == "graph"
    a, b = ({(r.qid, r.band, r.id) for r in d.collect()} for d in (scan, graph))
    assert len(a & b) >= 0.9 * len(a) and len(a) == len(b)
    assert exact.topk(c.objects.where(condition), c.queries, c.norm, 10).count() == len(a)
    with pytest.raises(ValueError):
        planner.topk(c.objects, c.queries, c.norm, guarantee="approximate")


def test_index_source(spark, small):
    ix = case(spark, small).index(None, ShardParams(3))
    path = new_path(spark, "saved")
    index.write_index(ix, path)
    range_index.register(spark)
    read = spark.read.format("range_index").load(path)
    want = sorted(map(tuple, ix.edges().select("shard", "src", "dst", "lo", "hi").collect()))
    assert sorted(map(tuple, read.collect())) == want
    at = spark.read.format("range_index").option("alpha", "0.25").load(path).collect()
    assert sorted(map(tuple, at)) == [r for r in want if r[3] <= 2500 <= r[4]]
    back = index.read_index(spark, path)
    assert back.params == ix.params and back.norm.e == ix.norm.e
