"""Frontiers and layers: worked example, definition, invariance, decomposition of the rim."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from rangegraph.operators import pareto, seeds

# Points (ds, de) 1 to 5 and their layers.
POINTS = [(1, 1.0, 5.0), (2, 2.0, 3.0), (3, 3.0, 4.0), (4, 4.0, 1.0), (5, 5.0, 5.0)]
LAYERS = {1: 1, 2: 1, 4: 1, 3: 2, 5: 3}


def brute_layers(de, ds, twins_together: bool):
    left, out, k = set(range(len(de))), {}, 0
    while left:
        k += 1
        now = {i for i in left if not any((de[j] <= de[i] and ds[j] <= ds[i] and (de[j] < de[i] or ds[j] < ds[i])) or (not twins_together and de[j] == de[i] and ds[j] == ds[i] and j < i) for j in left if j != i)}
        out |= {i: k for i in now}
        left -= now
    return [out[i] for i in range(len(de))]


def test_worked_layers(spark):
    df = spark.createDataFrame([(0, i, de, ds) for i, ds, de in POINTS], "p long, x long, de double, ds double")
    assert {r.x: r.layer for r in pareto.layers(df).collect()} == LAYERS
    assert {r.x: r.layer for r in pareto.layers_by_peeling(df, 3).collect()} == LAYERS
    assert {r.x for r in pareto.frontier(df).collect()} == {1, 2, 4}


def test_layers_are_peeled_frontiers():
    rng = np.random.default_rng(0)
    for ties in ("peel", "definition"):
        for _ in range(40):
            n = int(rng.integers(1, 40))
            de, ds = rng.integers(0, 8, n).astype(float), rng.integers(0, 8, n).astype(float)
            got = pareto.layer_block(de, ds, np.arange(n), ties)
            assert got.tolist() == brute_layers(de, ds, ties == "definition")
            order = rng.permutation(n)
            again = pareto.layer_block(de[order], ds[order], np.arange(n)[order], ties)
            assert again.tolist() == got[order].tolist()


def test_bound_keeps_whole_layers():
    layer = np.array([1, 1, 1, 2, 2, 3])
    assert pareto.keep_bound(layer, 5).tolist() == [True] * 5 + [False]
    assert pareto.keep_bound(layer, 4).tolist() == [True] * 3 + [False] * 3
    assert pareto.keep_bound(layer, 2).tolist() == [True] * 3 + [False] * 3
    assert pareto.keep_bound(layer, None).all()


def test_frontier_has_a_nearest_object_at_every_weight(spark):
    rng = np.random.default_rng(5)
    de, ds = rng.random(200), rng.random(200)
    df = spark.createDataFrame([(0, i, float(a), float(b)) for i, (a, b) in enumerate(zip(de, ds))], "p long, x long, de double, ds double")
    front = [r.x for r in pareto.frontier(df).collect()]
    for a in np.linspace(0, 1, 101):
        d = a * de + (1 - a) * ds
        assert d[front].min() <= d.min() + 1e-12


def test_rim_is_decomposable(spark):
    rng = np.random.default_rng(6)
    rows = [(i, float(a), float(b)) for i, (a, b) in enumerate(rng.integers(0, 30, (300, 2)))]
    df = spark.createDataFrame(rows, "id long, de double, ds double")
    whole = {r.id for r in seeds.rim_of(df).collect()}
    parts = seeds.rim_of(df.where("id % 3 = 0"))
    for k in (1, 2):
        parts = seeds.update(parts, df.where(F.col("id") % 3 == k))
    assert {r.id for r in parts.collect()} == whole
    for i, a, b in rows:
        beats = [j for j, x, y in rows if x >= a and y >= b and (x > a or y > b or j < i)]
        assert (i in whole) == (not beats)
    ids = np.arange(300)
    block = seeds.rim_block(np.array([r[1] for r in rows]), np.array([r[2] for r in rows]), ids)
    assert set(ids[block].tolist()) == whole


def test_first_layers_of_few_rows_are_those_of_all():
    """What is left out before the layers are made belongs to none of the first ones, nor to the bounded ones."""
    rng = np.random.default_rng(3)
    for n, places in ((1, 3), (40, 1), (900, 2), (900, 6)):
        de, ds, ids = np.round(rng.random(n), places), np.round(rng.random(n), places), np.arange(n)
        want = pareto.layer_block(de, ds, ids)
        for most in (1, 3):
            at = pareto.in_first_layers(de, ds, most)
            got = pareto.layer_block(de[at], ds[at], ids[at])
            assert {i: k for i, k in zip(at.tolist(), got.tolist()) if k <= most} == {i: k for i, k in enumerate(want.tolist()) if k <= most}
        assert n < 900 or len(at) < n / 2
        for bound in (1, 20, 100):
            at = pareto.in_bounded_layers(de, ds, bound)
            got = pareto.layer_block(de[at], ds[at], ids[at])
            assert at[pareto.keep_bound(got, bound)].tolist() == np.flatnonzero(pareto.keep_bound(want, bound)).tolist()


def test_dominated_pairs_are_counted_without_pairs():
    rng = np.random.default_rng(4)
    for n in (0, 1, 2, 63, 64, 65, 200, 700):
        for places in (1, 9):
            de, ds = np.round(rng.random(n), places), np.round(rng.random(n), places)
            a, b, c, d = de[:, None], de, ds[:, None], ds
            assert pareto.dominated_pairs(de, ds) == ((a <= b) & (c <= d) & ((a < b) | (c < d))).sum()
