"""Weight intervals: worked examples, brute force over a grid of weights, the stored form."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangegraph.functions import alpha as al
from rangegraph.operators import prune
from rangegraph.operators.pareto import layer_block
from rangegraph.schema import BuildParams, Norm, SearchParams

# The worked triangles, (s, e) of xy, xz, yz, and the pruned set of the edge from x to z by witness y.
TRIANGLES = [((0.3, 0.4), (0.8, 0.9), (0.1, 0.7), None), ((0.5, 0.7), (0.2, 0.4), (0.3, 0.5), (0.0, 1.0)), ((0.2, 0.6), (0.4, 0.5), (0.3, 0.4), (2 / 3, 1.0))]


def holds(xy, xz, yz, a):
    d = lambda p: a * p[1] + (1 - a) * p[0]
    return d(xz) < d(xy) and d(yz) < d(xy)


@pytest.mark.parametrize("xy,xz,yz,_", TRIANGLES)
def test_triangles_by_grid(xy, xz, yz, _):
    """z removes the edge from x to y exactly at the weights where both inequalities hold."""
    lo, hi = al.pruned_block(*map(np.array, (xz[1], xz[0], xy[1], xy[0], yz[1], yz[0])))
    for a in np.linspace(0, 1, 1001):
        if abs(a - lo) > 1e-6 and abs(a - hi) > 1e-6:
            assert holds(xy, xz, yz, a) == bool(lo < a < hi)


def test_worked_ranges():
    for xy, xz, yz, want in TRIANGLES:
        lo, hi = al.pruned_block(*map(np.array, (xz[1], xz[0], xy[1], xy[0], yz[1], yz[0])))
        if want is None:
            assert hi - lo < 1e-9
        else:
            assert (float(lo), float(hi)) == pytest.approx(want, abs=1e-9)


def test_halfline_cases():
    a = np.array([0.2, 0.2, -0.2, -0.2, 0.0, 0.0, 0.0, 0.3])
    b = np.array([0.5, -0.5, 0.5, -0.5, 0.5, -0.5, 0.0, 0.1])
    lo, hi = al.halfline_block(a, b)
    for x, y, i, j in zip(a, b, lo, hi):
        inside = [t for t in np.linspace(0, 1, 101) if t * y < x - 1e-12]
        assert (j <= i) == (len([t for t in inside if 0 < t < 1]) == 0)


def test_gaps_and_length():
    rng = np.random.default_rng(0)
    for _ in range(200):
        iv = [tuple(sorted(rng.random(2))) for _ in range(rng.integers(0, 6))]
        free = al.gaps(iv)
        grid = np.linspace(0, 1, 2001)
        covered = np.zeros(len(grid), bool)
        for i, j in iv:
            covered |= (grid > i) & (grid < j)
        for t, c in zip(grid, covered):
            if not any(abs(t - x) < 1e-6 for f in iv for x in f):
                assert any(i <= t <= j for i, j in free) != c
        assert all(x[1] < y[0] for x, y in zip(free, free[1:]))


def test_columns_agree_with_numpy(spark):
    rng = np.random.default_rng(1)
    rows = [(int(i), [{"lo": float(a), "hi": float(b)} for a, b in np.sort(rng.random((rng.integers(0, 5), 2)), axis=1)]) for i in range(60)]
    df = spark.createDataFrame(rows, "id int, v array<struct<lo:double,hi:double>>")
    got = {r.id: r for r in df.select("id", al.complement(F.col("v")).alias("c"), al.length(F.col("v")).alias("n"), al.decode(al.encode(F.col("v"))).alias("back")).collect()}
    for i, v in rows:
        free = al.gaps([(x["lo"], x["hi"]) for x in v])
        assert len(got[i].c) == len(free) and np.allclose([(c.lo, c.hi) for c in got[i].c], free)
        assert got[i].n == pytest.approx(1 - sum(b - a for a, b in free))
        for x, y in zip(v, got[i].back):
            assert y.lo <= x["lo"] and x["hi"] <= y.hi and x["lo"] - y.lo < 1e-4 + 1e-9


def test_tags_of_bands():
    assert [al.overlay_tag(a) for a in (0, 0.1, 0.2, 0.2001, 0.4, 0.5, 0.6, 0.61, 0.8, 0.99, 1)] == [0, 0, 0, 1, 1, 2, 2, 3, 3, 4, 4]


@pytest.mark.parametrize("witness", ["any", "active"])
def test_gate_block_against_grid(witness):
    """th = 0, no cap: an edge is active at a weight iff no earlier kept candidate is a witness there (and active there, in that mode)."""
    rng = np.random.default_rng(3)
    for _ in range(20):
        n = 14
        e, s, p = rng.random((n, 3)), rng.random((n, 2)), (rng.random(3), rng.random(2))
        de, ds = np.linalg.norm(e - p[0], axis=1), np.linalg.norm(s - p[1], axis=1)
        xe, xs = np.linalg.norm(e[:, None] - e[None], axis=2), np.linalg.norm(s[:, None] - s[None], axis=2)
        layer = layer_block(de, ds, np.arange(n))
        got = prune.gate_block(de, ds, layer, np.arange(n), lambda: (xe, xs), 10**9, 0.0, witness=witness)
        order = prune.order_of(layer, de, ds, np.arange(n)).tolist()
        have = dict(got)
        for a in np.linspace(0.005, 0.995, 60):
            d, x = a * de + (1 - a) * ds, a * xe + (1 - a) * xs
            active: set[int] = set()
            for c in order:
                pool = [k for k in order[: order.index(c)] if k in have and (witness == "any" or k in active)]
                free = not any(d[k] < d[c] and x[k, c] < d[c] for k in pool)
                inside = c in have and any(i <= a <= j for i, j in have[c])
                near_end = c in have and any(abs(a - t) < 1e-6 for r in have[c] for t in r)
                assert near_end or inside == free or c not in have and not free
                if inside:
                    active.add(c)


def test_remap_keeps_order():
    rng = np.random.default_rng(4)
    de, ds = rng.random(50), rng.random(50)
    true, used = Norm(2.0, 0.7), Norm(1.5, 1.1)
    for a in (0.0, 0.2, 0.5, 0.9, 1.0):
        b = used.remap(a, true)
        assert (np.argsort(a * de / true.e + (1 - a) * ds / true.s) == np.argsort(b * de / used.e + (1 - b) * ds / used.s)).all()


def test_parameters_are_checked():
    with pytest.raises(ValueError):
        BuildParams(pruning="other")
    with pytest.raises(ValueError):
        SearchParams(k=0)
    with pytest.warns(UserWarning):
        assert SearchParams(k=10, ef_search=3).ef_search == 10
