"""The experiments have all methods, the whole published sweep, and measures that are consistent with each other."""

from __future__ import annotations

from rangegraph.catalogue import core
from rangegraph.workloads import SWEEP, case


def rows(df):
    return [r.asDict() for r in df.collect()]


def test_sweep_is_the_published_one():
    assert SWEEP == tuple(range(10, 201, 10))


def test_extreme_weights_compare_all_methods(spark, small):
    got = rows(core.wl_extreme(spark, small))
    assert {r["method"] for r in got} == {"range", "fixed", "merge", "overlay", "oracle"}
    for m in {r["method"] for r in got}:
        mine = [r for r in got if r["method"] == m]
        assert {r["ef"] for r in mine} == set(SWEEP) and {r["band"] for r in mine} == {None, 0, 1}
        assert all(0 <= r["recall"] <= 1 and r["n_dist"] > 0 and r["qps"] > 0 for r in mine)
        whole = {r["ef"]: r for r in mine if r["band"] is None}
        assert whole[200]["n_dist"] >= whole[10]["n_dist"] and whole[200]["recall"] >= whole[10]["recall"] - 0.02
    best = {m: max(r["recall"] for r in got if r["method"] == m and r["band"] is None) for m in ("range", "oracle", "merge")}
    assert min(best.values()) >= 0.95


def test_bands_have_their_active_degree(spark, small):
    got = rows(core.wl_bands(spark, small))
    assert {r["method"] for r in got} == {"range", "fixed", "overlay"} and {r["band"] for r in got} == set(range(5))
    fixed = {r["active_degree"] for r in got if r["method"] == "fixed"}
    assert len(fixed) == 1  # its edges are active at every weight
    assert len({r["active_degree"] for r in got if r["method"] == "range"}) > 1


def test_prior_methods_are_exact_and_have_a_cost(spark, small):
    got = {r["method"]: r for r in rows(core.wl_spatial_prior(spark, small)) if r["band"] is None and r["ef"] == 10}
    n = case(spark, small, "emb_geo").n
    assert got["scan"]["n_dist"] == n
    for m in ("scan", "quad_ring", "pivot", "clusters"):
        assert got[m]["recall"] == 1.0 and 0 < got[m]["n_dist"] <= n and got[m]["qps"] > 0
    assert set(got) == {"scan", "quad_ring", "pivot", "clusters", "clusters_approx", "range"}


def test_sides_of_the_merge_have_rates(spark, small):
    got = rows(core.merge_sides(spark, small))
    assert {(r["side"], r["k_prime"]) for r in got} == {(s, k) for s in ("graph", "rectangle_tree") for k in (10, 50, 200)}
    assert all(r["qps"] > 0 and r["n_dist"] > 0 for r in got)


def test_curves(spark, small):
    curve = rows(core.tradeoff_curve(spark, small))
    by_rate = sorted(curve, key=lambda r: -r["qps"])
    assert [r["recall"] for r in by_rate] == sorted(r["recall"] for r in curve)
    assert {r["method"] for r in rows(core.qps_at_recall(spark, small))} <= {"range", "fixed", "merge"}
