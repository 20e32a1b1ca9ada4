"""Graphs: search equals an exact scan where it must, early stop and shards change nothing, ranges obey their rules."""

from __future__ import annotations

from threading import Lock

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangegraph.baselines import graphs
from rangegraph.functions import hashing, vectors
from rangegraph.operators import bsp, exact, index, kernel, metrics, normalisers, prune, waves, whole
from rangegraph.schema import BuildParams, Norm, SearchParams, ShardParams
from rangegraph.workloads import Case, case


@pytest.fixture(scope="module")
def points():
    rng = np.random.default_rng(8)
    return np.arange(120), rng.normal(size=(120, 8)), rng.normal(size=(120, 2)), Norm(8.0, 7.0)


def brute(points, qe, qs, a, k):
    ids, e, s, norm = points
    d = a * vectors.l2_rows(qe, e) / norm.e + (1 - a) * vectors.l2_rows(qs, s) / norm.s
    return np.lexsort((ids, d))[:k].tolist()


@pytest.mark.parametrize("params", [BuildParams(M=8, ef_c=40), BuildParams(M=8, ef_c=40, witness="active", th=0.0), BuildParams(M=8, ef_c=40, candidates="greedy"), BuildParams(M=8, ef_c=40, seeds="random"), BuildParams(M=8, ef_c=40, seeds="centroid"), BuildParams(M=8, ef_c=40, pruning="none"), BuildParams(M=8, ef_c=40, reverse="append"), BuildParams(M=8, ef_c=40, levels=True, pruning="rng"), BuildParams(M=8, ef_c=40, cap="hard")])
def test_wide_search_is_exact_over_what_it_reaches(points, params):
    ids, e, s, norm = points
    g = kernel.build(ids, e, s, norm, params)
    rng = np.random.default_rng(9)
    for _ in range(10):
        qe, qs, a = rng.normal(size=8), rng.normal(size=2), float(rng.random())
        if params.levels:
            got = [i for _, i in kernel.descend(g, qe, qs, a, 120, {})]
            assert len(set(got[:10]) & set(brute(points, qe, qs, a, 10))) >= 9
            continue
        reach = kernel.reachable(g, a)
        got = [i for _, i in kernel.best_first(g, qe, qs, a, g.seeds, 120)]
        want = [i for i in brute(points, qe, qs, a, 120) if reach[i]]
        assert got[:10] == want[:10]
        assert got == [i for _, i in kernel.best_first(g, qe, qs, a, g.seeds, 120, early_stop=False)]
    degree = [len(x) for x in g.nbrs]
    if params.cap == "hard":
        assert max(degree) <= 8
    if params.pruning == "range":
        assert all(sum(j - i for i, j in free) >= params.th - 1e-9 for r in g.ranges for free in r)


def test_building_is_deterministic(points):
    ids, e, s, norm = points
    a, b = (kernel.build(ids, e, s, norm, BuildParams(M=6, ef_c=30)) for _ in range(2))
    assert all((x == y).all() for x, y in zip(a.nbrs, b.nbrs))


def test_odd_shards():
    norm = Norm(1.0, 1.0)
    p = BuildParams(M=4, ef_c=10)
    one = kernel.build(np.array([7]), np.ones((1, 3)), np.ones((1, 2)), norm, p)
    assert kernel.best_first(one, np.zeros(3), np.zeros(2), 0.5, one.seeds, 5)[0][1] == 0
    same = kernel.build(np.arange(30), np.ones((30, 3)), np.ones((30, 2)), norm, p)
    assert len(kernel.best_first(same, np.ones(3), np.ones(2), 0.5, same.seeds, 30)) >= 1
    assert not len(kernel.build(np.zeros(0, int), np.zeros((0, 3)), np.zeros((0, 2)), norm, p).ids)
    line = kernel.build(np.arange(20), np.arange(20.0)[:, None], np.arange(20.0)[:, None], norm, p)
    assert kernel.reachable(line).all()


def test_range_graph_has_every_rng_edge_and_active_witnesses_make_greedy_exact():
    rng = np.random.default_rng(11)
    n = 40
    e, s = rng.normal(size=(n, 6)), rng.normal(size=(n, 2))
    norm = Norm(6.0, 6.0)
    xe, xs = vectors.l2_block(e, e) / norm.e, vectors.l2_block(s, s) / norm.s
    from rangegraph.operators.pareto import layer_block

    for witness in ("any", "active"):
        g = kernel.Graph(np.arange(n), e, s, norm)
        for p in range(n):
            o = np.array([i for i in range(n) if i != p])
            got = prune.gate_block(xe[p, o], xs[p, o], layer_block(xe[p, o], xs[p, o], o), o, lambda o=o: (xe[np.ix_(o, o)], xs[np.ix_(o, o)]), 10**9, 0.0, witness=witness)
            g.set_edges(p, o[[x for x, _ in got]], [r for _, r in got])
        for a in (0.1, 0.5, 0.9):
            want = prune.rng_edges_block(a * xe + (1 - a) * xs)
            for p, x in zip(*np.nonzero(want)):
                dst, lo, hi = g.arcs(p)
                assert ((dst == x) & (lo <= a * 10_000) & (a * 10_000 <= hi)).any()
            if witness == "active":
                for start in range(0, n, 7):
                    for target in range(n):
                        assert kernel.best_first(g, e[target], s[target], a, [start], 1)[0][0] < 1e-9


def test_index_search_and_shards(spark, small):
    c = case(spark, small)
    truth = c.truth()
    mean = lambda hits: metrics.recall(hits, truth).agg(F.avg("recall")).first()[0]
    one = c.index()
    assert mean(index.topk(one, c.queries, SearchParams(10, 100))) >= 0.9
    low, high = mean(index.topk(one, c.queries, SearchParams(10, 10))), mean(index.topk(one, c.queries, SearchParams(10, 100)))
    assert low <= high
    for by in ("hash", "cluster"):
        many = c.index(None, ShardParams(3, by))
        assert mean(index.topk(many, c.queries, SearchParams(10, 100))) >= 0.9
        rounds = index.topk(many, c.queries, SearchParams(10, 100, probes="bound"))
        assert mean(rounds) >= 0.9 and rounds.agg(F.max("probed")).first()[0] <= 3
    edges = one.edges()
    assert edges.where("hi - lo < 999").groupBy("src", "dst").count().count() <= edges.count()
    assert edges.where("lo < 0 or hi > 10000 or lo > hi").count() == 0


def test_exact_scan_and_threshold(spark, small):
    c = case(spark, small)
    got = {(r.qid, r.band, r["rank"]): r.id for r in exact.threshold_topk(c.objects, c.queries, c.norm)[0].collect()}
    assert got == {(r.qid, r.band, r["rank"]): r.id for r in c.truth().collect()}
    few = exact.topk(c.objects.limit(4), c.queries, c.norm, 10)
    assert few.groupBy("qid", "band").count().agg(F.max("count")).first()[0] == 4
    assert exact.topk(c.objects, c.queries.where("false"), c.norm).count() == 0


def test_exact_scan_keeps_queries_apart(spark):
    """Large ids that are equal as doubles, and one id with other vectors per band, are queries of their own."""
    rng = np.random.default_rng(3)
    e, s = rng.normal(size=(300, 5)).astype(np.float32), rng.normal(size=(300, 2)).astype(np.float32)
    objects = spark.createDataFrame([(i, a.tolist(), b.tolist()) for i, (a, b) in enumerate(zip(e, s))], "id long, e array<float>, s array<float>").repartition(3)
    asked = [(2**60, 0, 0.4, [0.0] * 5, [0.0] * 2), (2**60 + 1, 0, 0.4, [0.0, 9.0, 0.0, 0.0, 0.0], [0.0] * 2), (7, 0, 0.3, [1.0] * 5, [0.0] * 2), (7, 1, 0.3, [1.0, 0.0, 0.0, 0.0, 0.0], [0.0] * 2), (8, 0, 1.0, [1.0] * 5, [0.0] * 2)]
    norm = Norm(3.0, 2.0)
    got: dict = {}
    for r in exact.topk(objects, spark.createDataFrame(asked, "qid long, band int, alpha double, e array<double>, s array<double>"), norm, 5).collect():
        got.setdefault((r.qid, r.band), {})[r["rank"]] = r.id
    for qid, band, a, qe, qs in asked:
        d = a * vectors.l2_rows(np.array(qe), e.astype(float)) / norm.e + (1 - a) * vectors.l2_rows(np.array(qs), s.astype(float)) / norm.s
        assert [got[qid, band][k + 1] for k in range(5)] == np.lexsort((np.arange(300), d))[:5].tolist()


def test_distances_by_products_are_those_by_differences():
    rng = np.random.default_rng(4)
    a, b = rng.normal(size=(70, 33)), rng.normal(size=(90, 33))
    b[:20] = a[:20]
    b[20:30] = a[20:30] + 1e-9
    got = vectors.l2_block(a, b)
    assert (got[np.arange(20), np.arange(20)] == 0).all()
    assert np.abs(got - np.sqrt(((a[:, None] - b[None]) ** 2).sum(axis=2))).max() < 1e-10
    assert vectors.l2_block(np.ones((3, 2)), np.zeros((0, 2))).shape == (3, 0)


def test_shards_keep_their_bound(spark, small):
    """Whatever is asked for, a shard does not outgrow max_rows by more than chance."""
    c = case(spark, small)
    for shards in (ShardParams(max_rows=50), ShardParams(1, max_rows=50), ShardParams(2, "cluster", max_rows=60)):
        sizes = [r.n for r in c.index(BuildParams(M=6, ef_c=20), shards).shards.collect()]
        assert sum(sizes) == c.n and max(sizes) <= 1.6 * shards.max_rows and len(sizes) > 1


def test_a_sweep_is_its_single_searches(spark, small):
    c = case(spark, small)
    key = lambda df: sorted((r.qid, r.band, r["rank"], r.id, r.n_dist) for r in df.collect())
    for ix in (c.index(), c.fixed(), c.index(None, ShardParams(3, "cluster"))):
        many = index.sweep(ix, c.queries, (10, 30, 60), SearchParams(10))
        for ef in (10, 30, 60):
            assert key(many.where(F.col("ef") == ef)) == key(index.topk(ix, c.queries, SearchParams(10, ef)))
    parted = SearchParams(10, 30, copies=3)
    assert key(index.topk(c.index(), c.queries, parted)) == key(index.topk(c.index(), c.queries, SearchParams(10, 30, copies=1)))
    assert {r[0] for r in index.lists(c.fixed(), c.queries, (7, 20)).groupBy("qid", "band", "ef").count().select(F.col("count") - F.col("ef")).collect()} == {0}


def test_rectangle_tree_and_quadtree():
    from rangegraph.operators import spatial

    rng = np.random.default_rng(6)
    for n, d, metric in ((1, 2, "l2"), (33, 2, "l2"), (500, 2, "l2"), (700, 4, "max")):
        points = np.round(rng.normal(size=(n, d)), 1)
        tree, q = spatial.RectTree(points, 8, metric), rng.normal(size=d)
        got = list(tree.nearest(q))
        away = np.sqrt(((points - q) ** 2).sum(axis=1)) if metric == "l2" else np.abs(points - q).max(axis=1)
        assert sorted(i for _, i in got) == list(range(n)) and np.allclose([x for x, _ in got], np.sort(away))
    e, s = rng.normal(size=(400, 5)), np.round(rng.normal(size=(400, 2)), 1)
    s[:150] = s[0]  # more equal places than a leaf holds
    found = list(spatial.QuadTree(e, s, 16).leaves(np.zeros(2)))
    assert sorted(np.concatenate([leaf[4] for _, leaf in found]).tolist()) == list(range(400))
    assert [x for x, _ in found] == sorted(x for x, _ in found) and max(len(leaf[4]) for _, leaf in found[1:]) <= 150


def test_merge_reads_a_rectangle_tree_where_s_is_flat(spark, small):
    c = case(spark, small, "emb_geo")
    m = c.merge()
    assert m.by_s is None
    lists = m.sides(c.queries, (10,))[1]
    want = exact.topk(c.objects, c.queries.withColumn("alpha", F.lit(0.0)), c.norm, 10)
    key = lambda df: sorted((r.qid, r.band, r["rank"], r.id) for r in df.collect())
    assert key(lists) == key(want)
    assert metrics.recall(m.search(c.queries, 10, c.n), c.truth()).agg(F.min("recall")).first()[0] == 1.0


def test_oracle_refuses_other_weights(spark, small):
    c = case(spark, small)
    with pytest.raises(ValueError):
        graphs.Oracle({0.5: c.fixed()}).search(c.queries)


def test_merge_with_all_rows_is_exact_and_overlay_follows_its_tag(spark, small):
    c = case(spark, small)
    merged = graphs.merge_exact(c.objects, c.queries, c.norm, 10, c.n)
    assert metrics.recall(merged, c.truth()).agg(F.min("recall")).first()[0] == 1.0
    o = c.overlay(BuildParams(M=4, ef_c=16))
    parts = o.edges().where("lo > 0").select(F.col("lo") % 2000).distinct().collect()
    assert {r[0] for r in parts} <= {1}
    assert graphs.tag_of(0.2) == 0.1 and graphs.tag_of(0.21) == 0.3


def test_supersteps(spark, small):
    c = case(spark, small)
    ix = c.index()
    hits = bsp.search(ix.edges(), c.objects, c.queries, ix.seeds(), c.norm, 10, 30)
    assert metrics.recall(hits, c.truth()).agg(F.avg("recall")).first()[0] >= 0.85


def test_bounds_of_normalisers(spark, small):
    c = case(spark, small, "emb_geo")
    b = normalisers.bounded(c.objects)
    assert b.e <= c.norm.e + 1e-9 <= b.extra["e_upper"] + 1e-6 and b.s <= c.norm.s + 1e-9 <= b.extra["s_upper"] + 1e-6


def test_normalisers_are_true_at_every_size(spark, small, monkeypatch):
    from rangegraph.workloads import Case

    rng = np.random.default_rng(5)
    e, s = rng.normal(size=(400, 16)).astype(np.float32), rng.normal(size=(400, 2)).astype(np.float32)
    objects = spark.createDataFrame([(i, a.tolist(), b.tolist()) for i, (a, b) in enumerate(zip(e, s))], "id long, e array<float>, s array<float>")
    c = Case.__new__(Case)
    c.objects, c._lock = objects, Lock()
    monkeypatch.setattr(Case, "n", 20_001)
    true = [max(float(np.linalg.norm(v.astype(float) - x, axis=1).max()) for x in v.astype(float)) for v in (e, s)]
    assert [c.norm.e, c.norm.s] == pytest.approx(true, abs=1e-6)
    assert normalisers.bounded(objects).e < true[0] - 1e-6


def test_table_function_too_large_is_a_scan(spark, small, monkeypatch):
    from rangegraph.catalogue import relational
    from rangegraph.functions import udx

    key = lambda df: sorted((r.qid, r.band, r["rank"], r.id) for r in df.collect())
    want = key(relational.udtf_topk(spark, small))
    monkeypatch.setattr(udx, "PUBLISHED_BYTES", 0)
    assert want and key(relational.udtf_topk(spark, small)) == want


def test_hops_have_no_silent_end(spark):
    """A chain is walked to its end; a bound that is too small is an error."""
    objects = spark.createDataFrame([(i, [float(i)], [float(i)]) for i in range(6)], "id long, e array<float>, s array<float>")
    edges = spark.createDataFrame([(i, i + 1, 0, 10_000) for i in range(5)], "src long, dst long, lo int, hi int")
    seeds = spark.createDataFrame([(0,)], "id long")
    target = spark.createDataFrame([(9, [5.0], [5.0])], "id long, e array<float>, s array<float>")
    query = target.selectExpr("id AS qid", "0 AS band", "0.5D AS alpha", "e", "s")
    assert bsp.search(edges, objects, query, seeds, Norm(1.0, 1.0), 1, 6).first().id == 5
    assert {r.x for r in bsp.frontier_search(edges, objects, target, seeds, Norm(1.0, 1.0), 6).collect()} == set(range(6))
    with pytest.raises(RuntimeError):
        bsp.search(edges, objects, query, seeds, Norm(1.0, 1.0), 1, 6, most=2)
    with pytest.raises(RuntimeError):
        bsp.frontier_search(edges, objects, target, seeds, Norm(1.0, 1.0), 6, most=2)


def test_grown_index_is_asked_by_the_usual_queries(spark):
    from rangegraph.streaming.events import grown_queries

    objects = spark.range(400).selectExpr("id", "array(1f) AS e", "array(2f) AS s")
    got = grown_queries(objects).collect()
    assert {r.qid for r in got} == set(range(7, 400, 20)) and len(got) == 100


def test_vectors_are_checked(spark):
    bad = spark.createDataFrame([(1, [1.0, float("nan")], [0.0]), (2, [1.0, 2.0], [0.0])], "id long, e array<float>, s array<float>")
    with pytest.raises(ValueError):
        vectors.assert_vectors(bad, "e", "s")
    uneven = spark.createDataFrame([(1, [1.0], [0.0]), (2, [1.0, 2.0], [0.0])], "id long, e array<float>, s array<float>")
    with pytest.raises(ValueError):
        vectors.assert_vectors(uneven, "e")


def test_inserted_objects_are_found(spark, small):
    """Half of the objects built, the rest inserted in two steps: nothing is lost, nothing twice, and recall holds."""
    c = case(spark, small)
    parts = [c.objects.where(F.pmod(F.xxhash64("id"), F.lit(4)).isin(*k)) for k in ([0, 1], [2], [3])]
    for shards in (ShardParams(), ShardParams(2)):
        ix = index.build_index(parts[0], c.params, c.norm, shards)
        before = {(r.shard, r.src, r.dst) for r in ix.edges().collect()}
        for p in parts[1:]:
            ix = index.insert(ix, p.unionByName(parts[0].limit(5)))  # known ids are left out
        ids = [r.id for r in ix.nodes.where("level = 0").select("id").collect()]
        assert len(ids) == len(set(ids)) == c.n
        assert metrics.recall(index.topk(ix, c.queries, SearchParams(10, 100)), c.truth()).agg(F.avg("recall")).first()[0] >= 0.9
        assert metrics.reachability(ix).first().reached == c.n
        assert len(before & {(r.shard, r.src, r.dst) for r in ix.edges().collect()}) > 0
    full = index.insert(index.build_index(parts[0], c.params, c.norm), parts[1], max_rows=10)
    assert sorted(r.shard for r in full.shards.collect()) == [0, 1]
    with pytest.raises(Exception):
        index.insert(c.fixed(), parts[2].withColumn("id", F.col("id") + 10**6)).nodes.count()


def test_waves_make_a_graph_that_reaches_its_nodes(spark, small):
    c = case(spark, small)
    edges, seeds = bsp.build(c.objects, BuildParams(M=10, ef_c=40), c.norm, wave0=40)
    assert {r.src for r in edges.select("src").distinct().collect()} == {r.id for r in c.objects.select("id").collect()}
    assert edges.where("src = dst or lo < 0 or hi > 10000 or lo > hi").count() == 0
    hits = bsp.search(edges, c.objects, c.queries, seeds, c.norm, 10, 50)
    assert metrics.recall(hits, c.truth()).agg(F.avg("recall")).first()[0] >= 0.9
    assert bsp.build(c.objects.where("false"), BuildParams(), c.norm)[0].count() == 0


def test_waves_with_sent_vectors_are_those_of_joins(spark, small, monkeypatch):
    """Candidates found inside tasks make the graph that hops make, and no hop is written where the objects fit."""
    c = case(spark, small)
    p = BuildParams(M=6, ef_c=20)
    part = c.objects.where(F.pmod(F.xxhash64("id"), F.lit(3)) == 0)
    with monkeypatch.context() as m:
        m.setattr(bsp, "frontier_search", lambda *_: pytest.fail("candidates are found by hops"))
        got = sorted(map(tuple, bsp.build(part, p, c.norm, wave0=30)[0].collect()))
    monkeypatch.setattr(whole, "fits", lambda objects: False)
    assert got == sorted(map(tuple, bsp.build(part, p, c.norm, wave0=30)[0].collect()))


@pytest.mark.parametrize("twins", [False, True])
@pytest.mark.parametrize("params", [BuildParams(M=8, ef_c=40), BuildParams(M=8, ef_c=40, levels=True, pruning="rng")])
def test_one_search_has_the_results_of_all_ef(points, params, twins, monkeypatch):
    """Results and counts of a sweep are those of a search per ef; with twins, of a sweep of one ef. It does the work of the largest ef only."""
    ids, e, s, norm = points
    if twins:
        ids, e, s = np.arange(240), np.concatenate([e, e]), np.concatenate([s, s])
    g = kernel.build(ids, e, s, norm, params)
    rng, efs = np.random.default_rng(4), (10, 30, 20, 60, 110)
    for _ in range(10):
        qe, qs, a = rng.normal(size=8), rng.normal(size=2), float(rng.random())
        c: dict = {}
        starts = kernel.entry(g, qe, qs, a, c, True)
        got = kernel.sweep(g, qe, qs, a, starts, efs, True, True, c)
        for ef in efs:
            if twins:
                want, spent, _ = kernel.sweep(g, qe, qs, a, starts, [ef], True, True, c)[ef]
            else:
                want = kernel.best_first(g, qe, qs, a, starts, ef, True, True, None, spent := dict(c))
            assert got[ef][0] == want and got[ef][1] == spent
    spent = []
    measured = kernel.l2_rows
    monkeypatch.setattr(kernel, "l2_rows", lambda q, m: spent.append(len(m)) or measured(q, m))
    kernel.sweep(g, qe, qs, a, starts, [110], True, True, c)
    once = sum(spent)
    spent.clear()
    kernel.sweep(g, qe, qs, a, starts, efs, True, True, c)
    assert sum(spent) == once


def test_first_wave_searches_for_its_candidates(spark, small, monkeypatch):
    """The rows of the first wave are inserted by the search, as an insertion one by one leaves them; no table of pairs is made."""
    c = case(spark, small)
    p = BuildParams(M=6, ef_c=12)
    part = c.objects.where(F.pmod(F.xxhash64("id"), F.lit(4)) == 0)
    monkeypatch.setattr(exact, "pair_distances", lambda *_: pytest.fail("pairs are compared outright"))
    monkeypatch.setattr(bsp, "pair_distances", exact.pair_distances, raising=False)
    got = sorted(map(tuple, bsp.build(part, p, c.norm, wave0=10**6)[0].collect()))
    one = part.select("id", "e", "s").orderBy("id").toPandas()
    ids, e, s = one["id"].to_numpy(), np.array(one.e.tolist(), np.float64), np.array(one.s.tolist(), np.float64)
    g = kernel.build(ids, e, s, c.norm, p, np.lexsort((ids, hashing.mix(ids, p.seed))))
    want = [(ids[i], ids[x], lo, hi) for i in range(len(ids)) for x, lo, hi in zip(*map(np.ndarray.tolist, g.arcs(i)))]
    assert len(ids) > p.ef_c and got == sorted(want)


def test_large_shards_are_built_by_waves(spark, small, monkeypatch):
    """Of a shard only FIRST rows, but for chance, are inserted one by one; the rest is there all the same, whatever the number of tasks."""
    c = case(spark, small)
    monkeypatch.setattr(waves, "FIRST", 90)
    sizes = {0: c.n}
    dealt = {r.wave: r["count"] for r in waves.numbered(c.objects.withColumn("shard", F.lit(0)), sizes, c.params).groupBy("wave").count().collect()}
    assert sum(dealt.values()) == c.n and 60 < dealt[0] < 120 and set(dealt) == set(range(waves._waves(c.n) + 1))
    p = BuildParams(M=10, ef_c=40)
    for params, tasks in ((p, (1, 4)), (p.but(levels=True, pruning="rng"), (4,))):
        made = []
        for most in tasks:
            monkeypatch.setattr(waves, "COPIES", most)
            ix = index.build_index(c.objects, params, c.norm)
            made.append(sorted((r.shard, r.id, r.level, r.seed, tuple(r.dst), str(r.lo), str(r.hi), r.n_dist) for r in ix.nodes.collect()))
        assert made[0] == made[-1]
        rows = [r for r in made[0] if r[2] == 0]
        assert [r[1] for r in rows] == sorted(r.id for r in c.objects.select("id").collect())
        assert all(r[1] not in r[4] and len(set(r[4])) == len(r[4]) for r in made[0])
        assert ix.edges().where("lo < 0 or hi > 10000 or lo > hi").count() == 0
        assert metrics.recall(index.topk(ix, c.queries, SearchParams(10, 100)), c.truth()).agg(F.avg("recall")).first()[0] >= 0.9
        one = c.objects.select("id", "e", "s").orderBy("id").toPandas()
        ids, e, s = one["id"].to_numpy(), np.array(one.e.tolist(), np.float64), np.array(one.s.tolist(), np.float64)
        g = kernel.build(ids, e, s, c.norm, params, np.lexsort((ids, hashing.mix(ids, params.seed))))
        assert sorted(ids[g.seeds].tolist()) == [r[1] for r in rows if r[3]]


def test_measures_of_a_written_index_are_those_of_sql(spark, small, tmp_path):
    """Degrees, ranges, bytes, active edges and reachability, against SQL over the written nodes."""
    import duckdb

    c = case(spark, small)
    ix = c.index()
    ix.nodes.write.parquet(str(tmp_path / "nodes"))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW n AS SELECT * FROM '{tmp_path}/nodes/*.parquet'")
    con.execute("CREATE VIEW d AS SELECT id AS src, unnest(dst) AS dst, unnest(lo) AS lo, unnest(hi) AS hi FROM n WHERE level = 0")
    con.execute("CREATE VIEW e AS SELECT src, dst, unnest(lo) AS lo, unnest(hi) AS hi FROM d")
    one = lambda sql: con.execute(sql).fetchone()
    row = lambda df: tuple(df.first())
    assert row(metrics.degree(ix.edges(), ix.nodes)) == pytest.approx(one("SELECT count(*), sum(len(dst)), avg(len(dst)), max(len(dst)) FROM n WHERE level = 0"))
    assert row(metrics.range_stats(ix.edges())) == pytest.approx(one("SELECT count(*), avg(l), avg(k), avg(CASE WHEN l >= 1 THEN 1.0 ELSE 0.0 END) FROM (SELECT src, dst, sum(hi - lo) / 1e4 AS l, count(*) AS k FROM e GROUP BY ALL)"))
    assert row(metrics.index_size(ix)) == one("SELECT sum(4 * (len(e) + len(s))), sum(8 * len(dst)), sum(4 * len(flatten(lo))) FROM n")
    got = {(r.band, r.alpha): r.active_edges for r in metrics.active_degree(ix.edges(), c.queries.select("band", "alpha").distinct()).collect()}
    assert len(got) > 20
    for (_, alpha), n in got.items():
        assert n == one(f"SELECT count(*) FROM (SELECT DISTINCT src, dst FROM e WHERE lo <= {round(alpha * 10_000)} AND hi >= {round(alpha * 10_000)})")[0]
    reached = one("WITH RECURSIVE g AS (SELECT id FROM n WHERE seed UNION SELECT e.dst FROM g JOIN e ON e.src = g.id) SELECT count(*) FROM g")[0]
    assert row(metrics.reachability(ix)) == (c.n, reached)


def test_edges_chosen_from_pools_obey_their_rules(spark, small):
    """Range-gated and fixed-weight choices on the tables, against the rules point by point on a grid of weights."""
    from rangegraph.catalogue import core

    c = case(spark, small)
    rows = {}
    for r in c.objects.select("id", "e", "s").collect():
        rows[r.id] = (np.array(r.e, float), np.array(r.s, float))
    dist = lambda a, b: (float(np.linalg.norm(rows[a][0] - rows[b][0])) / c.norm.e, float(np.linalg.norm(rows[a][1] - rows[b][1])) / c.norm.s)
    chosen: dict = {}
    for r in core.range_prune(spark, small).collect():
        chosen.setdefault(r.src, {}).setdefault(r.dst, []).append((r.lo, r.hi))
    for p in sorted(chosen)[:25]:
        order = list(chosen[p])
        for x in order:
            away = dist(p, x)
            for a in np.linspace(0.003, 0.997, 41):
                mix = lambda d, a=a: a * d[0] + (1 - a) * d[1]
                removed = any(mix(dist(p, y)) < mix(away) - 1e-9 and mix(dist(y, x)) < mix(away) - 1e-9 for y in order if y != x)
                active = any(lo <= a * 10_000 <= hi for lo, hi in chosen[p][x])
                if not removed:  # no other edge stands in the way at this weight
                    assert active
    greedy: dict = {}
    for r in core.rng_greedy(spark, small).collect():
        greedy.setdefault(r.src, set()).add(r.dst)
    mid = lambda a, b: sum(dist(a, b)) / 2
    for p in sorted(greedy)[:25]:
        for x in greedy[p]:
            assert all(mid(y, x) >= mid(p, x) - 1e-9 for y in greedy[p] if y != x and mid(p, y) < mid(p, x))


def test_range_graph_of_all_candidates_is_that_of_all_pairs(spark):
    """Chosen node by node, with distances between candidates measured when needed; twins in one or both vectors too."""
    rng = np.random.default_rng(5)
    e, s = rng.normal(size=(90, 6)).astype(np.float32), rng.normal(size=(90, 2)).astype(np.float32)
    e[7], s[7], s[20] = e[8], s[8], s[21]
    o = spark.createDataFrame([(i, e[i].tolist(), s[i].tolist()) for i in range(90)], "id long, e array<float>, s array<float>")
    norm = normalisers.exact(o)
    rows = exact.pair_distances(o, norm).join(o.withColumnRenamed("id", "x"), "x")
    for witness in ("any", "active"):
        want = sorted(map(tuple, prune.range_gated(rows, norm, 10**9, 0.0, witness=witness).collect()))
        assert sorted(map(tuple, whole.exact_range_graph(o, norm, witness).collect())) == want


def test_range_graph_needs_no_table_of_pairs(spark, small, monkeypatch):
    """The table of all pairs was 24 bytes for every two objects; nothing of its size is written now."""
    from rangegraph.catalogue import core

    monkeypatch.setattr(core, "all_pairs", lambda c: pytest.fail("all pairs are written"))
    c = Case(spark, small, "emb_geo")
    assert core.range_graph(c, "active").select("src").distinct().count() == c.n


def test_greedy_reach_needs_no_table_of_pairs(spark, small, monkeypatch):
    from rangegraph.catalogue import core

    c = Case(spark, small, "emb_geo")
    monkeypatch.setattr(core, "all_pairs", lambda c: pytest.fail("all pairs are written"))
    monkeypatch.setattr(core, "case", lambda *_: c)
    rows = core.greedy_reach(spark, small).collect()
    assert len(rows) == 10 and all(r.reached == 1.0 for r in rows if r.witness == "active")


def test_neighbourhood_graph_without_a_table_of_pairs(spark, small, monkeypatch):
    from rangegraph.catalogue import core

    monkeypatch.setattr(core, "case", lambda *_: c)
    c = Case(spark, small, "emb_geo")
    pairs = exact.pair_distances(c.objects, c.norm)
    want = sorted((r.p, r.x, round(r.d, 6)) for r in prune.rng(pairs, 0.5).collect())
    monkeypatch.setattr(core, "all_pairs", lambda c: pytest.fail("all pairs are written"))
    assert sorted((r.p, r.x, round(r.d, 6)) for r in core.rng_edges(spark, small).collect()) == want


def test_neighbourhood_graph_measures_few_pairs_more_than_once(spark, monkeypatch):
    """Nodes of a block remove each other's pairs with the distances that are there; few pairs are measured again. Twins are there too."""
    rng = np.random.default_rng(6)
    e, s = rng.normal(size=(700, 12)).astype(np.float32).astype(float), rng.normal(size=(700, 3)).astype(np.float32).astype(float)
    e[9], s[9], e[40] = e[8], s[8], e[41]
    ids = np.arange(700) * 3
    every, cells = whole.All(ids, e, s, Norm(9.0, 6.0)), []
    x_e, x_s = every.cross(np.arange(700), np.arange(700))
    dist = np.round(0.3 * x_e + 0.7 * x_s, 9)
    want = {(int(ids[p]), int(ids[x])) for p, x in zip(*np.nonzero(prune.rng_edges_block(dist)))}
    measured = whole.All.cross
    monkeypatch.setattr(whole.All, "cross", lambda self, a, b: cells.append(len(a) * len(b)) or measured(self, a, b))
    found = {(int(ids[p]), int(ids[x])): n for p, xs, _, near in whole.rng_candidates(every, ids, 0.3, 9) for x, n in zip(xs, near)}
    assert want <= set(found) and len(found) < 2 * len(want) and sum(cells) < 700 * 700 * 4
    for (p, x), n in found.items():
        assert n >= (dist[p // 3] < dist[p // 3, x // 3]).sum()
    objects = spark.createDataFrame([(int(i), a.tolist(), b.tolist()) for i, a, b in zip(ids, e, s)], "id long, e array<double>, s array<double>")
    rows = whole.rng_edges(objects, Norm(9.0, 6.0), 0.3).collect()
    assert {(r.p, r.x) for r in rows} == want and len(rows) == len(want)
    assert all(r.d == pytest.approx(dist[r.p // 3, r.x // 3], abs=1e-9) for r in rows)


@pytest.mark.parametrize("name", ["pareto_frontier", "pareto_layers", "pareto_layers_by_peeling", "pruned_union", "range_length", "dominance_pairs"])
def test_frontiers_need_no_table_of_pairs(spark, small, monkeypatch, name):
    """Their rows are held against SQL elsewhere; here, that the pairs of queries and objects are not written."""
    from rangegraph.catalogue import core

    c = Case(spark, small, "emb_geo")
    monkeypatch.setattr(core, "pairs_of", lambda c: pytest.fail("all pairs are written"))
    monkeypatch.setattr(core, "case", lambda *_: c)
    rows = core.QUERIES[name](spark, small).collect()
    assert len({r.p for r in rows}) == c.queries.where("band = 0").count()


@pytest.mark.parametrize("name", ["range_prune", "rng_greedy"])
def test_candidates_of_all_pairs_without_their_table(spark, small, monkeypatch, name):
    from rangegraph.catalogue import core

    c = Case(spark, small, "emb_geo", BuildParams(M=5, ef_c=30))
    monkeypatch.setattr(core, "case", lambda *_: c)
    rows = core.candidates(c, 30)
    want = prune.range_gated(rows, c.norm, 5, c.params.th) if name == "range_prune" else prune.rng_greedy(rows, c.norm, 0.5, 5)
    want = sorted(map(tuple, want.collect()))
    monkeypatch.setattr(core, "all_pairs", lambda c: pytest.fail("all pairs are written"))
    assert sorted(map(tuple, core.QUERIES[name](spark, small).collect())) == want


def test_triangles_join_no_vectors(spark, small, monkeypatch):
    """Vectors of both ends were joined to every triangle (256 bytes each in the workload of the queries)."""
    from rangegraph.catalogue import core

    c = Case(spark, small, "emb_geo")
    rows = core.triangles(c)
    assert "Join" not in rows._jdf.queryExecution().executedPlan().toString()
    got = sorted(map(tuple, rows.collect()))
    monkeypatch.setattr(core.whole, "fits", lambda objects: False)
    want = sorted(map(tuple, core.triangles(c).collect()))
    assert [r[:3] for r in got] == [r[:3] for r in want] and np.allclose(np.array(got), np.array(want), atol=1e-9)


def test_distances_of_all_queries_are_measured_once_per_vector(spark, small, monkeypatch):
    """Each query's five weights share its two vectors; the distances were made anew for every weight and object."""
    from rangegraph.catalogue import core

    monkeypatch.setattr(vectors, "hybrid", lambda *_: pytest.fail("distances are made for every weight"))
    c = case(spark, small)
    rows = core.hybrid_distance(spark, small)
    assert rows.count() == c.n * c.queries.count() == rows.select("qid", "band", "id").distinct().count()


def test_removed_weights_are_gathered_without_a_table_of_triangles(spark, small, monkeypatch):
    """Every triangle was shuffled to the edge that it may remove."""
    from rangegraph.catalogue import core

    c = Case(spark, small, "emb_geo")
    monkeypatch.setattr(core, "case", lambda *_: c)
    rows = core.range_length(spark, small)
    assert rows._jdf.queryExecution().executedPlan().toString().count("Exchange") == 1  # the nodes are dealt, no more
    got = {(r.p, r.x): r.length for r in rows.collect()}
    monkeypatch.setattr(core.whole, "fits", lambda objects: False)
    want = {(r.p, r.x): r.length for r in core.range_length(spark, small).collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 2e-6 for k in want)


@pytest.mark.parametrize("method", ["quad_ring_topk", "pivot_topk"])
def test_tasks_share_the_queries_of_a_part(spark, small, monkeypatch, method):
    """One part's queries all went to one task, and trees were read leaf by leaf or row by row; results are the exact ones."""
    from rangegraph.operators import spatial

    for name in ("nearest", "leaves"):
        monkeypatch.setattr(spatial.RectTree if name == "nearest" else spatial.QuadTree, name, lambda *_: pytest.fail("a tree is read one by one"))
    monkeypatch.setattr(spatial, "BLOCK_QUERIES", 5)
    monkeypatch.setattr(spatial, "merged", lambda found: found)
    c = case(spark, small, "emb_geo")
    found = getattr(spatial, method)(c.objects, c.queries, c.norm).withColumn("task", F.spark_partition_id()).collect()
    assert len({r.task for r in found}) > 1
    got = {(r.qid, r.band): set() for r in found}
    for r in found:
        got[r.qid, r.band].add(r.id)
    want: dict = {}
    for r in c.truth().collect():
        want.setdefault((r.qid, r.band), set()).add(r.id)
    assert got == want


def test_one_statement_needs_no_row_per_pair(spark, small):
    """Every query's five weights met every object as a row with both vectors; now blocks meet, and a query's vectors once."""
    from rangegraph.catalogue import relational

    plan = relational.cte_multi(spark, small)._jdf.queryExecution().optimizedPlan().toString()
    assert "hybrid_lists" in plan and "q_ids" in plan
