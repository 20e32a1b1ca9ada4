"""Building and searching in supersteps, without shards. For graphs that are not sharded, and to see each hop.

Each hop of a search joins the state with the edges, then with the vectors; the state is written after each hop, so a lost
executor costs one hop. The driver sees one count per hop. A build goes by waves; where the objects fit into what is sent
(whole.fits), the nodes of a wave are dealt and search the graph before it inside their tasks, else they search by hops.
"""

from __future__ import annotations

from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import mix
from ..functions.vectors import hybrid, l2, l2_rows, matrix
from ..schema import BuildParams, Norm
from ..storage import Steps, stash
from . import kernel, pareto, prune, whole
from .exact import final_topk


def search(edges: DataFrame, objects: DataFrame, queries: DataFrame, seeds: DataFrame, norm: Norm, k: int = 10, ef: int = 10, most: int | None = None) -> DataFrame:
    """qid, band, rank, id, dist. Each hop expands all unexpanded nodes among the ef best of a query over active edges.

    edges: src, dst, lo, hi; seeds: id (few). Visits at least what the one-by-one search does. Ends when no node
    is left to expand; more hops than `most` are an error.
    """
    from ..schema import SCALE

    q = queries.select("qid", "band", "alpha", F.col("e").alias("qe"), F.col("s").alias("qs"))
    vectors = objects.select("id", "e", "s")

    def scored(rows: DataFrame) -> DataFrame:
        d = rows.join(vectors, "id").join(q, ["qid", "band"])
        return d.select("qid", "band", "id", hybrid("e", "s", "qe", "qs", F.col("alpha"), norm.e, norm.s).alias("dist"))

    start = q.select("qid", "band").join(seeds.select("id").distinct(), F.lit(True))
    steps = Steps(objects.sparkSession, "hop")
    state = steps.write(scored(start).withColumn("expanded", F.lit(False)))
    best = Window.partitionBy("qid", "band").orderBy("dist", "id")
    for hops in count():
        ranked = state.withColumn("r", F.row_number().over(best))
        now = ranked.where(F.col("r") <= ef).where(~F.col("expanded")).select("qid", "band", "id")
        if not now.limit(1).count():
            break
        _within(hops, most)
        at = F.round(F.col("alpha") * SCALE)
        arcs = now.join(q.select("qid", "band", "alpha"), ["qid", "band"]).join(edges.select(F.col("src").alias("id"), "dst", "lo", "hi"), "id").where((F.col("lo") <= at) & (at <= F.col("hi")))
        new = arcs.select("qid", "band", F.col("dst").alias("id")).distinct().join(state.select("qid", "band", "id"), ["qid", "band", "id"], "left_anti")
        marked = state.join(now.withColumn("now", F.lit(True)), ["qid", "band", "id"], "left").select("qid", "band", "id", "dist", (F.col("expanded") | F.coalesce("now", F.lit(False))).alias("expanded"))
        state = steps.write(marked.unionByName(scored(new).withColumn("expanded", F.lit(False))))
    return final_topk(state.select("qid", "band", "id", "dist"), k)


def _within(hops: int, most: int | None) -> None:
    if most is not None and hops >= most:
        raise RuntimeError(f"nodes are left to expand after {most} hops")


STATE = "p long, x long, de double, ds double, layer int, explored boolean, now boolean"


def _layered(t: pa.Table, ef: int) -> pa.Table:
    """The pool of one node layered anew and cut to ef; the nearest layer with unexplored nodes is up next. Cut rows keep layer 0."""
    de, ds, x = (t.column(c).to_numpy() for c in ("de", "ds", "x"))
    layer, explored = t.column("layer").to_numpy().copy(), t.column("explored").to_numpy(zero_copy_only=False).copy()
    pool = np.flatnonzero(layer != 0)
    fresh = pareto.layer_block(de[pool], ds[pool], x[pool])
    keep = pareto.keep_bound(fresh, ef)
    layer[pool] = np.where(keep, fresh, 0)
    left = ~explored & (layer > 0)
    now = left & (layer == layer[left].min()) if left.any() else left
    return pa.table({"p": t.column("p"), "x": t.column("x"), "de": t.column("de"), "ds": t.column("ds"), "layer": pa.array(layer.astype(np.int32)), "explored": pa.array(explored | now), "now": pa.array(now)})


def frontier_search(edges: DataFrame, objects: DataFrame, targets: DataFrame, seeds: DataFrame, norm: Norm, ef: int, most: int | None = None) -> DataFrame:
    """p, x, de, ds, layer: candidates of each target (id, e, s) found over the edges (src, dst). One job per hop,
    until no node is left to explore; more hops than `most` are an error."""
    t = targets.select(F.col("id").alias("p"), F.col("e").alias("pe"), F.col("s").alias("ps"))
    vectors = objects.select(F.col("id").alias("x"), "e", "s")
    arcs = stash(edges.select("src", "dst").distinct(), "arcs")
    steps = Steps(objects.sparkSession, "hop")

    def entered(rows: DataFrame) -> DataFrame:
        d = rows.join(vectors, "x").join(t, "p")
        return d.select("p", "x", (l2("e", "pe") / norm.e).alias("de"), (l2("s", "ps") / norm.s).alias("ds"), F.lit(-1).alias("layer"), F.lit(False).alias("explored"), F.lit(False).alias("now"))

    def hop(state: DataFrame) -> DataFrame:
        return steps.write(state.groupBy("p").applyInArrow(lambda g: _layered(g, ef), STATE))

    state = hop(entered(t.select("p").join(seeds.select(F.col("id").alias("x")).distinct(), F.lit(True))))
    for hops in count():
        if not state.where("now").limit(1).count():
            break
        _within(hops, most)
        new = state.where("now").select("p", F.col("x").alias("src")).join(arcs, "src").select("p", F.col("dst").alias("x")).distinct().where("p <> x")
        state = hop(state.unionByName(entered(new.join(state.select("p", "x"), ["p", "x"], "left_anti"))))
    return state.where("layer > 0").select("p", "x", "de", "ds", "layer")


WHOLE = 1 << 30  # of the hash that orders the rows


class _Joined:
    """Candidates of a wave by hops, distances and choices by joins with the vectors."""

    def __init__(self, objects: DataFrame, params: BuildParams, norm: Norm):
        self.objects, self.params, self.norm = objects, params, norm

    def near(self, edges: DataFrame, have: DataFrame, wave: DataFrame, starts: DataFrame) -> DataFrame:
        return frontier_search(edges, have, wave, starts, self.norm, self.params.ef_c).select("p", "x", "de", "ds")

    def measured(self, pairs: DataFrame) -> DataFrame:
        a = self.objects.select(F.col("id").alias("p"), F.col("e").alias("pe"), F.col("s").alias("ps"))
        b = self.objects.select(F.col("id").alias("x"), "e", "s")
        return pairs.join(a, "p").join(b, "x").select("p", "x", (l2("e", "pe") / self.norm.e).alias("de"), (l2("s", "ps") / self.norm.s).alias("ds"))

    def choose(self, pairs: DataFrame) -> DataFrame:
        rows = pairs.join(self.objects.select(F.col("id").alias("x"), "e", "s"), "x").select("p", "x", "de", "ds", "e", "s")
        return prune.range_gated(rows, self.norm, self.params.M, self.params.th, self.params.cap, self.params.witness, self.params.ties)


class _Sent:
    """The same with all vectors in the tasks: only ids are dealt, and a wave takes one job to find its candidates."""

    def __init__(self, objects: DataFrame, params: BuildParams, norm: Norm):
        self.params, self.norm = params, norm
        self.tasks = objects.sparkSession.sparkContext.defaultParallelism
        self.ids, self.vectors = whole.send(objects)

    def near(self, edges: DataFrame, have: DataFrame, wave: DataFrame, starts: DataFrame) -> DataFrame:
        arcs = edges.select("src", "dst").distinct().toArrow()
        src, dst = (np.searchsorted(self.ids, arcs.column(c).to_numpy()).astype(np.int32) for c in ("src", "dst"))
        order = np.lexsort((dst, src))
        first = np.searchsorted(src[order], np.arange(1, len(self.ids)))
        begin = np.sort(np.searchsorted(self.ids, starts.toArrow().column("id").to_numpy()))
        graph = edges.sparkSession.sparkContext.broadcast((first, dst[order], begin))
        vectors, norm, params = self.vectors, self.norm, self.params

        def run(batches):
            g = None
            for b in batches:
                if g is None:
                    every = whole.All.of(vectors.value, norm)
                    g = kernel.Graph(every.ids, every.e, every.s, norm)
                    g.nbrs = np.split(graph.value[1], graph.value[0])
                for p in b.column("id").to_numpy().tolist():
                    i = np.searchsorted(g.ids, p)
                    pool = kernel.frontier_search(g, g.e[i], g.s[i], graph.value[2], params.ef_c, params.ties)[0]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(pool), p)), pa.array(g.ids[pool])], names=["p", "x"])

        return wave.select("id").repartition(self.tasks, "id").mapInArrow(run, "p long, x long")

    def measured(self, pairs: DataFrame) -> DataFrame:
        return pairs.select("p", "x")

    def choose(self, pairs: DataFrame) -> DataFrame:
        vectors, norm, params = self.vectors, self.norm, self.params

        def run(batches):
            every = None
            for b in batches:
                if every is None:
                    every = whole.All.of(vectors.value, norm)
                rows: tuple[list, ...] = ([], [], [], [])
                for p, xs in zip(b.column("p").to_pylist(), b.column("xs")):
                    x, i = np.sort(xs.values.to_numpy()), np.searchsorted(every.ids, p)
                    at = np.searchsorted(every.ids, x)
                    de, ds = l2_rows(every.e[i], every.e[at]) / norm.e, l2_rows(every.s[i], every.s[at]) / norm.s
                    got = prune.gate_block(de, ds, pareto.layer_block(de, ds, x, params.ties), x, lambda at=at: every.cross(at, at), params.M, params.th, params.cap, params.witness)
                    for column, more in zip(rows, prune.edge_rows([p] * len(got), [int(x[k]) for k, _ in got], [r for _, r in got])):
                        column += more
                yield from prune._table(*rows).to_batches()

        return pairs.select("p", "x").repartition(self.tasks, "p").groupBy("p").agg(F.collect_list("x").alias("xs")).mapInArrow(run, prune.EDGES)


def build(objects: DataFrame, params: BuildParams, norm: Norm, wave0: int = 128, growth: int = 2) -> tuple[DataFrame, DataFrame]:
    """(edges src, dst, lo, hi; seeds) by waves: the nodes of a wave see the graph before it and each other.

    Waves are ranges of a seeded hash, each `growth` times as large as all before it, so no task orders the table. The
    first, of about wave0 rows, is inserted node by node in one task, so its nodes find their candidates by the same search
    as all others. Later ones search the graph before them; nodes of a wave then meet over the neighbours they share, in
    two steps along edges whose number per node is bounded. The rim of the whole table serves as seeds.
    """
    from . import seeds as sd

    spark = objects.sparkSession
    placed = stash(objects.select("id", "e", "s").withColumn("u", F.pmod(F.xxhash64("id", F.lit(params.seed)), F.lit(WHOLE))), "waves")
    total, low = placed.count(), 0
    if not total:
        return spark.createDataFrame([], prune.EDGES), placed.select("id")
    way = _Sent(placed, params, norm) if whole.fits(placed) else _Joined(placed, params, norm)
    rim = stash(sd.rim(objects, norm).select("id"), "rim")
    edges, steps = None, Steps(spark, "edges")
    share = min(1.0, wave0 / max(total, 1))
    while low < WHOLE:
        high = WHOLE if share >= 1 else int(share * WHOLE)
        wave, have = placed.where((F.col("u") >= low) & (F.col("u") < high)), placed.where(F.col("u") < low)
        low, share = high, share * growth
        if not wave.limit(1).count():
            continue
        if edges is None:
            edges = steps.write(_inserted(wave, params, norm))
            continue
        starts = have.join(rim, "id", "left_semi").select("id")
        starts = starts if starts.limit(1).count() else have.orderBy("u", "id").limit(1).select("id")
        found = stash(way.near(edges, have, wave, starts), "found")
        edges = steps.write(_joined(edges, wave, found, way))
    return edges, rim


def _inserted(wave: DataFrame, params: BuildParams, norm: Norm) -> DataFrame:
    """The edges of a first wave (id, e, s): its rows inserted one after the other, in the order of a seeded hash."""

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        ids = t.column("id").to_numpy()
        g = kernel.build(ids, matrix(t.column("e")), matrix(t.column("s")), norm, params, np.lexsort((ids, mix(ids, params.seed))))
        src = np.repeat(ids, [len(x) for x in g.nbrs])
        return prune._table(*prune.edge_rows(src.tolist(), ids[np.concatenate(g.nbrs)].tolist(), [r for p in g.ranges for r in p]))

    return wave.select("id", "e", "s", F.lit(0).alias("k")).groupBy("k").applyInArrow(run, prune.EDGES)


def _joined(edges: DataFrame, wave: DataFrame, found: DataFrame, way: _Joined | _Sent) -> DataFrame:
    """The edges with those of a wave, from its candidates in the graph before it: chosen once, and again with the nodes of the wave that were met."""
    chosen = stash(way.choose(found), "wave")
    first = stash(_refreshed(edges, chosen, way), "first")
    back = first.select(F.col("src").alias("y"), F.col("dst").alias("x")).distinct().join(wave.select(F.col("id").alias("x")), "x", "left_semi")
    met = chosen.select(F.col("src").alias("p"), F.col("dst").alias("y")).distinct().join(back, "y").where("p <> x").select("p", "x").distinct()
    again = stash(way.choose(found.unionByName(way.measured(met))), "wave")
    return _refreshed(edges, again, way)


def _refreshed(edges: DataFrame, chosen: DataFrame, way: _Joined | _Sent) -> DataFrame:
    """The edges with those of new nodes, and with every touched node's choice made anew."""
    pair = lambda df: df.select(F.col("src").alias("p"), F.col("dst").alias("x")).distinct()
    back = chosen.select(F.col("dst").alias("p"), F.col("src").alias("x")).distinct()
    touched = back.select("p").distinct()
    pool = back.unionByName(pair(chosen)).unionByName(pair(edges))
    anew = way.choose(way.measured(pool.distinct().join(touched, "p", "left_semi")))
    return anew.unionByName(chosen.unionByName(edges).join(touched.select(F.col("p").alias("src")), "src", "left_anti"))
