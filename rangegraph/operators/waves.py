"""The graphs of large shards, built by many tasks.

The first rows of a shard, in the order of a seeded hash, are inserted one by one in one task. The others come in waves, each half
as large as all before it. A task has the graph before a wave whole and some of the wave's nodes, and finds and chooses their edges
as an insertion does. Then every node that was chosen chooses again, once, among its neighbours and all that chose it. Nodes of
a wave that such a choice keeps are met by the others that chose the same node: in the next round those choose again with them.
So no step is quadratic in a wave, and the number of tasks does not change the graph.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import mix
from ..functions.vectors import matrix
from ..schema import NODES, SCALE, BuildParams, Norm
from ..storage import Steps, stash
from . import kernel
from .prune import FULL, params_rule

FIRST = 2_500  # rows of a shard that are inserted one by one
GROWTH = 1.5  # rows of a shard after a wave to those before it
COPIES = 8  # at most so many tasks have a shard's graph
KEY = ["shard", "id", "level"]
CHOSEN = "shard int, id long, level int, dst array<long>, lo array<array<smallint>>, hi array<array<smallint>>, fresh array<boolean>, isnew boolean, n_dist long"
REFRESHED = NODES + ", askers array<long>, kept array<long>"
_ENDS = pa.list_(pa.list_(pa.int16()))


def _stored(free) -> tuple[list, list]:
    return [[int(np.floor(i * SCALE)) for i, _ in f] for f in free], [[int(np.ceil(j * SCALE)) for _, j in f] for f in free]


def _waves(n: int) -> int:
    """Waves after the first rows of a shard of n."""
    return max(0, int(np.ceil(np.log(max(n, 1) / FIRST) / np.log(GROWTH))))


def numbered(placed: DataFrame, sizes: dict[int, int], params: BuildParams) -> DataFrame:
    """placed with `wave`, by ranges of the hash that orders a shard's rows."""
    last = {shard: _waves(n) for shard, n in sizes.items()}

    def run(batches):
        for b in batches:
            u = (mix(b.column("id").to_numpy(), params.seed) >> np.uint64(11)).astype(np.float64) / 2.0**53
            shard = b.column("shard").to_numpy()
            rows, most = (np.array([d[x] for x in shard.tolist()], np.int64) for d in (sizes, last))
            wave = np.ceil(np.log(np.maximum(u * rows / FIRST, 1.0)) / np.log(GROWTH))
            yield b.append_column("wave", pa.array(np.minimum(wave, most).astype(np.int32)))

    rows = placed.select("shard", "id", F.col("e").cast("array<float>").alias("e"), F.col("s").cast("array<float>").alias("s"))
    return rows.mapInArrow(run, "shard int, id long, e array<float>, s array<float>, wave int")


def build(placed: DataFrame, sizes: dict[int, int], params: BuildParams, norm: Norm, first, load) -> DataFrame:
    """NODES of all shards. first: a shard's table of rows to its nodes, one by one; load: a shard's nodes to a graph to be read."""
    spark = placed.sparkSession
    rows = stash(numbered(placed, sizes, params), "waves")
    copies = max(1, min(COPIES, spark.sparkContext.defaultParallelism // max(1, len(sizes))))
    copy = F.pmod(F.xxhash64("id"), F.lit(copies)).cast("int").alias("copy")
    every = F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("copy")
    steps, graphs = Steps(spark, "met"), Steps(spark, "graph")
    nodes, late = graphs.write(rows.where("wave = 0").drop("wave").groupBy("shard").applyInArrow(first, NODES)), None
    for wave in range(1, max(map(_waves, sizes.values())) + 2):  # in the last round nodes only meet
        asked = rows.where(F.col("wave") == wave).select("shard", "id", F.lit(-1).alias("level"), "e", "s", F.lit(None).cast("array<long>").alias("met"))
        if late is not None:
            none = F.lit(None).cast("array<float>")
            asked = asked.unionByName(late.select(*KEY, none.alias("e"), none.alias("s"), "met"))
        chosen = steps.write(nodes.select("*", every).groupBy("shard", "copy").cogroup(asked.select("*", copy).groupBy("shard", "copy")).applyInArrow(_choosing(params, norm, load), CHOSEN))
        near = chosen.select("shard", "level", F.col("id").alias("src"), "isnew", F.explode(F.arrays_zip("dst", "lo", "hi", "fresh")).alias("z")).where("z.fresh")
        back = near.groupBy("shard", F.col("z.dst").alias("id"), "level").agg(F.sort_array(F.collect_list(F.struct("src", "isnew", F.col("z.lo").alias("lo"), F.col("z.hi").alias("hi")))).alias("back"))
        arcs = [*KEY, "dst", "lo", "hi", "n_dist"]
        same = nodes.select(*arcs).join(chosen.select(*KEY), KEY, "left_anti").unionByName(chosen.select(*arcs))
        work = same.join(back, KEY, "left").select("*", copy)
        vectors = rows.where(F.col("wave") <= wave).select("shard", "id", "e", "s", every)
        out = graphs.write(vectors.groupBy("shard", "copy").cogroup(work.groupBy("shard", "copy")).applyInArrow(_refreshing(params, norm), REFRESHED))
        met = out.where("size(kept) > 0").select("shard", "level", F.explode("askers").alias("id"), "kept").groupBy(*KEY).agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("kept")))).alias("met"))
        nodes, late = out.drop("askers", "kept"), met
    return nodes


def _choosing(params: BuildParams, norm: Norm, load):
    """Edges of new nodes in the graph before them, and those of nodes of the last wave anew, with the ones they met."""

    def run(nodes: pa.Table, asked: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        if nodes.num_rows and asked.num_rows:
            g = load(nodes, norm)
            is_new = asked.column("level").to_numpy() < 0
            rows += _new(g, params, asked.filter(pa.array(is_new)))
            if not is_new.all():
                spent = dict(zip(zip(nodes.column("id").to_pylist(), nodes.column("level").to_pylist()), nodes.column("n_dist").to_pylist()))
                rows += _again(g, params, asked.filter(pa.array(~is_new)), spent)
            rows = [(nodes.column("shard")[0].as_py(), *r) for r in rows]
        types = [pa.int32(), pa.int64(), pa.int32(), pa.list_(pa.int64()), _ENDS, _ENDS, pa.list_(pa.bool_()), pa.bool_(), pa.int64()]
        return pa.table({f.split()[0]: pa.array([r[i] for r in rows], t) for i, (f, t) in enumerate(zip(CHOSEN.split(", "), types))})

    return run


def _new(g: kernel.Graph, params: BuildParams, asked: pa.Table):
    ids, qe, qs = asked.column("id").to_numpy(), matrix(asked.column("e")), matrix(asked.column("s"))
    if params.levels:
        level, pick = kernel.node_levels(ids, params.M, params.seed), params_rule(params.but(pruning="rng"))
        top = max(0, len(g.levels) - 1)
    else:
        pick = params_rule(params)
    for i, p in enumerate(ids.tolist()):
        before = g.n_dist
        if not params.levels:
            pool, de, ds = kernel.candidates(g, qe[i], qs[i], g.seeds, params)
            places, free = pick(de, ds, g.ids[pool], g.e[pool], g.s[pool], g.norm)
            dst = g.ids[pool[places]].tolist()
            yield p, 0, dst, *_stored(free), [True] * len(dst), True, g.n_dist - before
            continue
        for k in range(top + 1, int(level[i]) + 1):
            yield p, k, [], [], [], [], True, 0
        at = g.seeds
        for k in range(top, -1, -1):
            c: dict = {}
            got = kernel.best_first(g, qe[i], qs[i], params.alpha0, at, params.ef_c if k <= level[i] else 1, False, False, g.levels[k] if k else None, c)
            g.n_dist += c["n_dist"]
            at = np.array([x for _, x in got], np.int64)
            if k <= level[i]:
                de, ds = g.to_query(qe[i], qs[i], at)
                dst = g.ids[at[pick(de, ds, g.ids[at], g.e[at], g.s[at], g.norm)[0]]].tolist()
                yield p, k, dst, *_stored([FULL] * len(dst)), [True] * len(dst), True, (g.n_dist - before) if k == 0 else 0


def _again(g: kernel.Graph, params: BuildParams, asked: pa.Table, spent: dict):
    pick = params_rule(params.but(pruning="rng") if params.levels else params)
    for p, k, met in zip(asked.column("id").to_pylist(), asked.column("level").to_pylist(), asked.column("met").to_pylist()):
        at = int(np.searchsorted(g.ids, p))
        near = np.unique((g.arcs(at) if k == 0 else g.levels[k].get(at, kernel.NO_ARCS))[0])
        pool = np.union1d(near, np.searchsorted(g.ids, np.array(met, np.int64)))
        pool = pool[pool != at]
        before = g.n_dist
        de, ds = g.pair(at, pool)
        places, free = pick(de, ds, g.ids[pool], g.e[pool], g.s[pool], g.norm)
        dst = pool[places]
        yield p, k, g.ids[dst].tolist(), *_stored(free), (~np.isin(dst, near)).tolist(), False, spent[p, k] + g.n_dist - before


def _refreshing(params: BuildParams, norm: Norm):
    """All nodes with their vectors; those that were chosen choose among their neighbours and the ones that chose them."""

    def run(vectors: pa.Table, work: pa.Table) -> pa.Table:
        vectors = vectors.sort_by("id")
        ids = vectors.column("id").to_numpy()
        g = kernel.Graph(ids, matrix(vectors.column("e")), matrix(vectors.column("s")), norm)
        seeds = ids[kernel.entries(ids, g.e, g.s, norm, params)] if len(ids) else ids
        touched = np.asarray(work.column("back").is_valid())
        names = ["shard", "id", "level", "dst", "lo", "hi", "n_dist"]
        quiet = work.filter(pa.array(~touched)).select(names)
        none = pa.array([[]] * quiet.num_rows, pa.list_(pa.int64()))
        parts = [quiet.append_column("askers", none).append_column("kept", none)]
        rows = [_refreshed(g, params, *r) for r in zip(*(work.filter(pa.array(touched)).column(c).to_pylist() for c in (*names, "back")))]
        parts.append(pa.table({f.name: pa.array([r[i] for r in rows], f.type) for i, f in enumerate(parts[0].schema)}))
        out = pa.concat_tables(parts)
        base = out.column("level").to_numpy() == 0
        done = []
        for level0 in (True, False):
            t = out.filter(pa.array(base == level0))
            at = pa.array(np.searchsorted(ids, t.column("id").to_numpy()))
            for c in ("e", "s"):
                t = t.append_column(c, vectors.column(c).take(at) if level0 else pa.array([[]] * t.num_rows, pa.list_(pa.float32())))
            t = t.append_column("seed", pa.array(np.isin(t.column("id").to_numpy(), seeds)))
            done.append(t.select([f.split()[0] for f in REFRESHED.split(", ")]))
        return pa.concat_tables([t.cast(done[0].schema) for t in done])

    return run


def _refreshed(g: kernel.Graph, params: BuildParams, shard, p, level, dst, lo, hi, n_dist, back) -> tuple:
    at = int(np.searchsorted(g.ids, p))
    have = set(dst)
    back = [b for b in back if b["src"] not in have]  # edges both ways that were chosen in one round
    pool = np.searchsorted(g.ids, np.array(dst + [b["src"] for b in back], np.int64))
    most = params.M * (params.level0_factor if level == 0 else 1) if params.levels else params.M
    rule = params.but(pruning="rng", M=most) if params.levels else params
    full = [[0]] * len(pool), [[SCALE]] * len(pool)
    if params.levels and len(pool) <= most or params.pruning == "none" and len(pool) <= params.M:
        lo, hi = full
    elif not params.levels and params.reverse == "append" and len(pool) <= 2 * params.M:
        lo, hi = lo + [b["lo"] for b in back], hi + [b["hi"] for b in back]
    else:
        before = g.n_dist
        de, ds = g.pair(at, pool)
        n_dist += g.n_dist - before
        places, free = params_rule(rule)(de, ds, g.ids[pool], g.e[pool], g.s[pool], g.norm)
        pool = pool[places]
        lo, hi = _stored(free)
    near = g.ids[pool].tolist()
    askers = [b["src"] for b in back if b["isnew"]]
    kept = set(near) & set(askers)
    if not kept or len(askers) < 2:
        askers, kept = [], set()
    return shard, p, level, near, lo, hi, n_dist, askers, sorted(kept)
