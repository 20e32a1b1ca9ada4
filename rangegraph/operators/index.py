"""Sharded indexes: building, storing, routing, searching.

Each shard holds its own graph, of a bounded number of rows, so building is one shuffle by shard and one
task per shard (a large one goes on by waves), and a search reads the shards it is routed to. A shard's lower bound of distance holds for
every weight (triangle inequality per modality), so one layout serves all weights.

Routing moves numbers only (query, shard, bound); vectors are joined to what is left after the bounds have pruned.
A shard is read as flat arrays, once per task, for all settings of a sweep. With fewer shards than cores several
tasks share a shard's queries.
"""

from __future__ import annotations

import json
import time
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import mix
from ..functions.vectors import assert_vectors, l2_block, l2_rows, matrix
from ..schema import NODES, SCALE, BuildParams, Norm, SearchParams, ShardParams
from ..storage import stash
from . import kernel, waves
from .exact import final_topk

FOUND = "qid long, band int, ef int, id long, dist double, shard int, n_dist long, hops long, scanned long, gated long, stopped long, seconds double"
SHARDS = "shard int, n long, ce array<double>, cs array<double>, re double, rs double"
ROUTE_BYTES = 64_000_000
NAMES = [f.split()[0] for f in NODES.split(", ")]


@dataclass
class Index:
    """A built index. nodes: a row per node and level (NODES); shards: its summary."""

    nodes: DataFrame
    shards: DataFrame
    norm: Norm
    params: BuildParams
    metrics: dict = field(default_factory=dict)

    def edges(self) -> DataFrame:
        """src, dst, lo, hi of the bottom level: a row per active interval, ends in 1/10,000."""
        each = F.explode(F.arrays_zip("dst", "lo", "hi")).alias("z")
        one = self.nodes.where("level = 0").select("shard", F.col("id").alias("src"), each)
        pair = F.explode(F.arrays_zip(F.col("z.lo").alias("lo"), F.col("z.hi").alias("hi"))).alias("i")
        return one.select("shard", "src", F.col("z.dst").alias("dst"), pair).select("shard", "src", "dst", F.col("i.lo").alias("lo"), F.col("i.hi").alias("hi"))

    def seeds(self) -> DataFrame:
        return self.nodes.where("seed and level = 0").select("shard", "id")


def assign(objects: DataFrame, params: ShardParams, norm: Norm | None = None) -> DataFrame:
    """objects with `shard`; no shard is meant to get more than max_rows. Hash: even sizes, as many shards as that needs.
    Cluster: nearest of trained centroids, too large clusters split by hash."""
    rows = objects.count()
    n = max(params.n or 1, -(-rows // params.max_rows), 1)
    if n == 1:
        return objects.withColumn("shard", F.lit(0))
    if params.by == "hash":
        return objects.withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(n)).cast("int"))
    norm = norm or Norm(1.0, 1.0)
    sample = objects.orderBy(F.xxhash64("id")).limit(min(20_000, 200 * n)).select("e", "s").collect()
    points = np.array([np.concatenate([np.array(r.e) / norm.e, np.array(r.s) / norm.s]) for r in sample])
    centers = _centers(points, n)

    def near(batches):
        for b in batches:
            x = np.hstack([matrix(b.column("e")) / norm.e, matrix(b.column("s")) / norm.s])
            yield b.append_column("shard", pa.array(l2_block(x, centers).argmin(axis=1).astype(np.int32)))

    from pyspark.sql.types import IntegerType, StructType

    schema = StructType([*objects.schema.fields]).add("shard", IntegerType())
    out = objects.mapInArrow(near, schema)
    sizes = {r.shard: -(-r.n // params.max_rows) for r in out.groupBy("shard").agg(F.count(F.lit(1)).alias("n")).collect()}
    if max(sizes.values(), default=1) <= 1:
        return out
    parts = F.element_at(F.create_map(*[F.lit(x) for kv in sizes.items() for x in kv]), F.col("shard"))
    return out.withColumn("shard", (F.col("shard") * 1_000 + F.pmod(F.xxhash64("id"), parts)).cast("int"))


def _centers(points: np.ndarray, n: int, rounds: int = 8) -> np.ndarray:
    """Centroids of a bounded sample; starts spread by distance."""
    c = [points[0]]
    for _ in range(1, min(n, len(points))):
        c.append(points[np.min(l2_block(points, np.array(c)), axis=1).argmax()])
    c = np.array(c)
    for _ in range(rounds):
        own = l2_block(points, c).argmin(axis=1)
        c = np.array([points[own == k].mean(axis=0) if (own == k).any() else c[k] for k in range(len(c))])
    return c


def _node_table(g: kernel.Graph, shard: int) -> pa.Table:
    seeds = set(g.seeds.tolist())
    rows: dict[str, list] = {k: [] for k in ("shard", "id", "seed", "level", "e", "s", "dst", "lo", "hi", "n_dist")}
    for p in range(len(g.ids)):
        lo = [[int(np.floor(i * SCALE)) for i, _ in free] for free in g.ranges[p]]
        hi = [[int(np.ceil(j * SCALE)) for _, j in free] for free in g.ranges[p]]
        for k, v in zip(rows, (shard, int(g.ids[p]), p in seeds, 0, g.e[p].astype(np.float32).tolist(), g.s[p].astype(np.float32).tolist(), g.ids[g.nbrs[p]].tolist(), lo, hi, g.n_dist if p == 0 else 0)):
            rows[k].append(v)
    for k in range(1, len(g.levels)):
        for p, (near, low, high) in g.levels[k].items():
            for c, v in zip(rows, (shard, int(g.ids[p]), p in seeds, k, [], [], g.ids[near].tolist(), [[x] for x in low.tolist()], [[x] for x in high.tolist()], 0)):
                rows[c].append(v)
    types = [pa.int32(), pa.int64(), pa.bool_(), pa.int32(), pa.list_(pa.float32()), pa.list_(pa.float32()), pa.list_(pa.int64()), pa.list_(pa.list_(pa.int16())), pa.list_(pa.list_(pa.int16())), pa.int64()]
    return pa.table({k: pa.array(v, t) for (k, v), t in zip(rows.items(), types)})


def _one(column: pa.ChunkedArray) -> pa.Array:
    return column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)


def _arcs(rows: pa.Table, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """start, dst, lo, hi: the arcs of all rows as flat arrays, one place per interval, read from the buffers of the lists."""
    near, low, high = (_one(rows.column(c)) for c in ("dst", "lo", "hi"))
    degree = np.diff(near.offsets.to_numpy())
    dst = np.searchsorted(ids, near.flatten().to_numpy())
    inner, pieces = low.flatten(), np.diff(low.flatten().offsets.to_numpy()) if len(dst) else np.zeros(0, np.int64)
    lo, hi = (x.flatten().to_numpy().astype(np.int32) if len(dst) else np.zeros(0, np.int32) for x in (inner, high.flatten()))
    total = np.concatenate([[0], np.cumsum(pieces)])
    start = total[np.concatenate([[0], np.cumsum(degree)])]
    return start, np.repeat(dst, pieces), lo, hi


def _graph(nodes: pa.Table, norm: Norm) -> kernel.Graph:
    base = nodes.filter(pc.equal(nodes.column("level"), 0)).sort_by("id").combine_chunks()
    ids = base.column("id").to_numpy()
    g = kernel.Graph(ids, matrix(base.column("e")), matrix(base.column("s")), norm)
    g.load(*_arcs(base, ids))
    g.seeds = np.flatnonzero(base.column("seed").to_numpy(zero_copy_only=False))
    upper = nodes.filter(pc.greater(nodes.column("level"), 0)).combine_chunks()
    if upper.num_rows:
        level, at = upper.column("level").to_numpy(), np.searchsorted(ids, upper.column("id").to_numpy())
        start, dst, lo, hi = _arcs(upper, ids)
        g.levels = [dict() for _ in range(int(level.max()) + 1)]
        for i, (k, p) in enumerate(zip(level.tolist(), at.tolist())):
            x = slice(start[i], start[i + 1])
            g.levels[k][p] = dst[x], lo[x], hi[x]
    return g


def build_index(objects: DataFrame, params: BuildParams, norm: Norm, shards: ShardParams = ShardParams(), tag: str = "index") -> Index:
    """Builds and writes an index (to the shared folder); each shard in the order of a seeded hash, in one task, or by waves where it is large."""
    began = time.time()
    assert_vectors(objects, "e", "s")

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        ids = t.column("id").to_numpy()
        order = np.lexsort((ids, mix(ids, params.seed)))
        g = kernel.build(ids, matrix(t.column("e")), matrix(t.column("s")), norm, params, order)
        return _node_table(g, t.column("shard")[0].as_py())

    placed = assign(objects.select("id", "e", "s"), shards, norm)
    sizes = {r.shard: r["count"] for r in placed.groupBy("shard").count().collect()}
    if max(sizes.values(), default=0) > waves.FIRST:
        nodes = waves.build(placed, sizes, params, norm, run, _graph)
    else:
        nodes = stash(placed.groupBy("shard").applyInArrow(run, NODES), tag)
    built = Index(nodes, stash(summarise(nodes), "shards"), norm, params)
    built.metrics["build_s"] = time.time() - began
    return built


def insert(index: Index, objects: DataFrame, max_rows: int = 1_000_000) -> Index:
    """The index with further objects inserted into its shards' graphs, written as a new table; readers of the old one are
    not disturbed. Objects whose id is there already are left out. Shards are chosen by a hash of the id; one that is full
    takes no more, and what it would get goes to a new shard beside it."""
    assert_vectors(objects, "e", "s")
    began = time.time()
    sizes = {r.shard: r.n for r in index.shards.select("shard", "n").collect()}
    names = sorted(sizes)
    params, norm = index.params, index.norm
    fresh = objects.select(*[F.col(c).alias(c) for c in ("id", "e", "s")]).dropDuplicates(["id"]).join(index.nodes.where("level = 0").select("id"), "id", "left_anti")
    if names:
        slot = F.pmod(F.xxhash64("id"), F.lit(len(names)))
        full = [sizes[n] >= max_rows for n in names]
        beside = max(names) + 1
        target = F.element_at(F.array(*[F.lit(int(beside + i if full[i] else n)) for i, n in enumerate(names)]), (slot + 1).cast("int"))
    else:
        target = F.lit(0)

    def run(nodes: pa.Table, new: pa.Table) -> pa.Table:
        shard = (nodes if nodes.num_rows else new).column("shard")[0].as_py()
        old = _graph(nodes, norm) if nodes.num_rows else kernel.Graph(np.zeros(0, np.int64), np.zeros((0, 1)), np.zeros((0, 1)), norm)
        if not new.num_rows:
            return nodes.select(NAMES)
        new = new.sort_by("id")
        ids = new.column("id").to_numpy()
        g = kernel.extend(old, ids, matrix(new.column("e")), matrix(new.column("s")), params, np.lexsort((ids, mix(ids, params.seed))))
        return _node_table(g, shard)

    placed = fresh.withColumn("shard", target.cast("int"))
    nodes = stash(index.nodes.groupBy("shard").cogroup(placed.groupBy("shard")).applyInArrow(run, NODES), "index")
    return Index(nodes, stash(summarise(nodes), "shards"), norm, params, {"build_s": time.time() - began})


def summarise(nodes: DataFrame) -> DataFrame:
    """Per shard its size, centroid and radii."""

    def run(t: pa.Table) -> pa.Table:
        e, s = matrix(t.column("e")), matrix(t.column("s"))
        ce, cs = e.mean(axis=0), s.mean(axis=0)
        return pa.table({"shard": pa.array([t.column("shard")[0].as_py()], pa.int32()), "n": pa.array([len(e)], pa.int64()), "ce": pa.array([ce.tolist()]), "cs": pa.array([cs.tolist()]), "re": [float(l2_rows(ce, e).max())], "rs": [float(l2_rows(cs, s).max())]})

    return nodes.where("level = 0").select("shard", "e", "s").groupBy("shard").applyInArrow(run, SHARDS)


def write_index(index: Index, path: str) -> None:
    """nodes/ by shard, shards/, and last meta/ as the mark that the index is whole."""
    index.nodes.write.partitionBy("shard").parquet(f"{path}/nodes")
    index.shards.write.parquet(f"{path}/shards")
    meta = json.dumps({"e": index.norm.e, "s": index.norm.s, "params": asdict(index.params)})
    index.nodes.sparkSession.createDataFrame([(meta,)], "value string").coalesce(1).write.text(f"{path}/meta")


def read_index(spark: SparkSession, path: str) -> Index:
    meta = json.loads(spark.read.text(f"{path}/meta").first().value)
    nodes = spark.read.schema(NODES).parquet(f"{path}/nodes")
    return Index(nodes, spark.read.parquet(f"{path}/shards"), Norm(meta["e"], meta["s"]), BuildParams(**meta["params"]))


def route(index: Index, queries: DataFrame, probes: int | str = "all") -> DataFrame:
    """qid, band, shard, bound, place: a row per shard to visit, by rising bound; the table of shards is sent along (its size is checked)."""
    shards = index.shards.collect()
    width = max((len(r.ce) + len(r.cs) for r in shards), default=0)
    if len(shards) * width * 8 > ROUTE_BYTES:
        raise ValueError("too many shards to route by one table; build fewer, larger shards")
    names = np.array([r.shard for r in shards], np.int32)
    ce, cs = np.array([r.ce for r in shards]), np.array([r.cs for r in shards])
    re, rs = np.array([r.re for r in shards]), np.array([r.rs for r in shards])
    most = len(names) if probes in ("all", "bound") else min(int(probes), len(names))
    norm = index.norm

    def run(batches):
        for b in batches:
            if not b.num_rows or not most:
                continue
            a = b.column("alpha").to_numpy()[:, None]
            low = a * np.maximum(0, l2_block(matrix(b.column("e")), ce) - re) / norm.e + (1 - a) * np.maximum(0, l2_block(matrix(b.column("s")), cs) - rs) / norm.s
            pick = np.lexsort((np.broadcast_to(names, low.shape), low), axis=1)[:, :most]
            row = pa.array(np.repeat(np.arange(b.num_rows), most))
            yield pa.RecordBatch.from_arrays(
                [b.column("qid").take(row), b.column("band").take(row), pa.array(names[pick.reshape(-1)]), pa.array(np.take_along_axis(low, pick, 1).reshape(-1)), pa.array(np.tile(np.arange(1, most + 1, dtype=np.int32), b.num_rows))],
                names=["qid", "band", "shard", "bound", "place"],
            )

    return queries.select("qid", "band", "alpha", "e", "s").mapInArrow(run, ROUTED)


ROUTED = "qid long, band int, shard int, bound double, place int"


def search_shards(index: Index, queries: DataFrame, routed: DataFrame | None, params: SearchParams, efs: tuple[int, ...] | None = None) -> DataFrame:
    """FOUND: results of each query in each shard it is routed to (None: all), for each ef, with counters and seconds of work.

    params.k results for every ef, or ef of them where params.whole says so (lists for a merge). One search of the largest ef
    passes the ends of all others; seconds are those from its start to the end of an ef.
    """
    norm, levels, efs = index.norm, index.params.levels, tuple(efs or (params.ef_search,))
    n = index.shards.count()
    cores = index.nodes.sparkSession.sparkContext.defaultParallelism
    copies = params.copies or max(1, min(8, cores // max(1, n)))

    def run(nodes: pa.Table, asked: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        if nodes.num_rows and asked.num_rows:
            g, shard = _graph(nodes, norm), nodes.column("shard")[0].as_py()
            qe, qs = matrix(asked.column("e")), matrix(asked.column("s"))
            ids = g.ids.tolist()
            for i, (qid, band, alpha) in enumerate(zip(asked.column("qid").to_pylist(), asked.column("band").to_pylist(), asked.column("alpha").to_pylist())):
                c: dict = {}
                began = time.perf_counter()
                starts = kernel.entry(g, qe[i], qs[i], alpha, c, params.gate) if levels else g.seeds
                per = kernel.sweep(g, qe[i], qs[i], alpha, starts, efs, params.gate, levels or params.early_stop, c)
                for ef in efs:
                    got, spent, at = per[ef]
                    rows += [(qid, band, ef, ids[x], d, shard, *(spent[n] for n in kernel.COUNTS), at - began) for d, x in got[: ef if params.whole else params.k]]
        types = [pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.int32()] + [pa.int64()] * 5 + [pa.float64()]
        return pa.table({f.split()[0]: pa.array([r[j] for r in rows], t) for j, (f, t) in enumerate(zip(FOUND.split(", "), types))})

    # named anew: queries may come from the same table as the nodes
    q = queries.select(*[F.col(c).alias(c) for c in ("qid", "band", "alpha", "e", "s")])
    if routed is None:
        asked = q.join(F.broadcast(index.shards.select("shard")), F.lit(True))
    else:
        asked = q.join(routed.select("qid", "band", "shard"), ["qid", "band"])
    asked = asked.withColumn("copy", F.pmod(F.xxhash64("qid", "band"), F.lit(copies)).cast("int"))
    nodes = index.nodes.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))) if copies > 1 else index.nodes.withColumn("copy", F.lit(0))
    return nodes.groupBy("shard", "copy").cogroup(asked.groupBy("shard", "copy")).applyInArrow(lambda a, b: run(a, b), FOUND)


def topk(index: Index, queries: DataFrame, params: SearchParams = SearchParams()) -> DataFrame:
    """qid, band, rank, id, dist and the counters of work per query, from a gated best-first search."""
    return sweep(index, queries, (params.ef_search,), params).drop("ef")


def sweep(index: Index, queries: DataFrame, efs: tuple[int, ...], params: SearchParams = SearchParams()) -> DataFrame:
    """The same for several ef at once, with the column `ef`: every shard is read once."""
    efs = tuple(max(params.k, ef) for ef in efs)
    if params.probes == "bound":
        found = _by_rounds(index, queries, efs, params)
    else:
        found = search_shards(index, queries, None if params.probes == "all" else route(index, queries, params.probes), params, efs)
    return merge(found, params.k)


def lists(index: Index, queries: DataFrame, efs: tuple[int, ...]) -> DataFrame:
    """As `sweep` over all shards, but the ef best for each ef."""
    return merge(search_shards(index, queries, None, SearchParams(k=1, whole=True), efs), 0)


WORK = ("n_dist", "hops", "scanned", "gated", "stopped", "seconds")


def merge(found: DataFrame, k: int) -> DataFrame:
    """Final top-k of the shards' results (k = 0: the ef best); counters are summed over shards."""
    per = found.groupBy("qid", "band", "ef", "shard").agg(*[F.first(c).alias(c) for c in WORK]).groupBy("qid", "band", "ef").agg(*[F.sum(c).alias(c) for c in WORK], F.count(F.lit(1)).alias("probed"))
    w = Window.partitionBy("qid", "band", "ef").orderBy(F.round("dist", 9), "id")
    best = found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= (F.lit(k) if k else F.col("ef"))).select("qid", "band", "ef", "rank", "id", "dist")
    return best.join(per, ["qid", "band", "ef"])


def _by_rounds(index: Index, queries: DataFrame, efs: tuple[int, ...], params: SearchParams) -> DataFrame:
    """First the shard of least bound, then all shards whose bound is below the k-th result so far (of the least ef)."""
    routed = stash(route(index, queries, "all"), "route")
    first = stash(search_shards(index, queries, routed.where("place = 1"), params, efs), "round")
    kth = final_topk(first.where(F.col("ef") == min(efs)), params.k).groupBy("qid", "band").agg(F.max("dist").alias("kth"), F.count(F.lit(1)).alias("have"))
    again = routed.where("place > 1").join(kth, ["qid", "band"], "left").where(F.col("kth").isNull() | (F.col("have") < params.k) | (F.col("bound") < F.col("kth")))
    return first.unionByName(search_shards(index, queries, again, params, efs))
