"""Exact and approximate methods for text with coordinates: rectangle trees, a quadtree with rings, pivots, hybrid clusters.

All bound distances from below per unit (box, cell, cluster), visit units in the order of the bound, and stop where
it exceeds the k-th result. The table is dealt to parts of a bounded number of rows; each part builds its structure
once and answers all blocks of queries.
"""

from __future__ import annotations

import heapq
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import l2, l2_block, l2_rows, matrix
from ..schema import Norm
from ..storage import stash
from .blocks import SENT_BYTES, Queries, pack_queries
from .exact import final_topk

PART_ROWS = 100_000
FOUND = "qid long, band int, ef int, id long, dist double, part int, n_dist long, seconds double"


# --- a packed rectangle tree as tables ---------------------------------------------------------------------


def str_pack(objects: DataFrame, leaf: int = 64) -> DataFrame:
    """objects (2-dimensional s) with `slab` and `leaf` of a sort-tile packing, leaves of about `leaf` rows.

    Slabs are cut at quantiles of the first coordinate, so no task sees all rows: a slab has about the square root
    of rows times `leaf`.
    """
    leaves = max(1, -(-objects.count() // leaf))
    slabs = max(1, round(leaves**0.5))
    x, y = F.col("s")[0], F.col("s")[1]
    cuts = objects.agg(F.percentile_approx(x, [i / slabs for i in range(1, slabs)], 10 * slabs)).first()[0] if slabs > 1 else []
    bounds = np.array(cuts or [], float)

    def place(batches):
        for b in batches:
            at = np.searchsorted(bounds, matrix(b.column("s"))[:, 0]) if b.num_rows else np.zeros(0)
            yield b.append_column("slab", pa.array(at.astype(np.int32)))

    from pyspark.sql.types import IntegerType, StructType

    one = objects.mapInArrow(place, StructType([*objects.schema.fields]).add("slab", IntegerType()))
    w = Window.partitionBy("slab")
    n = F.ceil(F.count(F.lit(1)).over(w) / F.lit(leaf))
    place_in = F.row_number().over(w.orderBy(y, x, "id")) - 1
    return one.withColumn("leaf", (F.floor(place_in / F.ceil(F.count(F.lit(1)).over(w) / n)) + 1).cast("int"))


def boxes(packed: DataFrame, *level: str) -> DataFrame:
    """The boxes of a level (slabs, or leaves inside them) and how many rows each has."""
    x, y = F.col("s")[0].cast("double"), F.col("s")[1].cast("double")
    return packed.groupBy(*level).agg(F.min(x).alias("x0"), F.max(x).alias("x1"), F.min(y).alias("y0"), F.max(y).alias("y1"), F.count(F.lit(1)).alias("n"))


def _near_far() -> tuple[Column, Column]:
    x, y, zero = F.col("qs")[0].cast("double"), F.col("qs")[1].cast("double"), F.lit(0.0)
    near = F.sqrt(F.pow(F.greatest(F.col("x0") - x, zero, x - F.col("x1")), 2) + F.pow(F.greatest(F.col("y0") - y, zero, y - F.col("y1")), 2))
    far = F.sqrt(F.pow(F.greatest(F.abs(F.col("x0") - x), F.abs(F.col("x1") - x)), 2) + F.pow(F.greatest(F.abs(F.col("y0") - y), F.abs(F.col("y1") - y)), 2))
    return near, far


def _within(reached: DataFrame, k: int, *level: str) -> DataFrame:
    """Of the boxes a query has reached, those no farther than the far side of the boxes that surely hold k rows."""
    near, far = _near_far()
    both = reached.withColumn("near", near).withColumn("far", far)
    w = Window.partitionBy("qid", "band").orderBy("far", *level).rowsBetween(Window.unboundedPreceding, 0)
    limit = both.withColumn("have", F.sum("n").over(w)).where(F.col("have") >= k).groupBy("qid", "band").agg(F.min("far").alias("limit"))
    return both.join(limit, ["qid", "band"], "left").where(F.col("limit").isNull() | (F.col("near") <= F.col("limit"))).select("qid", "band", "qs", *level)


def box_topk(packed: DataFrame, queries: DataFrame, norm: Norm, k: int) -> DataFrame:
    """Exact top-k by coordinate, down the tree: slabs, then leaves of the slabs reached, then their rows.

    Slabs are few (about the square root of the leaves) and sent along behind a check of their size; leaves and rows
    are met by equal keys.
    """
    q = queries.select("qid", "band", F.col("s").alias("qs"))
    low = stash(boxes(packed, "slab", "leaf"), "boxes")
    top = low.groupBy("slab").agg(F.min("x0").alias("x0"), F.max("x1").alias("x1"), F.min("y0").alias("y0"), F.max("y1").alias("y1"), F.sum("n").alias("n"))
    top = F.broadcast(top) if low.select("slab").distinct().count() * 48 <= SENT_BYTES else top
    slabs = _within(q.join(top, F.lit(True)), k, "slab")
    leaves = _within(slabs.join(low, "slab"), k, "slab", "leaf")
    rows = packed.select("slab", "leaf", "id", "s").join(leaves, ["slab", "leaf"])
    return final_topk(rows.select("qid", "band", "id", (l2("s", "qs") / norm.s).alias("dist")), k)


# --- structures inside a part ------------------------------------------------------------------------------


class RectTree:
    """A packed rectangle tree over points of any dimension, read by rising distance."""

    def __init__(self, points: np.ndarray, leaf: int = 32, metric: str = "l2"):
        self.points, self.metric, self.evaluated = points, metric, 0
        groups = self._tiles(np.arange(len(points)), leaf, 0)
        self.levels = [[(points[g].min(axis=0), points[g].max(axis=0), g) for g in groups]]
        while len(self.levels[-1]) > 1:
            below = self.levels[-1]
            lo, hi = np.array([b[0] for b in below]), np.array([b[1] for b in below])
            if len(below) <= leaf:
                groups = [np.arange(len(below))]
            else:
                groups = self._tiles(np.arange(len(below)), leaf, 0, (lo + hi) / 2)
            self.levels.append([(lo[g].min(axis=0), hi[g].max(axis=0), g) for g in groups])
        self.lo = [np.array([b[0] for b in level]) for level in self.levels]
        self.hi = [np.array([b[1] for b in level]) for level in self.levels]

    def _tiles(self, rows: np.ndarray, leaf: int, dim: int, points: np.ndarray | None = None) -> list[np.ndarray]:
        p = self.points if points is None else points
        if len(rows) <= leaf:
            return [rows]
        order = rows[np.argsort(p[rows, dim], kind="stable")]
        left = p.shape[1] - dim
        if left == 1:
            return [order[i : i + leaf] for i in range(0, len(order), leaf)]
        slabs = max(1, round((len(rows) / leaf) ** (1 / left)))
        size = -(-len(order) // slabs)
        return [t for i in range(0, len(order), size) for t in self._tiles(order[i : i + size], leaf, dim + 1, points)]

    def _away(self, gap: np.ndarray) -> np.ndarray:
        return np.sqrt(np.einsum("ij,ij->i", gap, gap)) if self.metric == "l2" else np.abs(gap).max(axis=1)

    def nearest(self, q: np.ndarray) -> Iterator[tuple[float, int]]:
        """(distance, row) of all points, nearest first."""
        top = len(self.levels) - 1
        todo = [(0.0, 0, top, 0)] if len(self.points) else []
        while todo:
            d, _, level, i = heapq.heappop(todo)
            if level < 0:
                yield d, i
                continue
            inside = self.levels[level][i][2]
            if level:
                gap = np.maximum(0, np.maximum(self.lo[level - 1][inside] - q, q - self.hi[level - 1][inside]))
            else:
                self.evaluated += len(inside)
                gap = self.points[inside] - q
            for x, j in zip(self._away(gap).tolist(), inside.tolist()):
                heapq.heappush(todo, (x, j if not level else -1, level - 1, j))


class QuadTree:
    """Cells of the plane, cut in four while they hold more than `leaf` points; in each leaf the points by their distance to a pivot of e."""

    def __init__(self, e: np.ndarray, s: np.ndarray, leaf: int = 64, depth: int = 16):
        self.nodes: list[tuple] = []
        self.e, self.s = e, s
        self.root = self._cut(np.arange(len(s)), leaf, depth) if len(s) else None

    def _cut(self, rows: np.ndarray, leaf: int, depth: int) -> int:
        lo, hi = self.s[rows].min(axis=0), self.s[rows].max(axis=0)
        at = len(self.nodes)
        self.nodes.append(())
        if len(rows) <= leaf or depth == 0 or (lo == hi).all():
            pivot = self.e[rows].mean(axis=0)
            ring = l2_rows(pivot, self.e[rows])
            order = np.argsort(ring, kind="stable")
            self.nodes[at] = (lo, hi, None, pivot, rows[order], ring[order])
        else:
            mid = (lo + hi) / 2
            quarter = (self.s[rows] > mid) @ np.array([1, 2])
            self.nodes[at] = (lo, hi, [self._cut(rows[quarter == k], leaf, depth - 1) for k in range(4) if (quarter == k).any()], None, None, None)
        return at

    def leaves(self, q: np.ndarray) -> Iterator[tuple[float, tuple]]:
        """(least distance, leaf) of all leaves, nearest first."""
        away = lambda n: float(np.linalg.norm(np.maximum(0, np.maximum(self.nodes[n][0] - q, q - self.nodes[n][1]))))
        todo = [] if self.root is None else [(away(self.root), self.root)]
        while todo:
            d, n = heapq.heappop(todo)
            if self.nodes[n][2] is None:
                yield d, self.nodes[n]
            else:
                for child in self.nodes[n][2]:
                    heapq.heappush(todo, (away(child), child))


class Best:
    """The k nearest so far of one query: distance to nine places, then smaller id."""

    def __init__(self, k: int):
        self.k, self.d, self.i, self.n_dist = k, np.zeros(0), np.zeros(0, np.int64), 0

    def add(self, d: np.ndarray, ids: np.ndarray) -> None:
        self.n_dist += len(ids)
        self.d, self.i = np.concatenate([self.d, d]), np.concatenate([self.i, ids])
        keep = np.lexsort((self.i, np.round(self.d, 9)))[: self.k]
        self.d, self.i = self.d[keep], self.i[keep]

    @property
    def limit(self) -> float:
        """What nothing of use may exceed."""
        return float(self.d[-1]) + 1e-9 if len(self.d) >= self.k else np.inf


FIRST_UNITS, MOST_UNITS = 4, 256  # leaves that are read at a time, at first and at most
BLOCK_QUERIES = 256


class Units:
    """The rows of leaves one leaf after the other."""

    def __init__(self, leaves: list[np.ndarray]):
        self.members = np.concatenate(leaves)
        self.size = np.array([len(x) for x in leaves])
        self.start = np.cumsum(self.size) - self.size

    def rows(self, leaves: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places in `members` of the rows of some leaves, and the leaf of each."""
        n = self.size[leaves]
        inside = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        return np.repeat(self.start[leaves], n) + inside, np.repeat(leaves, n)


def over_parts(objects: DataFrame, queries: DataFrame, prepare: Callable, ks: tuple[int, ...], columns: tuple[str, ...] = ("id", "e", "s")) -> DataFrame:
    """FOUND rows of all queries over parts of at most about PART_ROWS objects, for each wanted number of results (`ef`).

    prepare(table) builds a part's structure and gives search(qe, qs, alpha, k) -> Best. Queries reach the parts as blocks of
    bounded size, and in several portions, each with a structure of its own, where all of them are too many for one task or
    there are fewer parts than cores.
    """
    parts = max(1, -(-objects.count() // PART_ROWS))
    q = stash(pack_queries(queries, BLOCK_QUERIES), "query-blocks")
    size, blocks = q.agg(F.sum(F.octet_length("q_e") + F.octet_length("q_s")), F.count(F.lit(1))).first()
    spark = objects.sparkSession
    portions = max(-(-int(size or 0) // SENT_BYTES), min(blocks, -(-spark.sparkContext.defaultParallelism // parts)), 1)

    def run(rows: pa.Table, asked: pa.Table) -> pa.Table:
        out: list[tuple] = []
        if rows.num_rows and asked.num_rows:
            search, part = prepare(rows), rows.column("part")[0].as_py()
            for row in asked.to_pylist():
                b = Queries(row)
                for j, k in ((j, k) for j in range(len(b.qid)) for k in ks):
                    began = time.perf_counter()
                    best = search(b.e[b.which[j]], b.s[b.which[j]], float(b.alpha[j]), k)
                    seconds = time.perf_counter() - began
                    out += [(int(b.qid[j]), int(b.band[j]), k, x, d, part, best.n_dist, seconds) for d, x in zip(best.d.tolist(), best.i.tolist())]
        types = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.int32(), pa.int64(), pa.float64())
        return pa.table({f.split()[0]: pa.array([r[j] for r in out], t) for j, (f, t) in enumerate(zip(FOUND.split(", "), types))})

    left = objects.select(*columns).withColumn("part", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int")).withColumn("portion", F.explode(F.sequence(F.lit(0), F.lit(portions - 1))))
    right = q.withColumn("portion", F.pmod(F.xxhash64("block"), F.lit(portions)).cast("int")).join(F.broadcast(spark.range(parts).select(F.col("id").cast("int").alias("part"))), F.lit(True))
    key, tasks = ("part", "portion"), 4 * parts * portions  # enough for few to share a task; a number that is asked for stays
    return left.repartition(tasks, *key).groupBy(*key).cogroup(right.repartition(tasks, *key).groupBy(*key)).applyInArrow(lambda a, b: run(a, b), FOUND)


def merged(found: DataFrame) -> DataFrame:
    """qid, band, ef, rank, id, dist (the ef best of all parts), and the work over all parts: n_dist, seconds."""
    key = ["qid", "band", "ef"]
    work = found.groupBy(*key, "part").agg(F.first("n_dist").alias("n_dist"), F.first("seconds").alias("seconds")).groupBy(*key).agg(F.sum("n_dist").alias("n_dist"), F.sum("seconds").alias("seconds"))
    w = Window.partitionBy(*key).orderBy(F.round("dist", 9), "id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= F.col("ef")).select(*key, "rank", "id", "dist").join(work, key)


def _vectors(t: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return t.column("id").to_numpy(), matrix(t.column("e")), matrix(t.column("s"))


# --- the methods -------------------------------------------------------------------------------------------


def scan_topk(objects: DataFrame, queries: DataFrame, norm: Norm, k: int = 10) -> DataFrame:
    """Brute force in the same frame as the others, for their cost."""

    def prepare(t: pa.Table):
        ids, e, s = _vectors(t)

        def search(qe, qs, a, k):
            best = Best(k)
            best.add(a * l2_rows(qe, e) / norm.e + (1 - a) * l2_rows(qs, s) / norm.s, ids)
            return best

        return search

    return merged(over_parts(objects, queries, prepare, (k,)))


def early_stop_topk(objects: DataFrame, queries: DataFrame, norm: Norm, k: int = 10, step: int = 64) -> DataFrame:
    """A scan with two-part distances: the second part only where the first is within the k-th result so far."""
    from ..functions.vectors import hybrid_bounded

    def prepare(t: pa.Table):
        ids, e, s = _vectors(t)

        def search(qe, qs, a, k):
            best = Best(k)
            for at in range(0, len(ids), step):
                rows, got, _ = hybrid_bounded((qe, qs), e[at : at + step], s[at : at + step], a, norm, best.limit)
                best.add(got, ids[at : at + step][rows])
            return best

        return search

    return merged(over_parts(objects, queries, prepare, (k,)))


def rect_lists(objects: DataFrame, queries: DataFrame, norm: Norm, ks: tuple[int, ...] = (10,)) -> DataFrame:
    """Exact lists by s alone over a rectangle tree in each part, of each length (the merge's index for coordinates)."""

    def prepare(t: pa.Table):
        ids, _, s = _vectors(t)
        tree = RectTree(s)

        def search(qe, qs, a, k):
            best, d, x = Best(k), [], []
            tree.evaluated = 0
            for away, i in tree.nearest(qs):
                if len(d) >= k and away > d[k - 1] + 1e-9 * norm.s:  # equal ones all come, ids decide
                    break
                d.append(away), x.append(i)
            best.add(np.array(d) / norm.s, ids[x])
            best.n_dist = tree.evaluated
            return best

        return search

    return merged(over_parts(objects, queries, prepare, tuple(ks)))


def quad_ring_topk(objects: DataFrame, queries: DataFrame, norm: Norm, k: int = 10) -> DataFrame:
    """Exact: a quadtree of the plane, near leaves first; inside a leaf the rings around its pivot that can hold results.

    Leaves come some at a time, twice as many from step to step, and the rings of a step are cut by what the step before has found.
    """

    def prepare(t: pa.Table):
        ids, e, s = _vectors(t)
        leaves = [n for n in QuadTree(e, s).nodes if n[2] is None]
        lo, hi, pivot = (np.array([n[i] for n in leaves]) for i in (0, 1, 3))
        unit = Units([n[4] for n in leaves])
        ring = np.concatenate([n[5] for n in leaves])

        def search(qe, qs, a, k):
            best = Best(k)
            gap = np.maximum(0, np.maximum(lo - qs, qs - hi))
            near = (1 - a) * np.sqrt(np.einsum("ij,ij->i", gap, gap)) / norm.s
            mid = l2_rows(qe, pivot)
            order = np.argsort(near, kind="stable")
            at, many = 0, FIRST_UNITS
            while at < len(order) and near[order[at]] <= best.limit:
                places, leaf = unit.rows(order[at : at + many])
                if a > 0 and np.isfinite(best.limit):
                    inside = np.abs(ring[places] - mid[leaf]) <= (best.limit - near[leaf]) * norm.e / a + 1e-9
                    places = places[inside]
                rows = unit.members[places]
                best.add(a * l2_rows(qe, e[rows]) / norm.e + (1 - a) * l2_rows(qs, s[rows]) / norm.s, ids[rows])
                at, many = at + many, min(2 * many, MOST_UNITS)
            return best

        return search

    return merged(over_parts(objects, queries, prepare, (k,)))


def pivot_topk(objects: DataFrame, queries: DataFrame, norm: Norm, k: int = 10, pivots: int = 4) -> DataFrame:
    """Exact: a rectangle tree over s and one over the distances of e to a few pivots, the leaves of both read by rising distance.

    What neither has given yet is at least as far as the weighted sum of both fronts (differences of distances to a
    pivot bound e from below), so the search ends where that exceeds the k-th result.
    """

    def prepare(t: pa.Table):
        ids, e, s = _vectors(t)
        chosen = [0]
        for _ in range(1, min(pivots, len(e))):
            chosen.append(int(np.min(l2_block(e, e[chosen]), axis=1).argmax()))
        sides = []
        for points, metric in ((s, "l2"), (l2_block(e, e[chosen]), "max")):
            tree = RectTree(points, metric=metric)
            sides.append((tree, Units([leaf[2] for leaf in tree.levels[0]])))

        def search(qe, qs, a, k):
            best, seen = Best(k), np.zeros(len(ids), bool)
            fronts = []
            for (tree, unit), q, w in zip(sides, (qs, l2_rows(qe, e[chosen])), ((1 - a) / norm.s, a / norm.e)):
                away = tree._away(np.maximum(0, np.maximum(tree.lo[0] - q, q - tree.hi[0])))
                order = np.argsort(away, kind="stable")
                fronts.append((w, away[order], order, unit))
            at, many = 0, FIRST_UNITS  # both trees have equally many leaves read
            while sum(w * away[at] for w, away, _, _ in fronts if w and at < len(away)) <= best.limit:
                ended = False
                for w, away, order, unit in fronts:
                    if w:
                        rows = unit.members[unit.rows(order[at : at + many])[0]]
                        rows = rows[~seen[rows]]
                        seen[rows] = True
                        best.add(a * l2_rows(qe, e[rows]) / norm.e + (1 - a) * l2_rows(qs, s[rows]) / norm.s, ids[rows])
                        ended |= at + many >= len(away)
                if ended:  # one tree has given all its rows
                    break
                at, many = at + many, min(2 * many, MOST_UNITS)
            return best

        return search

    return merged(over_parts(objects, queries, prepare, (k,)))


def hybrid_clusters(objects: DataFrame, norm: Norm, ke: int = 8, ks: int = 8, dims: int = 8, seed: int = 42):
    """objects with `ce`, `cs` (clusters of the reduced e and of s) and `low` (reduced e), and the reduction (mean, axes)."""
    from .index import _centers

    sample = objects.orderBy(F.xxhash64("id", F.lit(seed))).limit(20_000).select("e", "s").collect()
    e, s = np.array([r.e for r in sample], float), np.array([r.s for r in sample], float)
    mean = e.mean(axis=0)
    axes = np.linalg.svd(e - mean, full_matrices=False)[2][:dims]
    center_e, center_s = _centers((e - mean) @ axes.T, ke), _centers(s, ks)

    def run(batches):
        for b in batches:
            low = (matrix(b.column("e")) - mean) @ axes.T
            ce, cs = l2_block(low, center_e).argmin(axis=1), l2_block(matrix(b.column("s")), center_s).argmin(axis=1)
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("e"), b.column("s"), pa.array(ce.astype(np.int32)), pa.array(cs.astype(np.int32)), pa.array(low.tolist(), pa.list_(pa.float64()))], names=["id", "e", "s", "ce", "cs", "low"])

    placed = objects.select("id", "e", "s").mapInArrow(run, "id long, e array<float>, s array<float>, ce int, cs int, low array<double>")
    return placed, (mean, axes)


def cluster_topk(objects: DataFrame, queries: DataFrame, norm: Norm, k: int = 10, exact: bool = True) -> DataFrame:
    """Clusters of both modalities: hybrid clusters with centroid and radius, visited in the order of the bound.

    exact: bounds on the original vectors. Otherwise bounds and the stop use distances in the reduced
    space, and the originals only order the results.
    """
    placed, (mean, axes) = hybrid_clusters(objects, norm)

    def prepare(t: pa.Table):
        t = t.sort_by("id")  # so that the order of rows decides ties as ids do
        ids, e, s = _vectors(t)
        low = matrix(t.column("low"))
        key = t.column("ce").to_numpy() * 1_000 + t.column("cs").to_numpy()
        space = e if exact else low
        units = []
        for c in np.unique(key):
            rows = np.flatnonzero(key == c)
            me, ms = space[rows].mean(axis=0), s[rows].mean(axis=0)
            units.append((me, ms, l2_rows(me, space[rows]).max(), l2_rows(ms, s[rows]).max(), rows))

        def search(qe, qs, a, k):
            q = qe if exact else (qe - mean) @ axes.T
            bound = np.array([a * max(0, np.linalg.norm(q - u[0]) - u[2]) / norm.e + (1 - a) * max(0, np.linalg.norm(qs - u[1]) - u[3]) / norm.s for u in units])
            best = Best(k if exact else 4 * k)
            for j in np.argsort(bound, kind="stable"):
                if bound[j] > best.limit:
                    break
                rows = units[j][4]
                best.add(a * l2_rows(q, space[rows]) / norm.e + (1 - a) * l2_rows(qs, s[rows]) / norm.s, rows)
            rows, out = best.i, Best(k)
            out.n_dist = best.n_dist - len(rows)
            out.add(a * l2_rows(qe, e[rows]) / norm.e + (1 - a) * l2_rows(qs, s[rows]) / norm.s, ids[rows])
            return out

        return search

    return merged(over_parts(placed, queries, prepare, (k,), ("id", "e", "s", "low", "ce", "cs")))
