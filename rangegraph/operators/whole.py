"""Nodes against all objects, without a table of pairs: the objects go to the tasks behind a check of their size, nodes are dealt.

A task has the distances of a few nodes to all objects at a time and gives what is chosen from them only, so what is
written grows with the nodes and not with the pairs. Tables above SENT_BYTES have to be joined block by block (exact.pair_distances).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import FloatType

from ..functions import alpha as al
from ..functions.vectors import l2_block, l2_rows, matrix
from ..schema import Norm
from . import pareto, prune
from .blocks import OBJECT_ROWS, SENT_BYTES, _slices

CELLS = 2_000_000  # distances of a modality that a task has at a time


class All:
    """All objects by rising id, as they are in a task."""

    def __init__(self, ids: np.ndarray, e: np.ndarray, s: np.ndarray, norm: Norm):
        self.ids, self.e, self.s, self.norm = ids, e, s, norm

    @classmethod
    def of(cls, sent: tuple[np.ndarray, np.ndarray, np.ndarray], norm: Norm) -> "All":
        ids, e, s = sent
        return cls(ids, e.astype(np.float64), s.astype(np.float64), norm)

    def cross(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Both distances between the objects at the places a and b."""
        return l2_block(self.e[a], self.e[b]) / self.norm.e, l2_block(self.s[a], self.s[b]) / self.norm.s


def fits(objects: DataFrame) -> bool:
    """Whether the objects, as they are sent, are at most SENT_BYTES."""
    return _bytes(objects) <= SENT_BYTES


def _kinds(objects: DataFrame) -> list:
    return [np.float32 if isinstance(objects.schema[c].dataType.elementType, FloatType) else np.float64 for c in ("e", "s")]


def _bytes(objects: DataFrame) -> int:
    width = sum((F.size(c) * np.dtype(k).itemsize for c, k in zip(("e", "s"), _kinds(objects))), F.lit(8))
    return objects.agg(F.sum(width)).first()[0] or 0


def send(objects: DataFrame):
    """(ids, broadcast of ids, e and s as they are stored): all objects by rising id; ids are at the driver too."""
    kinds = _kinds(objects)

    def pack(batches):
        for t in _slices(batches, OBJECT_ROWS):
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()]) for x in (t.column("id").to_numpy(), matrix(t.column("e")).astype(kinds[0]), matrix(t.column("s")).astype(kinds[1]))], names=["ids", "e", "s"])

    rows = objects.select("id", "e", "s").mapInArrow(pack, "ids binary, e binary, s binary").collect()
    ids = np.concatenate([np.frombuffer(r.ids, np.int64) for r in rows] or [np.zeros(0, np.int64)])
    order = np.argsort(ids, kind="stable")
    e, s = (np.concatenate([np.frombuffer(r[c], k).reshape(len(r.ids) // 8, -1) for r in rows] or [np.zeros((0, 1), k)])[order] for c, k in zip(("e", "s"), kinds))
    return ids[order], objects.sparkSession.sparkContext.broadcast((ids[order], e, s))


def per_node(objects: DataFrame, norm: Norm, nodes: DataFrame | None, work: Callable[[All, int, np.ndarray, np.ndarray, np.ndarray], Iterator[pa.RecordBatch] | pa.Table], schema: str) -> DataFrame:
    """work(all, p, places, de, ds) of each node p (id, e, s; default: every object): its distances to the objects at `places`, all but itself."""
    spark, (_, sent) = objects.sparkSession, send(objects)

    def run(batches):
        every = None
        for b in batches:
            if not b.num_rows:
                continue
            if every is None:
                every = All.of(sent.value, norm)
            n, p = len(every.ids), b.column("id").to_numpy()
            pe, ps = matrix(b.column("e")), matrix(b.column("s"))
            step, places = max(1, CELLS // max(1, n)), np.arange(n)
            for i in range(0, len(p) if n else 0, step):
                de, ds = l2_block(pe[i : i + step], every.e) / norm.e, l2_block(ps[i : i + step], every.s) / norm.s
                for k, one in enumerate(p[i : i + step].tolist()):
                    left, right = np.searchsorted(every.ids, one, "left"), np.searchsorted(every.ids, one, "right")
                    at = np.delete(places, np.s_[left:right])
                    yield from work(every, one, at, de[k, at], ds[k, at]).to_batches()

    ps = (objects if nodes is None else nodes).select("id", "e", "s")
    return ps.repartition(4 * spark.sparkContext.defaultParallelism, "id").mapInArrow(run, schema)


PAIRS = "p long, x long, de double, ds double"


def _pairs(every: All, p: int, at: np.ndarray, de: np.ndarray, ds: np.ndarray) -> pa.Table:
    return pa.table({"p": pa.array(np.full(len(at), p)), "x": pa.array(every.ids[at]), "de": pa.array(de), "ds": pa.array(ds)})


def pool(objects: DataFrame, norm: Norm, nodes: DataFrame | None, most: int, places: int = 12) -> DataFrame:
    """p, x, de, ds (to so many places) of all rows that may be in the first `most` layers of p, and of some more."""

    def work(every, p, at, de, ds):
        de, ds = np.round(de, places), np.round(ds, places)
        keep = pareto.in_first_layers(de, ds, most)
        return _pairs(every, p, at[keep], de[keep], ds[keep])

    return per_node(objects, norm, nodes, work, PAIRS)


def bounded(every: All, at: np.ndarray, de: np.ndarray, ds: np.ndarray, bound: int) -> tuple[np.ndarray, np.ndarray]:
    """Places in `at` of the whole layers of a node up to `bound` rows, and their layers."""
    near = pareto.in_bounded_layers(de, ds, bound)
    layer = pareto.layer_block(de[near], ds[near], every.ids[at[near]])
    keep = pareto.keep_bound(layer, bound)
    return near[keep], layer[keep]


TRIANGLES = ("pxe", "pxs", "pze", "pzs", "zxe", "zxs")


def _first_layers(every: All, at: np.ndarray, de: np.ndarray, ds: np.ndarray, most: int) -> tuple[np.ndarray, list[np.ndarray]]:
    """Places in `at` of the first `most` layers, and both distances between every two of them, by differences as in SQL."""
    near = pareto.in_first_layers(de, ds, most)
    near = near[pareto.layer_block(de[near], ds[near], every.ids[at[near]]) <= most]
    e, s = every.e[at[near]], every.s[at[near]]
    return near, [np.array([l2_rows(v, m) for v in m]).reshape(len(near), -1) / n for m, n in ((e, every.norm.e), (s, every.norm.s))]


def triangles(objects: DataFrame, norm: Norm, nodes: DataFrame, most: int, places: int = 12) -> DataFrame:
    """p, x, z and the six distances of every two of the first `most` layers of p."""

    def work(every, p, at, de, ds):
        de, ds = np.round(de, places), np.round(ds, places)
        near, (zxe, zxs) = _first_layers(every, at, de, ds, most)
        i, j = np.nonzero(~np.eye(len(near), dtype=bool))
        x, z = near[i], near[j]
        rows = dict(zip(TRIANGLES, (de[x], ds[x], de[z], ds[z], zxe[j, i], zxs[j, i])))
        return pa.table({"p": pa.array(np.full(len(x), p)), "x": pa.array(every.ids[at[x]]), "z": pa.array(every.ids[at[z]])} | {k: pa.array(v) for k, v in rows.items()})

    return per_node(objects, norm, nodes, work, "p long, x long, z long, " + ", ".join(f"{c} double" for c in TRIANGLES))


def pruned_sets(objects: DataFrame, norm: Norm, nodes: DataFrame, most: int, places: int = 12) -> DataFrame:
    """p, x, r: for each of the first `most` layers of p the intervals at which one of the others removes it. No triangle leaves its task."""

    def work(every, p, at, de, ds):
        de, ds = np.round(de, places), np.round(ds, places)
        near, (zxe, zxs) = _first_layers(every, at, de, ds, most)
        a, b = de[near], ds[near]
        lo, hi = al.pruned_block(a[None, :], b[None, :], a[:, None], b[:, None], zxe.T, zxs.T)
        some = (lo < hi) & ~np.eye(len(near), dtype=bool)
        each = pa.StructArray.from_arrays([pa.array(lo[some]), pa.array(hi[some])], names=["lo", "hi"])
        ends = np.concatenate([[0], np.cumsum(some.sum(axis=1))]).astype(np.int32)
        return pa.table({"p": pa.array(np.full(len(near), p)), "x": pa.array(every.ids[at[near]]), "r": pa.ListArray.from_arrays(pa.array(ends), each)})

    return per_node(objects, norm, nodes, work, f"p long, x long, r {al.EMPTY}")


def dominance(objects: DataFrame, norm: Norm, nodes: DataFrame, places: int = 12) -> DataFrame:
    """p, n: number of pairs of rows of which one dominates the other."""

    def work(every, p, at, de, ds):
        n = pareto.dominated_pairs(np.round(de, places), np.round(ds, places))
        return pa.table({"p": pa.array([p] * (n > 0), pa.int64()), "n": pa.array([n] * (n > 0), pa.int64())})

    return per_node(objects, norm, nodes, work, "p long, n long")


EDGES = pa.schema([("src", pa.int64()), ("dst", pa.int64()), ("lo", pa.int16()), ("hi", pa.int16())])


def _edges(p: int, dst: np.ndarray, ranges: list) -> pa.Table:
    rows = prune.edge_rows([p] * len(dst), dst.tolist(), ranges)
    return pa.table(dict(zip(EDGES.names, map(pa.array, rows, EDGES.types))), schema=EDGES)


def exact_range_graph(objects: DataFrame, norm: Norm, witness: str = "any", th: float = 0.0) -> DataFrame:
    """src, dst, lo, hi: the range-gated rule with all objects as candidates of all and no cap."""

    def work(every, p, at, de, ds):
        got = prune.gate_all(de, ds, every.ids[at], lambda a, b: every.cross(at[a], at[b]), th, witness)
        return _edges(p, every.ids[at[[i for i, _ in got]]] if got else np.zeros(0, np.int64), [r for _, r in got])

    return per_node(objects, norm, None, work, prune.EDGES)


def range_gated(objects: DataFrame, norm: Norm, bound: int, M: int, th: float) -> DataFrame:
    """src, dst, lo, hi: the range-gated rule on the whole layers of each object up to `bound` candidates."""

    def work(every, p, at, de, ds):
        near, layer = bounded(every, at, de, ds, bound)
        x = at[near]
        got = prune.gate_block(de[near], ds[near], layer, every.ids[x], lambda: every.cross(x, x), M, th)
        return _edges(p, every.ids[x[[i for i, _ in got]]] if got else np.zeros(0, np.int64), [r for _, r in got])

    return per_node(objects, norm, None, work, prune.EDGES)


def rng_greedy(objects: DataFrame, norm: Norm, alpha: float, bound: int, M: int) -> DataFrame:
    """The fixed-weight rule on the same candidates: edges of full range."""

    def work(every, p, at, de, ds):
        near, _ = bounded(every, at, de, ds, bound)
        x = at[near]

        def between():
            x_e, x_s = every.cross(x, x)
            return alpha * x_e + (1 - alpha) * x_s

        got = prune.rng_block(alpha * de[near] + (1 - alpha) * ds[near], every.ids[x], between, M)
        return _edges(p, every.ids[x[got]] if got else np.zeros(0, np.int64), [prune.FULL] * len(got))

    return per_node(objects, norm, None, work, prune.EDGES)


BLOCK = 256  # nodes that are witnesses of each other
WITNESSES = 16  # of a node, from its block
FIRST = 16  # nearest of what these leave that are witnesses before the rest


def _rounded(every: All, a: np.ndarray, b: np.ndarray, alpha: float, places: int) -> np.ndarray:
    x_e, x_s = every.cross(a, b)
    return np.round(alpha * x_e + (1 - alpha) * x_s, places)


def _about(every: All, at: np.ndarray, alpha: float) -> tuple[np.ndarray, float]:
    """Hybrid distances of the objects at `at` to all, by products, and twice what one may be wrong by (rounding to nine places included)."""
    out, wrong = np.zeros((len(at), len(every.ids))), 1e-9
    for v, w in ((every.e, alpha / every.norm.e), (every.s, (1 - alpha) / every.norm.s)):
        vv = np.einsum("ij,ij->i", v, v)
        for i in range(0, len(v), OBJECT_ROWS):
            part = v[at] @ v[i : i + OBJECT_ROWS].T
            part *= -2.0
            part += vv[at, None]
            part += vv[None, i : i + OBJECT_ROWS]
            np.maximum(part, 0.0, out=part)
            np.sqrt(part, out=part)
            part *= w
            out[:, i : i + OBJECT_ROWS] += part
        wrong += w * np.sqrt(16 * (v.shape[1] + 4) * np.finfo(float).eps * vv.max(initial=0.0))
    return out, 2 * wrong


def _blocks(every: All, ids: np.ndarray, alpha: float) -> Iterator[tuple[np.ndarray, np.ndarray, float]]:
    """(places, distances to all, twice their error) of some nodes at a time."""
    at, step = np.searchsorted(every.ids, ids), max(16, min(BLOCK, 4 * CELLS // max(1, len(every.ids))))
    for i in range(0, len(at), step):
        yield at[i : i + step], *_about(every, at[i : i + step], alpha)


def _alike(every: All, ids: np.ndarray, alpha: float) -> np.ndarray:
    """The nodes, with those beside each other that have the same nearest one among some of them."""
    some = ids[:: BLOCK // 2]
    if len(some) < 2:
        return ids
    at, cell = np.searchsorted(every.ids, ids), []
    for i in range(0, len(ids), OBJECT_ROWS):
        cell.append(_rounded(every, at[i : i + OBJECT_ROWS], np.searchsorted(every.ids, some), alpha, 9).argmin(axis=1))
    return ids[np.argsort(np.concatenate(cell), kind="stable")]


def rng_candidates(every: All, ids: np.ndarray, alpha: float, places: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(place of p, places x, d, objects about as near to p as x): per node the pairs that no witness in its block and none of what that leaves removes.

    All objects were held against each other's nearest before; here most fall to nodes whose distances are there anyway.
    """
    for at, d, m in _blocks(every, _alike(every, ids, alpha), alpha):
        for k, one in enumerate(at.tolist()):
            mine = d[k]
            among = mine[at]
            left = None
            for y in np.argsort(among, kind="stable")[: WITNESSES + 1].tolist():
                if y == k:
                    continue
                if left is None:
                    left = np.flatnonzero((d[y] + m >= mine) | (mine <= among[y] + m))
                    continue
                far = mine[left]
                left = left[(d[y][left] + m >= far) | (far <= among[y] + m)]
            left = np.arange(len(mine)) if left is None else left
            left = left[left != one]
            if len(left):
                near = _rounded(every, np.array([one]), left, alpha, places)[0]
                keep = prune.rng_all(near, lambda a, b, left=left: _rounded(every, left[a], left[b], alpha, places), FIRST, 20_000)
                yield one, left[keep], near[keep], (mine[None, :] < near[keep, None] + m).sum(axis=1)


def rng_proved(every: All, ids: np.ndarray, pairs: list[tuple[np.ndarray, np.ndarray]], alpha: float, places: int) -> Iterator[tuple[int, np.ndarray]]:
    """(place of p, which of its pairs) that none of all objects removes. pairs: places x and d per node."""
    todo = iter(pairs)
    for at, d, m in _blocks(every, ids, alpha):
        for k, one in enumerate(at.tolist()):
            x, dist = next(todo)
            y = np.flatnonzero(d[k] < dist.max(initial=0.0) + m)
            y = y[y != one]
            near = _rounded(every, np.array([one]), y, alpha, places)[0]
            good = np.ones(len(x), bool)
            for i in range(0, len(y), OBJECT_ROWS):
                part = slice(i, i + OBJECT_ROWS)
                good &= ~((near[part, None] < dist[None, :]) & (_rounded(every, y[part], x, alpha, places) < dist[None, :])).any(axis=0)
            yield one, good


def rng_edges(objects: DataFrame, norm: Norm, alpha: float, places: int = 9) -> DataFrame:
    """p, x, d of the exact relative neighbourhood graph at a weight; d to so many places.

    An edge is one both ways, so a pair has to be a candidate of both its nodes, and all its witnesses are
    among the objects nearer than d to either: they are looked for around the node that has fewer of them.
    """
    spark, (_, sent) = objects.sparkSession, send(objects)
    tasks = 4 * spark.sparkContext.defaultParallelism

    def find(batches):
        every = None
        for b in batches:
            every = All.of(sent.value, norm) if every is None else every
            for one, x, d, n in rng_candidates(every, b.column("id").to_numpy(), alpha, places):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), every.ids[one])), pa.array(every.ids[x]), pa.array(d), pa.array(n.astype(np.int64))], names=["p", "x", "d", "n"])

    def prove(batches):
        every = None
        for b in batches:
            every = All.of(sent.value, norm) if every is None else every
            p, xs = b.column("p").to_numpy(), [r.values for r in b.column("pairs")]
            pairs = [(np.searchsorted(every.ids, r.field("x").to_numpy()), r.field("d").to_numpy()) for r in xs]
            for (one, good), (x, d) in zip(rng_proved(every, p, pairs, alpha, places), pairs):
                a, b_, d = np.full(int(good.sum()), every.ids[one]), every.ids[x[good]], d[good]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([a, b_])), pa.array(np.concatenate([b_, a])), pa.array(np.concatenate([d, d]))], names=["p", "x", "d"])

    found = objects.select("id").repartition(tasks, "id").mapInArrow(find, "p long, x long, d double, n long")
    both = found.groupBy(F.least("p", "x").alias("a"), F.greatest("p", "x").alias("b")).agg(F.count(F.lit(1)).alias("ways"), F.min(F.struct("n", "p", "x", "d")).alias("r")).where("ways = 2").select("r.p", "r.x", "r.d")
    return both.repartition(tasks, "p").groupBy("p").agg(F.collect_list(F.struct("x", "d")).alias("pairs")).mapInArrow(prove, "p long, x long, d double")
