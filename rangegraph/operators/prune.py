"""Edge selection: the range-gated rule, the fixed-weight rule, the exact relative neighbourhood graph."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import alpha as al
from ..functions.vectors import l2_block, matrix
from ..schema import SCALE, BuildParams, Norm
from ..storage import stash
from .pareto import layer_block

FULL = [(0.0, 1.0)]


def order_of(layer: np.ndarray, de: np.ndarray, ds: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Candidates from the nearest layer on, each layer by (ds, de, id)."""
    return np.lexsort((ids, de, ds, layer))


def gate_block(de: np.ndarray, ds: np.ndarray, layer: np.ndarray, ids: np.ndarray, cross, M: int, th: float, cap: str = "layer", witness: str = "any") -> list[tuple[int, list[tuple[float, float]]]]:
    """Edges of one node: (place of the candidate, its active ranges), by layers from near to far.

    de, ds: distances from the node to its candidates; cross(): distances between candidates, as two matrices.
    A candidate keeps the weights at which no edge chosen before it is a witness; it becomes an edge if
    these are at least `th` of [0, 1]. After a layer (or inside it, cap='hard') M edges end the choice.
    """
    order = order_of(layer, de, ds, ids).tolist()
    x_e, x_s = cross()
    # for candidate x and witness y: the interval at which y removes x
    lo, hi = al.pruned_block(de[None, :], ds[None, :], de[:, None], ds[:, None], x_e, x_s)
    lo, hi, layer = lo.tolist(), hi.tolist(), layer.tolist()
    least = max(th, 1e-12)
    kept: list[int] = []
    ranges: dict[int, list[tuple[float, float]]] = {}
    now = layer[order[0]] if order else 0
    for x in order:
        if layer[x] != now:
            if len(kept) >= M:
                break
            now = layer[x]
        if cap == "hard" and len(kept) >= M:
            break
        a, b = lo[x], hi[x]
        if witness == "any":
            taken = [(a[y], b[y]) for y in kept if b[y] > a[y]]
        else:
            taken = [(max(a[y], i), min(b[y], j)) for y in kept if b[y] > a[y] for i, j in ranges[y]]
        taken.sort()
        free, at, total = [], 0.0, 0.0
        for i, j in taken:
            if j <= i:
                continue
            if i > at:
                free.append((at, i))
                total += i - at
            if j > at:
                at = j
                if total + 1.0 - at < least:  # what is left can't reach the threshold
                    break
        else:
            if at < 1.0:
                free.append((at, 1.0))
                total += 1.0 - at
            if total >= least:
                kept.append(x)
                ranges[x] = free
    return [(x, ranges[x]) for x in kept]


FIRST = 8  # candidates that are looked at before the first removal of others


def _free(lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Per column the length of [0, 1] that no interval of it covers."""
    if not len(lo):
        return np.ones(lo.shape[1])
    order = lo.argsort(axis=0)
    lo = np.take_along_axis(lo, order, 0)
    reach = np.maximum(np.maximum.accumulate(np.take_along_axis(hi, order, 0), axis=0), 0.0)
    gaps = np.maximum(lo[1:] - reach[:-1], 0.0).sum(axis=0)
    return np.maximum(lo[0], 0.0) + gaps + np.maximum(1.0 - reach[-1], 0.0)


def gate_all(de: np.ndarray, ds: np.ndarray, ids: np.ndarray, cross, th: float = 0.0, witness: str = "any", ties: str = "peel") -> list[tuple[int, list[tuple[float, float]]]]:
    """As gate_block without a cap, for very many candidates: cross(a, b) measures the places a against b when they are needed.

    Some of the nearest candidates left are chosen from at a time; then those whose weights the new edges take leave the rest.
    """
    left, least = order_of(layer_block(de, ds, ids, ties), de, ds, ids), max(th, 1e-12)
    lo, hi = np.zeros((0, len(left))), np.zeros((0, len(left)))  # intervals that edges have taken, per candidate left; empty ones as (2, -1)
    out, many = [], FIRST

    def taken(x_e, x_s, y, x):
        a, b = al.pruned_block(de[y][:, None], ds[y][:, None], de[x][None, :], ds[x][None, :], x_e, x_s)
        return a, b

    while len(left):
        now, rest = left[:many], left[many:]
        a, b = taken(*cross(now, now), now, now)
        a, b, old_lo, old_hi = a.tolist(), b.tolist(), lo[:, :many].T.tolist(), hi[:, :many].T.tolist()
        kept, ranges = [], {}
        for i in range(len(now)):
            mine = [(j, k) for j, k in zip(old_lo[i], old_hi[i]) if k > j]
            for y in kept:
                if b[y][i] > a[y][i]:
                    mine += [(a[y][i], b[y][i])] if witness == "any" else [(max(a[y][i], j), min(b[y][i], k)) for j, k in ranges[y]]
            mine.sort()
            free, at, total = [], 0.0, 0.0
            for j, k in mine:
                if k <= j:
                    continue
                if j > at:
                    free.append((at, j))
                    total += j - at
                if k > at:
                    at = k
                    if total + 1.0 - at < least:
                        break
            else:
                if at < 1.0:
                    free.append((at, 1.0))
                    total += 1.0 - at
                if total >= least:
                    kept.append(i)
                    ranges[i] = free
        out += [(int(now[i]), ranges[i]) for i in kept]
        lo, hi = lo[:, many:], hi[:, many:]
        if kept and len(rest):
            y = now[kept]
            a, b = taken(*cross(y, rest), y, rest)
            if witness != "any":
                row, j, k = (np.array(v) for v in zip(*[(i, *r) for i, x in enumerate(kept) for r in ranges[x]]))
                a, b = np.maximum(a[row], j[:, None]), np.minimum(b[row], k[:, None])
            none = b <= a
            a[none], b[none] = 2.0, -1.0
            lo, hi = np.vstack([lo, a]), np.vstack([hi, b])
            stay = _free(np.minimum(lo, 1.0), hi) >= least
            rest, lo, hi = rest[stay], lo[:, stay], hi[:, stay]
        left, many = rest, min(2 * many, 64)
    return out


def rng_block(dist: np.ndarray, ids: np.ndarray, cross, M: int) -> list[int]:
    """The fixed-weight rule: a candidate becomes an edge if no chosen one is nearer to it than the node is."""
    kept: list[int] = []
    d, left = cross(), np.lexsort((ids, dist))
    while len(left) and len(kept) < M:
        y, left = int(left[0]), left[1:]
        kept.append(y)
        left = left[d[left, y] >= dist[left]]
    return kept


def rng_all(dist: np.ndarray, cross, first: int = 4, cells: int = 60_000) -> np.ndarray:
    """Places, by rising distance, of the neighbours of one node in the exact relative neighbourhood graph.

    cross(a, b): distances between places. Witnesses come from near to far, more at a time the fewer candidates are left.
    """
    order = dist.argsort(kind="stable")
    left, at, many = order, 0, first
    while at < len(order) and len(left):
        y = order[at : at + many]
        left = left[~((dist[y][:, None] < dist[left][None, :]) & (cross(y, left) < dist[left][None, :])).any(axis=0)]
        at += len(y)
        if len(left) and at < len(order) and dist[order[at]] >= dist[left[-1]]:
            break  # no witness is nearer than any that is left
        many = max(first, cells // max(1, len(left)))
    return left


EDGES = "src long, dst long, lo short, hi short"


def edge_rows(src, dst, ivals) -> tuple[list, list, list, list]:
    """Edges as a row per interval, ends rounded outwards."""
    a, b, c, d = [], [], [], []
    for s, t, free in zip(src, dst, ivals):
        for i, j in free:
            lo, hi = al.encode_pair(i, j)
            a.append(s), b.append(t), c.append(lo), d.append(hi)
    return a, b, c, d


def _grouped(candidates: DataFrame, run) -> DataFrame:
    return candidates.groupBy("p").applyInArrow(run, EDGES)


def _table(a, b, c, d) -> pa.Table:
    return pa.table({"src": pa.array(a, pa.int64()), "dst": pa.array(b, pa.int64()), "lo": pa.array(c, pa.int16()), "hi": pa.array(d, pa.int16())})


def range_gated(candidates: DataFrame, norm: Norm, M: int, th: float, cap: str = "layer", witness: str = "any", ties: str = "peel") -> DataFrame:
    """src, dst, lo, hi of the edges of each p from its candidate rows (p, x, de, ds, e, s of x); one group per node, of bounded size."""

    def run(t: pa.Table) -> pa.Table:
        de, ds, x = (t.column(c).to_numpy() for c in ("de", "ds", "x"))
        e, s = matrix(t.column("e")), matrix(t.column("s"))
        layer = layer_block(de, ds, x, ties)
        got = gate_block(de, ds, layer, x, lambda: (l2_block(e, e) / norm.e, l2_block(s, s) / norm.s), M, th, cap, witness)
        return _table(*edge_rows([t.column("p")[0].as_py()] * len(got), [int(x[i]) for i, _ in got], [r for _, r in got]))

    return _grouped(candidates, run)


def rng_greedy(candidates: DataFrame, norm: Norm, alpha: float, M: int) -> DataFrame:
    """The same at one weight: edges of full range."""

    def run(t: pa.Table) -> pa.Table:
        de, ds, x = (t.column(c).to_numpy() for c in ("de", "ds", "x"))
        e, s = matrix(t.column("e")), matrix(t.column("s"))
        got = rng_block(alpha * de + (1 - alpha) * ds, x, lambda: alpha * l2_block(e, e) / norm.e + (1 - alpha) * l2_block(s, s) / norm.s, M)
        return _table(*edge_rows([t.column("p")[0].as_py()] * len(got), [int(x[i]) for i in got], [FULL] * len(got)))

    return _grouped(candidates, run)


def rng(distances: DataFrame, alpha: float, places: int = 9, first: int = 10) -> DataFrame:
    """p, x, d of the exact relative neighbourhood graph at a weight, from all pair rows (p, x, de, ds); for small tables.

    Anti-joins on witnesses: the `first` nearest of each p remove most pairs, and only what they leave meets all others.
    """
    d = stash(distances.select("p", "x", F.round(F.lit(alpha) * F.col("de") + F.lit(1 - alpha) * F.col("ds"), places).alias("d")), "pairs")
    w1 = d.select("p", F.col("x").alias("y"), F.col("d").alias("py"))
    w2 = d.select(F.col("p").alias("y"), "x", F.col("d").alias("yx"))

    def without(pairs: DataFrame, witnesses: DataFrame) -> DataFrame:
        removed = pairs.join(witnesses, "p").where("py < d").join(w2, ["y", "x"]).where("yx < d").select("p", "x").distinct()
        return pairs.join(removed, ["p", "x"], "left_anti")

    near = w1.withColumn("r", F.row_number().over(Window.partitionBy("p").orderBy("py", "y"))).where(F.col("r") <= first).drop("r")
    return without(stash(without(d, near), "pairs"), w1).select("p", "x", "d")


def rng_edges_block(dist: np.ndarray) -> np.ndarray:
    """The relative neighbourhood graph of a distance matrix, as a boolean matrix."""
    n = len(dist)
    out = np.zeros((n, n), bool)
    for p in range(n):
        for x in range(n):
            if p != x:
                out[p, x] = not ((dist[p] < dist[p, x]) & (dist[:, x] < dist[p, x])).any()
    return out


def params_rule(params: BuildParams):
    """The selection of a build: (de, ds, ids, e, s, norm) -> (places, ranges)."""

    def pick(de, ds, ids, e, s, norm: Norm):
        if not len(de):
            return [], []
        if params.pruning == "none":
            order = order_of(layer_block(de, ds, ids, params.ties), de, ds, ids)[: params.M].tolist()
            return order, [FULL] * len(order)
        if params.pruning == "rng":
            a = params.alpha0
            got = rng_block(a * de + (1 - a) * ds, ids, lambda: a * l2_block(e, e) / norm.e + (1 - a) * l2_block(s, s) / norm.s, params.M)
            return got, [FULL] * len(got)
        got = gate_block(de, ds, layer_block(de, ds, ids, params.ties), ids, lambda: (l2_block(e, e) / norm.e, l2_block(s, s) / norm.s), params.M, params.th, params.cap, params.witness)
        return [x for x, _ in got], [r for _, r in got]

    return pick


assert SCALE < 2**15
