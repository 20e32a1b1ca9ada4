"""The graph of one shard: insertion one by one, and best-first search over it. Runs inside a task, in numpy."""

from __future__ import annotations

import heapq
import time
from bisect import bisect_right

import numpy as np

from ..functions.hashing import mix
from ..functions.vectors import l2_rows
from ..schema import SCALE, BuildParams, Norm
from .pareto import keep_bound, layer_block
from .prune import FULL, params_rule
from .seeds import rim_block


class Graph:
    """Nodes with two vectors, adjacency with active ranges, start nodes, and counters of work.

    While it is built, a node has its neighbours and ranges in lists; a graph that is only read has its arcs as flat
    arrays (`load`). levels: per upper level a dict from node to its arcs.
    """

    def __init__(self, ids: np.ndarray, e: np.ndarray, s: np.ndarray, norm: Norm):
        self.ids, self.e, self.s, self.norm = ids, e, s, norm
        self.nbrs: list[np.ndarray] = [np.zeros(0, np.int64)] * len(ids)
        self.ranges: list[list] = [[] for _ in range(len(ids))]
        self.seeds = np.zeros(0, np.int64)
        self.levels: list[dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]] = []
        self.n_dist = 0
        self.flat: list[tuple[np.ndarray, np.ndarray, np.ndarray] | None] = [None] * len(ids)
        self.start: np.ndarray | None = None

    def load(self, start: np.ndarray, dst: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> None:
        """All arcs as flat arrays; those of node p are in start[p] to start[p + 1]."""
        self.start, self.dst, self.lo, self.hi = start, dst, lo, hi

    def pair(self, p: int, xs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        self.n_dist += len(xs)
        return l2_rows(self.e[p], self.e[xs]) / self.norm.e, l2_rows(self.s[p], self.s[xs]) / self.norm.s

    def to_query(self, qe, qs, xs) -> tuple[np.ndarray, np.ndarray]:
        return l2_rows(qe, self.e[xs]) / self.norm.e, l2_rows(qs, self.s[xs]) / self.norm.s

    def set_edges(self, p: int, nbrs, ranges) -> None:
        self.nbrs[p] = np.asarray(nbrs, np.int64)
        self.ranges[p] = list(ranges)
        self.flat[p] = None

    def arcs(self, p: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Neighbours of p, one place per active interval, with stored ends."""
        if self.start is not None:
            at = slice(self.start[p], self.start[p + 1])
            return self.dst[at], self.lo[at], self.hi[at]
        if self.flat[p] is None:
            dst, lo, hi = [], [], []
            for x, free in zip(self.nbrs[p].tolist(), self.ranges[p]):
                for i, j in free:
                    dst.append(x), lo.append(int(np.floor(i * SCALE))), hi.append(int(np.ceil(j * SCALE)))
            self.flat[p] = np.array(dst, np.int64), np.array(lo, np.int32), np.array(hi, np.int32)
        return self.flat[p]

    def near(self, p: int) -> np.ndarray:
        """Neighbours of p; in a graph that is only read one of several intervals is there as often."""
        return self.nbrs[p] if self.start is None else self.dst[self.start[p] : self.start[p + 1]]


NO_ARCS = (np.zeros(0, np.int64), np.zeros(0, np.int32), np.zeros(0, np.int32))


def always(nbrs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Arcs that are active at every weight."""
    return nbrs, np.zeros(len(nbrs), np.int32), np.full(len(nbrs), SCALE, np.int32)


def frontier_search(g: Graph, qe, qs, starts: np.ndarray, ef: int, ties: str = "peel") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Approximate layers of frontiers around a point: (nodes, de, ds), at most about ef.

    The pool starts from the seeds; the nearest layer with nodes not yet explored is explored whole, its
    neighbours join the pool, which is layered anew and cut to ef. Ends when all is explored.
    """
    seen = np.zeros(len(g.ids), bool)
    pool = np.asarray(starts, np.int64)
    seen[pool] = True
    de, ds = g.to_query(qe, qs, pool)
    g.n_dist += len(pool)
    explored = np.zeros(len(pool), bool)
    layer = None
    while True:
        if layer is None:  # the pool has changed
            layer = layer_block(de, ds, g.ids[pool], ties)
            if len(pool) > ef:
                keep = keep_bound(layer, ef)
                pool, de, ds, explored, layer = pool[keep], de[keep], ds[keep], explored[keep], layer[keep]
        left = ~explored
        if not left.any():
            return pool, de, ds
        now = left & (layer == layer[left].min())
        explored |= now
        new = np.concatenate([g.near(p) for p in pool[now].tolist()])
        new = new[~seen[new]]
        if len(new):
            seen[new] = True
            new = np.unique(new)
            a, b = g.to_query(qe, qs, new)
            g.n_dist += len(new)
            pool, de, ds = np.concatenate([pool, new]), np.concatenate([de, a]), np.concatenate([ds, b])
            explored = np.concatenate([explored, np.zeros(len(new), bool)])
            layer = None


COUNTS = ("n_dist", "hops", "scanned", "gated", "stopped")


def best_first(g: Graph, qe, qs, alpha: float, starts, ef: int, gate: bool = True, early_stop: bool = True, adjacency=None, counts: dict | None = None) -> list[tuple[float, int]]:
    """The ef nearest nodes found from the starts, in order: (distance, node).

    gate: edges that are not active at alpha are left out. adjacency: the arcs of an upper level. early_stop: the part of the distance that is
    cheaper for its weight is computed first, and the rest only where that part is within the worst result.
    """
    c = counts if counts is not None else {}
    for name in COUNTS:
        c.setdefault(name, 0)
    a = int(round(alpha * SCALE))
    we, ws = alpha / g.norm.e, (1 - alpha) / g.norm.s
    parts = [(g.s, qs, ws), (g.e, qe, we)]
    if g.s.shape[1] * max(we, 1e-12) > g.e.shape[1] * max(ws, 1e-12):
        parts.reverse()
    (m1, q1, w1), (m2, q2, w2) = parts
    seen = np.zeros(len(g.ids), bool)
    starts = np.asarray(starts, np.int64)
    seen[starts] = True
    d = w1 * l2_rows(q1, m1[starts]) + w2 * l2_rows(q2, m2[starts])
    c["n_dist"] += len(starts)
    todo = list(zip(d.tolist(), starts.tolist()))
    heapq.heapify(todo)
    found = [(-x, -i) for x, i in todo]
    heapq.heapify(found)
    while len(found) > ef:
        heapq.heappop(found)
    while todo:
        dist, p = heapq.heappop(todo)
        if len(found) >= ef and dist > -found[0][0]:
            break
        c["hops"] += 1
        dst, lo, hi = g.arcs(p) if adjacency is None else adjacency.get(p, NO_ARCS)
        c["scanned"] += len(dst)
        xs = dst
        if gate:
            xs = dst[(lo <= a) & (a <= hi)]
            c["gated"] += len(dst) - len(xs)
        xs = xs[~seen[xs]]
        if not len(xs):
            continue
        if len(xs) > 1:  # the intervals of an edge stand side by side
            new = np.ones(len(xs), bool)
            new[1:] = xs[1:] != xs[:-1]
            xs = xs[new]
        seen[xs] = True
        c["n_dist"] += len(xs)
        part = w1 * l2_rows(q1, m1[xs])
        if early_stop and len(found) >= ef:
            near = part <= -found[0][0]
            c["stopped"] += int((~near).sum())
            xs, part = xs[near], part[near]
        total = part + w2 * l2_rows(q2, m2[xs])
        for x, y in zip(total.tolist(), xs.tolist()):
            if len(found) < ef:
                heapq.heappush(found, (-x, -y))
                heapq.heappush(todo, (x, y))
            elif x < -found[0][0]:
                heapq.heapreplace(found, (-x, -y))
                heapq.heappush(todo, (x, y))
    return sorted((-x, -i) for x, i in found)


def sweep(g: Graph, qe, qs, alpha: float, starts, efs, gate: bool = True, early_stop: bool = True, counts: dict | None = None) -> dict[int, tuple[list[tuple[float, int]], dict, float]]:
    """best_first for several ef in one search: per ef (results, counts, clock), as they are when a search with that ef ends.

    A search always expands the nearest node that is left, so one with a larger ef goes the same way and then on. A node that
    `place` others are no farther than when it is met is of use to an ef above that only. Of equal distances the one met first comes first.
    """
    c = {name: (counts or {}).get(name, 0) for name in COUNTS}
    active, a = sorted(set(efs)), int(round(alpha * SCALE))
    most, stopped = active[-1], dict.fromkeys(active, c["stopped"])
    we, ws = alpha / g.norm.e, (1 - alpha) / g.norm.s
    parts = [(g.s, qs, ws), (g.e, qe, we)]
    if g.s.shape[1] * max(we, 1e-12) > g.e.shape[1] * max(ws, 1e-12):
        parts.reverse()
    (m1, q1, w1), (m2, q2, w2) = parts
    seen = np.zeros(len(g.ids), bool)
    starts = np.asarray(starts, np.int64)
    seen[starts] = True
    d = w1 * l2_rows(q1, m1[starts]) + w2 * l2_rows(q2, m2[starts])
    c["n_dist"] += len(starts)
    todo = [(x, i, y) for i, (x, y) in enumerate(sorted(zip(d.tolist(), starts.tolist())))]
    near, nodes = [x for x, _, _ in todo[:most]], [y for _, _, y in todo[:most]]  # the `most` nearest so far
    out = {}

    def end(ef: int) -> None:
        out[ef] = sorted(zip(near[:ef], nodes[:ef])), c | {"stopped": stopped[ef]}, time.perf_counter()

    while todo:
        dist, place, p = heapq.heappop(todo)
        while active and (place >= active[0] or (len(near) >= active[0] and dist > near[active[0] - 1])):
            end(active.pop(0))
        if not active:
            break
        c["hops"] += 1
        xs, lo, hi = g.arcs(p)
        c["scanned"] += len(xs)
        if gate:
            on = (lo <= a) & (a <= hi)
            c["gated"] += len(xs) - int(on.sum())
            xs = xs[on]
        xs = xs[~seen[xs]]
        if not len(xs):
            continue
        if len(xs) > 1:  # the intervals of an edge stand side by side
            new = np.ones(len(xs), bool)
            new[1:] = xs[1:] != xs[:-1]
            xs = xs[new]
        seen[xs] = True
        c["n_dist"] += len(xs)
        part = w1 * l2_rows(q1, m1[xs])
        if early_stop and len(near) >= active[0]:
            full = [ef for ef in active if len(near) >= ef]
            far = (part > np.array([near[ef - 1] for ef in full])[:, None]).sum(axis=1)
            for ef, n in zip(full, far.tolist()):
                stopped[ef] += n
            if full[-1] == most and far[-1]:
                xs, part = xs[part <= near[-1]], part[part <= near[-1]]
        total = part + w2 * l2_rows(q2, m2[xs])
        for x, y in zip(total.tolist(), xs.tolist()):
            if len(near) < most or x < near[-1]:
                place = bisect_right(near, x)
                near.insert(place, x)
                nodes.insert(place, y)
                heapq.heappush(todo, (x, place, y))
                if len(near) > most:
                    near.pop()
                    nodes.pop()
    for ef in active:
        end(ef)
    return out


def node_levels(ids: np.ndarray, M: int, seed: int) -> np.ndarray:
    """Geometric levels from a seeded hash of the id."""
    import hashlib

    u = np.array([(int(hashlib.md5(f"{seed}:{i}".encode()).hexdigest()[:12], 16) + 1) / 2**48 for i in ids.tolist()])
    return np.floor(-np.log(u) / np.log(max(M, 2))).astype(np.int32)


def build(ids: np.ndarray, e: np.ndarray, s: np.ndarray, norm: Norm, params: BuildParams, order: np.ndarray | None = None) -> Graph:
    """Inserts the nodes one after the other."""
    g = Graph(ids, e, s, norm)
    if not len(ids):
        return g
    order = np.arange(len(ids)) if order is None else order
    if params.levels:
        return _build_levels(g, params, order)
    return _insert(g, params, order, 0)


def extend(old: Graph, ids: np.ndarray, e: np.ndarray, s: np.ndarray, params: BuildParams, order: np.ndarray | None = None) -> Graph:
    """The graph with further nodes inserted into it, as if they had come last. Not for graphs with levels.

    The rim is seen from the centroid of all nodes, old and new. Stored ranges are read back as they are stored.
    """
    if params.levels:
        raise ValueError("a graph with levels is built anew")
    n = len(old.ids)
    g = Graph(np.concatenate([old.ids, ids]), np.concatenate([old.e, e]) if n else e, np.concatenate([old.s, s]) if n else s, old.norm)
    for p in range(n):
        dst, lo, hi = old.arcs(p)
        at = np.flatnonzero(np.concatenate([[True], dst[1:] != dst[:-1]])) if len(dst) else np.zeros(0, np.int64)
        ends = np.append(at[1:], len(dst))
        g.set_edges(p, dst[at], [list(zip((lo[a:b] / SCALE).tolist(), (hi[a:b] / SCALE).tolist())) for a, b in zip(at, ends)])
    order = np.arange(len(ids)) if order is None else order
    first = old.seeds.astype(np.int64)
    return _insert(g, params, np.concatenate([np.arange(n), n + order]), n, first) if len(g.ids) else g


def _insert(g: Graph, params: BuildParams, order: np.ndarray, have: int, first: np.ndarray | None = None) -> Graph:
    """Inserts order[have:] into a graph whose nodes order[:have] are there (order[0] with no edges counts as there)."""
    ids, e, s, norm = g.ids, g.e, g.s, g.norm
    pick = params_rule(params)
    ce, cs = e.mean(axis=0), s.mean(axis=0)
    rim_e, rim_s = g.to_query(ce, cs, np.arange(len(ids)))
    sign = 1 if params.seeds == "rim" else -1
    start = np.array([int(order[0])])
    there = order[: max(have, 1)]
    rim = there[rim_block(sign * rim_e[there], sign * rim_s[there], ids[there])] if params.seeds in ("rim", "centroid") else start
    fixed = start
    if params.seeds == "random":  # as many as the rim of the whole shard
        fixed = np.random.default_rng(params.seed).permutation(len(ids))[: len(rim_block(rim_e, rim_s, ids))]
    done = np.zeros(len(ids), bool)
    done[there] = True
    for p in order[max(have, 1) :].tolist():
        starts = {"rim": rim, "first": start, "centroid": rim, "random": fixed[done[fixed]] if done[fixed].any() else start}[params.seeds]
        if first is not None and len(first):  # entries of the stored graph reach what the new rim may not
            starts = np.union1d(starts, first)
        pool, de, ds = candidates(g, e[p], s[p], starts, params)
        places, free = pick(de, ds, ids[pool], e[pool], s[pool], norm)
        g.set_edges(p, pool[places], free)
        for y, r in zip(pool[places].tolist(), free):
            refresh_reverse(g, y, p, r, params, pick)
        done[p] = True
        if params.seeds in ("rim", "centroid"):
            both = np.append(rim, p)
            rim = both[rim_block(sign * rim_e[both], sign * rim_s[both], ids[both])]
    g.seeds = {"rim": rim, "centroid": rim, "first": start, "random": fixed}[params.seeds]
    g.seeds = _thinned(g.seeds, rim_s, params)
    return g


def candidates(g: Graph, qe, qs, starts: np.ndarray, params: BuildParams) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(nodes, de, ds) among which a new node chooses its edges."""
    if params.candidates != "greedy":
        return frontier_search(g, qe, qs, starts, params.ef_c, params.ties)
    got = best_first(g, qe, qs, params.alpha0, starts, params.ef_c, gate=params.pruning == "range", early_stop=False, counts=(c := {}))
    g.n_dist += c["n_dist"]
    pool = np.array([i for _, i in got], np.int64)
    return pool, *g.to_query(qe, qs, pool)


def _thinned(seeds: np.ndarray, rim_s: np.ndarray, params: BuildParams) -> np.ndarray:
    """At most max_seeds of the start nodes, evenly along the staircase."""
    if not params.max_seeds or len(seeds) <= params.max_seeds:
        return seeds
    along = seeds[np.argsort(rim_s[seeds], kind="stable")]
    return along[np.linspace(0, len(along) - 1, params.max_seeds).round().astype(int)]


def entries(ids: np.ndarray, e: np.ndarray, s: np.ndarray, norm: Norm, params: BuildParams) -> np.ndarray:
    """Start nodes of a finished graph of these nodes, as one-by-one insertion leaves them."""
    order = np.lexsort((ids, mix(ids, params.seed)))
    if params.levels:
        level = node_levels(ids, params.M, params.seed)
        return order[[level[order].argmax()]]
    if params.seeds == "first":
        return order[:1]
    rim_e, rim_s = l2_rows(e.mean(axis=0), e) / norm.e, l2_rows(s.mean(axis=0), s) / norm.s
    if params.seeds == "random":
        seeds = np.random.default_rng(params.seed).permutation(len(ids))[: len(rim_block(rim_e, rim_s, ids))]
    else:
        sign = 1 if params.seeds == "rim" else -1
        seeds = rim_block(sign * rim_e, sign * rim_s, ids)
    return _thinned(seeds, rim_s, params)


def refresh_reverse(g: Graph, y: int, p: int, ranges, params: BuildParams, pick) -> None:
    """The edge back from y to the new node p: y chooses again among its neighbours and p, with all ranges anew."""
    if params.reverse == "append":
        have = np.append(g.nbrs[y], p)
        if len(have) <= 2 * params.M:
            g.set_edges(y, have, g.ranges[y] + [ranges])
            return
    pool = np.append(g.nbrs[y], p)
    if params.pruning == "none" and len(pool) <= params.M:
        g.set_edges(y, pool, [FULL] * len(pool))
        return
    de, ds = g.pair(y, pool)
    places, free = pick(de, ds, g.ids[pool], g.e[pool], g.s[pool], g.norm)
    g.set_edges(y, pool[places], free)


def _build_levels(g: Graph, params: BuildParams, order) -> Graph:
    """A hierarchical small-world graph at alpha0: levels by a geometric law, descent, fixed-weight selection."""
    ids, e, s, norm, a = g.ids, g.e, g.s, g.norm, params.alpha0
    order = np.arange(len(ids)) if order is None else order
    level = node_levels(ids, params.M, params.seed)
    g.levels = [dict() for _ in range(int(level.max()) + 1)]
    pick = params_rule(params.but(pruning="rng"))
    top = int(order[0])
    for k in range(level[top] + 1):
        g.levels[k][top] = NO_ARCS
    for p in order[1:].tolist():
        at = [top]
        for k in range(int(level[top]), -1, -1):
            ef = params.ef_c if k <= level[p] else 1
            c: dict = {}
            got = best_first(g, e[p], s[p], a, at, ef, False, False, g.levels[k], c)
            g.n_dist += c["n_dist"]
            at = [i for _, i in got]
            if k <= level[p]:
                pool = np.array(at, np.int64)
                de, ds = g.to_query(e[p], s[p], pool)
                places, _ = pick(de, ds, ids[pool], e[pool], s[pool], norm)
                g.levels[k][p] = always(pool[places])
                cap = params.M * (params.level0_factor if k == 0 else 1)
                for y in pool[places].tolist():
                    back = np.append(g.levels[k].get(y, NO_ARCS)[0], p)
                    if len(back) > cap:
                        de, ds = g.pair(y, back)
                        keep, _ = params_rule(params.but(pruning="rng", M=cap))(de, ds, ids[back], e[back], s[back], norm)
                        back = back[keep]
                    g.levels[k][y] = always(back)
        for k in range(int(level[p]) + 1):
            g.levels[k].setdefault(p, NO_ARCS)
        if level[p] > level[top]:
            top = p
    g.seeds = np.array([top])
    for p in range(len(ids)):
        near = g.levels[0].get(p, NO_ARCS)[0]
        g.set_edges(p, near, [FULL] * len(near))
    return g


def entry(g: Graph, qe, qs, alpha: float, counts: dict, gate: bool = False) -> np.ndarray | list[int]:
    """Start nodes at the bottom of a graph: its seeds, or in a graph with levels where the greedy descent ends."""
    at = g.seeds
    for k in range(len(g.levels) - 1, 0, -1):
        if any(int(i) in g.levels[k] for i in at):
            at = [i for _, i in best_first(g, qe, qs, alpha, at, 1, gate, False, g.levels[k], counts)]
    return at


def descend(g: Graph, qe, qs, alpha: float, ef: int, counts: dict, gate: bool = False) -> list[tuple[float, int]]:
    """Search of a graph with levels: greedy above, best-first at the bottom."""
    return best_first(g, qe, qs, alpha, entry(g, qe, qs, alpha, counts, gate), ef, gate, True, None, counts)


def reachable(g: Graph, alpha: float | None = None) -> np.ndarray:
    """Nodes that can be reached from the seeds (at a weight: over active edges)."""
    seen = np.zeros(len(g.ids), bool)
    todo = g.seeds.tolist()
    seen[g.seeds] = True
    while todo:
        dst, lo, hi = g.arcs(todo.pop())
        if alpha is not None:
            a = int(round(alpha * SCALE))
            dst = dst[(lo <= a) & (a <= hi)]
        new = np.unique(dst[~seen[dst]])
        seen[new] = True
        todo += new.tolist()
    return seen
