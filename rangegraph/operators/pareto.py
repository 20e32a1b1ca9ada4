"""Frontiers in the plane of the two distances: dominance, the frontier, peeled layers."""

from __future__ import annotations

from bisect import bisect_right

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..schema import FRONTIER


def dominates(a_de, a_ds, b_de, b_ds) -> Column:
    """a is no farther in both and nearer in one."""
    a_de, a_ds, b_de, b_ds = (F.col(c) if isinstance(c, str) else c for c in (a_de, a_ds, b_de, b_ds))
    return (a_de <= b_de) & (a_ds <= b_ds) & ((a_de < b_de) | (a_ds < b_ds))


def frontier(pairs: DataFrame, by: str | None = "p", ties: str = "peel", order: str = "x") -> DataFrame:
    """The rows of (de, ds) that nothing dominates, per group; with ties='peel' one of equal rows only."""
    keys = [by] if by else []
    w = Window.partitionBy(*keys).orderBy("ds", "de", order) if keys else Window.orderBy("ds", "de", order)
    before = F.min("de").over(w.rowsBetween(Window.unboundedPreceding, -1))
    kept = pairs.withColumn("_min", before).where(F.col("_min").isNull() | (F.col("de") < F.col("_min"))).drop("_min")
    if ties == "peel":
        return kept
    twins = kept.select(*keys, "de", "ds")
    return pairs.join(twins, [*keys, "de", "ds"], "left_semi")


def global_frontier(rows: DataFrame, order: str = "id") -> DataFrame:
    """The frontier of a whole table without one task seeing all rows: the frontier of the partitions' frontiers.

    A task keeps the frontier of what it has read so far and gives it once, so the last step gets a few rows per task.
    """

    def local(batches):
        held = None
        for b in batches:
            t = pa.Table.from_batches([b] if held is None else [*held, b]).combine_chunks()
            de, ds, ids = (t.column(c).to_numpy() for c in ("de", "ds", order))
            at = np.lexsort((ids, de, ds))
            least = np.minimum.accumulate(np.concatenate([[np.inf], de[at]]))[:-1]
            held = t.take(pa.array(np.sort(at[de[at] < least]))).to_batches()
        yield from held or []

    return frontier(rows.mapInArrow(local, rows.schema), None, order=order)


def layer_block(de: np.ndarray, ds: np.ndarray, ids: np.ndarray, ties: str = "peel") -> np.ndarray:
    """Layer (from 1) of each point in one pass.

    Points come in the order (ds, de, id); a point belongs to the first layer whose least de so far is
    larger, and these least values rise from layer to layer, so it is found by bisection.
    """
    order = np.lexsort((ids, de, ds))
    out = np.empty(len(de), np.int32)
    tails: list[float] = []
    got: list[int] = []
    if ties == "definition":
        last = (None, None, 0)
        for x, y in zip(de[order].tolist(), ds[order].tolist()):
            k = last[2] if (x, y) == last[:2] else bisect_right(tails, x)
            if k == len(tails):
                tails.append(x)
            else:
                tails[k] = x
            last = (x, y, k)
            got.append(k + 1)
    else:
        n = 0
        for x in de[order].tolist():
            k = bisect_right(tails, x)
            if k == n:
                tails.append(x)
                n += 1
            else:
                tails[k] = x
            got.append(k + 1)
    out[order] = got
    return out


def keep_bound(layer: np.ndarray, bound: int | None) -> np.ndarray:
    """Whole layers from the nearest on, up to `bound` points; the first always."""
    if bound is None or len(layer) <= bound:
        return np.ones(len(layer), bool)
    upto = np.cumsum(np.bincount(layer)[1:])
    last = max(1, int(np.searchsorted(upto, bound, "right")))
    return layer <= last


#: Weights at which chains are looked for; any would do, these leave few rows.
WEIGHTS = (0.5, 0.25, 0.75, 0.1, 0.9, 0.03, 0.97)


def in_first_layers(de: np.ndarray, ds: np.ndarray, most: int) -> np.ndarray:
    """Places of all points of the first `most` layers, and of some more.

    A point left out is farther in both distances than the last of a chain of `most` points that are each farther in both
    than the one before, so its layer is above `most`; the others keep their layers up to `most` without it.
    """
    at = np.arange(len(de))
    for w in WEIGHTS:
        a, b = de[at], ds[at]
        d, left = w * a + (1 - w) * b, np.arange(len(at))
        for _ in range(most):
            if not len(left):
                break
            end = left[d[left].argmin()]
            left = left[(a[left] > a[end]) & (b[left] > b[end])]
        keep = np.ones(len(at), bool)
        keep[left] = False
        at = at[keep]
    return at


def in_bounded_layers(de: np.ndarray, ds: np.ndarray, bound: int) -> np.ndarray:
    """Places of all points of the layers that keep_bound keeps and of the next one, and of some more.

    Layers of up to `bound` points and the next hold only points that at most `bound` others come before. A point left out
    is farther in both distances than `bound` + 1 others, and so is all that it comes before, so the rest keep their layers.
    """
    at, low = np.arange(len(de)), np.arange(len(de))
    while len(low) > 2 * (bound + 1):
        half = len(low) // 2
        low = low[np.argpartition(de[low], half)[: half + 1]]
        x, y = de[low].max(), np.partition(ds[low], bound)[bound]
        at = at[~((de[at] > x) & (ds[at] > y))]
    return at


def dominated_pairs(de: np.ndarray, ds: np.ndarray, first: int = 64) -> int:
    """Number of ordered pairs of which the one is no farther in both distances and nearer in one.

    In the order (de, ds) these are the pairs whose ds does not fall, without equal points. Runs of `first` are compared
    outright; then runs are doubled, and the places of a left run's rows among both, sorted by ds, give its pairs with the right.
    """
    n = len(de)
    if n < 2:
        return 0
    order = np.lexsort((ds, de))
    x, y = de[order], ds[order]
    same = np.flatnonzero(np.concatenate([[True], (x[1:] != x[:-1]) | (y[1:] != y[:-1]), [True]]))
    twins = np.diff(same)
    rank = np.unique(y, return_inverse=True)[1].astype(np.int64)
    size = first << max(0, int(np.ceil(np.log2(n / first))))
    rank = np.concatenate([rank, np.full(size - n, -1, np.int64)])  # the rows that fill up come last and are under all
    runs = rank.reshape(-1, first)
    below = sum(int((runs[:, i : i + 1] <= runs[:, i + 1 :]).sum()) for i in range(first - 1))
    below -= _among(size - n, first)
    while first < size:
        # left rows come before right ones of equal rank
        both = np.sort(rank.reshape(-1, 2 * first) * 2 + np.repeat([0, 1], first), axis=1)
        right = (both & 1).astype(np.int64)
        after = right.sum(axis=1, keepdims=True) - np.cumsum(right, axis=1)
        below += int(after[(right == 0) & (both >= 0)].sum())
        first *= 2
    return below - int((twins * (twins - 1) // 2).sum())


def _among(fill: int, first: int) -> int:
    """Pairs inside runs of `first` of the last `fill` rows."""
    whole_runs, rest = divmod(fill, first)
    return whole_runs * (first * (first - 1) // 2) + rest * (rest - 1) // 2


def layers(pairs: DataFrame, bound: int | None = None, ties: str = "peel") -> DataFrame:
    """Rows with their layer, per p, in one pass; groups are candidate pools of bounded size."""

    def run(t: pa.Table) -> pa.Table:
        de, ds, x = (t.column(c).to_numpy() for c in ("de", "ds", "x"))
        layer = layer_block(de, ds, x, ties)
        return t.append_column("layer", pa.array(layer)).filter(pa.array(keep_bound(layer, bound))).cast(pa.schema([("p", pa.int64()), ("x", pa.int64()), ("de", pa.float64()), ("ds", pa.float64()), ("layer", pa.int32())]))

    return pairs.select("p", "x", "de", "ds").groupBy("p").applyInArrow(run, FRONTIER)


def layers_by_peeling(pairs: DataFrame, most: int) -> DataFrame:
    """The first `most` layers by windows and anti-joins only."""
    rest, out = pairs, None
    for k in range(1, most + 1):
        now = frontier(rest).withColumn("layer", F.lit(k))
        out = now if out is None else out.unionByName(now)
        rest = rest.join(now.select("p", "x"), ["p", "x"], "left_anti")
    return out
