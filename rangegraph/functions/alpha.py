"""Intervals of the weight alpha: half-lines, pruned intervals, interval sets, their stored form.

A linear inequality alpha * B < A holds on a half-line; clipped to [0, 1] that is an interval or nothing. Pruned
sets are open and active sets closed, so an edge stays at the ends of its range. Sets are arrays of disjoint
intervals in order.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..schema import SCALE

INTERVAL = "struct<lo:double,hi:double>"
EMPTY = "array<struct<lo:double,hi:double>>"


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.col(x) if isinstance(x, str) else F.lit(float(x))


def _none() -> Column:
    return F.lit(None).cast(INTERVAL)


def _interval(lo: Column, hi: Column) -> Column:
    return F.struct(lo.alias("lo"), hi.alias("hi"))


def halfline(a, b) -> Column:
    """{alpha in [0, 1]: alpha * b < a} as struct(lo, hi), null if it has no length."""
    a, b = _col(a), _col(b)
    cut = a / F.nullif(b, F.lit(0.0))
    lo = F.when(b < 0, F.greatest(cut, F.lit(0.0))).otherwise(F.lit(0.0))
    hi = F.when(b > 0, F.least(cut, F.lit(1.0))).otherwise(F.lit(1.0))
    return F.when((b == 0) & (a <= 0), _none()).when(lo < hi, _interval(lo, hi)).otherwise(_none())


def intersect_one(x: Column, y: Column) -> Column:
    lo, hi = F.greatest(x.lo, y.lo), F.least(x.hi, y.hi)
    return F.when(x.isNull() | y.isNull() | (lo >= hi), _none()).otherwise(_interval(lo, hi))


def pruned_by(de_pz, ds_pz, de_px, ds_px, de_zx, ds_zx) -> Column:
    """Weights at which witness z removes the edge from p to x: z is nearer to p, and nearer to x, than they are to each other."""
    de_pz, ds_pz, de_px, ds_px, de_zx, ds_zx = map(_col, (de_pz, ds_pz, de_px, ds_px, de_zx, ds_zx))
    nearer_p = halfline(ds_px - ds_pz, (de_pz - ds_pz) - (de_px - ds_px))
    nearer_x = halfline(ds_px - ds_zx, (de_zx - ds_zx) - (de_px - ds_px))
    return intersect_one(nearer_p, nearer_x)


def normalise(ivals: Column) -> Column:
    """Disjoint intervals in order, from any."""
    ordered = F.array_sort(F.filter(ivals, lambda i: i.isNotNull() & (i.lo < i.hi)))
    start = F.lit(None).cast(EMPTY)

    def step(acc, i):
        last = F.element_at(acc, -1)
        joined = F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(_interval(last.lo, F.greatest(last.hi, i.hi))))
        return F.when(acc.isNull(), F.array(_interval(i.lo, i.hi))).when(i.lo <= last.hi, joined).otherwise(F.concat(acc, F.array(_interval(i.lo, i.hi))))

    return F.coalesce(F.aggregate(ordered, start, step), F.array().cast(EMPTY))


def union(a: Column, b: Column) -> Column:
    return normalise(F.concat(a, b))


def complement(ivals: Column) -> Column:
    """What [0, 1] has besides."""
    n = normalise(ivals)
    los = F.concat(F.array(F.lit(0.0)), F.transform(n, lambda i: i.hi))
    his = F.concat(F.transform(n, lambda i: i.lo), F.array(F.lit(1.0)))
    return F.filter(F.zip_with(los, his, lambda lo, hi: _interval(lo, hi)), lambda i: i.lo < i.hi)


def intersect(a: Column, b: Column) -> Column:
    return complement(F.concat(complement(a), complement(b)))


def length(ivals: Column) -> Column:
    return F.aggregate(normalise(ivals), F.lit(0.0), lambda acc, i: acc + i.hi - i.lo)


def contains(ivals: Column, alpha: Column) -> Column:
    """The edge gate: whether an edge with these active ranges may be used at alpha."""
    return F.exists(ivals, lambda i: (i.lo <= alpha) & (alpha <= i.hi))


def encode(ivals: Column) -> Column:
    """Ranges as small integers, rounded outwards so that rounding never closes an edge."""
    return F.transform(ivals, lambda i: F.struct(F.floor(i.lo * SCALE).cast("short").alias("lo"), F.ceil(i.hi * SCALE).cast("short").alias("hi")))


def decode(ivals: Column) -> Column:
    return F.transform(ivals, lambda i: _interval(i.lo / float(SCALE), i.hi / float(SCALE)))


# --- the same on numpy -------------------------------------------------------------------------------------


def halfline_block(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """As `halfline`, for arrays; no length: hi <= lo."""
    with np.errstate(divide="ignore", invalid="ignore"):
        cut = a / b
    lo = np.where(b < 0, np.maximum(cut, 0.0), 0.0)
    hi = np.where(b > 0, np.minimum(cut, 1.0), 1.0)
    flat = b == 0
    if flat.any():
        none = flat & (a <= 0)
        lo[none], hi[none] = 1.0, 0.0
    return lo, hi


def pruned_block(de_pz, ds_pz, de_px, ds_px, de_zx, ds_zx) -> tuple[np.ndarray, np.ndarray]:
    """As `pruned_by`, for arrays that broadcast; no length: hi <= lo. Both inequalities at once."""
    slope = de_px - ds_px
    shape = np.broadcast_shapes(de_pz.shape, de_px.shape, de_zx.shape)
    a, b = np.empty((2, *shape)), np.empty((2, *shape))
    a[0], b[0] = ds_px - ds_pz, (de_pz - ds_pz) - slope
    a[1], b[1] = ds_px - ds_zx, (de_zx - ds_zx) - slope
    falls, rises = b < 0, b > 0
    with np.errstate(divide="ignore", invalid="ignore"):
        cut = a / b
    lo = np.maximum(np.where(falls, cut, 0.0).max(axis=0), 0.0)
    hi = np.minimum(np.where(rises, cut, 1.0).min(axis=0), 1.0)
    never = ~(falls | rises) & (a <= 0)
    if never.any():
        hi[never.any(axis=0)] = -1.0
    return lo, hi


def gaps(intervals: list[tuple[float, float]]) -> list[tuple[float, float]]:
    """Complement in [0, 1] of the union of intervals."""
    out, at = [], 0.0
    for lo, hi in sorted(i for i in intervals if i[1] > i[0]):
        if lo > at:
            out.append((at, lo))
        if hi > at:
            at = hi
    if at < 1.0:
        out.append((at, 1.0))
    return out


def encode_pair(lo: float, hi: float) -> tuple[int, int]:
    return int(np.floor(lo * SCALE)), int(np.ceil(hi * SCALE))


def overlay_tag(alpha: float) -> int:
    """Which of the five bands of width 0.2 a weight is in; a weight on an edge belongs to the lower band."""
    return int(min(4, max(0, np.ceil(round(alpha / 0.2, 9)) - 1)))
