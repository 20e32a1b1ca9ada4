"""Distances: Column forms for SQL, block forms for the kernels. Always metrics, never squared."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def l2(a: Column | str, b: Column | str) -> Column:
    """Euclidean distance of two array columns, in double."""
    d = F.zip_with(a, b, lambda x, y: x.cast("double") - y.cast("double"))
    return F.sqrt(F.aggregate(d, F.lit(0.0), lambda acc, x: acc + x * x))


def norm2(a: Column | str) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda acc, x: acc + x.cast("double") * x.cast("double")))


def hybrid(e1, s1, e2, s2, alpha, e_max, s_max) -> Column:
    """alpha-weighted sum of the normalised distances of both modalities."""
    one = lambda x: x if isinstance(x, Column) else F.lit(float(x))
    return one(alpha) * l2(e1, e2) / one(e_max) + (F.lit(1.0) - one(alpha)) * l2(s1, s2) / one(s_max)


def l2_block(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """All distances between the rows of two blocks, by products; near twins again by differences, so twins are at exactly 0."""
    aa, bb = np.einsum("ij,ij->i", a, a), np.einsum("ij,ij->i", b, b)
    out = a @ b.T
    out *= -2.0
    out += aa[:, None]
    out += bb[None, :]
    low = 1e-6 * (aa.max(initial=0.0) + bb.max(initial=0.0))
    if out.size and out.min() < low:
        i, j = np.nonzero(out < low)
        for k in range(0, len(i), 100_000):
            d = a[i[k : k + 100_000]] - b[j[k : k + 100_000]]
            out[i[k : k + 100_000], j[k : k + 100_000]] = np.einsum("ij,ij->i", d, d)
    return np.sqrt(out, out=out)


def l2_rows(a: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Distances of one vector to the rows of a block."""
    d = rows - a
    return np.sqrt(np.einsum("ij,ij->i", d, d))


def hybrid_bounded(q, e: np.ndarray, s: np.ndarray, alpha: float, norm, threshold: float) -> tuple[np.ndarray, np.ndarray, int]:
    """Rows whose hybrid distance does not exceed threshold, with it, and how many rows needed one part only.

    The cheaper part (fewer dimensions for the larger weight) comes first; rows it already lifts over the
    threshold are left.
    """
    we, ws = alpha / norm.e, (1 - alpha) / norm.s
    s_first = s.shape[1] * max(we, 1e-12) <= e.shape[1] * max(ws, 1e-12)
    first, second = ((q[1], s, ws), (q[0], e, we)) if s_first else ((q[0], e, we), (q[1], s, ws))
    part = first[2] * l2_rows(first[0], first[1])
    left = np.flatnonzero(part <= threshold)
    full = part[left] + second[2] * l2_rows(second[0], second[1][left]) if second[2] else part[left]
    keep = full <= threshold
    return left[keep], full[keep], len(e) - len(left)


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """A list column of equal lengths as a matrix of doubles."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.list_(pa.float32()))
    n = len(column)
    flat = np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64)
    return flat.reshape(n, -1) if n else np.zeros((0, 1))


def assert_vectors(df: DataFrame, *columns: str) -> DataFrame:
    """The rows, after a check that all vectors are there, finite and of one length each (one aggregate, columns pruned)."""
    checks = []
    for c in columns:
        bad = F.col(c).isNull() | F.exists(c, lambda x: x.isNull() | F.isnan(x))
        checks += [F.sum(F.when(F.coalesce(bad, F.lit(True)), 1).otherwise(0)).alias(f"{c}_bad"), F.min(F.size(c)).alias(f"{c}_min"), F.max(F.size(c)).alias(f"{c}_max")]
    r = df.agg(*checks).first()
    for c in columns:
        if r[f"{c}_bad"] or r[f"{c}_min"] != r[f"{c}_max"]:
            raise ValueError(f"column {c}: {r[f'{c}_bad']} null or NaN vectors, lengths {r[f'{c}_min']} to {r[f'{c}_max']}")
    return df
