"""Start nodes: the rim of the data, seen from its centroid, and the alternatives it is compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import l2, matrix
from ..schema import Norm
from . import pareto


def centroid_df(objects: DataFrame) -> DataFrame:
    """One row: e, s means. Sums per task first, so one row per task is shuffled."""

    def run(batches):
        total = None
        for b in batches:
            now = (matrix(b.column("e")).sum(axis=0), matrix(b.column("s")).sum(axis=0), b.num_rows)
            total = now if total is None else (total[0] + now[0], total[1] + now[1], total[2] + now[2])
        if total is not None and total[2]:
            yield pa.RecordBatch.from_arrays([pa.array([total[0].tolist()], pa.list_(pa.float64())), pa.array([total[1].tolist()], pa.list_(pa.float64())), pa.array([total[2]], pa.int64())], names=["e", "s", "n"])

    part = objects.select("e", "s").mapInArrow(run, "e array<double>, s array<double>, n long")
    n = part.agg(F.sum("n").alias("n"), F.collect_list("e").alias("e"), F.collect_list("s").alias("s"))
    total = lambda c: F.aggregate(c, F.array_repeat(F.lit(0.0), F.coalesce(F.array_size(F.try_element_at(c, F.lit(1))), F.lit(0))), lambda acc, x: F.zip_with(acc, x, lambda a, b: a + b), lambda acc: F.transform(acc, lambda v: v / F.col("n")))
    return n.select(total("e").alias("e"), total("s").alias("s"))


def centroid(objects: DataFrame) -> tuple[list[float], list[float]]:
    r = centroid_df(objects).first()
    return r.e, r.s


def from_centroid(objects: DataFrame, ce, cs, norm: Norm) -> DataFrame:
    """id, de, ds to the centroid."""
    at = lambda c: F.array(*[F.lit(float(x)) for x in c])
    return objects.select("id", (l2("e", at(ce)) / norm.e).alias("de"), (l2("s", at(cs)) / norm.s).alias("ds"))


def rim(objects: DataFrame, norm: Norm, at: tuple[list, list] | None = None) -> DataFrame:
    """id, de, ds of the objects that are farther from the centroid than any other, in the sense of frontiers."""
    ce, cs = at or centroid(objects)
    return rim_of(from_centroid(objects, ce, cs, norm))


def rim_of(distances: DataFrame) -> DataFrame:
    turned = distances.select("id", (-F.col("de")).alias("de"), (-F.col("ds")).alias("ds"))
    return pareto.global_frontier(turned).select("id", (-F.col("de")).alias("de"), (-F.col("ds")).alias("ds"))


def update(old: DataFrame, new: DataFrame) -> DataFrame:
    """Seeds after more objects: the rim of the old seeds and the new rows (id, de, ds to the same centroid)."""
    return rim_of(old.select("id", "de", "ds").unionByName(new.select("id", "de", "ds")))


def inner(objects: DataFrame, norm: Norm) -> DataFrame:
    """The alternative: the frontier nearest to the centroid."""
    ce, cs = centroid(objects)
    return pareto.global_frontier(from_centroid(objects, ce, cs, norm))


def random(objects: DataFrame, n: int, seed: int = 42) -> DataFrame:
    """The alternative: n objects by a seeded hash, one that other engines have too."""
    return objects.select("id", F.md5(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string"))).alias("h")).orderBy("h", "id").limit(n).select("id")


def rim_block(de: np.ndarray, ds: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Places of the rim of a block."""
    order = np.lexsort((ids, -de, -ds))
    best = np.maximum.accumulate(np.concatenate([[-np.inf], de[order]]))[:-1]
    return order[de[order] > best]
