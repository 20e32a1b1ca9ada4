"""The normalisers: the largest pairwise distance of each modality, exactly or within bounds."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import l2_block, matrix
from ..schema import Norm
from . import seeds

BLOCK = 1_000


def blocks(objects: DataFrame, size: int = BLOCK) -> DataFrame:
    """block, e BINARY, s BINARY, and the widths: objects packed by the thousand."""

    def run(batches):
        for b in batches:
            for i in range(0, b.num_rows, size):
                part = b.slice(i, size)
                e, s = matrix(part.column("e")), matrix(part.column("s"))
                yield pa.RecordBatch.from_arrays(
                    [pa.array([int(part.column("id")[0].as_py())], pa.int64()), pa.array([e.tobytes()]), pa.array([s.tobytes()]), pa.array([e.shape[1]], pa.int32()), pa.array([s.shape[1]], pa.int32())],
                    names=["block", "e", "s", "de", "ds"],
                )

    return objects.select("id", "e", "s").mapInArrow(run, "block long, e binary, s binary, de int, ds int")


def exact_df(objects: DataFrame) -> DataFrame:
    """One row: e_max, s_max. Quadratic; for tables of a few thousand rows."""
    a = blocks(objects)
    b = a.select(*[F.col(c).alias(f"{c}2") for c in a.columns])

    def run(batches):
        for t in batches:
            out = []
            for r in t.to_pylist():
                m = lambda x, w: np.frombuffer(x, float).reshape(-1, w)
                out.append((l2_block(m(r["e"], r["de"]), m(r["e2"], r["de"])).max(), l2_block(m(r["s"], r["ds"]), m(r["s2"], r["ds"])).max()))
            yield pa.RecordBatch.from_arrays([pa.array([o[0] for o in out]), pa.array([o[1] for o in out])], names=["e_max", "s_max"])

    pairs = a.join(b, F.col("block") <= F.col("block2"))  # of blocks, not of rows
    return pairs.mapInArrow(run, "e_max double, s_max double").agg(F.max("e_max").alias("e_max"), F.max("s_max").alias("s_max"))


def exact(objects: DataFrame) -> Norm:
    r = exact_df(objects).first()
    return Norm(r.e_max or 1.0, r.s_max or 1.0)


def bounded(objects: DataFrame, rounds: int = 3) -> Norm:
    """Lower bounds by sweeps to the farthest object, in linear time; `extra` has the upper bounds 2 r.

    With r the largest distance to the centroid, the diameter is in [r, 2 r]. Results at a weight are those of
    the true normalisers only at the weight of Norm.remap.
    """
    ce, cs = seeds.centroid(objects)
    out = {}
    for name, c in (("e", ce), ("s", cs)):
        far = _farthest(objects, name, c)
        radius, low = far.d, far.d
        for _ in range(rounds):
            far = _farthest(objects, name, far.v)
            low = max(low, far.d)
        out[name] = (low, 2 * radius, radius)
    return Norm(out["e"][0] or 1.0, out["s"][0] or 1.0, {"e_upper": out["e"][1], "s_upper": out["s"][1], "e_radius": out["e"][2], "s_radius": out["s"][2]})


def pruned(objects: DataFrame) -> Norm:
    """The same as `exact`: two objects at distance d are together at least d from the centroid, so those whose
    distance is below the lower bound less the radius are left out of the pairs. In many dimensions few
    are, and the pairs of blocks stay quadratic.
    """
    from ..functions.vectors import l2

    low, center, out = bounded(objects), seeds.centroid(objects), {}
    for name, c, least in (("e", center[0], low.e - low.extra["e_radius"]), ("s", center[1], low.s - low.extra["s_radius"])):
        at = F.array(*[F.lit(float(x)) for x in c])
        far = objects.where(l2(name, at) >= F.lit(least - 1e-6 * max(abs(least), 1.0)))
        out[name] = exact_df(far).first()[f"{name}_max"]
    return Norm(out["e"] or 1.0, out["s"] or 1.0)


def _farthest(objects: DataFrame, column: str, point):
    from ..functions.vectors import l2

    at = F.array(*[F.lit(float(x)) for x in point])
    return objects.select(F.col(column).alias("v"), l2(column, at).alias("d"), "id").agg(F.max("d").alias("d"), F.max_by("v", F.struct("d", "id")).alias("v")).first()
