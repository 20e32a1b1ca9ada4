"""Functions for SQL users: hybrid_dist(e1, s1, e2, s2, alpha), vector_mean(v), and the table function hybrid_topk."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from .vectors import l2_block

PUBLISHED_BYTES = 64_000_000


def hybrid_dist(e_max: float, s_max: float):
    @pandas_udf("double")
    def f(e1: pd.Series, s1: pd.Series, e2: pd.Series, s2: pd.Series, alpha: pd.Series) -> pd.Series:
        de = np.sqrt(((np.stack(e1).astype(float) - np.stack(e2).astype(float)) ** 2).sum(axis=1)) / e_max
        ds = np.sqrt(((np.stack(s1).astype(float) - np.stack(s2).astype(float)) ** 2).sum(axis=1)) / s_max
        a = alpha.to_numpy()
        return pd.Series(a * de + (1 - a) * ds)

    return f


@pandas_udf("array<double>")
def vector_mean(v: pd.Series) -> np.ndarray:
    return np.stack(v).astype(float).mean(axis=0)


def hybrid_lists(e_max: float, s_max: float):
    """For a block of queries and one of objects (operators.blocks): the k nearest by each vector alone, as structs."""

    @pandas_udf("array<struct<qid:bigint,v:int,side:int,id:bigint,d:double>>")
    def f(q: pd.DataFrame, o: pd.DataFrame, k: pd.Series) -> pd.Series:
        from ..operators.blocks import Objects, Queries, best_columns

        out = []
        for one, other, most in zip(q.to_dict("records"), o.to_dict("records"), k):
            a, b, rows = Queries(one), Objects(other), []
            for side, d in enumerate((l2_block(a.e, b.e) / e_max, l2_block(a.s, b.s) / s_max)):
                near, ids = best_columns(d, b.ids, int(most))
                for j, w in enumerate(a.which.tolist()):
                    rows += [{"qid": int(a.qid[j]), "v": int(a.band[j]), "side": side, "id": i, "d": x} for x, i in zip(near[w].tolist(), ids[w].tolist()) if x < np.inf]
            out.append(rows)
        return pd.Series(out)

    return f


def topk_function(ids: np.ndarray, e: np.ndarray, s: np.ndarray, e_max: float, s_max: float):
    """A table function over a published set of objects; the set is sent along, so its size is bounded."""
    if e.nbytes + s.nbytes > PUBLISHED_BYTES:
        raise ValueError("too many objects for a table function; search an index instead")

    @udtf(returnType="rank int, id bigint, dist double")
    class HybridTopK:
        def eval(self, qe, qs, alpha, k):
            d = alpha * np.sqrt(((e - np.asarray(qe, float)) ** 2).sum(axis=1)) / e_max + (1 - alpha) * np.sqrt(((s - np.asarray(qs, float)) ** 2).sum(axis=1)) / s_max
            for r, i in enumerate(np.lexsort((ids, np.round(d, 9)))[:k].tolist()):
                yield r + 1, int(ids[i]), float(d[i])

    return HybridTopK


def register(spark: SparkSession, case) -> bool:
    """Views objects and queries of a workload, and the functions with its normalisers.

    False if the objects are too many for the table function, which is then not there: callers scan instead.
    """
    case.objects.select("id", "e", "s").createOrReplaceTempView("objects")
    case.queries.createOrReplaceTempView("queries")
    spark.udf.register("hybrid_dist", hybrid_dist(case.norm.e, case.norm.s))
    spark.udf.register("hybrid_lists", hybrid_lists(case.norm.e, case.norm.s))
    spark.udf.register("vector_mean", vector_mean)
    width = case.objects.select("e", "s").first()
    fits = case.n * (len(width.e) + len(width.s)) * 8 <= PUBLISHED_BYTES if width else True
    if fits:
        rows = case.objects.select("id", "e", "s").orderBy("id").collect()
        spark.udtf.register("hybrid_topk", topk_function(np.array([r.id for r in rows]), np.array([r.e for r in rows], float), np.array([r.s for r in rows], float), case.norm.e, case.norm.s))
    return fits
