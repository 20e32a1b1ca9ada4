"""Exact search: the ground truth. Blocks of queries against blocks of objects, partial then final top-k."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import l2_block
from ..schema import Norm
from ..storage import stash
from .blocks import SENT_BYTES, Objects, Queries, best_columns, every_pair

PARTIAL = "qid long, band int, id long, dist double"
_ARROW = pa.schema([("qid", pa.int64()), ("band", pa.int32()), ("id", pa.int64()), ("dist", pa.float64())])


def pairs_of_blocks(batches):
    """(object block, query block) of joined rows; equal neighbours are unpacked once."""
    last_o = last_q = None
    for t in batches:
        names = t.schema.names
        for i in range(t.num_rows):
            row = {c: t.column(j)[i].as_buffer() if c != "block" else t.column(j)[i].as_py() for j, c in enumerate(names)}
            if last_o is None or not row["o_ids"].equals(last_o[0]) or not row["o_e"].equals(last_o[1]):
                last_o = (row["o_ids"], row["o_e"], Objects(row))
            if last_q is None or last_q[0] != row["block"] or not row["q_alphas"].equals(last_q[1]):
                last_q = (row["block"], row["q_alphas"], Queries(row))
            yield last_o[2], last_q[2]


def _nearest(batches, norm: Norm, k: int):
    """The k best of each query over all object blocks that a task sees."""
    best: dict[str, tuple] = {}
    for o, q in pairs_of_blocks(batches):
        de, ds = l2_block(q.e, o.e) / norm.e, l2_block(q.s, o.s) / norm.s
        d = q.alpha[:, None] * de[q.which] + (1 - q.alpha[:, None]) * ds[q.which]
        now = best_columns(d, o.ids, k)
        if q.name in best:
            _, old_d, old_i = best[q.name]
            now = best_columns(np.hstack([old_d, now[0]]), np.hstack([old_i, now[1]]), k)
        best[q.name] = (q, *now)
    for q, d, i in best.values():
        r, c = np.nonzero(np.isfinite(d))
        yield pa.RecordBatch.from_arrays([pa.array(q.qid[r]), pa.array(q.band[r]), pa.array(i[r, c]), pa.array(d[r, c])], schema=_ARROW)


def final_topk(partial: DataFrame, k: int, by: tuple[str, ...] = ("qid", "band")) -> DataFrame:
    """The k best rows per query of partial results; the window's group limit runs before the shuffle too."""
    w = Window.partitionBy(*by).orderBy(F.round("dist", 9), "id")
    return partial.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "band", "rank", "id", "dist")


def topk(objects: DataFrame, queries: DataFrame, norm: Norm, k: int = 10) -> DataFrame:
    """The k objects of least hybrid distance for each query: qid, band, rank, id, dist."""
    return final_topk(every_pair(objects, queries).mapInArrow(lambda it: _nearest(it, norm, k), PARTIAL), k)


def topk_many(objects: DataFrame, queries: DataFrame, columns: list[str], norms: list[float], k: int = 10) -> DataFrame:
    """Exact top-k over any number of vectors per object; queries (qid, weights ARRAY<DOUBLE>, the vectors). Queries whose
    size is checked go to all tasks; more are dealt as well."""
    from ..functions.vectors import l2

    q = stash(queries.select("qid", "weights", *[F.col(c).alias(f"q_{c}") for c in columns]), "queries")
    size = q.agg(F.sum(sum((F.size(f"q_{c}") for c in columns), F.lit(2)) * 8)).first()[0] or 0
    d = sum((F.element_at("weights", i + 1) * l2(f"q_{c}", c) / F.lit(float(n)) for i, (c, n) in enumerate(zip(columns, norms))), F.lit(0.0))
    every = objects.join(F.broadcast(q) if size <= SENT_BYTES else q.hint("shuffle_replicate_nl"), F.lit(True)).select("qid", F.lit(0).alias("band"), "id", d.alias("dist"))
    return final_topk(every, k).drop("band")


def pair_distances(objects: DataFrame, norm: Norm, nodes: DataFrame | None = None) -> DataFrame:
    """p, x, de, ds for the given nodes p (default: all) against all other objects, by blocks. For small tables."""

    def run(batches):
        for o, q in pairs_of_blocks(batches):
            step = max(1, 200_000 // max(1, len(o.ids)))
            for i in range(0, len(q.qid), step):
                p, w = q.qid[i : i + step], q.which[i : i + step]
                de, ds = l2_block(q.e[w], o.e) / norm.e, l2_block(q.s[w], o.s) / norm.s
                r, c = np.nonzero(p[:, None] != o.ids[None, :])
                yield pa.RecordBatch.from_arrays([pa.array(p[r]), pa.array(o.ids[c]), pa.array(de[r, c]), pa.array(ds[r, c])], names=["p", "x", "de", "ds"])

    ps = (nodes if nodes is not None else objects).select(F.col("id").alias("qid"), F.lit(0).alias("band"), F.lit(0.5).alias("alpha"), "e", "s")
    return every_pair(objects, ps).mapInArrow(run, "p long, x long, de double, ds double")


def every_distance(objects: DataFrame, queries: DataFrame, norm: Norm, places: int) -> DataFrame:
    """qid, band, id, dist (to so many places) of every query and object, by blocks; vectors that queries share are measured once."""

    def run(batches):
        for o, q in pairs_of_blocks(batches):
            de, ds = l2_block(q.e, o.e) / norm.e, l2_block(q.s, o.s) / norm.s
            n = len(o.ids)
            step = max(1, 200_000 // max(1, n))
            for i in range(0, len(q.qid), step):
                at = slice(i, i + step)
                alpha, w = q.alpha[at, None], q.which[at]
                d = np.round(alpha * de[w] + (1 - alpha) * ds[w], places)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(q.qid[at], n)), pa.array(np.repeat(q.band[at], n)), pa.array(np.tile(o.ids, len(w))), pa.array(d.reshape(-1))], schema=_ARROW)

    return every_pair(objects, queries).mapInArrow(run, PARTIAL)


def threshold_topk(objects: DataFrame, queries: DataFrame, norm: Norm, k: int = 10, depth: int = 32) -> tuple[DataFrame, int]:
    """Exact top-k from the two lists sorted by one modality each, read to a depth that doubles until it suffices.

    All objects a query has seen in either list are scored; unseen ones are at least as far as the weighted
    sum of both lists' ends, so a query is done when its k-th score is below that. Returns (hits, last depth).
    """
    n = objects.count()
    done, left = None, queries
    while True:
        depth = min(depth, n)
        by_e, by_s = (stash(topk(objects, left.withColumn("alpha", F.lit(a)), norm, depth).select("qid", "band", "id", "rank", F.col("dist").alias("end")), "list") for a in (1.0, 0.0))
        ends = by_e.groupBy("qid", "band").agg(F.max("end").alias("e_end")).join(by_s.groupBy("qid", "band").agg(F.max("end").alias("s_end")), ["qid", "band"])
        seen = by_e.select("qid", "band", "id").union(by_s.select("qid", "band", "id")).distinct()
        hits = stash(rescore(seen, objects, left, norm, k), "hits")
        kth = hits.groupBy("qid", "band").agg(F.max("dist").alias("kth"))
        bound = ends.join(left.select("qid", "band", "alpha"), ["qid", "band"]).join(kth, ["qid", "band"]).withColumn("floor", F.col("alpha") * F.col("e_end") + (1 - F.col("alpha")) * F.col("s_end"))
        ok = bound.where(F.col("kth") < F.col("floor")).select("qid", "band") if depth < n else left.select("qid", "band")
        fine = hits.join(ok, ["qid", "band"], "left_semi")
        done = fine if done is None else done.unionByName(fine)
        left = left.join(ok, ["qid", "band"], "left_anti")
        if depth >= n or not left.limit(1).count():
            return done, depth
        depth *= 2


def distances(candidates: DataFrame, objects: DataFrame, queries: DataFrame, norm: Norm) -> DataFrame:
    """qid, band, id, dist of candidate rows (qid, band, id)."""
    from ..functions.vectors import hybrid

    q = queries.select("qid", "band", "alpha", F.col("e").alias("qe"), F.col("s").alias("qs"))
    rows = candidates.join(objects.select("id", "e", "s"), "id").join(q, ["qid", "band"])
    return rows.select("qid", "band", "id", hybrid("e", "s", "qe", "qs", F.col("alpha"), norm.e, norm.s).alias("dist"))


def rescore(candidates: DataFrame, objects: DataFrame, queries: DataFrame, norm: Norm, k: int) -> DataFrame:
    """Top-k of candidate rows (qid, band, id) by their hybrid distance."""
    return final_topk(distances(candidates, objects, queries, norm), k)


def similarity_pairs(objects: DataFrame, norm: Norm, alpha: float, radius: float) -> DataFrame:
    """p < x with hybrid distance at most radius (blocked; both sides in bounded blocks)."""
    d = pair_distances(objects, norm).where("p < x")
    return d.withColumn("dist", F.lit(alpha) * F.col("de") + F.lit(1 - alpha) * F.col("ds")).where(F.col("dist") <= radius)
