"""Exact inner-product top-k, exhaustive and term at a time.

Vectors are rows of (term, weight). Candidates are turned into postings per block: for each term the
places and weights of the candidates that have it. Each query scatters its weights times the postings of
its own terms into a dense array of scores, one per candidate of the block; a partition selection keeps
the best of the block, and a running merge keeps the best of the task. Tasks send k rows per query, and
a window merges them.

Queries and candidates are packed into blocks of a bounded number of rows, one row per block, and every block of
queries meets every block of candidates inside Spark. Query blocks whose size is checked go to all tasks; more
of them are dealt like the candidates. No query passes through the driver.

Defined cases: vectors that are null, or hold null, NaN or infinities, take no part; neither do rows with
a null id. Ties go to the smaller id. A query's own row is the one with its id; rows that repeat an id
with the same vector count once, rows that repeat an id with another vector are candidates of their own
but never for queries of that id. Vectors of unequal length: missing places count 0.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import lean, stash

QUERY_BLOCK = 2_048
CANDIDATES = 4_096
SENT_BYTES = 64_000_000
PACKED = "ids binary, width int, weights binary"
OUT = "query_id long, vec_id long, score long"


def quantised(vectors: DataFrame, scale: int = 256) -> DataFrame:
    """vec_id, w ARRAY<LONG>: floor(scale * x) of each component, rows that can't take part left out."""
    fit = F.col("embedding").isNotNull() & F.col("vec_id").isNotNull() & ~F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    return vectors.where(F.coalesce(fit, F.lit(False))).select("vec_id", F.transform("embedding", lambda x: F.floor(x.cast("double") * scale).cast("long")).alias("w"))


def dense(column: pa.Array, width: int) -> np.ndarray:
    """Rows of a list column as a matrix, short rows filled with 0 (longer ones cut by nobody: width is the longest)."""
    flat, size = column.flatten().to_numpy(zero_copy_only=False), np.diff(column.offsets.to_numpy())
    if len(size) and (size == width).all():
        return flat.reshape(-1, width).astype(np.int64)
    out = np.zeros((len(size), width), np.int64)
    for i, (a, n) in enumerate(zip(np.cumsum(size) - size, size)):
        out[i, :n] = flat[a : a + n]
    return out


def best(scores: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Per row the k best (score, then smaller id): a partition for the k-th score, then an order of the few that reach it."""
    n = scores.shape[1]
    if n > k:
        least = np.partition(scores, n - k, axis=1)[:, n - k]
        rows, cols = np.nonzero(scores >= least[:, None])
    else:
        rows, cols = np.divmod(np.arange(scores.size), max(n, 1))
    s, i = scores[rows, cols], (ids[rows, cols] if ids.ndim == 2 else ids[cols])
    order = np.lexsort((i, -s, rows))
    rows, s, i = rows[order], s[order], i[order]
    place = np.arange(len(rows)) - np.searchsorted(rows, rows)
    keep = place < k
    out_s = np.full((scores.shape[0], k), NONE)
    out_i = np.full((scores.shape[0], k), -1, np.int64)
    out_s[rows[keep], place[keep]], out_i[rows[keep], place[keep]] = s[keep], i[keep]
    return out_s, out_i


NONE = np.iinfo(np.int64).min


def scatter(queries: np.ndarray, block: np.ndarray) -> np.ndarray:
    """Scores of all queries against a block of candidates, by accumulating one term after the other."""
    narrow = np.int64 if np.abs(queries).max(initial=0) * np.abs(block).max(initial=0) * max(1, block.shape[1]) >= 2**31 else np.int32
    scores = np.zeros((len(queries), len(block)), narrow)
    queries, terms = queries.astype(narrow), np.ascontiguousarray(block.T).astype(narrow)
    for t in range(terms.shape[0]):
        users = np.flatnonzero(queries[:, t])
        places = np.flatnonzero(terms[t])
        if not len(users) or not len(places):
            continue
        if len(places) * 2 > terms.shape[1]:  # most have the term: the dense row is the posting list
            for q in users:
                scores[q] += queries[q, t] * terms[t]
        else:
            weights = terms[t, places]
            for q in users:
                scores[q, places] += queries[q, t] * weights
    return scores


def packed(rows: DataFrame, size: int) -> DataFrame:
    """PACKED rows of (vec_id, w): blocks of at most `size` rows, short vectors filled with 0."""

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, size):
                part = b.slice(at, size)
                width = int(np.diff(part.column("w").offsets.to_numpy()).max(initial=0))
                m = dense(part.column("w"), width)
                yield pa.RecordBatch.from_arrays([pa.array([part.column("vec_id").cast(pa.int64()).to_numpy().tobytes()]), pa.array([width], pa.int32()), pa.array([m.tobytes()])], names=["ids", "width", "weights"])

    return rows.select("vec_id", "w").mapInArrow(lean(run), PACKED)


def search(queries: DataFrame, candidates: DataFrame, k: int = 5, block: int = QUERY_BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score of each query against every candidate row but its own. Inputs: (vec_id, w)."""
    asked = stash(packed(queries.dropDuplicates(), block), "queries").select(F.monotonically_increasing_id().alias("block"), *[F.col(c).alias(f"q_{c}") for c in ("ids", "width", "weights")])
    size = asked.agg(F.sum(F.octet_length("q_weights"))).first()[0] or 0
    asked = F.broadcast(asked) if size <= SENT_BYTES else asked.hint("shuffle_replicate_nl")
    found = packed(candidates, CANDIDATES).join(asked, F.lit(True)).mapInArrow(lean(lambda it: _run(it, k)), OUT)
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def _padded(m: np.ndarray, width: int) -> np.ndarray:
    return np.pad(m, ((0, 0), (0, width - m.shape[1]))) if width > m.shape[1] else m


def _run(batches, k: int, chunk: int = 256):
    """The k best of each query over all blocks of candidates that a task sees."""
    top: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
    for t in batches:
        for row in t.to_pylist():
            ids, query_ids = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["q_ids"], np.int64)
            width = max(row["width"], row["q_width"])
            block = _padded(np.frombuffer(row["weights"], np.int64).reshape(len(ids), row["width"]), width)
            matrix = _padded(np.frombuffer(row["q_weights"], np.int64).reshape(len(query_ids), row["q_width"]), width)
            n = len(query_ids)
            _, top_s, top_i = top.setdefault(row["block"], (query_ids, np.full((n, k), NONE), np.full((n, k), -1, np.int64)))
            for q in range(0, n, chunk):
                scores = scatter(matrix[q : q + chunk], block).astype(np.int64)
                scores[query_ids[q : q + chunk, None] == ids[None, :]] = NONE
                s, i = best(scores, ids, k)
                both_s, both_i = np.hstack([top_s[q : q + chunk], s]), np.hstack([top_i[q : q + chunk], i])
                top_s[q : q + chunk], top_i[q : q + chunk] = best(both_s, both_i, k)
    for query_ids, top_s, top_i in top.values():
        r, c = np.nonzero(top_s != NONE)
        yield pa.RecordBatch.from_arrays([pa.array(query_ids[r]), pa.array(top_i[r, c]), pa.array(top_s[r, c])], names=["query_id", "vec_id", "score"])
