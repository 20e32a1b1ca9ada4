"""Rows packed into blocks: bounded numbers of objects or queries as binaries, joined block by block inside Spark.

A block is one row, so two tables of blocks meet in a join of few rows, no query passes through the driver, and
a task sees one pair of blocks at a time.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import matrix

OBJECT_ROWS, QUERY_ROWS = 2_000, 2_048
SENT_BYTES = 64_000_000  # of query blocks that may go to all tasks; above that both sides are dealt
OBJECT_BLOCK = "o_ids binary, o_e binary, o_s binary"
QUERY_BLOCK = "block string, q_ids binary, q_bands binary, q_alphas binary, q_which binary, q_e binary, q_s binary"


def _slices(batches, rows: int):
    """Batches joined and cut to `rows` rows."""
    held, have = [], 0
    for b in batches:
        at = 0
        while at < b.num_rows:
            part = b.slice(at, rows - have)
            held.append(part)
            have += part.num_rows
            at += part.num_rows
            if have == rows:
                yield pa.Table.from_batches(held).combine_chunks()
                held, have = [], 0
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def pack_objects(objects: DataFrame, rows: int = OBJECT_ROWS) -> DataFrame:
    """OBJECT_BLOCK rows of objects (id, e, s)."""

    def run(batches):
        for t in _slices(batches, rows):
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()]) for x in (t.column("id").to_numpy(), matrix(t.column("e")), matrix(t.column("s")))], names=["o_ids", "o_e", "o_s"])

    return objects.select("id", "e", "s").mapInArrow(run, OBJECT_BLOCK)


def distinct_vectors(e: np.ndarray, s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First rows of the distinct (e, s), compared by all their bytes, and which of them each row has."""
    seen: dict[bytes, int] = {}
    first, which = [], np.empty(len(e), np.int64)
    for i, key in enumerate(x.tobytes() + y.tobytes() for x, y in zip(e, s)):
        at = seen.setdefault(key, len(first))
        if at == len(first):
            first.append(i)
        which[i] = at
    return np.array(first, np.int64), which


def pack_queries(queries: DataFrame, rows: int = QUERY_ROWS) -> DataFrame:
    """QUERY_BLOCK rows of queries (qid, band, alpha, e, s); queries of a block that share both vectors store them once."""

    def run(batches):
        for t in _slices(batches, rows):
            qid, band, alpha = (t.column(c).to_numpy() for c in ("qid", "band", "alpha"))
            if len(alpha) and not ((alpha >= 0) & (alpha <= 1)).all():
                raise ValueError(f"alpha {alpha[~((alpha >= 0) & (alpha <= 1))][0]} is not in [0, 1]")
            e, s = matrix(t.column("e")), matrix(t.column("s"))
            first, which = distinct_vectors(e, s)
            yield pa.RecordBatch.from_arrays([pa.array([uuid.uuid4().hex]), *(pa.array([x.tobytes()]) for x in (qid.astype(np.int64), band.astype(np.int32), alpha.astype(float), which, e[first], s[first]))], names=["block", "q_ids", "q_bands", "q_alphas", "q_which", "q_e", "q_s"])

    return queries.select("qid", "band", "alpha", "e", "s").mapInArrow(run, QUERY_BLOCK)


def every_pair(objects: DataFrame, queries: DataFrame) -> DataFrame:
    """A row per object block and query block. Queries whose size is checked go to all tasks; more of them are dealt too."""
    from ..storage import stash

    q = stash(pack_queries(queries), "query-blocks")
    size = q.agg(F.sum(F.octet_length("q_e") + F.octet_length("q_s") + 28 * F.octet_length("q_bands") / 4)).first()[0] or 0
    o = pack_objects(objects)
    return o.join(F.broadcast(q), F.lit(True)) if size <= SENT_BYTES else o.join(q.hint("shuffle_replicate_nl"), F.lit(True))


class Objects:
    """The arrays of a packed object block."""

    def __init__(self, row: dict):
        self.ids = np.frombuffer(row["o_ids"], np.int64)
        self.e, self.s = (np.frombuffer(row[c], float).reshape(len(self.ids), -1) for c in ("o_e", "o_s"))


class Queries:
    """The arrays of a packed query block: qid, band, alpha and which of the distinct vectors e, s each has."""

    def __init__(self, row: dict):
        self.name = row["block"]
        self.qid, self.band = np.frombuffer(row["q_ids"], np.int64), np.frombuffer(row["q_bands"], np.int32)
        self.alpha, self.which = np.frombuffer(row["q_alphas"], float), np.frombuffer(row["q_which"], np.int64)
        n = int(self.which.max()) + 1 if len(self.which) else 0
        self.e, self.s = (np.frombuffer(row[c], float).reshape(n, -1) for c in ("q_e", "q_s"))


def best_columns(d: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Per row the k least distances (to nine places, then smaller id): a partition first, an order of the few that reach it.

    ids: one row for all, or as many as d. Missing places have distance infinity and id -1.
    """
    n, r = d.shape[1], np.round(d, 9)
    if n > k:
        rows, cols = np.nonzero(r <= np.partition(r, k - 1, axis=1)[:, k - 1 : k])
    else:
        rows, cols = np.divmod(np.arange(d.size), max(n, 1))
    x, i = d[rows, cols], ids[rows, cols] if ids.ndim == 2 else ids[cols]
    order = np.lexsort((i, r[rows, cols], rows))
    rows, x, i = rows[order], x[order], i[order]
    place = np.arange(len(rows)) - np.searchsorted(rows, rows)
    keep = place < k
    out_d, out_i = np.full((len(d), k), np.inf), np.full((len(d), k), -1, np.int64)
    out_d[rows[keep], place[keep]], out_i[rows[keep], place[keep]] = x[keep], i[keep]
    return out_d, out_i
