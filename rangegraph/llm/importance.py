"""Quality selection by importance resampling with hashed n-gram models.

Two bags of hashed n-grams are counted: one over labelled good documents (the target), one over all
documents (the raw text). A document's log weight is the ratio of its likelihoods under the two models,
and documents are drawn without replacement by Gumbel top-k on weight plus noise.

Features of a text cut at white space: its words, its pairs of words, and n-grams of one to three word
forms (kinds of characters, first kind, last character, same as the word before). Each stream has its own
range of BUCKETS counts, so the models have a fixed size at any size of corpus. A document's log weight is its
log-likelihood under the target model less that under the raw one, the mean over the streams: the scale on which the
noise (deviation 1.28) decides between documents that the models rate alike.

k, the number of documents to draw, is an argument. Without it, it is the number that rejection by the same ratios
would accept: the sum over all documents of the likelihood ratio, at most one each. All labelled good rows make the
target, all documents the raw model; labels of bad rows have no part.

Defined cases: null text is empty; texts without words have log weight 0 and are judged like any other;
without good labels nothing is rejected unless k says so; a document with several labels counts as
good if one says so; repeated rows share their noise and are kept or dropped alike up to k (ties: smaller doc_id
first); an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .chosen_path import word_hashes
from .common import lean, mix64, stash, text_bytes, texts
from .suffix_dedup import slices

BUCKETS = 1 << 14
STREAMS = 5
SMOOTH = 30.0  # n-grams of each bucket that the target has seen, as it were, at the raw rate
SEED = 17
SENT_BYTES = 64_000_000  # of doc_ids of the target that may go to all tasks

# Kinds of bytes: 0 white space, 1 small letter or part of a longer character, 2 capital, 3 digit, 4 other.
_KIND = np.full(256, 4, np.uint8)
_KIND[[9, 10, 11, 12, 13, 32]] = 0
_KIND[97:123] = 1
_KIND[128:] = 1
_KIND[65:91] = 2
_KIND[48:58] = 3


def features(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(document, bucket) of all n-grams; stream s has the buckets from s * BUCKETS on."""
    if not len(buf):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    words, doc = word_hashes(buf, off)
    if not len(words):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    kind = _KIND[buf]
    inside = kind > 0
    start = inside.copy()
    start[1:] &= ~inside[:-1]
    lows = off[:-1][off[:-1] < off[1:]]
    start[lows] = inside[lows]
    first = np.flatnonzero(start)
    # capitals of longer characters are two bytes whose second is below 0x9F in the Latin block
    capital = np.zeros(len(buf), bool)
    capital[:-1] = (buf[:-1] == 0xC3) & (buf[1:] < 0x9F)
    bits = (np.uint8(1) << kind).astype(np.uint8)
    bits[capital] = 4
    bits[1:][capital[:-1]] = 4
    mask = np.bitwise_or.reduceat(np.where(inside, bits, np.uint8(0)), first)
    ends = np.append(first[1:], len(buf)) - 1
    back = np.where(inside, np.arange(len(buf)), -1)
    last = np.maximum.accumulate(back)[ends]
    tail = np.where(kind[last] == 4, buf[last], kind[last]).astype(np.uint64)
    same = np.zeros(len(words), bool)
    same[1:] = (words[1:] == words[:-1]) & (doc[1:] == doc[:-1])
    form = mix64(mask.astype(np.uint64) | bits[first].astype(np.uint64) << np.uint64(8) | tail << np.uint64(16) | same.astype(np.uint64) << np.uint64(32))
    two = np.flatnonzero(doc[1:] == doc[:-1])
    three = two[:-1][(two[1:] == two[:-1] + 1)] if len(two) > 1 else two[:0]
    c1, c2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
    streams = [
        (doc, words), (doc[two], words[two] * c1 + words[two + 1]),
        (doc, form), (doc[two], form[two] * c1 + form[two + 1]), (doc[three], form[three] * c2 + form[three + 1] * c1 + form[three + 2]),
    ]
    return np.concatenate([d for d, _ in streams]), np.concatenate([(mix64(h) % np.uint64(BUCKETS)).astype(np.int64) + s * BUCKETS for s, (_, h) in enumerate(streams)])


def _count(batches, ids: np.ndarray | None):
    """Sums of raw and target counts per bucket, over a task. ids: the sorted doc_ids of the target; None: the rows say so."""
    total = np.zeros((2, STREAMS * BUCKETS), np.int64)
    for b in slices(batches, 1_500_000):
        doc, bucket = features(*text_bytes(b))
        total[0] += np.bincount(bucket, minlength=total.shape[1])
        if ids is None:
            good = b.column("good").fill_null(0).to_numpy(zero_copy_only=False) == 1
        else:
            own = b.column("doc_id").cast(pa.int64())
            good = np.isin(own.fill_null(0).to_numpy(zero_copy_only=False), ids) & own.is_valid().to_numpy(zero_copy_only=False)
        total[1] += np.bincount(bucket[good[doc]], minlength=total.shape[1])
    some = np.flatnonzero(total[0])
    yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(total[0][some]), pa.array(total[1][some])], names=["bucket", "raw", "target"])


def ratios(raw: np.ndarray, target: np.ndarray) -> np.ndarray:
    """Log of the target model over the raw one, per bucket. Each is a distribution over the buckets of its stream; the target
    is smoothed towards the raw model bucket by bucket, so that buckets it has hardly seen decide little."""
    out = np.zeros(STREAMS * BUCKETS)
    for s in range(STREAMS if target.sum() else 0):
        part = slice(s * BUCKETS, (s + 1) * BUCKETS)
        share = raw[part] / max(raw[part].sum(), 1)
        relative = (target[part] + SMOOTH) / (target[part].sum() * share + SMOOTH)
        out[part] = np.where(share > 0, np.log(relative / max((relative * share).sum(), 1e-300)), 0.0)
    return out


def log_ratios(docs: DataFrame, good: DataFrame) -> DataFrame:
    """doc_id, log_weight of every document. good: the doc_ids (distinct) of the target text."""
    spark = docs.sparkSession
    schema = "bucket int, raw long, target long"
    if 8 * good.count() <= SENT_BYTES:  # ids of this size go to all tasks, and no text is shuffled
        ids = spark.sparkContext.broadcast(np.sort(good.select(F.col("doc_id").cast("long")).toArrow().column(0).to_numpy()))
        counted = texts(docs).mapInArrow(lean(lambda it: _count(it, ids.value)), schema)
    else:
        marked = texts(docs).join(good.select("doc_id", F.lit(1).alias("good")), "doc_id", "left")
        counted = marked.select("text", "good").mapInArrow(lean(lambda it: _count(it, None)), schema)
    rows = counted.groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).collect()  # at most STREAMS * BUCKETS
    raw, target = np.zeros(STREAMS * BUCKETS), np.zeros(STREAMS * BUCKETS)
    for r in rows:
        raw[r.bucket], target[r.bucket] = r.raw, r.target
    sent_ratio = ratios(raw, target)
    sent = spark.sparkContext.broadcast(sent_ratio)
    schema = pa.schema([("doc_id", pa.int64()), ("log_weight", pa.float64())])

    def score(batches):
        table = sent.value
        for b in slices(batches, 1_500_000):
            doc, bucket = features(*text_bytes(b))
            total = np.bincount(doc, table[bucket], b.num_rows) / STREAMS
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array(total)], schema=schema)

    return texts(docs).mapInArrow(lean(score), "doc_id long, log_weight double")


def gumbel(seed: Column, doc_id: Column) -> Column:
    """Standard Gumbel noise from a hash of the seed and the id."""
    uniform = (F.pmod(F.xxhash64(seed, doc_id), F.lit(1 << 52)).cast("double") + 0.5) / float(1 << 52)
    return -F.log(-F.log(uniform))


def radix_select(keys: DataFrame, column: str, k: int) -> int:
    """The k-th largest value of a LONG column, by histograms of 16 bits at a time (never more than 65,536 rows here)."""
    prefix, rest = None, k
    for shift in (48, 32, 16, 0):
        digit = F.shiftright(F.col(column), shift)
        part = keys if prefix is None else keys.where(F.shiftright(F.col(column), shift + 16) == prefix)
        for r in sorted(part.groupBy(digit.alias("d")).count().collect(), key=lambda r: -r.d):
            if rest <= r["count"]:
                prefix = r.d
                break
            rest -= r["count"]
    return prefix


def resample(docs: DataFrame, labels: DataFrame, column: str = "quality", seed: int = SEED, k: int | None = None) -> DataFrame:
    """doc_id, log_weight, gumbel_key of the k documents that the draw keeps."""
    one = labels.where(F.col("doc_id").isNotNull() & F.col(column).isNotNull()).groupBy("doc_id").agg(F.max(column).cast("int").alias("label"))
    scored = log_ratios(docs, one.where("label = 1").select("doc_id"))
    keyed = scored.withColumn("gumbel_key", F.col("log_weight") + gumbel(F.lit(seed), F.col("doc_id")))
    # doubles as integers of the same order, to the ten-thousandth
    keyed = stash(keyed.withColumn("order_key", F.round(F.col("gumbel_key") * 1e4).cast("long")), "weights")
    r = keyed.agg(F.count(F.lit(1)).alias("n"), F.sum(F.exp(F.least(F.col("log_weight"), F.lit(0.0)))).alias("accepted")).first()
    n, k = r.n, round(r.accepted or 0) if k is None else k
    result = keyed.select("doc_id", "log_weight", "gumbel_key")
    if k >= n:
        return result
    if k < 1:
        return result.where("false")
    least = radix_select(keyed, "order_key", k)
    above = keyed.where(F.col("order_key") > least)
    room = k - above.count()
    ties = keyed.where(F.col("order_key") == least).orderBy("doc_id").limit(room)
    return above.unionByName(ties).select("doc_id", "log_weight", "gumbel_key")
