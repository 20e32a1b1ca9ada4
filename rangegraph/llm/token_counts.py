"""Token counts behind a cache of digests.

A text is known by the SHA-256 of its bytes and a tokenizer by the digest of its file. Texts are joined
with the cache on both digests. Of the texts without a stored count one row per digest is chosen, only
these are encoded (by the tokenizer's own library), and the new counts are appended to the cache.

The text itself moves once, for distinct misses only; hits move 32 bytes. Choosing the row per digest is
a plain aggregate, so copies are combined before the shuffle however many there are. Counts of texts with very many
copies (by their share of the rows, so they are few) are sent to all tasks, and only the others are joined by
digest: a text that a third of all documents have does not gather in one task.

Defined cases: null text is the empty text (0 tokens); rows with null doc_id are kept; repeated rows give
repeated results; an empty table gives an empty result; other columns are ignored. A cache written twice
with the same digest (two writers) still gives one count per row.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, new_path, stash, texts

CACHE_SCHEMA = "text_digest binary, tokenizer_digest string, n_tokens long"
LIMIT = 4096
HOT = 500  # copies below which a text is never hot

_encoders: dict[str, object] = {}


def tokenizer_digest(model_path: str) -> str:
    with open(model_path, "rb") as f:
        return hashlib.sha256(f.read()).hexdigest()


def _counter(model_path: str):
    """Counts of a list of texts, without added special tokens."""
    if model_path not in _encoders:
        if model_path.endswith(".model"):
            import sentencepiece

            sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
            _encoders[model_path] = lambda xs: [len(ids) for ids in sp.encode(xs, num_threads=1)]
        else:
            from tokenizers import Tokenizer

            tk = Tokenizer.from_file(model_path)
            tk.no_truncation()
            tk.no_padding()
            _encoders[model_path] = lambda xs: [len(e.ids) for e in tk.encode_batch(xs, add_special_tokens=False)]
    return _encoders[model_path]


def read_cache(spark: SparkSession, path: str) -> DataFrame:
    """The stored counts; an absent cache is an empty one."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    if not p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p):
        return spark.createDataFrame([], CACHE_SCHEMA)
    return spark.read.schema(CACHE_SCHEMA).parquet(path)


def _encode(batches, model_path: str, version: str):
    """Counts of a partition of distinct texts, some hundred kilobytes at a time."""
    count = _counter(model_path)
    schema = pa.schema([("text_digest", pa.binary()), ("tokenizer_digest", pa.string()), ("n_tokens", pa.int64())])
    for b in batches:
        out, held, size = [], [], 0
        for x in b.column("text"):
            held.append(x.as_py() or "")
            size += len(held[-1])
            if size > 500_000:
                out += count(held)
                held, size = [], 0
        out += count(held) if held else []
        yield pa.RecordBatch.from_arrays([b.column("text_digest").cast(pa.binary()), pa.array([version] * b.num_rows, pa.string()), pa.array(out, pa.int64())], schema=schema)


def count_tokens(docs: DataFrame, model_path: str, cache_path: str | None = None) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit. Fills the cache at cache_path (a new one if None)."""
    spark = docs.sparkSession
    cache_path = cache_path or new_path(spark, "token-cache")
    version = tokenizer_digest(model_path)
    keyed = texts(docs).withColumn("text_digest", F.unhex(F.sha2(F.encode("text", "UTF-8"), 256)))
    rows = stash(keyed.select("doc_id", "text_digest", F.octet_length("text").cast("long").alias("n_bytes")), "digests")
    stored = read_cache(spark, cache_path).where(F.col("tokenizer_digest") == version).select("text_digest")
    fresh = keyed.select("text_digest", "text").join(stored.distinct(), "text_digest", "left_anti") if stored.limit(1).count() else keyed.select("text_digest", "text")
    misses = fresh.groupBy("text_digest").agg(F.first("text").alias("text"))
    misses.mapInArrow(lean(lambda it: _encode(it, model_path, version)), CACHE_SCHEMA).write.mode("append").parquet(cache_path)
    counts = read_cache(spark, cache_path).where(F.col("tokenizer_digest") == version).groupBy("text_digest").agg(F.max("n_tokens").alias("n_tokens"))
    many = max(HOT, rows.count() // (4 * int(spark.conf.get("spark.sql.shuffle.partitions"))))
    hot = stash(rows.groupBy("text_digest").count().where(F.col("count") > many).select("text_digest"), "hot")  # at most rows / many
    sent = F.broadcast(counts.join(F.broadcast(hot), "text_digest", "left_semi"))
    joined = rows.join(sent, "text_digest").unionByName(rows.join(F.broadcast(hot), "text_digest", "left_anti").join(counts, "text_digest"))
    return joined.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > LIMIT).alias("over_limit"))
