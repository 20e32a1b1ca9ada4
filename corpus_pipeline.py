"""A corpus pipeline of five stages, each written and reread as the next one's documents.

Quality selection, one document per class of near copies, removal of repeated substrings, mixing to target
weights, and encoding. Each stage sees all that its predecessor kept. All but the last return the columns
of documents; the last returns doc_id, n_tokens and ids.

Nulls, empty tables, repeated rows and further columns are treated as the operators state; a document that
loses all its text in the third stage goes on with an empty text, and its n_chars is 0.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangegraph.llm import chosen_path, importance, mixing, pieces, suffix_dedup
from rangegraph.llm.common import fresh, stash

MODEL = "piece_bpe_32k.model"


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the importance draw keeps."""
    name = fresh(docs.columns, "drawn")
    drawn = importance.resample(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")).select(F.col("doc_id").alias(name)).distinct()
    return docs.join(drawn, docs.doc_id.eqNullSafe(drawn[name]), "left_semi")


def ngram_jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies."""
    return chosen_path.one_per_class(docs)


def suffix_array_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the substrings that smaller documents have."""
    return suffix_dedup.without_repeats(docs)


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents drawn to the target weights, each at most once."""
    return mixing.mix(docs, epochs=1)


def piece_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids of each document, and the digest of the text decoded from them."""
    coded = pieces.encode_documents(docs, public_tokenizers.path(MODEL))
    return coded.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), "ids", F.sha2(F.encode("decoded", "UTF-8"), 256).alias("decoded_sha256"))


STAGES = [
    ("quality_classifier", quality_classifier),
    ("ngram_jaccard_join", ngram_jaccard_join),
    ("suffix_array_dedup", suffix_array_dedup),
    ("source_mixing", source_mixing),
    ("piece_encoding", piece_encoding),
]

#: SQL can't express the chosen-path join, the draw and the encoding; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = stash(docs, name)
    return docs
