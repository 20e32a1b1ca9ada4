"""Removal of repeated units (lines or paragraphs, and sentences inside them) by global digests.

Units are cut at the separator, and units of several sentences also after `.`, `!` or `?` and a space, so
that a passage in the middle of a line is found by its sentences. A unit's normal form is its text in
lower case with runs of white space as one space and none at the ends. Digests of the normal forms are
grouped over all documents, the occurrence of least rank (doc_id, then place) stays, and all others are
removed with their separator. What is a repeat is judged on the input, not on what is left. Only digests
and offsets are shuffled: the minimum per digest is combined before the shuffle, so a line that a third of
all documents share costs one row per task; the join back splits it where it is hot.

Every line that is not empty counts, however short. Sentences inside lines are there to find passages, so those of
fewer than MIN_SENTENCE words have no digest of their own; they go where their whole line goes.

Defined cases: null text is empty; empty units stay; a line whose sentences all go is removed as a whole;
rows that repeat a doc_id share their rank, so equal units at equal places of them stay together; null
doc_ids rank last; other columns are ignored. Offsets are in characters of the input text.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, stash, texts

MIN_WORDS = 1
MIN_SENTENCE = 8
_END = re.compile("(?<=[.!?]) ")
LAST = (1 << 63) - 1


def _parts(text: str, separator: str):
    """(start, line, [(start, sentence), ...]) of each line; one sentence alone is the line itself."""
    at = 0
    for line in text.split(separator):
        inner, x = [], at
        for sentence in _END.split(line):
            inner.append((x, sentence))
            x += len(sentence) + 1
        yield at, line, inner
        at += len(line) + len(separator)


def units(docs: DataFrame, separator: str = "\n", min_words: int = MIN_WORDS, min_sentence: int = MIN_SENTENCE) -> DataFrame:
    """doc_id, start, end, digest of every unit that can be removed."""
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int32()), ("end", pa.int32()), ("digest", pa.binary())])

    def run(batches):
        for b in batches:
            out: list[list] = [[] for _ in range(4)]

            def add(d, at: int, unit: str, least: int, out=out) -> None:
                words = unit.lower().split()
                if len(words) >= least:
                    for column, value in zip(out, (d, at, at + len(unit), hashlib.blake2b(" ".join(words).encode(), digest_size=16).digest())):
                        column.append(value)

            for d, x in zip(b.column("doc_id").to_pylist(), b.column("text")):
                for at, line, inner in _parts(x.as_py() or "", separator):
                    add(d, at, line, min_words)
                    if len(inner) > 1:
                        for y, sentence in inner:
                            add(d, y, sentence, min_sentence)
                if len(out[0]) > 50_000:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, schema)], schema=schema)
                    for c in out:
                        c.clear()
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, schema)], schema=schema)

    return texts(docs).mapInArrow(lean(run), "doc_id long, start int, end int, digest binary")


def repeated_units(docs: DataFrame, separator: str = "\n", min_words: int = MIN_WORDS, min_sentence: int = MIN_SENTENCE) -> DataFrame:
    """doc_id, start, end of all units that occur at a lesser rank (also sentences of lines that go as a whole)."""
    # written once: the text is cut and hashed by one pass, and both sides of the join read the digests
    every = stash(units(docs, separator, min_words, min_sentence), "units").withColumn("rank", F.struct(F.coalesce("doc_id", F.lit(LAST)).alias("doc_id"), "start"))
    kept = every.groupBy("digest").agg(F.min("rank").alias("kept"), F.count(F.lit(1)).alias("n")).where("n > 1").select("digest", "kept")
    return every.join(kept, "digest").where("rank > kept").select("doc_id", "start", "end")


def remove_units(docs: DataFrame, separator: str = "\n", min_words: int = MIN_WORDS, min_sentence: int = MIN_SENTENCE) -> DataFrame:
    """doc_id, text (what remains), n_units, n_removed, removed ARRAY<start, end> in characters of the input."""
    spans = repeated_units(docs, separator, min_words, min_sentence).groupBy(F.coalesce("doc_id", F.lit(LAST)).alias("_id")).agg(F.array_sort(F.collect_set(F.struct("start", "end"))).alias("removed"))
    base = texts(docs).withColumn("_id", F.coalesce("doc_id", F.lit(LAST)))
    none = F.from_json(F.lit("[]"), "array<struct<start:int,end:int>>")
    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string()), ("n_units", pa.int32()), ("removed", pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))])

    def run(batches):
        for b in batches:
            out: list[list] = [[], [], []]
            for x, spans_ in zip(b.column("text"), b.column("removed").to_pylist()):
                text, bounds = x.as_py(), {(s["start"], s["end"]) for s in spans_}
                kept, n, gone = [], 0, []
                for at, line, inner in _parts(text, separator):
                    n += 1
                    left = [] if (at, at + len(line)) in bounds else [(x, t) for x, t in inner if len(inner) == 1 or (x, x + len(t)) not in bounds]
                    if len(left) == len(inner):
                        kept.append(line)
                    elif not left:
                        gone.append({"start": at, "end": at + len(line)})
                    else:
                        kept.append(" ".join(t for _, t in left))
                        gone += [{"start": x, "end": x + len(t)} for x, t in inner if (x, x + len(t)) in bounds]
                for column, value in zip(out, (separator.join(kept), n, gone)):
                    column.append(value)
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), *(pa.array(c, f.type) for c, f in zip(out, list(schema)[1:]))], schema=schema)

    joined = base.join(spans, "_id", "left").select("doc_id", "text", F.coalesce("removed", none).alias("removed"))
    cut = joined.mapInArrow(lean(run), "doc_id long, text string, n_units int, removed array<struct<start:int,end:int>>")
    return cut.select("doc_id", "text", "n_units", F.size("removed").alias("n_removed"), "removed")
