"""Encoding, decoding and counting against the tokenizer's own library."""

from __future__ import annotations

import hashlib
import random

import public_tokenizers
import pytest
import sentencepiece
from tokenizers import Tokenizer

from rangegraph.llm import pieces, token_counts
from rangegraph.llm.common import new_path

MODEL = public_tokenizers.path("piece_bpe_32k.model")
PARTS = ["a", "b", " ", "  ", "\n", "\t", "▁", "the", "ing", "한", "국", "😀", "\x00", "é", "ß", ".", "!!", "<s>", "</s>", "<0x0A>", "1", "==", "    ", "梦", "‍", "\r\n", "́", "<unk>"]
SCHEMA = "doc_id long, text string, ids int"  # an extra column whose name an output also has


@pytest.fixture(scope="module")
def texts():
    rng = random.Random(5)
    made = ["".join(rng.choice(PARTS) for _ in range(rng.randint(0, 16))) for _ in range(3_000)]
    return [*made, "", None, " ", "x" * 20_000, "héllo wörld " * 3_000, "▁" * 50, " " * 70 + "a", "日本語" * 500]


def test_round_trip_is_the_library(texts):
    sp, t = sentencepiece.SentencePieceProcessor(model_file=MODEL), pieces.PieceTable(MODEL, units=50, pairs=50)
    for x in texts:
        ids = [*sp.encode(x or ""), 2]
        got, back = t.round_trip(x or "")
        assert got == ids
        assert back == sp.decode(ids) == t.decode(ids)
        assert t.encode(x or "") == ids[:-1]


def test_decoding_reads_the_ids_alone():
    """Any ids decode as in the library, whether a text has them or not."""
    sp, t, rng = sentencepiece.SentencePieceProcessor(model_file=MODEL), pieces.PieceTable(MODEL), random.Random(7)
    n = sp.get_piece_size()
    odd = [t.unk, t.eos, *t.byte_of, *t.control]
    for _ in range(2_000):
        ids = [rng.choice(odd) if rng.random() < 0.3 else rng.randrange(n) for _ in range(rng.randint(0, 12))]
        assert t.decode(ids) == sp.decode(ids), ids


def test_frames(spark, texts):
    sp = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    rows = [(i, x, 1) for i, x in enumerate(texts)] + [(0, texts[0], 2), (None, "no id", 3)]
    df = spark.createDataFrame(rows, SCHEMA)
    got = pieces.encode_digests(df, MODEL).collect()
    assert len(got) == len(rows)
    by_id = {r.doc_id: r for r in got}
    for i, x in enumerate(texts):
        ids = [*sp.encode(x or ""), 2]
        assert by_id[i].n_tokens == len(ids)
        assert by_id[i].ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert by_id[i].decoded_sha256 == hashlib.sha256(sp.decode(ids).encode()).hexdigest()
    full = {r.doc_id: r for r in pieces.encode_documents(df, MODEL).collect()}
    assert full[7].ids == [*sp.encode(texts[7]), 2] and full[7].decoded == sp.decode(full[7].ids)
    assert pieces.encode_digests(df.where("false"), MODEL).count() == 0


@pytest.mark.parametrize("name", ["piece_bpe_32k.model", "byte_bpe_50k.json"])
def test_counts(spark, texts, name):
    path = public_tokenizers.path(name)
    few = texts[:300] + texts[-8:]
    rows = [(i, x) for i, x in enumerate(few)] + [(0, few[0])]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    cache = new_path(spark, "cache")
    got = token_counts.count_tokens(df, path, cache).collect()
    assert len(got) == len(rows)
    if name.endswith(".model"):
        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        want = [len(sp.encode(x or "")) for x in few]
    else:
        want = [len(Tokenizer.from_file(path).encode(x or "", add_special_tokens=False).ids) for x in few]
    for r in got:
        assert (r.n_tokens, r.n_bytes, r.over_limit) == (want[r.doc_id], len((few[r.doc_id] or "").encode()), want[r.doc_id] > 4096)
    size = token_counts.read_cache(spark, cache).count()
    assert size == len({x or "" for x in few})
    more = spark.createDataFrame([(1, few[3]), (2, "a new text")], "doc_id long, text string")
    again = {r.doc_id: r.n_tokens for r in token_counts.count_tokens(more, path, cache).collect()}
    assert again[1] == want[3] and token_counts.read_cache(spark, cache).count() == size + 1


def test_counts_of_a_hot_text(spark, monkeypatch):
    """A text with very many copies, and one just below: same counts however they are joined."""
    monkeypatch.setattr(token_counts, "HOT", 20)
    sp = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    rows = [(i, ["the same text again", None, f"text {i}", "a rarer one"][0 if i % 3 == 0 else 1 if i % 3 == 1 else 2 if i % 2 else 3]) for i in range(300)]
    got = {r.doc_id: r.n_tokens for r in token_counts.count_tokens(spark.createDataFrame(rows, "doc_id long, text string"), MODEL).collect()}
    assert got == {i: len(sp.encode(t or "")) for i, t in rows}


def test_counts_of_an_empty_table(spark):
    assert token_counts.count_tokens(spark.createDataFrame([], "doc_id long, text string"), MODEL).count() == 0
