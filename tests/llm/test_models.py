"""Quality draw, toxicity, mixing, exact search and the pipeline."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from rangegraph.llm import exact_topk, importance, mixing, toxicity

SF = "/root/testdata/sf0.01"


# --- quality -----------------------------------------------------------------------------------------------


def labelled_halves(spark, sf=SF):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    fit = F.pmod(F.crc32(F.concat(F.lit("half"), F.col("doc_id").cast("string"))), F.lit(2)) == 0
    return docs, labels.where(fit), labels.where(~fit).collect()


def test_draw_keeps_good_and_drops_bad_rows_it_has_not_learnt_from(spark, capsys):
    docs, fit, other = labelled_halves(spark)
    kept = {r.doc_id for r in importance.resample(docs, fit).collect()}
    good, bad = ([r.doc_id for r in other if r.quality == y] for y in (1, 0))
    with capsys.disabled():
        print(f"unseen labels: good kept {np.mean([d in kept for d in good]):.3f}, bad kept {np.mean([d in kept for d in bad]):.3f}")
    assert np.mean([d in kept for d in good]) >= 0.97
    assert np.mean([d in kept for d in bad]) <= 0.1
    assert kept == {r.doc_id for r in importance.resample(docs.repartition(7), fit).collect()}


def test_draw_is_gumbel_top_k_of_the_models(spark):
    """Counts from the table, ratio of the two models, noise and order, all by brute force; another seed draws others."""
    docs, fit, _ = labelled_halves(spark)
    good = {r.doc_id for r in fit.where("quality = 1").collect()}
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).collect()
    per = []
    for r in rows:
        raw = np.frombuffer(r.text.encode(), np.uint8)
        per.append(importance.features(raw, np.array([0, len(raw)]))[1])
    n, b = importance.STREAMS, importance.BUCKETS
    raw, target = np.zeros(n * b), np.zeros(n * b)
    for r, x in zip(rows, per):
        np.add.at(raw, x, 1)
        if r.doc_id in good:
            np.add.at(target, x, 1)
    model = {}  # bucket -> (raw share, target share), each summing to one per stream
    for s in range(n):
        own = range(s * b, (s + 1) * b)
        all_raw, all_target = sum(raw[own]), sum(target[own])
        towards = {i: raw[i] / all_raw * (target[i] + importance.SMOOTH) / (all_target * raw[i] / all_raw + importance.SMOOTH) for i in own if raw[i]}
        whole = sum(towards.values())
        model |= {i: (raw[i] / all_raw, v / whole) for i, v in towards.items()}
        assert sum(model[i][1] for i in towards) == pytest.approx(1)
    weight = {r.doc_id: sum(np.log(model[i][1] / model[i][0]) for i in x.tolist()) / n for r, x in zip(rows, per)}
    noise = {r.doc_id: r.g for r in docs.select("doc_id", importance.gumbel(F.lit(5), F.col("doc_id")).alias("g")).collect()}
    for k in (100, 700):
        got = {r.doc_id: r for r in importance.resample(docs, fit, k=k, seed=5).collect()}
        want = sorted(weight, key=lambda d: (-round((weight[d] + noise[d]) * 1e4), d))[:k]
        assert set(got) == set(want)
        assert all(r.log_weight == pytest.approx(weight[d], abs=1e-6) and r.gumbel_key == pytest.approx(weight[d] + noise[d], abs=1e-6) for d, r in got.items())
    draws = [{r.doc_id for r in importance.resample(docs, fit, k=700, seed=s).collect()} for s in (17, 99)]
    assert 2 <= len(draws[0] ^ draws[1]) <= 700


def test_target_ids_are_sent_or_joined_alike(spark, monkeypatch):
    docs, fit, _ = labelled_halves(spark)
    odd = docs.select("doc_id", "text").unionByName(spark.createDataFrame([(None, "no id at all"), (0, None)], "doc_id long, text string"))
    draws = []
    for limit in (importance.SENT_BYTES, 0):
        monkeypatch.setattr(importance, "SENT_BYTES", limit)
        draws.append(sorted((str(r.doc_id), round(r.log_weight, 6)) for r in importance.resample(odd, fit).collect()))
    assert draws[0] == draws[1] and draws[0]


def test_noise_draws_in_proportion_to_weights(spark):
    """The first of many draws falls on each row as often as its weight says."""
    weights = {1: 0.0, 2: 1.0, 3: -0.7, 4: 0.3}
    rows = spark.createDataFrame([(i, w) for i, w in weights.items()], "doc_id long, w double")
    n = 20_000
    keys = spark.range(n).join(rows, F.lit(True)).withColumn("key", F.col("w") + importance.gumbel(F.col("id"), F.col("doc_id")))
    first = {r.best: r["count"] / n for r in keys.groupBy("id").agg(F.max_by("doc_id", "key").alias("best")).groupBy("best").count().collect()}
    total = sum(np.exp(list(weights.values())))
    assert all(first[i] == pytest.approx(np.exp(w) / total, abs=0.015) for i, w in weights.items())


def test_ties_at_the_cut_and_long_texts(spark):
    rows = [(i, "the same text of some words") for i in (5, 3, 9, 3)] + [(20, "x " * 200_000), (21, "word" * 50_000), (22, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(5, 1), (20, 0)], "doc_id long, quality int")
    assert importance.resample(docs, labels, k=7).count() == 7
    for k in range(1, 8):
        got = importance.resample(docs, labels, k=k).collect()
        assert len(got) == k
    assert importance.resample(docs, labels, k=0).count() == 0 and importance.resample(docs, labels, k=99).count() == 7


def test_draw_on_odd_tables(spark):
    docs = spark.createDataFrame([(1, "a b c", 0), (2, None, 0), (2, "", 0), (None, "x", 0)], "doc_id long, text string, label int")
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert importance.resample(docs, none).count() == 4
    assert importance.resample(docs.where("false"), none).count() == 0


def test_radix_select(spark):
    v = [int(x) for x in np.random.default_rng(0).integers(-(2**40), 2**40, 500)] + [3, 3, 3]
    df = spark.createDataFrame([(x,) for x in v], "k long")
    for k in (1, 2, 250, 503):
        assert importance.radix_select(df, "k", k) == sorted(v, reverse=True)[k - 1]


# --- toxicity ----------------------------------------------------------------------------------------------


def toxic_texts(spark, n: int = 600):
    rng = np.random.default_rng(1)
    stems, tails = ["vilgar", "zhlob"], ["o", "en", "ing", "ed", "ous", "ism", "er", "est"]
    words = ["".join(rng.choice(list("etaoinshr"), rng.integers(2, 8))) for _ in range(400)]
    rows, labels = [], []
    for i in range(n):
        t = list(rng.choice(words, rng.integers(5, 60)))
        bad = i % 5 == 0
        if bad:
            for _ in range(3):
                t.insert(int(rng.integers(len(t))), str(rng.choice(stems)) + str(rng.choice(tails)))
        rows.append((i, " ".join(t)))
        if i % 2 == 0 or i % 5 == 0:
            labels.append((i, 1, int(bad)))
    return spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_held_out_toxicity(spark):
    docs, labels = toxic_texts(spark)
    got = {r.doc_id: r for r in toxicity.score(docs, labels).collect()}
    assert len(got) == 600
    for r in got.values():
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7)
    held = [r for r in got.values() if r.held_out]
    assert np.mean([r.predicted for r in held if r.doc_id % 5 == 0]) >= 0.9
    assert np.mean([r.predicted for r in held if r.doc_id % 5]) <= 0.05


def test_held_out_labels_have_no_influence(spark):
    docs, labels = toxic_texts(spark, 300)
    held = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(3)) == 1
    turned = labels.withColumn("toxic", F.when(held, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = ({r.doc_id: r.score for r in toxicity.score(docs, x).collect()} for x in (labels, turned))
    assert a == pytest.approx(b, abs=1e-12)


def test_labels_are_sent_or_joined_alike(spark, monkeypatch):
    docs, labels = toxic_texts(spark, 300)
    docs = docs.unionByName(spark.createDataFrame([(None, "vilgaro"), (5, "again vilgaro")], "doc_id long, text string"))
    models = []
    for limit in (toxicity.SENT_BYTES, 0):
        monkeypatch.setattr(toxicity, "SENT_BYTES", limit)
        models.append(toxicity.fit(docs, labels)[0].digest)
    assert models[0] == models[1]


def test_toxicity_on_odd_tables(spark):
    docs, labels = toxic_texts(spark, 200)
    odd = docs.unionByName(spark.createDataFrame([(900, None), (901, ""), (902, "!!!"), (0, "again"), (None, "x")], "doc_id long, text string")).withColumn("score", F.lit("x"))
    got = toxicity.score(odd, labels).collect()
    assert len(got) == 205 and len({r.score for r in got if r.doc_id in (900, 901, 902)}) == 1
    assert {r.score for r in toxicity.score(docs, labels.where("toxic = 0")).collect()} == {0.0}
    assert toxicity.score(docs.where("false"), labels).count() == 0


def brute_models(words, counts):
    """Interpolated Kneser-Ney models of two classes, straight from the definition: p(class, context, character)."""
    order, shared, discount = toxicity.ORDER, toxicity.SHARED, toxicity.DISCOUNT
    seen = [{}, {}]
    for w, both in zip(words, counts):
        run = "\x01" * (order - 1) + w + "\x02"
        for i in range(order - 1, len(run)):
            for y in (0, 1):
                g = run[i - order + 1 : i + 1]
                seen[y][g] = seen[y].get(g, 0) + both[y]
    every = set(seen[0]) | set(seen[1])
    letters = sorted({g[-1] for g in every})

    def count(y, n):
        """Counts of the grams of n characters: of places at the top, of longer grams below."""
        if n == order:
            return seen[y]
        out = {}
        for longer in {g[-n - 1 :] for g in every if n + 1 > shared + 1 and seen[y][g] > 0} if n > shared else {g[-n - 1 :] for g in every}:
            out[longer[1:]] = out.get(longer[1:], 0) + 1
        return out

    table = {(y, n): count(y, n) for y in (0, 1) for n in range(1, order + 1)}

    def p(y, context, c):
        if not context and c is None:
            return None
        n = len(context) + 1
        lower = p(y, context[1:], c) if context else 1 / len(letters)
        own = {a: table[y, n].get(context + a, 0) for a in letters}
        total, kinds = sum(own.values()), sum(v > 0 for v in own.values())
        if not total:
            return lower
        return max(own[c] - discount, 0) / total * (own[c] > 0) + discount * kinds / total * lower

    return p, letters


def test_models_are_kneser_ney_distributions():
    """The brute-force probabilities sum to one in every context, and the tables hold the difference of their logarithms."""
    words = ["abba", "abc", "bac", "cab", "aab", "abcabca"]
    t, o = np.array([5, 0, 1, 0, 2, 3]), np.array([0, 3, 1, 4, 2, 0])
    p, letters = brute_models(words, list(zip(t, o)))
    for context in ("", "a", "ab", "\x01\x01", "\x01\x01\x01\x01a", "cabca", "bbbbb"):
        for y in (0, 1):
            assert sum(p(y, context, c) for c in letters) == pytest.approx(1, abs=1e-9)
    m = toxicity.Evidence(words, t.astype(float), o.astype(float))
    probe = [*words, "ab", "bb", "cccc", "bacab", "a"]
    for w, got in zip(probe, m.of(probe)):
        run = "\x01" * (toxicity.ORDER - 1) + w + "\x02"
        places = range(toxicity.ORDER - 1, len(run))
        want = sum(np.log(p(0, run[i - toxicity.ORDER + 1 : i], run[i]) / p(1, run[i - toxicity.ORDER + 1 : i], run[i])) for i in places)
        assert got == pytest.approx(want, abs=1e-3), w
    assert m.of([]).shape == (0,)


def test_memory_belongs_to_one_model():
    words = ["abba", "cab"]
    a, b = toxicity.Evidence(words, np.array([9.0, 0]), np.array([0, 9.0])), toxicity.Evidence(words, np.array([0, 9.0]), np.array([9.0, 0]))
    x, y = toxicity.text_features(["abba"], a)[0, 0], toxicity.text_features(["abba"], b)[0, 0]
    assert x > 0 > y and toxicity.text_features(["abba"], a)[0, 0] == x
    assert toxicity._memory[0] == a.digest and len(toxicity._memory[1]) == 1
    many = [f"w{i}" for i in range(50)]
    toxicity.text_features([" ".join(many)], a, most=20)
    toxicity.text_features(["abba"], a, most=20)
    assert len(toxicity._memory[1]) <= 51


def test_models_learn_from_every_labelled_row(spark, monkeypatch):
    """The bound on rows is the curve's alone: rare words far beyond it are in the toxic model."""
    monkeypatch.setattr(toxicity, "SAMPLE", 20)
    docs, labels = toxic_texts(spark)
    curve = {r.doc_id for r in toxicity.labelled_sample(labels.where(F.pmod(F.xxhash64("doc_id"), F.lit(4)) == 0), "toxic", 20).collect()}
    rare = [i for i in range(0, 600, 5) if zlib.crc32(str(i).encode()) % 3 != 1 and i not in curve]
    word = F.concat(F.lit(" q"), F.translate(F.col("doc_id").cast("string"), "0123456789", "bcdfgjkmpw"), F.lit("x"))
    docs = docs.withColumn("text", F.when(F.col("doc_id").isin(rare), F.concat("text", word)).otherwise(F.col("text")))
    model = toxicity.fit(docs, labels)[0]
    evidence = model.of(["q" + str(i).translate(str.maketrans("0123456789", "bcdfgjkmpw")) + "x" for i in rare])
    assert len(rare) > 40 and (evidence > 2).all()


def test_models_of_grams_are_those_of_words():
    words, rng = ["abba", "abc", "bac", "cab", "aab", "abracadabra"], np.random.default_rng(4)
    t, o = rng.integers(0, 9, 6), rng.integers(0, 9, 6)
    rows = [(w, y) for w, a, b in zip(words, t, o) for y, n in ((1, a), (0, b)) for _ in range(n)]
    batch = pa.RecordBatch.from_pydict({"text": [w for w, _ in rows], "label": [y for _, y in rows]})
    (got,) = toxicity._gram_counts([batch])
    high, low, toxic, ordinary = (c.to_numpy() for c in got.columns)
    a, b = toxicity.Evidence.of_grams(toxicity.gram_table(high, low), toxic, ordinary), toxicity.Evidence(words, t.astype(float), o.astype(float))
    probe = [*words, "abb", "zzz", "cabba"]
    assert a.of(probe) == pytest.approx(b.of(probe), abs=1e-5)


def test_every_character_of_a_long_run_counts():
    bad, fine = "vilgaro", "etaoinshr"
    model = toxicity.Evidence([bad, fine], np.array([50.0, 0]), np.array([0, 50.0]))
    run = fine * 30
    for n in (1, 39, 40, 41, 80, 81, 270):
        pieces = toxicity.words_of(run[:n])
        codes, owner = toxicity.characters(pieces)
        assert "".join(map(chr, codes[toxicity.places(owner)])) == run[:n] + "\x02" and len(pieces) == (1 if n <= 40 else -(-(n + 1) // 40))
    for at in (0, 38, 100, 200, 270):
        a, b = toxicity.text_features([run, run[:at] + bad * 2 + run[at:]], model)
        assert b[0] > a[0] + 0.5
    joined = pa.RecordBatch.from_pydict({"text": [run + bad], "label": [1]})
    (got,) = toxicity._gram_counts([joined])
    grams = {"".join(map(chr, g)) for g in toxicity.gram_table(got.column(0).to_numpy(), got.column(1).to_numpy())}
    assert {"vilgar", "ilgaro", "lgaro\x02"} <= grams and sum(got.column(2).to_pylist()) == len(run + bad) + 1


def test_lookup():
    rng = np.random.default_rng(0)
    k = np.unique(rng.integers(1, 2**63, 5_000).astype(np.uint64))
    t = toxicity.Lookup(k, np.arange(len(k), dtype=np.float32))
    found, v = t.get(np.concatenate([k, k + np.uint64(1)]))
    assert found[: len(k)].all() and (v[: len(k)] == np.arange(len(k))).all()
    assert not found[len(k) :][~np.isin(k + np.uint64(1), k)].any()


# --- mixing ------------------------------------------------------------------------------------------------


def fill(children, budget):
    """Brute force: shares by weight, shortages shared again among those that can take more."""
    got = {c: 0.0 for c, _, _ in children}
    left, open_ = budget, {c for c, w, cap in children if w > 0 and cap > 0}
    while left > 1e-9 and open_:
        total = sum(w for c, w, _ in children if c in open_)
        used, full = 0.0, set()
        for c, w, cap in children:
            if c in open_:
                add = min(left * w / total, cap - got[c])
                got[c] += add
                used += add
                if cap - got[c] < 1e-9:
                    full.add(c)
        left -= used
        open_ -= full
        if not full:
            break
    return got


def test_water_level(spark):
    rng = np.random.default_rng(2)
    rows = [(int(f), int(c), float(rng.choice([0, 1, 2, 0.5])), float(rng.integers(0, 50)), float(20 + 30 * f)) for f in range(6) for c in range(7)]
    rows = [(f, c, w, cap if w > 0 else 0.0, b) for f, c, w, cap, b in rows]
    got = {(r.f, r.c): r.budget for r in mixing.water_level(spark.createDataFrame(rows, "f int, c int, weight double, capacity double, parent_budget double"), ["f"], ["c"]).collect()}
    for f in range(6):
        want = fill([(c, w, cap) for g, c, w, cap, _ in rows if g == f], 20 + 30 * f)
        for c, v in want.items():
            assert got[f, c] == pytest.approx(v, abs=1e-6)


def test_draws(spark):
    rows = [(i, "w " * (i % 9), "en" if i % 3 else None, f"src{i % 5}" if i % 11 else None) for i in range(400)] + [(7, "again some", "en", "src2")]
    docs = spark.createDataFrame([(*r, 0) for r in rows], "doc_id long, text string, lang string, source string, n_tokens int")
    d = mixing.draw(docs, share=0.5).collect()
    total = sum(len((t or "").split()) for _, t, _, _ in rows)
    assert sum(r.n_tokens for r in d) <= 0.5 * total and sum(r.n_tokens for r in d) >= 0.4 * total
    again = mixing.draw(docs.repartition(5), share=0.5).collect()
    assert sorted(map(tuple, d), key=str) == sorted(map(tuple, again), key=str)
    m = mixing.mix(docs, epochs=1, share=0.5)
    assert m.columns == docs.columns and m.groupBy("doc_id").count().where("count > 2").count() == 0
    assert mixing.mix(docs.where("false")).count() == 0
    everything = mixing.draw(docs, share=5.0, epochs=2).groupBy("doc_id").count()
    assert everything.where("count < 2").count() == 0


def test_mixing_keeps_its_budget_with_repeated_ids(spark):
    """A repeated doc_id is no way past the budget, and columns may have any names."""
    rows = [(1, "a b c d", "en", "src1", 1, 2, 3), (1, "a b", "en", "src1", 4, 5, 6), (1, "a b", "en", "src2", 7, 8, 9), (2, "w " * 6, "en", "src1", 0, 0, 0), (None, "x y", None, None, 0, 0, 0), (None, "x y", None, None, 1, 0, 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, _n int, _id int, _times int")
    for share in (0.2, 0.4, 0.6, 0.9, 1.5, 3.0):
        d = mixing.draw(docs, share=share).collect()
        m = mixing.mix(docs, share=share)
        assert m.columns == docs.columns
        got = m.collect()
        assert len(got) == len(d)
        leaf = lambda rows, n: {k: sum(n(r) for r in rows if (r.doc_id, r.lang, r.source) == k) for k in {(r.doc_id, r.lang, r.source) for r in rows}}
        assert leaf(got, lambda r: len(r.text.split())) == leaf(d, lambda r: r.n_tokens)


# --- search ------------------------------------------------------------------------------------------------


def test_exact_search(spark):
    rng = np.random.default_rng(3)
    v = [(i, [float(x) for x in rng.normal(size=6)]) for i in range(300)]
    v += [(300, None), (301, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (302, [float("nan")] * 6), (303, [float("inf")] * 6), (None, [1.0] * 6), (50, v[50][1]), (304, v[7][1]), (305, v[7][1])]
    df = spark.createDataFrame([(*r, 1) for r in v], "vec_id long, embedding array<float>, score int").repartition(4)
    q = exact_topk.quantised(df)
    got = {}
    for r in exact_topk.search(q.where("vec_id % 50 = 0"), q, 5, block=3).collect():
        got.setdefault(r.query_id, {})[r["rank"]] = (r.score, r.vec_id)
    ok = [(i, np.floor(256 * np.array(e, np.float32).astype(float)).astype(int)) for i, e in v if i is not None and e is not None and None not in e and np.isfinite(e).all()]
    queries = {i: w for i, w in ok if i % 50 == 0}
    assert set(got) == set(queries)
    for i, w in queries.items():
        want = sorted(((-int(w @ x), j) for j, x in ok if j != i))[:5]
        assert [got[i][k + 1] for k in range(5)] == [(-s, j) for s, j in want]
    few = q.where("vec_id in (0, 50, 51)")
    assert exact_topk.search(few.where("vec_id = 0"), few, 5).count() <= 3
    assert exact_topk.search(q.where("false"), q, 5).count() == 0


# --- pipeline ----------------------------------------------------------------------------------------------


def brute_mix(rows, share):
    """The rows (doc_id, text, lang, source) that one epoch at most gives, by budgets down the tree and prefixes of a hashed order."""
    import hashlib
    import re

    def domain(source):
        number = re.search(r"([0-9]+)$", source or "")
        return mixing.DOMAINS[int(number.group(1)) % 4] if number else "other"

    leaves: dict = {}
    for d, text, lang, source in rows:
        leaves.setdefault((domain(source), lang, source), []).append((d, len((text or "").split())))
    tokens = {k: sum(n for _, n in v) for k, v in leaves.items()}
    names = lambda depth: sorted({k[:depth] for k in leaves}, key=str)
    capacity = lambda node: float(sum(t for k, t in tokens.items() if k[: len(node)] == node))
    weight = lambda node: mixing.DOMAIN_WEIGHTS.get(node[0], 1.0) if len(node) == 1 else mixing.LANGUAGE_WEIGHTS.get(node[1], 1.0) if len(node) == 2 else 1.0
    budget = {(): share * sum(tokens.values())}
    for depth in (1, 2, 3):
        for parent in [()] if depth == 1 else names(depth - 1):
            budget |= fill([(n, weight(n), capacity(n)) for n in names(depth) if n[:-1] == parent], budget[parent])
    out = []
    for leaf, docs in leaves.items():
        have, total = int(budget[leaf] + 1e-6), tokens[leaf]
        if total and have >= total:
            out += [d for d, _ in docs]
        elif have > 0:
            for d, n in sorted(docs, key=lambda x: (hashlib.md5(f"{mixing.SEED}:0:{x[0]}".encode()).hexdigest(), x)):
                have -= n
                if have < 0:
                    break
                out.append(d)
    return out


def test_pipeline_against_brute_force(spark):
    """Every stage on what its predecessor kept: draw, classes, repeated bytes, mix and ids, each worked out without the operator."""
    import public_tokenizers
    import sentencepiece
    from test_dedup import brute_classes, sets_of  # noqa: F401

    from rangegraph.llm.common import stash

    small = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{small}/documents.parquet")
    seen = [docs]
    for name, stage in corpus_pipeline.STAGES:
        seen.append(stash(stage(spark, seen[-1], small), name))
    for a in seen[1:-1]:
        assert a.columns == docs.columns
    rows = [{r.doc_id: r for r in d.collect()} for d in seen]
    assert all(set(b) <= set(a) for a, b in zip(rows, rows[1:]))
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{small}/labels.parquet").collect()}
    assert all(d in rows[1] for d, q in labels.items() if q == 1) and not any(d in rows[1] for d, q in labels.items() if q == 0)
    assert set(rows[2]) == {c for c, _ in brute_classes([(d, rows[1][d].text) for d in sorted(rows[1])]).values()}
    marks: dict = {}
    for d in sorted(rows[2]):
        raw = (rows[2][d].text or "").encode()
        for i in range(len(raw) - 49):
            marks.setdefault(raw[i : i + 50], d)
    for d in rows[2]:
        raw = (rows[2][d].text or "").encode()
        gone = bytearray(len(raw))
        for i in range(len(raw) - 49):
            if marks[raw[i : i + 50]] < d:
                gone[i : i + 50] = b"\1" * 50
        assert rows[3][d].text == bytes(x for x, g in zip(raw, gone) if not g).decode("utf-8", "ignore") and rows[3][d].n_chars == len(rows[3][d].text)
    assert sorted(rows[4]) == sorted(brute_mix([(d, r.text, r.lang, r.source) for d, r in rows[3].items()], mixing.BUDGET_SHARE))
    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    for d, r in rows[5].items():
        assert list(r.ids) == [*sp.encode(rows[4][d].text), 2] and r.n_tokens == len(r.ids)
    assert len(rows[5]) == len(rows[4]) > 20


def test_pipeline_run_is_its_stages(spark):
    got = {r.doc_id: r.n_tokens for r in corpus_pipeline.run(spark, "/root/testdata/sf0.001").collect()}
    assert got and set(got) <= {r.doc_id for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()}
