"""Near copies, repeated substrings and repeated lines against brute force."""

from __future__ import annotations

import hashlib
import itertools
import random

import numpy as np
import pytest

from rangegraph.llm import chosen_path, suffix_dedup, unit_dedup
from rangegraph.llm.components import components

WORDS = [f"w{i}" for i in range(300)]


def near_copies(seed: int, n: int = 120):
    """Documents with copies, edited copies, a shared passage, and odd ones."""
    rng = random.Random(seed)
    base = [[rng.choice(WORDS) for _ in range(rng.randint(8, 120))] for _ in range(n // 4)]
    out = []
    for i in range(n):
        w = list(rng.choice(base))
        for _ in range(rng.choice([0, 0, 1, 1, 2, 4, 9])):
            w[rng.randrange(len(w))] = rng.choice(WORDS)
        if rng.random() < 0.3:
            w = ["common", "passage", "of", "some", "length", "that", "many", "texts", "share"] + w
        out.append((i, " ".join(w)))
    return out + [(n, ""), (n + 1, None), (n + 2, "one"), (n + 3, "one"), (n + 4, "a b c d"), (n + 5, "A  b\nc d"), (n + 6, "   ")]


def sets_of(text):
    w = (text or "").lower().split()
    return frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) > 4 else frozenset([tuple(w)] if w else [])


def brute_classes(rows):
    s = [sets_of(t) for _, t in rows]
    parent, links = list(range(len(rows))), [0] * len(rows)

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(range(len(rows)), 2):
        if s[a] == s[b] or 5 * len(s[a] & s[b]) >= 4 * len(s[a] | s[b]):
            links[a] += 1
            links[b] += 1
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    return {rows[i][0]: (rows[root(i)][0], links[i]) for i in range(len(rows))}


@pytest.mark.parametrize("seed", [1, 2])
def test_classes_and_links(spark, seed):
    rows = near_copies(seed)
    got = {r.doc_id: (r.class_id, r.n_links) for r in chosen_path.link_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == brute_classes(rows)


def test_links_through_every_level(spark, capsys):
    """Buckets of a few sets are split on further tokens, leaves and families are dealt in blocks: the links stay whole."""
    found = wanted = wrong = 0
    for seed in (3, 4, 5):
        rows = near_copies(seed, 160)
        want = brute_classes(rows)
        got = {r.doc_id: (r.class_id, r.n_links) for r in chosen_path.link_classes(spark.createDataFrame(rows, "doc_id long, text string"), limits=chosen_path.Limits(bucket=6, leaf=8, block=8)).collect()}
        found, wanted = found + sum(n for _, n in got.values()), wanted + sum(n for _, n in want.values())
        wrong += sum(got[d][0] != c for d, (c, _) in want.items())
    with capsys.disabled():
        print(f"links through splits: {found // 2} of {wanted // 2}, documents in a wrong class: {wrong}")
    assert found >= 0.999 * wanted and wrong <= 1


def test_a_large_family_is_verified_in_blocks(spark):
    rng = random.Random(8)
    base = [rng.choice(WORDS) for _ in range(90)]
    rows = []
    for i in range(400):
        w = list(base)
        for _ in range(rng.randint(0, 3)):
            w[rng.randrange(90)] = rng.choice(WORDS)
        rows.append((i, " ".join(w)))
    rows.append((400, " ".join(rng.choice(WORDS) for _ in range(60_000))))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_classes(rows)
    for limits in (chosen_path.Limits(), chosen_path.Limits(block=50), chosen_path.Limits(tokens=3_000)):
        assert {r.doc_id: (r.class_id, r.n_links) for r in chosen_path.link_classes(df, limits=limits).collect()} == want


def test_products_and_marks_give_the_same(monkeypatch):
    """Both ways of verifying a pair of blocks, against every pair of sets."""
    import pyarrow as pa

    rng = random.Random(2)
    base = [rng.sample(range(300), 40) for _ in range(6)]
    made = [sorted(set(rng.choice(base)[: rng.randint(30, 40)]) | set(rng.sample(range(300, 400), rng.randint(0, 4)))) for _ in range(60)] + [[]]
    names, copies = rng.sample(range(10**6), 61), [rng.randint(1, 3) for _ in range(61)]
    for alone in (True, False):
        second = [False] * 61 if alone else [i % 3 == 0 for i in range(61)]
        batch = pa.RecordBatch.from_pydict({"task": [1] * 61, "set": names, "copies": copies, "second": second, "alone": [alone] * 61, "tokens": [np.array(t, np.uint64).tobytes() for t in made]})
        links, joined = [0] * 61, list(range(61))
        for i, j in itertools.combinations(range(61), 2):
            a, b = set(made[i]), set(made[j])
            if a and b and (alone or second[i] != second[j]) and 5 * len(a & b) >= 4 * len(a | b):
                links[i] += copies[j]
                links[j] += copies[i]
                x, y = joined[i], joined[j]
                joined = [x if k == y else k for k in joined]
        want = {names[i]: (min(names[k] for k in range(61) if joined[k] == joined[i]), links[i]) for i in range(61) if links[i]}
        for dense in (10**9, 0):
            monkeypatch.setattr(chosen_path, "DENSE", dense)
            (got,) = chosen_path._verify(iter([batch]), 0.8)
            assert {u: (v, n) for u, v, n in zip(*(got.column(c).to_pylist() for c in ("u", "v", "links")))} == want


def test_leaves_in_blocks_and_sets():
    """Every pair of a leaf meets in some pair of its blocks; sets are those of the texts."""
    rows = near_copies(3, 80)
    value, at = chosen_path.shingle_sets(_batch(rows))
    buckets = list(chosen_path._grouped(iter(_leaf(range(20))), True, chosen_path.Limits(leaf=6)))
    pairs = {frozenset(p) for b in buckets for key in set(b.column("key").to_pylist()) for p in itertools.combinations([s for s, k in zip(b.column("set").to_pylist(), b.column("key").to_pylist()) if k == key], 2)}
    assert len(pairs) == 20 * 19 // 2
    assert len(at) == len(rows) + 1 and (np.diff(at) == [len(sets_of(t)) for _, t in rows]).all() and len(value) == at[-1]


def _batch(rows):
    import pyarrow as pa

    return pa.RecordBatch.from_pydict({"doc_id": [r[0] for r in rows], "text": pa.array([r[1] for r in rows], pa.string())})


def _leaf(sets):
    import pyarrow as pa

    n = len(sets)
    raw = suffix_dedup.planes(np.full(n, 9, np.uint64), np.zeros(n, np.int16), np.array(list(sets), np.int64))
    return [pa.RecordBatch.from_arrays([pa.array([1], pa.int32()), pa.array([raw])], names=["bucket", "payload"])]


def test_one_per_class(spark):
    rows = near_copies(4)
    extra = [(i, t, "x") for i, t in rows] + [(0, rows[0][1], "x")]
    kept = chosen_path.one_per_class(spark.createDataFrame(extra, "doc_id long, text string, n_links string"))
    want = {c for c, _ in brute_classes(rows).values()}
    assert sorted(r.doc_id for r in kept.collect()) == sorted(want)
    assert kept.columns == ["doc_id", "text", "n_links"]
    assert chosen_path.link_classes(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_components(spark):
    rng = random.Random(7)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(130)] + [(i, i + 1) for i in range(300, 340)] + [(5, 5)]
    parent = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in edges:
        if a != b:
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {x: root(x) for x in list(parent)}


# --- substrings --------------------------------------------------------------------------------------------


def brute_repeats(rows):
    seen: dict[bytes, int] = {}
    for i, t in rows:
        b = (t or "").encode()
        for k in range(len(b) - 49):
            w = b[k : k + 50]
            seen[w] = min(seen.get(w, 1 << 60), i)
    out = {}
    for i, t in rows:
        b = (t or "").encode()
        mark = bytearray(len(b))
        for k in range(len(b) - 49):
            if seen[b[k : k + 50]] < i:
                mark[k : k + 50] = b"\1" * 50
        spans = sum(1 for k in range(len(b)) if mark[k] and (k == 0 or not mark[k - 1]))
        out.setdefault(i, []).append((len(b), sum(mark), spans, hashlib.sha256(bytes(x for x, m in zip(b, mark) if not m)).hexdigest()))
    return out


def passages(seed: int):
    rng = random.Random(seed)
    pool = ["x" * 90, "the quick brown fox jumps over the lazy dog and then it runs away from me today", "äöü" * 30, "ab" * 60, "z" * 49, "exactly fifty bytes of text are needed for a match"]
    docs = []
    for i in range(50):
        parts = ["".join(rng.choice("abc é") for _ in range(rng.randint(0, 60))), rng.choice(pool)[rng.randint(0, 5) :], rng.choice(docs)[1][: rng.randint(0, 300)] if docs else ""]
        rng.shuffle(parts)
        docs.append((i * 3, "".join(parts)))
    return docs + [(1_000, None), (1_001, ""), (1_002, docs[0][1]), (1_003, docs[0][1]), (1_004, "q" * 50), (1_005, "q" * 50), (1_006, "q" * 49)]


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_repeats_against_brute_force(spark, seed):
    rows = passages(seed)
    df = spark.createDataFrame([(i, t, 0) for i, t in rows], "doc_id long, text string, n_bytes int").repartition(5)
    want = brute_repeats(rows)
    for r in suffix_dedup.repeat_digests(df).collect():
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == want[r.doc_id][0]


def test_repeated_ids_keep_their_own_spans(spark):
    a, b, c = "first " * 30, "second text " * 20, "third one here " * 10
    rows = [(1, a), (2, b + a), (2, c + a), (2, c + a), (None, a + c)]
    got = [(r.doc_id, hashlib.sha256(bytes(r.kept)).hexdigest()) for r in suffix_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    want = brute_repeats([(1 << 50 if i is None else i, t) for i, t in rows])
    assert sorted(got, key=str) == sorted(((None if i == 1 << 50 else i, x[3]) for i, each in want.items() for x in each), key=str)


def test_spans_and_text(spark):
    p = "a passage that is certainly longer than fifty bytes, ünïcode included."
    df = spark.createDataFrame([(1, p, "en", 9), (2, "head " + p + " tail", "en", 9)], "doc_id long, text string, lang string, n_chars long")
    r = {x.doc_id: x for x in suffix_dedup.remove_repeats(df).collect()}[2]
    assert [(s.start, s.end) for s in r.spans] == [(5, 5 + len(p.encode()))]
    back = {x.doc_id: x for x in suffix_dedup.without_repeats(df).collect()}
    assert (back[2].text, back[2].n_chars, back[2].lang) == ("head  tail", 10, "en")
    assert suffix_dedup.without_repeats(df).columns == df.columns
    assert suffix_dedup.repeat_digests(df.where("false")).count() == 0


def test_anchors_depend_on_windows_only():
    """Every window is in one run, and its anchor lies at the same place wherever it stands, also across chunks and for avoided grams."""
    rng = np.random.default_rng(0)
    text = rng.integers(97, 103, 400_000).astype(np.uint8)
    text[300_000:300_200] = text[100:300]
    text[200_000:210_000] = 65  # a constant stretch
    plain = suffix_dedup.anchors(text, np.array([0, len(text)]))
    for marks in (None, suffix_dedup.frequency_filter(plain[1][::7].view(np.int64))):
        place, _, first, last, _ = suffix_dedup.anchors(text, np.array([0, len(text)]), marks)
        windows = np.concatenate([np.arange(a, b + 1) for a, b in zip(first, last)])
        assert (windows == np.arange(len(text) - 49)).all()
        own = np.repeat(place, last - first + 1)
        assert ((own >= windows) & (own <= windows + 30)).all()
        assert (own[100:251] - 100 == own[300_000:300_151] - 300_000).all()


def test_digit_passes_order_and_group():
    rng = np.random.default_rng(1)
    rows = rng.integers(97, 99, (400, 11)).astype(np.uint8)
    rows[200:260] = rows[:60]
    group, doc = rng.integers(0, 3, 400), rng.integers(0, 40, 400)
    group = np.sort(group)
    left, equal = suffix_dedup.sort_digits(rows, group, doc)
    want = {}
    for i in range(400):
        want.setdefault((int(group[i]), rows[i].tobytes()), []).append(i)
    several = {k: v for k, v in want.items() if len(set(doc[v])) > 1}
    got = {}
    for i, g in zip(left, equal):
        got.setdefault(int(g), []).append(int(i))
    assert sorted(map(sorted, got.values())) == sorted(map(sorted, several.values()))
    keys = [(int(group[i]), rows[i].tobytes()) for i in left]
    assert keys == sorted(keys)


def test_hot_passages_and_constant_texts(spark, monkeypatch):
    """A passage of most documents, texts of one letter or of a short period, and avoided grams change nothing in the result."""
    rng = random.Random(9)
    hot = "this passage is part of a great many documents, and it is longer than any window of fifty bytes."
    rows = [(i, "".join(rng.choice("abcd ") for _ in range(rng.randint(0, 80))) + (hot if i % 3 else "") + rng.choice(["z" * 400, "xy" * 150, "abc" * 70, ""])) for i in range(90)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = brute_repeats(rows)
    for limit in (24, 2):
        monkeypatch.setattr(suffix_dedup, "FREQUENT", limit)
        for r in suffix_dedup.repeat_digests(df).collect():
            assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == want[r.doc_id][0]


def test_repeats_with_clashing_columns(spark):
    p = "a passage that is certainly longer than fifty bytes, for sure it is."
    df = spark.createDataFrame([(1, p, 9, "x", 1), (2, "head " + p, 9, "y", 2)], "doc_id int, text string, n_chars int, _id string, _removed int")
    got = {r.doc_id: r for r in suffix_dedup.without_repeats(df).collect()}
    assert (got[2].text, got[2].n_chars, got[2]["_id"], got[2]["_removed"]) == ("head ", 5, "y", 2)
    assert suffix_dedup.without_repeats(df).schema == df.schema


# --- lines -------------------------------------------------------------------------------------------------


def test_units(spark):
    line, other = "This is a line of some words", "Another line with enough words"
    rows = [(1, f"{line}\nshort one\n{other}"), (2, f"top of it all here\n  this IS a   line of some words \n\nshort one\n{line}"), (3, line), (4, None), (5, ""), (3, line)]
    got = sorted(((r.doc_id, r.text, r.n_units, r.n_removed, [(s.start, s.end) for s in r.removed]) for r in unit_dedup.remove_units(spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, place int")).collect()), key=str)
    d2 = rows[1][1]
    a, b = d2.index("  this"), d2.index(line)
    c = d2.index("short one")
    assert got == sorted([(1, rows[0][1], 3, 0, []), (2, "top of it all here\n", 5, 3, [(a, a + 33), (c, c + 9), (b, b + len(line))]), (3, "", 1, 1, [(0, len(line))]), (3, "", 1, 1, [(0, len(line))]), (4, "", 1, 0, []), (5, "", 1, 0, [])], key=str)
    assert d2[a : a + 33].lower().split() == line.lower().split()
    assert unit_dedup.remove_units(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    paragraphs = spark.createDataFrame([(1, "one two three four\n\nfive six seven eight"), (2, "five six seven eight\n\nnine")], "doc_id long, text string")
    assert {r.doc_id: r.text for r in unit_dedup.remove_units(paragraphs, "\n\n").collect()} == {1: "one two three four\n\nfive six seven eight", 2: "nine"}


def test_sentences_inside_lines(spark):
    """A passage in the middle of a line goes by its sentences; the first occurrence, short forms and other text stay."""
    first, second = "A long enough sentence of the passage that repeats here.", "And a second sentence with more than eight words in it!"
    rows = [(1, f"Opening words differ. {first} {second} Short one."), (2, f"Nothing alike at the start of this one. {first} {second} Short one. The end is new."), (3, f"{second}\nplain last line of it"), (4, first)]
    got = {r.doc_id: r for r in unit_dedup.remove_units(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1].text == rows[0][1] and got[1].n_removed == 0
    assert got[2].text == "Nothing alike at the start of this one. Short one. The end is new."
    assert [rows[1][1][s.start : s.end] for s in got[2].removed] == [first, second]
    assert (got[3].text, got[3].n_removed) == ("plain last line of it", 1)
    assert (got[4].text, got[4].n_removed) == ("", 1)
