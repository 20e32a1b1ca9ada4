"""Set similarity join of documents by chosen paths over their word shingles.

A document is the set of its shingles of SHINGLE words (lower case, cut at ASCII white space; all words
together where there are fewer). Two documents are linked if the Jaccard similarity of their sets is at
least THRESHOLD.

* Equal sets are one class member with a number of copies.
* A run splits the sets: each set goes to the buckets of the tokens that a shared hash of the run selects,
  about 1/(threshold * size) of its tokens, so similar sets meet with constant probability. Buckets of more
  than LIMIT sets are split again on tokens that the next hash of the run selects. Runs are repeated
  until a pair at the threshold is lost with at most 1 - TARGET: `runs_for` gives the number.
* Small buckets are compared outright on sketches (first values of bins of the set), which gives the
  families of candidates of a bucket as stars, never its pairs. Equal buckets of several runs count once.
* The components of these stars are small families of sets. Inside a family all pairs are
  verified exactly on the sets, in blocks of bounded sets and tokens, by one product of matrices over the tokens that
  several sets of the two blocks share (or by marks, where these are many): each pair of blocks gives a number of links per set and the stars of true links, so a family of n sets ships each set
  n / block times and never a row per pair.
* The components of the true links are the classes.

So links within a family are exact; a true link is lost only if no run brings its two sets (or a chain of
candidates) together, or if it falls below the sketch bound wherever they meet: SLACK lies about seven deviations of
a full sketch below the threshold. Buckets are as many as the session's shuffle partitions times a factor, so they keep their
size as the input grows. `Limits` are arguments; tests take every level of the recursion with small ones.

Defined cases: null text is empty; documents without words have the empty set, and count as copies of each
other; n_links counts linked documents, copies included, the document itself not; rows with the same
doc_id are documents of their own; class_id is the least doc_id of the class (null ids are ignored unless
the class has no other); an empty table gives no rows; other columns are ignored.
Sets are known by 64-bit digests.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, fresh, lean, mix64, stash, texts
from .components import components
from .suffix_dedup import _TABLE, BUCKETS_PER_TASK, _blocks, _by_bucket, _runs, planes, slices, unplanes

SHINGLE = 5
THRESHOLD = 0.8
TARGET = 1 - 1e-6
BINS = 128
SLACK = 0.24  # a candidate's sketch may fall short of the threshold by so much


@dataclass(frozen=True)
class Limits:
    """bucket: sets compared outright; depth: levels of splitting; leaf: sets of a last bucket that one task compares;
    block, tokens: sets and tokens of a side of a verifying task."""

    bucket: int = 4_096
    depth: int = 3
    leaf: int = 4_096
    block: int = 1_024
    tokens: int = 2_000_000


_ODD = mix64(np.arange(1, 65, dtype=np.uint64)) | np.uint64(1)


def runs_for(threshold: float = THRESHOLD, target: float = TARGET) -> int:
    """Runs after which a pair at the threshold has met in some first-level bucket with probability `target`.

    At the threshold a run selects at least one shared token with probability 1 - 1/e or more.
    """
    return math.ceil(math.log(1 - target) / -1.0 + 2)


def word_hashes(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and document of each word. Words end at ASCII white space and at the end of a document."""
    space = np.zeros(256, bool)
    space[[9, 10, 11, 12, 13, 32]] = True
    inside = ~space[buf]
    start = inside.copy()
    start[1:] &= ~inside[:-1]
    lows = off[:-1][off[:-1] < off[1:]]
    start[lows] = inside[lows]
    first = np.flatnonzero(start)
    stop = np.zeros(len(buf) + 1, bool)
    stop[1:-1] = inside[:-1] & ~inside[1:]
    stop[off[1:]] = True
    ends = np.flatnonzero(stop)
    last = ends[np.searchsorted(ends, first, "right")] if len(first) else first
    size = last - first
    out = np.zeros(len(first), np.uint64)
    for low, high in ((0, 8), (8, 16), (16, 48)):
        rows = np.flatnonzero((size > low) & (size <= high))
        for i in range(0, len(rows), 100_000):
            r = rows[i : i + 100_000]
            at = first[r, None] + np.arange(high)
            v = _TABLE[buf[np.minimum(at, len(buf) - 1)]] * _ODD[:high]
            v[np.arange(high) >= size[r, None]] = 0
            out[r] = v.sum(axis=1, dtype=np.uint64)
    for r in np.flatnonzero(size > 48):
        out[r] = xxhash.xxh64_intdigest(buf[first[r] : last[r]].tobytes())
    return mix64(out), np.searchsorted(off, first, "right") - 1


def shingle_sets(b: pa.RecordBatch, width: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """The sorted shingle sets of a batch's texts: (values, bounds)."""
    raw = [(x.as_py() or "").lower().encode() for x in b.column("text")]
    off = np.concatenate([[0], np.cumsum([len(x) for x in raw])]).astype(np.int64)
    buf = np.frombuffer(b"".join(raw), np.uint8)
    words, doc = word_hashes(buf, off) if len(buf) else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
    n = len(raw)
    count = np.bincount(doc, minlength=n)
    at = np.concatenate([[0], np.cumsum(count)])
    total = np.zeros(len(words), np.uint64)
    for k in range(width):
        total[: len(words) - k] += words[k:] * _ODD[k] if k else words * _ODD[0]
    rest = count - width + 1
    few = np.flatnonzero((count > 0) & (rest < 1))
    index = np.arange(len(words)) - at[:-1][doc]
    keep = index < np.maximum(rest, 0)[doc]
    value, owner = mix64(total[keep]), doc[keep]
    if len(few):
        short = [mix64(np.array([(words[at[d] : at[d + 1]] * _ODD[: count[d]]).sum(dtype=np.uint64) ^ np.uint64(count[d])], np.uint64))[0] for d in few]
        value, owner = np.concatenate([value, np.array(short, np.uint64)]), np.concatenate([owner, few])
    order = np.lexsort((value, owner))
    value, owner = value[order], owner[order]
    first = np.ones(len(value), bool)
    first[1:] = (value[1:] != value[:-1]) | (owner[1:] != owner[:-1])
    value, owner = value[first], owner[first]
    return value, np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=n))])


def set_digests(value: np.ndarray, at: np.ndarray) -> np.ndarray:
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix64(value ^ np.uint64(0x5851F42D4C957F2D)), dtype=np.uint64)])
    size = np.diff(at).astype(np.uint64)
    return mix64((total[at[1:]] - total[at[:-1]]) ^ size * np.uint64(0x9E3779B97F4A7C15)).view(np.int64)


def sketches(value: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Per set and bin (leading bits of the value) 16 bits of the bin's least value; 0 where the bin is empty."""
    n, shift = len(at) - 1, np.uint64(64 - BINS.bit_length() + 1)
    owner = np.repeat(np.arange(n), np.diff(at))
    key = owner * BINS + (value >> shift).astype(np.int64)
    first = _runs(key)
    out = np.zeros(n * BINS, np.uint16)
    low = (mix64(value[first]) & np.uint64(0xFFFF)).astype(np.uint16)
    out[key[first]] = np.maximum(low, 1)
    return out.reshape(n, BINS)


def picks(value: np.ndarray, at: np.ndarray, runs: int, threshold: float, level: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Selected tokens of a level: (set, run, token). Deeper levels select twice as many."""
    size = np.diff(at)
    owner = np.repeat(np.arange(len(size)), size)
    bound = np.minimum((1 + (level > 0)) / (threshold * np.maximum(size, 1)), 1.0) * (2**32 - 1)
    bound = bound.astype(np.uint32)[owner]
    sets, run, token = [], [], []
    for r in range(runs):
        seed = mix64(np.array([1 + r + 1_000 * level], np.uint64))
        h = (value ^ seed) * _ODD[3]
        h ^= h >> np.uint64(29)
        hit = np.flatnonzero(((h * _ODD[4]) >> np.uint64(32)).astype(np.uint32) <= bound)
        sets.append(owner[hit])
        run.append(np.full(len(hit), r, np.int16))
        token.append(value[hit])
    return np.concatenate(sets), np.concatenate(run), np.concatenate(token)


SUMMARY = "doc_id long, set long, n int, sketch binary, picks binary"


def _summaries(batches, runs: int, threshold: float, depth: int):
    """Digest, size, sketch and the selected tokens of all levels, per document."""
    for b in slices(batches, 1_500_000):
        value, at = shingle_sets(b)
        sk, size = sketches(value, at), np.diff(at)
        chosen = [picks(value, at, runs, threshold, level) for level in range(depth)]
        owner = np.concatenate([c[0] for c in chosen])
        run = np.concatenate([c[1] + 256 * level for level, c in enumerate(chosen)]).astype(np.int16)
        token = np.concatenate([c[2] for c in chosen])
        order = np.argsort(owner, kind="stable")
        owner, run, token = owner[order], run[order], token[order]
        cut = np.searchsorted(owner, np.arange(b.num_rows + 1))
        packed = [planes(run[x:y], token[x:y]) for x, y in zip(cut[:-1], cut[1:])]
        yield pa.RecordBatch.from_arrays(
            [b.column("doc_id").cast(pa.int64()), pa.array(set_digests(value, at)), pa.array(size.astype(np.int32)), pa.array([x.tobytes() for x in sk], pa.binary()), pa.array(packed, pa.binary())],
            names=["doc_id", "set", "n", "sketch", "picks"],
        )


def _first_keys(batches, radix: int):
    """The buckets of the first level: (bucket, packed (key, run, set))."""
    for b in batches:
        sets, keys, runs = [], [], []
        for s, raw in zip(b.column("set").to_pylist(), b.column("picks")):
            run, token = unplanes(raw.as_py(), np.int16, np.uint64)
            run, token = run[run < 256], token[run < 256]
            keys.append(mix64(token ^ mix64((run.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15))))
            runs.append(run)
            sets.append(np.full(len(run), s, np.int64))
        if keys:
            yield from _deal(np.concatenate(keys), np.concatenate(runs), np.concatenate(sets), radix)


def _deal(key, run, sets, radix):
    yield from _blocks(((key >> np.uint64(40)) % np.uint64(radix)).astype(np.int64), key, run, sets)


def _deeper_keys(batches, radix: int, level: int):
    """Paths of large buckets, longer by each token that the next hash of the run selects."""
    for b in batches:
        keys, runs, sets = [], [], []
        for s, k, r, raw in zip(b.column("set").to_pylist(), b.column("key").to_pylist(), b.column("run").to_pylist(), b.column("picks")):
            run, token = unplanes(raw.as_py(), np.int16, np.uint64)
            t = token[run == r + 256 * level]
            keys.append(mix64(t ^ mix64(np.array([k], np.int64).view(np.uint64) + np.uint64(level))))
            runs.append(np.full(len(t), r, np.int16))
            sets.append(np.full(len(t), s, np.int64))
        if keys and sum(map(len, keys)):
            yield from _deal(np.concatenate(keys), np.concatenate(runs), np.concatenate(sets), radix)


BUCKETS = "set long, key long, run short, large boolean"


def _grouped(batches, last: bool, limits: Limits):
    """Buckets with two sets or more. Small ones are named by their members, so equal ones coincide."""
    for _, held in _by_bucket(batches):
        key, run, sets = (np.concatenate(c) for c in zip(*(unplanes(x, np.uint64, np.int16, np.int64) for x in held)))
        order = np.lexsort((sets, key))
        key, run, sets = key[order], run[order], sets[order]
        first = np.ones(len(key), bool)
        first[1:] = (key[1:] != key[:-1]) | (sets[1:] != sets[:-1])
        key, run, sets = key[first], run[first], sets[first]
        at = _runs(key)
        size = np.diff(np.append(at, len(key)))
        name = np.add.reduceat(mix64(sets.view(np.uint64)), at)
        each = np.repeat(size, size)
        large = (each > limits.bucket) & (not last)
        label = np.where(large, key, np.repeat(name, size))
        keep = each > 1
        if last and (each > limits.leaf).any():  # leaves too large for one task: pairs of blocks
            keep &= each <= limits.leaf
            for a, n in zip(at[size > limits.leaf], size[size > limits.leaf]):
                own, parts = sets[a : a + n], -(-int(n) // limits.leaf)
                block = (mix64(own.view(np.uint64)) % np.uint64(parts)).astype(np.int64)
                for i in range(parts):
                    for j in range(i if parts == 1 else i + 1, parts):
                        mine = own[(block == i) | (block == j)]
                        tag = mix64(np.array([name[np.searchsorted(at, a)] + np.uint64(i * parts + j + 1)], np.uint64))[0]
                        yield pa.RecordBatch.from_arrays([pa.array(mine), pa.array(np.full(len(mine), tag).view(np.int64)), pa.array(np.zeros(len(mine), np.int16)), pa.array(np.zeros(len(mine), bool))], names=["set", "key", "run", "large"])
        if keep.any():
            yield pa.RecordBatch.from_arrays([pa.array(sets[keep]), pa.array(label[keep].view(np.int64)), pa.array(run[keep]), pa.array(large[keep])], names=["set", "key", "run", "large"])


def _groups(batches, key: str):
    """Batches cut into the runs of equal key of rows sorted by key; a run is joined across batches."""
    held, now = [], None
    for b in batches:
        if not b.num_rows:
            continue
        k = b.column(key).to_numpy(zero_copy_only=False)
        at = np.append(_runs(k), len(k))
        for x, y in zip(at[:-1], at[1:]):
            if held and k[x] != now:
                yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                held = []
            now = k[x]
            held.append(b.slice(x, y - x))
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def _forest(batches, threshold: float):
    """The families of candidates of each bucket, by search over the sets not yet reached: each member and the least one."""
    us, vs = [], []
    for g in _groups(batches, "key"):
        sets, n = g.column("set").to_numpy(), g.column("n").to_numpy().astype(np.int64)
        sk = np.frombuffer(b"".join(x.as_py() for x in g.column("sketch")), np.uint16).reshape(len(sets), BINS)
        open_ = np.arange(len(sets))
        while len(open_) > 1:
            frontier, open_, reached = [open_[0]], open_[1:], [open_[:1]]
            while frontier and len(open_):
                a = frontier.pop()
                both, either = (sk[open_] == sk[a]) & (sk[a] > 0), (sk[open_] > 0) | (sk[a] > 0)
                close = both.sum(axis=1) >= (threshold - SLACK) * either.sum(axis=1)
                close &= np.minimum(n[open_], n[a]) >= threshold * np.maximum(n[open_], n[a])
                got = open_[close]
                reached.append(got)
                frontier.extend(got)
                open_ = open_[~close]
            family = sets[np.concatenate(reached)]
            us.append(family[family != family.min()])
            vs.append(np.full(len(us[-1]), family.min()))
        if sum(map(len, us)) > 50_000:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(us)), pa.array(np.concatenate(vs))], names=["u", "v"])
            us, vs = [], []
    if us and sum(map(len, us)):
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(us)), pa.array(np.concatenate(vs))], names=["u", "v"])


def _members(batches):
    """Sets of the texts that stand for a family member; rows whose text is another one are left out."""
    for b in slices(batches, 1_500_000):
        value, at = shingle_sets(b)
        own = set_digests(value, at) == b.column("set").to_numpy()
        raw = [value[x:y].tobytes() for x, y in zip(at[:-1], at[1:])]
        yield pa.RecordBatch.from_arrays([b.column("set"), b.column("root"), b.column("copies"), b.column("parts"), pa.array(raw, pa.binary())], names=["set", "root", "copies", "parts", "tokens"]).filter(pa.array(own))


def _block_pairs(batches):
    """A row for each pair of blocks of its family that a set takes part in."""
    for b in batches:
        sets, root, parts = b.column("set").to_numpy(), b.column("root").to_numpy(), b.column("parts").to_numpy().astype(np.int64)
        block = (mix64(sets.view(np.uint64)) % parts.astype(np.uint64)).astype(np.int64)
        row = np.repeat(np.arange(len(sets)), parts)
        other = np.arange(len(row)) - np.repeat(np.cumsum(parts) - parts, parts)
        i, j = np.minimum(block[row], other), np.maximum(block[row], other)
        task = mix64(root[row].view(np.uint64) + mix64((i * parts[row] + j + 1).astype(np.uint64))).view(np.int64)
        for a in range(0, len(row), 5_000):
            s = slice(a, a + 5_000)
            t = b.take(pa.array(row[s]))
            yield pa.RecordBatch.from_arrays(
                [pa.array(task[s]), t.column("set"), t.column("copies"), pa.array((block[row[s]] != i[s])), pa.array(i[s] == j[s]), t.column("tokens")], names=["task", "set", "copies", "second", "alone", "tokens"]
            )


PAIRS = "task long, set long, copies long, second boolean, alone boolean, tokens binary"


DENSE = 20_000_000  # places of a matrix of sets by shared tokens that a task may hold


def _needed(threshold: float, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Shared tokens that sets of these sizes need for the threshold."""
    return np.ceil(threshold * (a + b) / (1 + threshold) - 1e-9)


def _verify(batches, threshold: float):
    """Exact similarities between two blocks (or inside one): links per set, and the least set it is connected with."""
    for g in _groups(batches, "task"):
        sets, copies = g.column("set").to_numpy(), g.column("copies").to_numpy()
        second, alone = g.column("second").to_numpy(zero_copy_only=False), bool(g.column("alone")[0].as_py())
        tokens = [np.frombuffer(x.as_py(), np.uint64) for x in g.column("tokens")]
        size = np.array([len(t) for t in tokens])
        left = np.flatnonzero(size > 0) if alone else np.flatnonzero(~second & (size > 0))
        right = left if alone else np.flatnonzero(second & (size > 0))
        if not len(right) or not len(left):
            continue
        order = left if alone else np.concatenate([left, right])
        _, code, times = np.unique(np.concatenate([tokens[r] for r in order]), return_inverse=True, return_counts=True)
        own = np.repeat(np.arange(len(order)), size[order])
        shared = times[code] > 1  # a token of one set alone is in no intersection
        names = np.cumsum(times > 1) - 1
        own, code, width = own[shared], names[code[shared]], int((times > 1).sum())
        if width * len(order) <= DENSE:
            links, least = _by_product(own, code, width, size, copies, sets, left, right, order, alone, threshold)
        else:
            links, least = _by_marks(own, code, width, size, copies, sets, left, right, order, alone, threshold)
        some = np.flatnonzero(links)
        yield pa.RecordBatch.from_arrays([pa.array(sets[some]), pa.array(least[some]), pa.array(links[some])], names=["u", "v", "links"])


def _by_product(own, code, width, size, copies, sets, left, right, order, alone, threshold):
    """All intersections of two blocks as one product of 0/1 matrices over the tokens that several sets have."""
    m = np.zeros((len(order), width), np.float32)
    m[own, code] = 1
    a, b = (m, m) if alone else (m[: len(left)], m[len(left) :])
    near = (a @ b.T) >= _needed(threshold, size[left][:, None], size[right][None, :])
    if alone:
        np.fill_diagonal(near, False)
    links, least = np.zeros(len(sets), np.int64), sets.copy()
    links[left] += near @ copies[right]
    if not alone:
        links[right] += copies[left] @ near
    last = np.iinfo(np.int64).max
    while True:  # the least set spreads along the links
        before = least[left], least[right]
        least[left] = np.minimum(least[left], np.where(near, least[right][None, :], last).min(axis=1))
        least[right] = np.minimum(least[right], np.where(near, least[left][:, None], last).min(axis=0))
        if (least[left] == before[0]).all() and (least[right] == before[1]).all():
            return links, least


def _by_marks(own, code, width, size, copies, sets, left, right, order, alone, threshold):
    """The same for blocks with many different tokens: each set of one side marks its tokens, and the other side counts them."""
    by_size = lambda rows: rows[np.argsort(size[rows], kind="stable")]
    place = np.empty(len(sets), np.int64)
    place[order] = np.arange(len(order))
    start = np.searchsorted(own, np.arange(len(order) + 1))
    left, right = by_size(left), by_size(right)
    if alone:
        right = left
    flat = np.concatenate([code[start[place[r]] : start[place[r] + 1]] for r in right])
    at = np.concatenate([[0], np.cumsum([start[place[r] + 1] - start[place[r]] for r in right])])
    mark, rsize = np.zeros(width + 1, bool), size[right]
    links, parent = np.zeros(len(sets), np.int64), np.arange(len(sets))

    def root(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for x, s in enumerate(left):
        lo = x + 1 if alone else int(np.searchsorted(rsize, math.ceil(threshold * size[s] - 1e-9)))
        hi = int(np.searchsorted(rsize, size[s] / threshold + 1e-9, "right"))
        if lo >= hi:
            continue
        mine = code[start[place[s]] : start[place[s] + 1]]
        mark[mine] = True
        found = np.concatenate([[0], np.cumsum(mark[flat[at[lo] : at[hi]]])])
        inter = found[at[lo + 1 : hi + 1] - at[lo]] - found[at[lo:hi] - at[lo]]
        mark[mine] = False
        got = right[lo:hi][inter >= _needed(threshold, size[s], rsize[lo:hi])]
        links[s] += copies[got].sum()
        links[got] += copies[s]
        for b in got:
            ra, rb = root(s), root(b)
            if ra != rb:
                parent[ra] = rb
    least = np.full(len(sets), np.iinfo(np.int64).max)
    top = np.array([root(x) for x in range(len(sets))], np.int64)
    np.minimum.at(least, top, sets)
    return links, least[top]


def link_classes(docs: DataFrame, threshold: float = THRESHOLD, target: float = TARGET, limits: Limits = Limits()) -> DataFrame:
    """doc_id, class_id, n_links, class_size (documents in the class), set (digest of the document's shingle set)."""
    runs, depth = runs_for(threshold, target), limits.depth
    radix = BUCKETS_PER_TASK * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    base, scratch = texts(docs), Scratch(docs.sparkSession)
    summaries = stash(base.mapInArrow(lean(lambda it: _summaries(it, runs, threshold, depth)), SUMMARY), "summaries")
    reps = stash(summaries.groupBy("set").agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("copies"), F.first("n").alias("n"), F.first("sketch").alias("sketch"), F.first("picks").alias("picks")), "sets")
    dealt = reps.where("n > 0").select("set", "picks").mapInArrow(lean(lambda it: _first_keys(it, radix)), "bucket int, payload binary")
    ready = None
    for level in range(1, depth + 1):
        last = level == depth
        found = scratch.stash(dealt.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(lean(lambda it, last=last: _grouped(it, last, limits)), BUCKETS), "buckets")
        small = found.where("not large").select("set", "key")
        ready = small if ready is None else ready.unionByName(small)
        if last or not found.where("large").limit(1).count():
            break
        deep = found.where("large").join(reps.select("set", "picks"), "set")
        dealt = deep.select("set", "key", "run", "picks").mapInArrow(lean(lambda it, level=level: _deeper_keys(it, radix, level)), "bucket int, payload binary")
    sketched = ready.distinct().join(reps.select("set", "n", "sketch"), "set")
    near = sketched.repartition("key").sortWithinPartitions("key").select("key", "set", "n", "sketch").mapInArrow(lean(lambda it: _forest(it, threshold)), "u long, v long")
    family = components(near, "families")
    sized = family.join(reps.select(F.col("set").alias("node"), "n"), "node")
    parts = F.greatest(F.ceil(F.count(F.lit(1)) / limits.block), F.ceil(F.sum("n") / limits.tokens)).cast("int")
    sizes = sized.groupBy("root").agg(parts.alias("parts"))
    chosen = family.join(sizes, "root").select(F.col("node").alias("set"), "root", "parts").join(reps.select("set", "doc_id", "copies"), "set")
    with_text = base.join(chosen, base.doc_id.eqNullSafe(chosen.doc_id)).select("text", "set", "root", "copies", "parts")
    members = with_text.mapInArrow(lean(_members), "set long, root long, copies long, parts int, tokens binary").dropDuplicates(["set"])
    tasks = members.mapInArrow(lean(_block_pairs), PAIRS)
    verified = stash(tasks.repartition("task").sortWithinPartitions("task").mapInArrow(lean(lambda it: _verify(it, threshold)), "u long, v long, links long"), "links")
    scratch.drop("buckets")
    classes = components(verified.where("u <> v").select("u", "v"), "classes")
    links = verified.where("links > 0").groupBy(F.col("u").alias("set")).agg(F.sum("links").alias("links"))
    mine = reps.select("set", "doc_id", "copies").join(links, "set", "left").join(classes.select(F.col("node").alias("set"), "root"), "set", "left").withColumn("root", F.coalesce("root", "set"))
    heads = mine.groupBy("root").agg(F.min("doc_id").alias("class_id"), F.sum("copies").alias("class_size"))
    result = mine.join(heads, "root").select("set", "class_id", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), "class_size")
    return summaries.select("doc_id", "set").join(result, "set").select("doc_id", "class_id", "n_links", "class_size", "set")


def one_per_class(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The documents with one row of each class: that with the least doc_id (any one where rows repeat that doc_id)."""
    name = fresh(docs.columns, "kept")
    keep = link_classes(docs, threshold).where(F.col("doc_id").eqNullSafe(F.col("class_id"))).select(F.col("doc_id").alias(name)).distinct()
    kept = docs.join(keep, docs.doc_id.eqNullSafe(keep[name]), "left_semi")
    if docs.groupBy("doc_id").count().where("count > 1").limit(1).count():
        kept = kept.dropDuplicates(["doc_id"])
    return kept
