"""Removal of repeated substrings by a depth-limited radix sort of suffixes.

A window is the first `depth` bytes of a suffix; two suffixes are a repeat if their windows agree. So suffixes are
ordered through `depth` bytes only, by most-significant-digit passes over distributed buckets, and the equal groups
are exactly the repeated windows.

* The leading digit of a window is its anchor: the gram of GRAM bytes with the least hash inside it (the first of
  equal ones). It depends on the window's bytes alone, so equal windows have it at the same place. Neighbouring
  windows mostly share their anchor; such a run travels as one string of bytes (about sixteen windows in sixty-five
  bytes), compressed, to the bucket of its anchor. Grams that are frequent in a bounded sample of the text are taken as
  anchors only where a window has no other, so common phrases do not gather in one bucket; that moves work, not results.
* Before that, runs of equal bytes inside a slice of text are combined: the one of the smallest document travels, and
  those of larger documents are repeats already. A passage of many documents costs a row per slice.
* In a bucket the anchors' own bytes are the next digits; groups that lie in one document are done. Then runs of equal
  bytes are found: all but those of the smallest document are repeats as a whole. Of the different runs that are left,
  the windows at each place are ordered by the remaining bytes of their suffix, a digit of eight bytes at a time, and
  only groups of several documents go on to the next digit.
* The covered bytes come back to their documents as intervals.

Every removal is proved on bytes. Hashes only deal rows to buckets, find runs that are then compared, and, where some
doc_id has several texts, tell these apart (by the CRC of the text).

Defined cases: null text is empty; matches never cross documents; documents with equal doc_id do not
remove from each other (each row keeps its own spans); a null doc_id counts as larger than any other;
texts shorter than `depth` lose nothing; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh, lean, mix64, new_path, release, text_bytes, texts

DEPTH = 50
GRAM = 20
LEFT = DEPTH - GRAM  # bytes that a window can have before its anchor
WIDTH = LEFT + DEPTH  # bytes that windows through an anchor can reach
LAST = np.iinfo(np.int64).max
CHUNK = 131_072  # window starts looked at together
SLICE = 4_000_000  # bytes of text packed together
BUCKETS_PER_TASK = 8  # of the session's shuffle partitions, so that buckets stay small as the input grows
SAMPLE_BYTES = 8_000_000  # of text in which frequent grams are counted
FREQUENT = 24  # anchors of one gram in the sample that make it frequent
FILTER_BITS = 22
BATCH = 60_000  # rows ordered together
ROUNDS = 2  # portions of the anchors, one after the other, so that the runs of only one portion are on disk

_TABLE = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_M = np.uint64(0xD1342543DE82EF95)
_POWER = np.cumprod(np.concatenate([[np.uint64(1)], np.full(CHUNK + 256, _M)]))
_INVERSE = np.cumprod(np.concatenate([[np.uint64(1)], np.full(CHUNK + 256, np.uint64(pow(int(_M), -1, 2**64)))]))


def sliding(x: np.ndarray, width: int, op) -> np.ndarray:
    """op over each `width` neighbours, by doubling."""
    size, have = 1, x
    while size * 2 <= width:
        have = op(have[:-size], have[size:])
        size *= 2
    return op(have[: len(x) - width + 1], have[width - size : len(x) - size + 1]) if width > size else have


def _filter_place(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(8)) & np.uint64((1 << FILTER_BITS) - 1)


def frequency_filter(grams) -> np.ndarray:
    """A table of marks over hashes of grams; others may share a mark, which moves anchors only."""
    marks = np.zeros(1 << FILTER_BITS, bool)
    marks[_filter_place(np.asarray(grams, np.int64).view(np.uint64)).astype(np.int64)] = True
    return marks


def anchors(buf: np.ndarray, off: np.ndarray, frequent: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Runs of windows with one anchor: place of the anchor, hash of its gram, first window, last window, hash of the run's bytes.

    off: bounds of the documents; windows lie inside them. frequent: marks of grams to avoid.
    """
    span, found = DEPTH - GRAM + 1, []
    ends, starts = off[1:], off[:-1]
    for s0 in range(0, len(buf) - DEPTH + 1, CHUNK):
        part = buf[s0 : s0 + CHUNK + 2 * DEPTH]
        n = min(CHUNK, len(buf) - DEPTH + 1 - s0)
        a, b = np.searchsorted(ends, s0, "right"), np.searchsorted(starts, s0 + n, "left")
        closed = np.zeros(n + 1, np.int32)
        np.add.at(closed, np.clip(np.maximum(starts[a:b], ends[a:b] - DEPTH + 1) - s0, 0, n), 1)
        np.add.at(closed, np.clip(ends[a:b] - s0, 0, n), -1)
        inside = np.flatnonzero(np.cumsum(closed[:n]) == 0)
        if not len(inside):
            continue
        total = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(_TABLE[part] * _POWER[: len(part)], out=total[1:])
        m = n + span - 1
        h = (total[GRAM : GRAM + m] - total[:m]) * _INVERSE[:m]
        h ^= h >> np.uint64(32)
        h *= np.uint64(0x9FB21C651E98DF25)
        key = (h >> np.uint64(33)) << np.uint64(32)
        if frequent is not None:
            key |= frequent[_filter_place(h)].astype(np.uint64) << np.uint64(63)
        key |= np.arange(m, dtype=np.uint64)
        place = (sliding(key, span, np.minimum)[inside] & np.uint64(0xFFFFFFFF)).astype(np.int64)
        new = np.ones(len(inside), bool)
        new[1:] = (place[1:] != place[:-1]) | (inside[1:] != inside[:-1] + 1)
        at = np.flatnonzero(new)
        first, last = inside[at], inside[np.append(at[1:], len(inside)) - 1]
        place = place[at]
        found.append((place + s0, h[place], first + s0, last + s0, mix64((total[last + DEPTH] - total[first]) * _INVERSE[first])))
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    return tuple(np.concatenate(c) for c in zip(*found))


def planes(*columns) -> bytes:
    """Columns of numbers as planes of bytes, which compress where high bytes are alike. (column, w): its w low bytes."""
    parts = [c if isinstance(c, tuple) else (c, None) for c in columns]
    n = len(parts[0][0])
    return n.to_bytes(4, "little") + b"".join(np.ascontiguousarray(np.ascontiguousarray(c).view(np.uint8).reshape(n, c.nbytes // n if n else 1)[:, :w].T).tobytes() for c, w in parts)


def unplanes(raw: bytes, *kinds) -> list[np.ndarray]:
    """The columns back. Kinds: a type, (type, w) for its w low bytes, or a number for rows of so many bytes."""
    n, at, out = int.from_bytes(raw[:4], "little"), 4, []
    for kind in kinds:
        kind, width = kind if isinstance(kind, tuple) else (kind, kind if isinstance(kind, int) else np.dtype(kind).itemsize)
        m = np.frombuffer(raw, np.uint8, n * width, at).reshape(width, n).T
        at += n * width
        if isinstance(kind, int):
            out.append(m)
            continue
        full = np.zeros((n, np.dtype(kind).itemsize), np.uint8)
        full[:, :width] = m
        out.append(full.view(kind).reshape(n))
    return out


def slices(batches, size: int = SLICE):
    """Record batches cut or joined so that each has about `size` bytes of text."""
    held, have = [], 0
    for b in batches:
        _, off = text_bytes(b)
        at = 0
        while at < b.num_rows:
            end = max(at + 1, int(np.searchsorted(off, off[at] + size - have, "right")) - 1)
            end = min(end, b.num_rows)
            held.append(b.slice(at, end - at))
            have += int(off[end] - off[at])
            at = end
            if have >= size * 0.9:
                yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                held, have = [], 0
    if held:
        t = pa.Table.from_batches(held).combine_chunks().to_batches()
        if t:
            yield t[0]


def _doc_ids(b: pa.RecordBatch) -> np.ndarray:
    return b.column("doc_id").cast(pa.int64()).fill_null(LAST).to_numpy(zero_copy_only=False)


def _blocks(bucket: np.ndarray, *columns):
    """Rows (bucket, payload) of columns (or (column, bytes)), one for each bucket that occurs."""
    order = np.argsort(bucket, kind="stable")
    bucket, widths, columns = bucket[order], [c[1] if isinstance(c, tuple) else None for c in columns], [(c[0] if isinstance(c, tuple) else c)[order] for c in columns]
    cuts = np.flatnonzero(np.diff(bucket)) + 1
    at = np.concatenate([[0], cuts, [len(bucket)]])
    if not len(bucket):
        return
    yield pa.RecordBatch.from_arrays(
        [pa.array(bucket[at[:-1]].astype(np.int32)), pa.array([planes(*((c[a:b], w) for c, w in zip(columns, widths))) for a, b in zip(at[:-1], at[1:])], pa.binary())], names=["bucket", "payload"]
    )


def _by_bucket(batches):
    """(bucket, payloads) of one bucket after the other, from rows sorted by bucket."""
    now, held = None, []
    for b in batches:
        for k, raw in zip(b.column("bucket").to_pylist(), b.column("payload")):
            if k != now:
                if held:
                    yield now, held
                now, held = k, []
            held.append(raw.as_py())
    if held:
        yield now, held


def _runs(key: np.ndarray) -> np.ndarray:
    """Starts of the runs of equal values in a sorted array."""
    return np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)


def frequent_grams(docs: DataFrame) -> np.ndarray:
    """Hashes of grams that are anchors FREQUENT times or more in a sample of about SAMPLE_BYTES of text, at most a thousandth
    as many as there are marks. The sample decides which anchors are avoided, never what is compared."""
    base = texts(docs)
    size = base.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    every = max(1, -(-int(size) // SAMPLE_BYTES))

    def run(batches):
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([pa.array(anchors(*text_bytes(b))[1].view(np.int64))], names=["gram"])

    some = base.where(F.pmod(F.xxhash64("doc_id"), F.lit(every)) == 0).select("text")
    common = some.mapInArrow(lean(run), "gram long").groupBy("gram").count().where(F.col("count") >= FREQUENT).orderBy(F.desc("count"), "gram").limit((1 << FILTER_BITS) // 1_000)
    return np.array([r.gram for r in common.collect()], np.int64)


def _strings(wide: np.ndarray, place: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """Per run a row of WIDTH bytes around its anchor; bytes outside the run are 0. wide: the text behind LEFT others."""
    at = place[:, None] + np.arange(WIDTH)
    out = wide[at]
    column = np.arange(WIDTH)
    out[(column < (first - place + LEFT)[:, None]) | (column >= (last - place + LEFT + DEPTH)[:, None])] = 0
    return out


def _pack(*columns) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(planes(*columns[:-1]) + np.ascontiguousarray(columns[-1]).tobytes())


KINDS = (np.int64, np.uint32, np.int32, np.int32, np.uint8, np.uint8)  # doc (as steps), text, pos, span, before, after


def _unpack(raw: bytes) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(raw)
    n = int.from_bytes(raw[:4], "little")
    size = 4 + n * sum(np.dtype(k).itemsize for k in KINDS)
    step, *others = unplanes(raw, *KINDS)
    return [np.cumsum(step), *others, np.frombuffer(raw, np.uint8, n * WIDTH, size).reshape(n, WIDTH)]


def _emit_runs(batches, radix: int, frequent: np.ndarray | None, turn: int = 0, rounds: int = 1, mark: bool = True):
    """Rows (bucket, payload) of runs by their anchor, of the anchors of one round; bucket -1: intervals that equal runs of
    the slice settle already. mark: whether rows are to be told apart by their text too."""
    for b in slices(batches):
        buf, off = text_bytes(b)
        place, h, first, last, whole = anchors(buf, off, frequent)
        mine = np.flatnonzero((h >> np.uint64(12)) % np.uint64(rounds) == turn)
        if not len(mine):
            continue
        place, h, first, last, whole = (c[mine] for c in (place, h, first, last, whole))
        row = np.searchsorted(off, place, "right") - 1
        doc, pos = _doc_ids(b)[row], place - off[row]
        raw = memoryview(buf)
        text = np.array([zlib.crc32(raw[x:y]) for x, y in zip(off[:-1], off[1:])], np.uint32)[row] if mark else np.zeros(len(row), np.uint32)
        wide = np.concatenate([np.zeros(LEFT, np.uint8), buf, np.zeros(DEPTH, np.uint8)])
        before, after = place - first, last + DEPTH - place
        # runs of equal bytes: side by side by document, then place
        order = np.argsort(whole)
        again = whole[order][1:] == whole[order][:-1]
        order = order[np.append(again, False) | np.append(False, again)]
        order = order[np.lexsort((pos[order], row[order], text[order], doc[order], before[order], whole[order]))]
        same = np.zeros(len(order), bool)
        if len(order):
            same[1:] = (whole[order][1:] == whole[order][:-1]) & (before[order][1:] == before[order][:-1]) & (after[order][1:] == after[order][:-1])
        twins = np.flatnonzero(same | np.append(same[1:], False))
        span, keep = np.zeros(len(place), np.int64), np.ones(len(place), bool)
        if len(twins):
            i = order[twins]
            bytes_ = _strings(wide, place[i], first[i], last[i])
            equal = np.zeros(len(i), bool)
            equal[1:] = same[twins][1:] & (bytes_[1:] == bytes_[:-1]).all(axis=1)
            group = np.cumsum(~equal) - 1
            head = np.flatnonzero(~equal)
            least = i[head][group]  # of the smallest document
            larger = doc[i] > doc[least]
            keep[i[larger]] = False
            if larger.any():
                j = i[larger]
                for k in range(0, len(j), 50_000):
                    c = j[k : k + 50_000]
                    yield from _blocks(np.full(len(c), -1), doc[c], text[c], (pos[c] - before[c]).astype(np.int32), (pos[c] + after[c]).astype(np.int32))
            # in one document: places no farther apart than a window cover one stretch together
            mine = i[~larger]
            if len(mine) > 1:
                g = group[~larger]
                near = np.zeros(len(mine), bool)
                near[1:] = (g[1:] == g[:-1]) & (doc[mine][1:] == doc[mine][:-1]) & (text[mine][1:] == text[mine][:-1]) & (row[mine][1:] == row[mine][:-1]) & (pos[mine][1:] - pos[mine][:-1] <= DEPTH)
                at = np.flatnonzero(~near)
                end = np.append(at[1:], len(mine)) - 1
                span[mine[at]] = pos[mine[end]] - pos[mine[at]]
                keep[mine[near]] = False
        left = np.flatnonzero(keep)
        bucket = _bucket_of(h[left], radix)
        left, bucket = (x[np.argsort(bucket, kind="stable")] for x in (left, bucket))
        cuts = np.concatenate([[0], np.flatnonzero(np.diff(bucket)) + 1, [len(bucket)]])
        for k in range(0, len(cuts) - 1, 64):
            few = list(zip(cuts[k : k + 64], cuts[k + 1 : k + 65]))
            packed = []
            for x, y in few:
                i = left[x:y]
                packed.append(_pack(np.diff(doc[i], prepend=0), text[i], pos[i].astype(np.int32), span[i].astype(np.int32), before[i].astype(np.uint8), after[i].astype(np.uint8), _strings(wide, place[i], first[i], last[i])))
            yield pa.RecordBatch.from_arrays([pa.array([int(bucket[x]) for x, _ in few], pa.int32()), pa.array(packed, pa.binary())], names=["bucket", "payload"])


def _bucket_of(h: np.ndarray, radix: int) -> np.ndarray:
    return ((h >> np.uint64(20)) % np.uint64(radix)).astype(np.int64)


def digits(rows: np.ndarray) -> list[np.ndarray]:
    """Rows of bytes as digits of eight bytes, the most significant first; their order is that of the bytes."""
    n, width = rows.shape
    full = np.zeros((n, -(-width // 8) * 8), np.uint8)
    full[:, :width] = rows
    words = full.view(">u8")
    return [words[:, k].astype(np.uint64) for k in range(words.shape[1])]


def next_digit(group: np.ndarray, digit: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One pass: rows ordered by (group, digit), without those whose new group lies in one document; and their new groups."""
    _, place = np.unique(digit, return_inverse=True)
    key = group * np.int64(len(digit) + 1) + place
    order = np.argsort(key, kind="stable")
    key = key[order]
    at = _runs(key)
    d = doc[order]
    many = np.minimum.reduceat(d, at) != np.maximum.reduceat(d, at)
    size = np.diff(np.append(at, len(key)))
    return order[np.repeat(many, size)], np.repeat(np.arange(int(many.sum())), size[many])


def sort_digits(rows: np.ndarray, group: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows of bytes in groups, ordered through all their digits: (places of rows whose bytes several documents of the group have, their groups)."""
    left, words = np.arange(len(rows)), digits(rows)
    for k, word in enumerate(words):
        if not len(left):
            break
        order, group = next_digit(group, word[left], doc[left])
        left = left[order]
    return left, group


def _settle(group, doc, before, after, around) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of runs in groups of one anchor: (row, farthest, nearest place before the anchor) of the windows that a smaller document has."""
    n = len(doc)
    far, near = np.full(n, -1, np.int64), np.full(n, DEPTH, np.int64)
    for o in range(LEFT + 1):  # the window that starts o bytes before the anchor
        rows = np.flatnonzero((before >= o) & (after >= DEPTH - o))
        if len(rows) < 2:
            continue
        rest = np.concatenate([around[rows, LEFT - o : LEFT], around[rows, DEPTH : DEPTH + LEFT - o]], axis=1)
        place, equal = sort_digits(rest, group[rows], doc[rows])
        if not len(place):
            continue
        got = rows[place]
        at = _runs(equal)
        least = np.repeat(np.minimum.reduceat(doc[got], at), np.diff(np.append(at, len(got))))
        hit = got[doc[got] > least]
        far[hit] = o
        near[hit] = np.minimum(near[hit], o)
    some = np.flatnonzero(far >= 0)
    return some, far[some], near[some]


SPANS = "doc_id long, text_crc long, lo int, hi int"


def _intervals(doc, text, lo, hi) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(doc), pa.array(text.astype(np.int64)), pa.array(lo.astype(np.int32)), pa.array(hi.astype(np.int32))], names=["doc_id", "text_crc", "lo", "hi"])


def _order_bucket(batches):
    """The intervals to remove that a bucket's runs prove."""
    for bucket, held in _by_bucket(batches):
        if bucket == -1:
            for raw in held:
                yield _intervals(*unplanes(raw, np.int64, np.uint32, np.int32, np.int32))
            continue
        doc, text, pos, span, before, after, around = (np.concatenate(c) for c in zip(*map(_unpack, held)))
        held.clear()
        # the anchor's own bytes first
        left, group = sort_digits(around[:, LEFT : LEFT + GRAM], np.zeros(len(doc), np.int64), doc)
        if not len(left):
            continue
        doc, text, pos, span, before, after, around = (c[left] for c in (doc, text, pos.astype(np.int64), span.astype(np.int64), before.astype(np.int64), after.astype(np.int64), around))
        # runs of equal bytes
        total = (_TABLE[around] * _POWER[:WIDTH]).sum(axis=1, dtype=np.uint64) ^ mix64((before * 64 + after).astype(np.uint64))
        order = np.lexsort((doc, total, group))
        first = np.ones(len(order), bool)
        first[1:] = (group[order][1:] != group[order][:-1]) | (total[order][1:] != total[order][:-1])
        at = np.flatnonzero(first)
        least = order[np.repeat(at, np.diff(np.append(at, len(order))))]
        same = (doc[least] < doc[order]) & (before[least] == before[order]) & (after[least] == after[order]) & (around[least] == around[order]).all(axis=1)
        whole = order[same]
        if len(whole):
            yield _intervals(doc[whole], text[whole], pos[whole] - before[whole], pos[whole] + span[whole] + after[whole])
        left = np.sort(order[~same])
        # the others window by window, whole groups together
        at = np.append(_runs(group[left]), len(left))
        many = np.repeat(np.diff(at) > 1, np.diff(at))
        left = left[many]
        at = np.append(_runs(group[left]), len(left))
        i = 0
        while i < len(at) - 1:
            j = max(i + 1, int(np.searchsorted(at, at[i] + BATCH, "right")) - 1)
            r = left[at[i] : at[j]]
            row, far, near = _settle(group[r], doc[r], before[r], after[r], around[r])
            if len(row):
                r = r[row]
                yield _intervals(doc[r], text[r], pos[r] - far, pos[r] + span[r] - near + DEPTH)
            i = j


def _with_removed(docs: DataFrame, frequent: np.ndarray | None = None) -> tuple[DataFrame, str]:
    """The rows of docs with a column of the intervals to take out, and that column's name."""
    spark = docs.sparkSession
    radix = BUCKETS_PER_TASK * int(spark.conf.get("spark.sql.shuffle.partitions"))
    common = frequent_grams(docs) if frequent is None else frequent
    marks = frequency_filter(common) if len(common) else None
    base = texts(docs).withColumn("doc_id", F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)))
    checked = F.crc32(F.encode("text", "UTF-8"))
    mark = base.groupBy("doc_id").agg(F.min(checked).alias("a"), F.max(checked).alias("b")).where("a <> b").limit(1).count() > 0
    path = new_path(spark, "repeats")
    for turn in range(ROUNDS):
        packed = base.mapInArrow(lean(lambda it, turn=turn: _emit_runs(it, radix, marks, turn, ROUNDS, mark)), "bucket int, payload binary")
        packed.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(lean(_order_bucket), SPANS).write.mode("append").parquet(path)
        del packed
        release(spark)
    spans = spark.read.schema(SPANS).parquet(path)
    name, crc, removed = (fresh(docs.columns, x) for x in ("id", "crc", "removed"))
    back = spans.groupBy(F.col("doc_id").alias(name), F.col("text_crc").alias(crc)).agg(F.collect_list(F.struct("lo", "hi")).alias(removed))
    none = F.from_json(F.lit("[]"), "array<struct<lo:int,hi:int>>")
    keyed = docs.withColumn(name, F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST))).withColumn(crc, F.crc32(F.encode(F.coalesce("text", F.lit("")), "UTF-8")) if mark else F.lit(0).cast("long"))
    return keyed.join(back, [name, crc], "left").withColumn(removed, F.coalesce(removed, none)).drop(name, crc), removed


def _spans(b: pa.RecordBatch, removed: str):
    """Text bytes, offsets and the removed runs of a batch."""
    buf, off = text_bytes(b)
    row, f = _flat(b, removed)
    return buf, off, *merged_spans(row, f["lo"].astype(np.int64), f["hi"].astype(np.int64))


def _flat(b: pa.RecordBatch, name: str) -> tuple[np.ndarray, dict[str, np.ndarray]]:
    """Row numbers and fields of a list-of-struct column."""
    col = b.column(name)
    off = col.offsets.to_numpy().astype(np.int64)
    fields = col.flatten()
    row = np.repeat(np.arange(b.num_rows), np.diff(off))
    return row, {f.name: fields.field(i).to_numpy(zero_copy_only=False) for i, f in enumerate(fields.type)}


def merged_spans(row: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs per row of intervals that overlap or touch."""
    if not len(row):
        return row, lo, hi
    order = np.lexsort((lo, row))
    row, lo, hi = row[order], lo[order], hi[order]
    base = row * (np.int64(1) << 33)
    reach = np.maximum.accumulate(base + hi)
    new = np.ones(len(row), bool)
    new[1:] = base[1:] + lo[1:] > reach[:-1]
    at = np.flatnonzero(new)
    return row[at], lo[at], np.maximum.reduceat(hi, at)


def _kept(buf: np.ndarray, off: np.ndarray, row, lo, hi) -> tuple[np.ndarray, np.ndarray]:
    """The remaining bytes and their bounds per document."""
    mark = np.zeros(len(buf) + 1, np.int8)
    mark[off[:-1][row] + lo] += 1
    ends = off[:-1][row] + hi
    np.add.at(mark, ends, -1)
    keep = np.cumsum(mark[:-1], dtype=np.int8) == 0
    count = np.concatenate([[0], np.cumsum(keep)])
    return buf[keep], count[off]


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, kept BINARY (the remaining bytes), spans ARRAY<start, end> in bytes of the input text."""
    schema = pa.schema([("doc_id", pa.int64()), ("kept", pa.binary()), ("spans", pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))])
    rows, removed = _with_removed(texts(docs))

    def run(batches):
        for b in slices(batches):
            buf, off, row, lo, hi = _spans(b, removed)
            kept, at = _kept(buf, off, row, lo, hi)
            raw = kept.tobytes()
            per = np.searchsorted(row, np.arange(b.num_rows + 1))
            spans = pa.ListArray.from_arrays(pa.array(per, pa.int32()), pa.StructArray.from_arrays([pa.array(lo, pa.int32()), pa.array(hi, pa.int32())], names=["start", "end"]))
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array([raw[x:y] for x, y in zip(at[:-1], at[1:])], pa.binary()), spans], schema=schema)

    return rows.mapInArrow(lean(run), "doc_id long, kept binary, spans array<struct<start:int,end:int>>")


def repeat_digests(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256."""
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())])
    rows, removed = _with_removed(texts(docs))

    def run(batches):
        for b in slices(batches):
            buf, off, row, lo, hi = _spans(b, removed)
            kept, at = _kept(buf, off, row, lo, hi)
            raw, size = memoryview(kept.tobytes()), np.diff(off)
            sha = [hashlib.sha256(raw[x:y]).hexdigest() for x, y in zip(at[:-1], at[1:])]
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array(size), pa.array(size - np.diff(at)), pa.array(np.bincount(row, minlength=b.num_rows)), pa.array(sha, pa.string())], schema=schema)

    return rows.mapInArrow(lean(run), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def without_repeats(docs: DataFrame) -> DataFrame:
    """The documents with the repeated bytes taken out of text and n_chars (if it is there, of any whole type) set anew;
    all other columns stay.

    Where a cut falls inside a character, the rest of its bytes is left out of the text. A null text becomes empty.
    """
    columns = docs.columns
    rows, removed = _with_removed(docs)

    def run(batches):
        for b in slices(batches):
            buf, off, row, lo, hi = _spans(b, removed)
            kept, at = _kept(buf, off, row, lo, hi)
            raw = kept.tobytes()
            text = [raw[x:y].decode("utf-8", "ignore") for x, y in zip(at[:-1], at[1:])]
            new = {"text": pa.array(text, pa.string())}
            if "n_chars" in columns:
                new["n_chars"] = pa.array(map(len, text), pa.int64()).cast(b.column("n_chars").type)
            yield pa.RecordBatch.from_arrays([new[c] if c in new else b.column(c) for c in columns], names=columns)

    return rows.mapInArrow(lean(run), docs.schema)
