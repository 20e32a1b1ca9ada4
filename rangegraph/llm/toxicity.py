"""Toxicity by two class-conditional Kneser-Ney models.

Each class (toxic, ordinary) has an interpolated Kneser-Ney model of characters inside words, of order
ORDER with word ends marked. Orders above SHARED have counts of their own class; the orders below are
continuation counts that both classes share, so rare expressions fall back on the same ground and their
stems decide. A word's evidence is the difference of its two log-likelihoods. The score of a text is a
logistic curve over its length-normalised evidence: the mean over all its words, over its strongest one to eight
words, what words exceed some levels by, over their number or its root, and the logarithm of that number. The curve
is fitted on labelled rows the models have not seen; which of these numbers it gets was decided by
cross-validation on rows that may be learnt from.

Runs of more than LONGEST characters (scripts without spaces, words joined by `_`) count as words of LONGEST
characters each, which see the ORDER - 1 characters before them, so every character of a run has its part.

Words with no place in the models are rated from their characters, so a new form of a known stem counts.

Training takes all labelled rows that are allowed for learning. At most SAMPLE rows per class (of one row
in four, those least by a hash of doc_id) fit the curve and all others train the models. Each place of a
word has one gram of ORDER characters, and the grams of lower orders are its ends, so the models need no
more than the counts of these grams in both classes: they are summed per task, then by gram over all
tasks, and only the distinct grams reach the driver. The fitted tables grow with the number of distinct
grams, not of rows, and are sent to the tasks. Labels, language, source and doc_id are no inputs of a score.

Defined cases: null text is empty; a text without words gets the score of no evidence; without labels of
both classes every score is 0; equal texts get equal scores; repeated rows give repeated results; other
columns are ignored; conflicting labels of a document count as toxic.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, mix64, texts

ORDER = 6
SHARED = 2
DISCOUNT = 0.75
SAMPLE = 8_000  # for the curve
ABOVE = (1, 2, 3)
STRONGEST = (1, 2, 4, 8)
FEATURES = 1 + len(ABOVE) + 2 + len(STRONGEST) + 1
CUT = 0.7
LONGEST = 40
SENT_BYTES = 64_000_000  # of labels that may go to all tasks
_WORD = re.compile(r"\w+")
_BITS = 21  # of a code point; half a gram is one number
_C = mix64(np.arange(1, ORDER + 2, dtype=np.uint64)) | np.uint64(1)


def words_of(text: str) -> list[str]:
    """The words of a text; a long run as pieces, each behind a mark with the ORDER - 1 characters before it."""
    out = []
    for w in _WORD.findall(text.lower()):
        if len(w) <= LONGEST:
            out.append(w)
        else:
            run = "\x01" * (ORDER - 1) + w + "\x02"
            out += ["\x03" + run[i : i + LONGEST + ORDER - 1] for i in range(0, len(w) + 1, LONGEST)]
    return out


def characters(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of words, each with ORDER - 1 characters or marks in front and, at its end, a mark; and the word of each place."""
    pad = "\x01" * (ORDER - 1)
    cut = [w[1:] if w[:1] == "\x03" else pad + w + "\x02" for w in words]
    size = np.array([len(w) for w in cut], np.int64)
    codes = np.frombuffer("".join(cut).encode("utf-32-le"), np.uint32)
    return codes, np.repeat(np.arange(len(words), dtype=np.int32), size)


def places(owner: np.ndarray) -> np.ndarray:
    """The places with ORDER - 1 others of the same word in front of them."""
    return (np.flatnonzero(owner[ORDER - 1 :] == owner[: len(owner) - ORDER + 1]) + ORDER - 1).astype(np.int32)


def grams(codes: np.ndarray, owner: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each of the places: hash of its context and of context plus character; its word."""
    at = places(owner)
    context = np.full(len(at), order, np.uint64)
    for k in range(order - 1, 0, -1):
        context ^= codes[at - k]
        context *= _C[k]
        context ^= context >> np.uint64(31)
    gram = (context ^ codes[at]) * _C[0]
    gram ^= gram >> np.uint64(29)
    return mix64(context), mix64(gram), owner[at]


class Lookup:
    """Values by hash, in an open table of twice the size."""

    def __init__(self, key: np.ndarray, value: np.ndarray):
        bits = max(4, int(2 * len(key) + 1).bit_length())
        self.mask = np.uint64((1 << bits) - 1)
        self.key = np.zeros(1 << bits, np.uint64)
        self.value = np.zeros(1 << bits, np.float32)
        slot, left = (key & self.mask).astype(np.int64), np.arange(len(key))
        self.steps = 0
        while len(left):
            self.steps += 1
            free = left[self.key[slot[left]] == 0]
            _, first = np.unique(slot[free], return_index=True)
            put = free[first]
            self.key[slot[put]], self.value[slot[put]] = key[put], value[put]
            left = np.setdiff1d(left, put, assume_unique=True)
            slot[left] = (slot[left] + 1) & int(self.mask)

    def get(self, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether each key is there, and its value (0 if not)."""
        slot = (key & self.mask).astype(np.int64)
        found, out = np.zeros(len(key), bool), np.zeros(len(key), np.float32)
        left = np.arange(len(key))
        for _ in range(self.steps + 1):
            got = self.key[slot[left]]
            hit = left[got == key[left]]
            found[hit], out[hit] = True, self.value[slot[hit]]
            left = left[(got != key[left]) & (got != 0)]
            if not len(left):
                break
            slot[left] = (slot[left] + 1) & int(self.mask)
        return found, out


class Evidence:
    """Log-likelihood differences (toxic minus ordinary) of words, as a table of grams and one of contexts."""

    def __init__(self, words: list[str], toxic: np.ndarray, ordinary: np.ndarray):
        """Words with their counts in the two classes."""
        self._fit(*characters(words), toxic, ordinary)

    @classmethod
    def of_grams(cls, table: np.ndarray, toxic: np.ndarray, ordinary: np.ndarray) -> Evidence:
        """The same from the distinct grams of ORDER code points (n x ORDER) with their counts in the two classes."""
        model = cls.__new__(cls)
        model._fit(np.ascontiguousarray(table, np.uint32).ravel(), np.repeat(np.arange(len(table), dtype=np.int32), ORDER), toxic, ordinary)
        return model

    def _fit(self, codes: np.ndarray, owner: np.ndarray, toxic: np.ndarray, ordinary: np.ndarray) -> None:
        self.levels: list[tuple[Lookup, Lookup]] = []
        size = len(np.unique(codes[places(owner)]))  # of the characters and the mark that a model can give
        below = None  # per character place: the two log-probabilities of the order below
        weights = None
        for order in range(1, ORDER + 1):
            context, gram, word = grams(codes, owner, order)
            if weights is None:
                weights = (toxic[word].astype(float), ordinary[word].astype(float))
            uniq, first, inverse = np.unique(gram, return_index=True, return_inverse=True)
            inverse = inverse.astype(np.int32)
            c_uniq, c_inverse = np.unique(context[first], return_inverse=True)
            del context, word
            if order < ORDER:  # continuation: in how many longer grams, per class or in both
                longer = grams(codes, owner, order + 1)[1]
                wide, one, place = np.unique(longer, return_index=True, return_inverse=True)
                del longer
                up = np.searchsorted(uniq, gram[one])
                if order > SHARED:
                    counts = [np.bincount(up, np.bincount(place, w, len(wide)) > 0, len(uniq)) for w in weights]
                else:
                    counts = [np.bincount(up, minlength=len(uniq)).astype(float)] * 2
                del wide, one, place, up
            else:
                counts = [np.bincount(inverse, w, len(uniq)) for w in weights]
            logs, back = [], []
            for k, c in enumerate(counts):
                total = np.bincount(c_inverse, c, len(c_uniq))
                kinds = np.bincount(c_inverse, c > 0, len(c_uniq))
                lower = np.full(len(uniq), 1.0 / max(size, 1)) if below is None else np.exp(below[k][first])
                free = np.where(total > 0, DISCOUNT * kinds / np.maximum(total, 1e-9), 1.0)
                p = np.where(total[c_inverse] > 0, np.maximum(c - DISCOUNT, 0) / np.maximum(total[c_inverse], 1e-9), 0) + free[c_inverse] * lower
                logs.append(np.log(np.maximum(p, 1e-12)))
                back.append(np.log(np.maximum(free, 1e-12)))
            self.levels.append((Lookup(uniq, (logs[0] - logs[1]).astype(np.float32)), Lookup(c_uniq, (back[0] - back[1]).astype(np.float32))))
            below = [x[inverse].astype(np.float32) for x in logs]
        digest = hashlib.sha256()
        for pair in self.levels:
            for table in pair:
                digest.update(table.key.tobytes())
                digest.update(table.value.tobytes())
        self.digest = digest.hexdigest()

    def of(self, words: list[str]) -> np.ndarray:
        """Evidence of each word."""
        codes, owner = characters(words)
        at = places(owner)
        total = np.zeros(len(at))
        left = np.arange(len(at))
        for order in range(ORDER, 0, -1):
            context, gram, _ = grams(codes, owner, order)
            known, value = self.levels[order - 1][0].get(gram[left])
            total[left[known]] += value[known]
            left = left[~known]
            if not len(left):
                break
            total[left] += self.levels[order - 1][1].get(context[left])[1]
        return np.bincount(owner[at], total, len(words)) if len(words) else np.zeros(0)


#: The digest of a model and the evidence of words under it; a worker keeps one model's.
_memory: tuple[str, dict[str, float]] = ("", {})


def text_features(texts_: list[str], model: Evidence, most: int = 300_000) -> np.ndarray:
    """Per text the length-normalised evidence: of all words, beyond each level, of the strongest words; and the number of words."""
    global _memory
    if _memory[0] != model.digest:
        _memory = (model.digest, {})
    known = _memory[1]
    split = [words_of(t) for t in texts_]
    new = [w for w in set().union(*split) if w not in known] if split else []
    if len(known) + len(new) > most:
        known.clear()
        new = list(set().union(*split))
    for i in range(0, len(new), 50_000):
        part = new[i : i + 50_000]
        known.update(zip(part, model.of(part).tolist()))
    out = np.zeros((len(texts_), FEATURES))
    for i, words in enumerate(split):
        if words:
            out[i] = _features(np.fromiter(map(known.__getitem__, words), float, len(words)))
    return out


def _features(v: np.ndarray) -> list[float]:
    """v: evidence of each word of a text."""
    n, most = len(v), STRONGEST[-1]
    over = [np.maximum(v - a, 0).sum() for a in ABOVE]
    top = np.sort(np.partition(v, n - most)[n - most :] if n > most else v)[::-1]
    return [v.mean(), *(x / n**0.5 for x in over), over[1] / n, over[2] / n, *(top[:k].sum() / k for k in STRONGEST), np.log1p(n)]


def _gram_counts(batches, most: int = 200_000):
    """high, low (a gram of ORDER code points as two numbers), toxic, ordinary: counts over a task, in parts of bounded memory."""
    seen: dict[str, list[int]] = {}

    def part():
        codes, owner = characters(list(seen))
        count = np.array(list(seen.values()), np.int64).reshape(-1, 2)
        at = places(owner)
        half = [np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)]
        for k in range(ORDER):
            h = half[k >= ORDER // 2]
            h <<= _BITS
            h |= codes[at - (ORDER - 1 - k)]
        _, first, inverse = np.unique(grams(codes, owner, ORDER)[1], return_index=True, return_inverse=True)
        sums = [np.bincount(inverse, count[owner[at], y], len(first)).astype(np.int64) for y in (1, 0)]
        seen.clear()
        return pa.RecordBatch.from_arrays([pa.array(x) for x in (half[0][first], half[1][first], *sums)], names=["high", "low", "toxic", "ordinary"])

    for b in batches:
        for t, y in zip(b.column("text"), b.column("label").to_pylist()):
            for w in words_of(t.as_py() or ""):
                seen.setdefault(w, [0, 0])[y] += 1
            if len(seen) > most:
                yield part()
    yield part()


def _labelled(batches, ids: np.ndarray, labels: np.ndarray):
    """text, label of the rows whose doc_id is among the sorted ids."""
    for b in batches:
        own = b.column("doc_id").cast(pa.int64())
        values = own.fill_null(0).to_numpy(zero_copy_only=False)
        at = np.minimum(np.searchsorted(ids, values), max(len(ids) - 1, 0))
        rows = np.flatnonzero((ids[at] == values) & own.is_valid().to_numpy(zero_copy_only=False)) if len(ids) else np.zeros(0, np.int64)
        yield pa.RecordBatch.from_arrays([b.column("text").take(pa.array(rows)), pa.array(labels[at[rows]])], names=["text", "label"])


def gram_table(high: np.ndarray, low: np.ndarray) -> np.ndarray:
    """n x ORDER code points of grams packed by _gram_counts."""
    out = np.zeros((len(high), ORDER), np.uint32)
    for k in range(ORDER):
        half, back = (high, ORDER // 2 - 1 - k) if k < ORDER // 2 else (low, ORDER - 1 - k)
        out[:, k] = half >> (_BITS * back) & ((1 << _BITS) - 1)
    return out


def logistic(x: np.ndarray, y: np.ndarray, steps: int = 60, ridge: float = 1e-2) -> np.ndarray:
    """Weights (last: constant) of a logistic curve, by Newton steps."""
    a = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(a.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + ridge * np.eye(a.shape[1]), a.T @ (y - p) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def labelled_sample(labels: DataFrame, column: str, rows: int = SAMPLE) -> DataFrame:
    """doc_id, label: at most `rows` labelled documents of each class, the least by a hash of doc_id."""
    one = labels.where(F.col("doc_id").isNotNull() & F.col(column).isNotNull()).groupBy("doc_id").agg(F.max(column).cast("int").alias("label"))
    order = F.md5(F.col("doc_id").cast("string"))
    return one.where("label = 1").orderBy(order).limit(rows).unionByName(one.where("label = 0").orderBy(order).limit(rows))


def fit(docs: DataFrame, labels: DataFrame) -> tuple[Evidence, np.ndarray, np.ndarray, np.ndarray] | None:
    """Models and curve from the labels whose rows may be learnt from."""
    spark = docs.sparkSession
    learn = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(3)) != 1
    allowed = labels.select(F.col("doc_id").cast("long").alias("doc_id"), "toxic").where(learn)
    sample = labelled_sample(allowed.where(F.pmod(F.xxhash64("doc_id"), F.lit(4)) == 0), "toxic", SAMPLE).collect()
    if len({r.label for r in sample}) < 2:
        return None
    curve = F.broadcast(spark.createDataFrame([(r.doc_id, r.label) for r in sample], "doc_id long, label int"))
    train = allowed.groupBy("doc_id").agg(F.max("toxic").cast("int").alias("label")).where("label in (0, 1)").join(curve, "doc_id", "left_anti")
    schema = "high long, low long, toxic long, ordinary long"
    if 12 * train.count() <= SENT_BYTES:  # labels of this size go to all tasks, and no text is shuffled
        held = train.select("doc_id", "label").orderBy("doc_id").toArrow()
        marks = spark.sparkContext.broadcast((held.column(0).to_numpy(), held.column(1).to_numpy()))
        parts = texts(docs).where(learn).mapInArrow(lean(lambda it: _gram_counts(_labelled(it, *marks.value))), schema)
    else:
        parts = texts(docs).where(learn).join(train, "doc_id").select("text", "label").mapInArrow(lean(_gram_counts), schema)
    counts = parts.groupBy("high", "low").agg(F.sum("toxic").alias("toxic"), F.sum("ordinary").alias("ordinary")).toArrow()
    if not len(counts):
        return None
    high, low, toxic, ordinary = (counts.column(c).to_numpy() for c in counts.column_names)
    order = np.lexsort((low, high))
    model = Evidence.of_grams(gram_table(high[order], low[order]), toxic[order], ordinary[order])
    del counts, high, low, toxic, ordinary, order
    sent = spark.sparkContext.broadcast(model)

    def measure(batches):
        for b in batches:
            f = text_features([t or "" for t in b.column("text").to_pylist()], sent.value)
            yield pa.RecordBatch.from_arrays([pa.array(f[:, i]) for i in range(f.shape[1])] + [b.column("label").cast(pa.int32())], names=[f"f{i}" for i in range(f.shape[1])] + ["label"])

    rows = texts(docs).where(learn).join(curve, "doc_id").select("text", "label")
    seen = rows.mapInArrow(lean(measure), ", ".join(f"f{i} double" for i in range(FEATURES)) + ", label int").toPandas()
    if not len(seen) or seen.label.nunique() < 2:
        return None
    x, y = seen[[f"f{i}" for i in range(FEATURES)]].to_numpy(), seen.label.to_numpy(float)
    middle, spread = x.mean(axis=0), np.maximum(x.std(axis=0), 1e-9)
    return model, middle, spread, logistic((x - middle) / spread, y)


def score(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    spark = docs.sparkSession
    fitted = fit(docs, labels)
    held = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(3)) == 1
    base = texts(docs).select("doc_id", F.coalesce(held, F.lit(False)).alias("held_out"), "text")
    if fitted is None:
        return base.select("doc_id", "held_out", F.lit(0.0).alias("score"), F.lit(0).alias("predicted"))
    sent = spark.sparkContext.broadcast(fitted)
    schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32())])

    def run(batches):
        model, middle, spread, w = sent.value
        for b in batches:
            for i in range(0, b.num_rows, 2_000):
                part = b.slice(i, 2_000)
                f = text_features([t or "" for t in part.column("text").to_pylist()], model)
                s = 1 / (1 + np.exp(-np.clip((f - middle) / spread @ w[:-1] + w[-1], -30, 30)))
                yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), part.column("held_out"), pa.array(s), pa.array((s >= CUT).astype(np.int32))], schema=schema)

    return base.mapInArrow(lean(run), "doc_id long, held_out boolean, score double, predicted int")
