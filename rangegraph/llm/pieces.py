"""Encoding and decoding with a merge-type piece vocabulary, by a table of prefixes.

For merge vocabularies the last token of the encoding of a prefix is unique. So the encoder walks the
text once: an automaton gives all pieces that end at a position, the longest first, and the first one
that is compatible with the last token of the prefix in front of it is stored. The ids are read
backwards from the end. Two neighbours are compatible if merging their joined surface by the
vocabulary's own priorities gives these two tokens again; the answer is remembered per pair.

Units: where no piece of the vocabulary spans two neighbouring characters, no merge can cross. The
text is cut there (before a run of the space symbol, around line ends), each unit's encoding is
remembered in a bounded cache, and long texts without such places are encoded in one go.

Defined cases: null text is the empty text and has the end id only; ids are those of the library
for every text, including control characters, runs of spaces, the space symbol itself and characters
outside the vocabulary (their UTF-8 bytes, or the unknown id without byte pieces). Decoding reads the ids alone.
"""

from __future__ import annotations

import hashlib
import heapq
import re

import ahocorasick
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame

from .common import lean, texts

SPACE = "▁"
PIECES = 1 << 22  # more than any vocabulary has
CHARACTER = 1 << 21  # keys of single characters start here


def characters(raw: bytes) -> str:
    """UTF-8 bytes as text; each byte that begins no character is one replacement character."""
    try:
        return raw.decode()
    except UnicodeDecodeError:
        out, at = [], 0
        while at < len(raw):
            size = 1 if raw[at] < 0x80 else 2 if raw[at] < 0xE0 else 3 if raw[at] < 0xF0 else 4
            try:
                out.append(raw[at : at + size].decode())
                at += size
            except UnicodeDecodeError:
                out.append("\ufffd")
                at += 1
        return "".join(out)


class PieceTable:
    """The vocabulary with its automaton, pair memory and unit cache; one per Python worker."""

    def __init__(self, model_path: str, units: int = 150_000, pairs: int = 400_000):
        sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
        n = sp.get_piece_size()
        self.surface = [sp.id_to_piece(i) for i in range(n)]
        self.eos = sp.eos_id()
        self.unk = sp.unk_id()
        self.control = {i for i in range(n) if sp.is_control(i)}
        self.byte_ids: dict[int, int] = {}
        self.byte_of: dict[int, int] = {}
        self.score: dict[str, tuple[float, int]] = {}
        for i, p in enumerate(self.surface):
            if sp.is_byte(i):
                b = int(p[3:5], 16)
                self.byte_ids[b], self.byte_of[i] = i, b
            elif not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)):
                self.score[p] = (sp.get_score(i), i)
        if sp.encode("a  b\tc ") != sp.encode("a  b\tc ", enable_sampling=False) or sp.decode(sp.encode(" a  b ")) != " a  b ":
            raise ValueError("only vocabularies with an identity normaliser are supported")
        joined = self.joined = {a + b for p in self.score for a, b in zip(p, p[1:])}
        if any(j[1] == SPACE and j[0] != SPACE for j in joined):
            raise ValueError("pieces span a word boundary")
        lone = any("\n" in j for j in joined)
        self.cut = re.compile(f"{SPACE}+[^{SPACE}]*|[^{SPACE}]+" if lone else f"\n|{SPACE}+[^{SPACE}\n]*|[^{SPACE}\n]+")
        self.automaton = ahocorasick.Automaton()
        for p, (_, i) in self.score.items():
            if len(p) > 1 and self.merged(p) == [p]:
                self.automaton.add_word(p, (len(p), p, i))
        self.automaton.make_automaton()
        self.id_of = {p: i for p, (_, i) in self.score.items()}
        self.number = [str(i) for i in range(n)]
        #: What an id decodes to; None for byte pieces, which are decoded together.
        self.text_of = [None if i in self.byte_of else "" if i in self.control else " ⁇ " if i == self.unk else p.replace(SPACE, " ") for i, p in enumerate(self.surface)]
        self.pair: dict[int, bool] = {}
        self.newer: dict[str, tuple[int, ...]] = {}
        self.older: dict[str, tuple[int, ...]] = {}
        self.max_units, self.max_pairs = units, pairs
        self.lines = not lone
        self.line_end = self.encode_unit("\n")
        self.single = {c: self.encode_unit(c) for c in map(chr, range(33, 127))}

    def merged(self, s: str) -> list[str]:
        """The merge procedure itself on a short string: best score first, then leftmost."""
        sym: list[str | None] = list(s)
        nxt, prv = list(range(1, len(s) + 1)), list(range(-1, len(s) - 1))
        heap: list[tuple[float, int, str, int]] = []

        def offer(a: int, b: int) -> None:
            if a >= 0 and b < len(s):
                w = sym[a] + sym[b]
                if w in self.score:
                    heapq.heappush(heap, (-self.score[w][0], a, w, b))

        for i in range(len(s) - 1):
            offer(i, i + 1)
        while heap:
            _, a, w, b = heapq.heappop(heap)
            if sym[a] is None or sym[b] is None or nxt[a] != b or sym[a] + sym[b] != w:
                continue
            sym[a], sym[b] = w, None
            nxt[a] = nxt[b]
            if nxt[a] < len(s):
                prv[nxt[a]] = a
            offer(prv[a], a)
            offer(a, nxt[a])
        return [x for x in sym if x is not None]

    def compatible(self, key: int, left: str, right: str) -> bool:
        """Whether two tokens may stand side by side, remembered under their key."""
        ok = self.merged(left + right) == [left, right]
        if len(self.pair) >= self.max_pairs:
            self.pair.clear()
        self.pair[key] = ok
        return ok

    def split(self, s: str) -> list[str]:
        """The tokens of one unit, from the table of its prefixes."""
        if s in self.automaton:
            return [s]
        n, pair = len(s), self.pair
        last: list[tuple | None] = [None] * (n + 1)  # None: no longer piece fits, so the character itself
        for e, found in self.automaton.iter(s):  # at each end the longest first
            e += 1
            if last[e] is None:
                size, p, own = found
                st = e - size
                if st:
                    left = last[st]
                    key = own + (left[2] if left is not None else ord(s[st - 1]) + CHARACTER) * PIECES
                    ok = pair.get(key)
                    if ok is None:
                        ok = self.compatible(key, left[1] if left is not None else s[st - 1], p)
                    if not ok:
                        continue
                last[e] = found
        out, i = [], n
        while i:
            p = last[i][1] if last[i] is not None else s[i - 1]
            out.append(p)
            i -= len(p)
        out.reverse()
        return out

    def ids_of(self, tokens: list[str]) -> list[int]:
        out: list[int] = []
        for t in tokens:
            known = self.score.get(t)
            if known is not None:
                out.append(known[1])
            elif self.byte_ids:
                out.extend(self.byte_ids[b] for b in t.encode())
            else:
                out.append(self.unk)
        return out

    def surface_of(self, ids: list[int]) -> str:
        """Decoded text of ids, before the space of the start is taken off."""
        try:
            return "".join([self.text_of[i] for i in ids])
        except TypeError:  # byte pieces among them: runs of these are characters together
            out, run = [], bytearray()
            for i in ids:
                if i in self.byte_of:
                    run.append(self.byte_of[i])
                else:
                    if run:
                        out.append(characters(bytes(run)))
                        run.clear()
                    out.append(self.text_of[i])
            return "".join(out) + characters(bytes(run))

    def units(self, text: str) -> list[str]:
        return self.cut.findall(SPACE + text.replace(" ", SPACE)) if text else []

    def encode_unit(self, u: str) -> tuple[int, ...]:
        """The ids of a unit."""
        tokens = self.split(u)
        try:
            return tuple([self.id_of[t] for t in tokens])
        except KeyError:
            return tuple(self.ids_of(tokens))

    def learn(self, word: str) -> tuple[int, ...]:
        """The unit of a word with a space in front: from the older half of the cache, or encoded now."""
        got = self.older.get(word)
        if got is None:
            if not 2 <= len(word) <= 64 or word[-2:] in self.joined:  # the length also bounds the recursion
                got = self.encode_unit(SPACE + word)
            else:  # no piece spans the last two characters (a stop behind a letter)
                stem, tail = word[:-1], word[-1]
                return (self.newer.get(stem) or self.learn(stem)) + (self.single.get(tail) or self.encode_unit(tail))
        if len(word) <= 64:
            if len(self.newer) >= self.max_units:  # what was used since the last turn stays
                self.older, self.newer = self.newer, {}
            self.newer[word] = got
        return got

    def encode(self, text: str) -> list[int]:
        """The ids of a text, without the end id."""
        out: list[int] = []
        if not text:
            return out
        if not self.lines or SPACE in text or text[0] == " " or "  " in text:
            for u in self.units(text):
                out += self.learn(u[1:]) if u[0] == SPACE else self.encode_unit(u)
            return out
        for k, line in enumerate(text.split("\n")):
            words = line.split(" ")
            if k:  # the first word of a later line has no space in front
                out += self.line_end
                if words[0]:
                    out += self.encode_unit(words[0])
                del words[0]
            for w in words:
                out += self.newer.get(w) or self.learn(w)
        return out

    def decode(self, ids: list[int]) -> str:
        s = self.surface_of(ids)
        return s[1:] if ids and self.surface[next((i for i in ids if i not in self.control), self.eos)].startswith(SPACE) else s

    def round_trip(self, text: str) -> tuple[list[int], str]:
        """The ids with the end id, and the text decoded from them."""
        ids = [*self.encode(text), self.eos]
        return ids, self.decode(ids)


_tables: dict[str, PieceTable] = {}


def piece_table(model_path: str) -> PieceTable:
    if model_path not in _tables:
        _tables[model_path] = PieceTable(model_path)
    return _tables[model_path]


def encode_documents(docs: DataFrame, model_path: str) -> DataFrame:
    """doc_id, ids ARRAY<INT> (with the end id), decoded STRING. Extra columns of docs are left out."""
    schema = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32())), ("decoded", pa.string())])

    def run(batches):
        t = piece_table(model_path)
        for b in batches:
            pairs = [t.round_trip(x or "") for x in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array([p[0] for p in pairs], pa.list_(pa.int32())), pa.array([p[1] for p in pairs], pa.string())], schema=schema)

    return texts(docs).mapInArrow(lean(run), "doc_id long, ids array<int>, decoded string")


def encode_digests(docs: DataFrame, model_path: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: the same ids and texts, as digests only."""
    schema = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])

    def run(batches):
        t = piece_table(model_path)
        for b in batches:
            count, ids, back = [], [], []
            for x in b.column("text"):
                got, text = t.round_trip(x.as_py() or "")
                count.append(len(got))
                ids.append(hashlib.sha256(" ".join([t.number[i] for i in got]).encode()).hexdigest())
                back.append(hashlib.sha256(text.encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array(count, pa.int64()), pa.array(ids, pa.string()), pa.array(back, pa.string())], schema=schema)

    return texts(docs).mapInArrow(lean(run), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
