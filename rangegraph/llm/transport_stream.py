"""MPEG transport streams as a media column.

`pack` writes bytes as a single-program transport stream: 188-byte packets, program association and
program map tables with their CRC, one elementary stream of private data whose access units are PES
packets with presentation timestamps; some units are marked as random-access points, carry a clock
reference and are preceded by the tables.

`unpack` reads streams of any writer with such content: tables over several packets or sections, repeated and with
new versions; several programs and elementary streams (one is chosen); adaptation fields; a packet sent twice, which
is read once; marked discontinuities, which are no error; packets marked as damaged, which are left out. It follows
the association table to the map table and that to the elementary stream, checks the continuity counter of each PID,
takes the payloads together to PES packets, and gives the payload with each unit's timestamp, byte position and
random-access mark.

Defined cases: null text is the empty text; payload of any length (also 0) packs to a stream; an input
whose length is no multiple of 188, or with a wrong sync byte, without an undamaged table, or without the program or
stream asked for raises ValueError in `unpack`; continuity gaps, repeated and damaged packets and damaged tables are
counted and reported, the rest is still read; scrambled packets raise ValueError.
"""

from __future__ import annotations

import hashlib
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import lean, texts

# Fixed values of the format.
PACKET = 188
SYNC = 0x47
PAT_PID = 0x0000
NULL_PID = 0x1FFF
CRC_POLYNOMIAL = 0x04C11DB7
PRIVATE_PES = 0x06
PRIVATE_STREAM_1 = 0xBD
CLOCK = 90_000

# Choices of this writer.
PMT_PID, ES_PID, PROGRAM = 0x1000, 0x0100, 1
UNIT = 16_384
UNIT_TICKS = 3_600
ACCESS_EVERY = 4


def _crc_table() -> np.ndarray:
    t = np.arange(256, dtype=np.uint32) << np.uint32(24)
    for _ in range(8):
        t = np.where(t & np.uint32(0x80000000), (t << np.uint32(1)) ^ np.uint32(CRC_POLYNOMIAL), t << np.uint32(1))
    return t


_CRC = [int(x) for x in _crc_table()]


def section_crc(data: bytes) -> int:
    c = 0xFFFFFFFF
    for b in data:
        c = (c << 8) & 0xFFFFFFFF ^ _CRC[c >> 24 ^ b]
    return c


def _section(table_id: int, ident: int, body: bytes) -> bytes:
    head = bytes([table_id]) + (0xB000 | len(body) + 9).to_bytes(2, "big") + ident.to_bytes(2, "big") + b"\xc1\x00\x00"
    return head + body + section_crc(head + body).to_bytes(4, "big")


def _table_packet(pid: int, section: bytes) -> np.ndarray:
    head = bytes([SYNC]) + (0x4000 | pid).to_bytes(2, "big") + b"\x10\x00"
    return np.frombuffer((head + section).ljust(PACKET, b"\xff"), np.uint8).copy()


_PAT = _table_packet(PAT_PID, _section(0x00, 1, PROGRAM.to_bytes(2, "big") + (0xE000 | PMT_PID).to_bytes(2, "big")))
_PMT = _table_packet(PMT_PID, _section(0x02, PROGRAM, (0xE000 | ES_PID).to_bytes(2, "big") + b"\xf0\x00" + bytes([PRIVATE_PES]) + (0xE000 | ES_PID).to_bytes(2, "big") + b"\xf0\x00"))


def _timestamp(t: int) -> bytes:
    return bytes([0x21 | t >> 29 & 0x0E, t >> 22 & 0xFF, 0x01 | t >> 14 & 0xFE, t >> 7 & 0xFF, 0x01 | t << 1 & 0xFE])


def pack(payload: bytes, unit: int = UNIT) -> bytes:
    """The transport stream of a payload, in access units of `unit` bytes."""
    blocks, cc, tables = [], 0, 0
    for k, at in enumerate(range(0, len(payload) or 1, unit)):
        part, pts, access = payload[at : at + unit], k * UNIT_TICKS, k % ACCESS_EVERY == 0
        if access:
            for kept in (_PAT, _PMT):
                p = kept.copy()
                p[3] = 0x10 | tables % 16
                blocks.append(p)
            tables += 1
        pes = b"\x00\x00\x01" + bytes([PRIVATE_STREAM_1]) + (len(part) + 8).to_bytes(2, "big") + b"\x84\x80\x05" + _timestamp(pts) + part
        field = b"\x07\x50" + (pts << 15 | 0x7E00).to_bytes(6, "big") if access else b""
        room = PACKET - 4 - len(field)
        rest = max(0, len(pes) - room)
        n = 1 + -(-rest // (PACKET - 4))
        out = np.full((n, PACKET), 0xFF, np.uint8)
        out[:, 0], out[:, 1], out[:, 2] = SYNC, ES_PID >> 8, ES_PID & 0xFF
        out[0, 1] |= 0x40
        out[:, 3] = 0x10 | (cc + np.arange(n)) % 16
        data = np.frombuffer(pes, np.uint8)
        whole = n - 1 if n > 1 else 0
        if n > 1:
            out[0, 4 + len(field) :] = data[:room]
            if whole > 1:
                out[1:whole, 4:] = data[room : room + (whole - 1) * (PACKET - 4)].reshape(-1, PACKET - 4)
        if field:
            out[0, 4 : 4 + len(field)] = np.frombuffer(field, np.uint8)
            out[0, 3] |= 0x20
        tail = data if n == 1 else data[room + (n - 2) * (PACKET - 4) :]
        lead = len(field) if n == 1 else 0
        gap = PACKET - 4 - lead - len(tail)
        if gap:
            out[-1, 3] |= 0x20
            if lead:
                out[-1, 4] += gap
            else:
                out[-1, 4] = gap - 1
                if gap > 1:
                    out[-1, 5] = 0
        out[-1, PACKET - len(tail) :] = tail
        blocks.append(out.reshape(-1))
        cc += n
    return np.concatenate(blocks).tobytes()


@dataclass
class Stream:
    payload: bytes
    pts: list[int]
    position: list[int]
    access: list[int]
    gaps: int
    packets: int
    pids: int
    repeated: int = 0
    damaged: int = 0
    marked: int = 0  # discontinuities that the writer announces


@dataclass
class Packets:
    """The packets of a stream with their header fields."""

    raw: np.ndarray
    pid: np.ndarray
    first: np.ndarray
    field: np.ndarray
    data: np.ndarray
    start: np.ndarray

    @classmethod
    def of(cls, media: bytes) -> Packets:
        if not media or len(media) % PACKET:
            raise ValueError("no whole number of packets")
        p = np.frombuffer(media, np.uint8).reshape(-1, PACKET)
        if (p[:, 0] != SYNC).any():
            raise ValueError("sync byte missing")
        pid = (p[:, 1].astype(np.int32) & 0x1F) << 8 | p[:, 2]
        field = p[:, 3] & 0x20 > 0
        start = np.minimum(4 + np.where(field, p[:, 4].astype(np.int32) + 1, 0), PACKET)
        return cls(p, pid, p[:, 1] & 0x40 > 0, field, p[:, 3] & 0x10 > 0, start)

    def flags(self, rows: np.ndarray) -> np.ndarray:
        """The flags of the adaptation fields; 0 without one."""
        return np.where(self.field[rows] & (self.raw[rows, 4] > 0), self.raw[rows, 5], 0)


def _continuity(p: Packets, whole: np.ndarray) -> tuple[np.ndarray, int, int, int]:
    """(packets to read, gaps, packets sent twice, marked discontinuities) from the counters of each PID."""
    keep, gaps, twice, marked = whole.copy(), 0, 0, 0
    for one in np.unique(p.pid[whole & (p.pid != NULL_PID)]):
        rows = np.flatnonzero(whole & (p.pid == one) & p.data)
        if len(rows) < 2:
            continue
        step = np.diff((p.raw[rows, 3] & 0x0F).astype(np.int32)) % 16
        announced = p.flags(rows)[1:] & 0x80 > 0
        same = np.zeros(len(step), bool)
        for i in np.flatnonzero((step == 0) & ~announced):
            a, b = rows[i], rows[i + 1]
            same[i] = p.start[a] == p.start[b] and (p.raw[a, p.start[a] :] == p.raw[b, p.start[b] :]).all() and not (i and same[i - 1])
        keep[rows[1:][same]] = False
        twice += int(same.sum())
        marked += int((announced & (step != 1)).sum())
        gaps += int(((step != 1) & ~same & ~announced).sum())
    return keep, gaps, twice, marked


def sections(p: Packets, rows: np.ndarray) -> tuple[list[bytes], int]:
    """The whole sections of a PID, taken together over its packets, and how many are damaged (by length or CRC)."""
    out, damaged, held = [], 0, None

    def cut(raw: bytearray) -> bytearray:
        nonlocal damaged
        while len(raw) >= 3 and raw[0] != 0xFF:
            size = 3 + (int.from_bytes(raw[1:3], "big") & 0x0FFF)
            if len(raw) < size:
                return raw
            if size < 12 or section_crc(bytes(raw[:size])):
                damaged += 1
            else:
                out.append(bytes(raw[:size]))
            del raw[:size]
        return raw if raw and raw[0] != 0xFF else bytearray()

    for r in rows:
        raw = p.raw[r, p.start[r] :].tobytes()
        if p.first[r]:
            if not raw:
                continue
            pointer = raw[0]
            if held is not None and held:
                held = cut(held + raw[1 : 1 + pointer])
                damaged += bool(held)
            held = cut(bytearray(raw[1 + pointer :]))
        elif held:
            held = cut(held + raw)
    return out, damaged + bool(held)


def _table(found: list[bytes], table_id: int) -> list[bytes]:
    """The bodies of the last version of a table that is in force, in the order of its sections."""
    now = [x for x in found if x[0] == table_id and x[5] & 1]
    if not now:
        return []
    version = now[-1][5] >> 1 & 0x1F
    last = {x[6]: x for x in now if x[5] >> 1 & 0x1F == version}
    return [last[k][8:-4] for k in sorted(last)]


def programs(media: bytes) -> dict[int, list[tuple[int, int]]]:
    """Program number -> (PID, stream type) of its elementary streams."""
    return _tables(p := Packets.of(media), _sound(p))[0]


def _sound(p: Packets) -> np.ndarray:
    return (p.raw[:, 1] & 0x80 == 0) & (p.start < PACKET + (~p.data))


def _tables(p: Packets, keep: np.ndarray) -> tuple[dict[int, list[tuple[int, int]]], int]:
    where = lambda which: np.flatnonzero(keep & (p.pid == which) & p.data)
    found, damaged = sections(p, where(PAT_PID))
    maps = {}
    for body in _table(found, 0x00):
        for i in range(0, len(body) - 3, 4):
            if number := int.from_bytes(body[i : i + 2], "big"):
                maps[number] = int.from_bytes(body[i + 2 : i + 4], "big") & 0x1FFF
    if not maps:
        raise ValueError("no association table")
    out: dict[int, list[tuple[int, int]]] = {}
    for number, pid in maps.items():
        found, bad = sections(p, where(pid))
        damaged += bad
        for body in _table([x for x in found if int.from_bytes(x[3:5], "big") == number], 0x02):
            i = 4 + (int.from_bytes(body[2:4], "big") & 0x0FFF)
            while i + 5 <= len(body):
                out.setdefault(number, []).append((int.from_bytes(body[i + 1 : i + 3], "big") & 0x1FFF, body[i]))
                i += 5 + (int.from_bytes(body[i + 3 : i + 5], "big") & 0x0FFF)
    if not out:
        raise ValueError("no program map")
    return out, damaged


def unpack(media: bytes, program: int | None = None, pid: int | None = None) -> Stream:
    """Payload, timestamps and random-access points of an elementary stream: that of `pid`, or the first of `program`
    (None: the least program number with a map)."""
    p = Packets.of(media)
    sound = _sound(p)
    keep, gaps, twice, marked = _continuity(p, sound)
    known, bad = _tables(p, keep)
    if program is not None and program not in known:
        raise ValueError(f"no program {program}")
    streams = [x for x, _ in known[min(known) if program is None else program]]
    if pid is not None and pid not in streams:
        raise ValueError(f"no stream {pid} in the program")
    rows = np.flatnonzero(keep & (p.pid == (streams[0] if pid is None else pid)) & p.data)
    if (p.raw[rows, 3] & 0xC0).any():
        raise ValueError("scrambled packets")
    own, begin = p.raw[rows], p.start[rows]
    data = own[np.arange(PACKET) >= begin[:, None]]
    ends = np.cumsum(PACKET - begin)
    heads = np.flatnonzero(p.first[rows])
    opens = ends[heads] - (PACKET - begin[heads])
    closes = np.append(opens[1:], len(data))
    random_access = p.flags(rows) & 0x40 > 0
    out, pts, position, access, size = [], [], [], [], 0
    for h, a, b in zip(heads, opens, closes):
        pes = data[a:b].tobytes()
        if pes[:3] != b"\x00\x00\x01":
            raise ValueError("no packet start code")
        length, t, skip = int.from_bytes(pes[4:6], "big"), pes[9:14], 9 + pes[8]
        if pes[7] & 0x80:
            pts.append((t[0] & 0x0E) << 29 | t[1] << 22 | (t[2] & 0xFE) << 14 | t[3] << 7 | t[4] >> 1)
            position.append(size)
            if random_access[h]:
                access.append(len(pts) - 1)
        out.append(pes[skip : 6 + length if length else None])
        size += len(out[-1])
    return Stream(b"".join(out), pts, position, access, gaps, len(p.raw), len(np.unique(p.pid)), twice, int((~sound).sum()) + bad, marked)


def padded(text: bytes, block: int = 64) -> bytes:
    return text.ljust(max(block, -(-len(text) // block) * block), b"\0")


def write_media(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media BINARY: each whole text as a transport stream."""
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("media", pa.binary())])

    def run(batches):
        for b in batches:
            for i in range(0, b.num_rows, 1_000):
                part = b.slice(i, 1_000)
                raw = [(x.as_py() or "").encode() for x in part.column("text")]
                yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(map(len, raw), pa.int64()), pa.array([pack(padded(x)) for x in raw], pa.binary())], schema=schema)

    return texts(docs).mapInArrow(lean(run), "doc_id long, n_bytes long, media binary")


FEATURES = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, pts array<long>, unit_position array<long>, access_points array<int>, continuity_errors int"


def read_media(stored: DataFrame) -> DataFrame:
    """Reads media back: digests of payload and media, timestamps, unit positions, access points."""
    schema = pa.schema(
        [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())]
        + [("pts", pa.list_(pa.int64())), ("unit_position", pa.list_(pa.int64())), ("access_points", pa.list_(pa.int32())), ("continuity_errors", pa.int32())]
    )

    def run(batches):
        for b in batches:
            got: list[list] = [[] for _ in range(10)]
            for m in b.column("media"):
                media = m.as_py()
                s = unpack(media)
                row = (
                    len(s.payload), hashlib.sha256(s.payload).hexdigest(), zlib.crc32(s.payload[-64:]), len(media), hashlib.sha256(media).hexdigest(),
                    f"packets={s.packets};pids={s.pids};units={len(s.pts)};first_pts={s.pts[0]};last_pts={s.pts[-1]};access={','.join(map(str, s.access))};gaps={s.gaps}",
                    s.pts, s.position, s.access, s.gaps,
                )
                for column, value in zip(got, row):
                    column.append(value)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("n_bytes"), *(pa.array(v, f.type) for v, f in zip(got, list(schema)[2:]))], schema=schema)

    return stored.select("doc_id", "n_bytes", "media").mapInArrow(lean(run), FEATURES)
