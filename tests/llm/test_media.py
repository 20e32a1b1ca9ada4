"""Transport streams: exact round trips, fields of the format, damage."""

from __future__ import annotations

import hashlib
import random
import zlib

import pytest

from rangegraph.llm import transport_stream as ts


@pytest.mark.parametrize("size", [*range(0, 400), 1_000, 16_383, 16_384, 16_385, 65_536, 200_001])
def test_round_trip(size):
    data = random.Random(size).randbytes(size)
    media = ts.pack(data)
    s = ts.unpack(media)
    assert s.payload == data and s.gaps == 0 and len(media) % 188 == 0
    units = max(1, -(-size // ts.UNIT))
    assert s.pts == [k * ts.UNIT_TICKS for k in range(units)]
    assert s.position == [k * ts.UNIT for k in range(units)]
    assert s.access == list(range(0, units, ts.ACCESS_EVERY))


def test_format():
    media = ts.pack(b"x" * 1_000)
    assert ts.section_crc(b"123456789") == 0x0376E6E7  # the check value of this CRC
    packets = [media[i : i + 188] for i in range(0, len(media), 188)]
    assert all(p[0] == 0x47 for p in packets)
    assert [(p[1] & 0x1F) << 8 | p[2] for p in packets[:3]] == [0, ts.PMT_PID, ts.ES_PID]
    assert packets[2][5] & 0x40  # random access
    for size in range(150, 400):  # packets end with their payload whatever has to be stuffed
        assert len(ts.pack(b"y" * size)) % 188 == 0


def test_large_timestamps():
    for t in (0, 1, 2**15, 2**30 - 1, 2**32, 2**33 - 1):
        b = ts._timestamp(t)
        assert ((b[0] & 0x0E) << 29 | b[1] << 22 | (b[2] & 0xFE) << 14 | b[3] << 7 | b[4] >> 1) == t


def test_damage():
    media = ts.pack(random.Random(1).randbytes(5_000))
    lost = media[: 188 * 5] + media[188 * 6 :]
    assert ts.unpack(lost).gaps == 1
    for broken in (b"", media[:-1], b"\x00" + media[1:], media[:20] + b"\xff" + media[21:], media[188 * 2 :]):
        with pytest.raises(ValueError):
            ts.unpack(broken)


def packets_of(media):
    return [bytearray(media[i : i + 188]) for i in range(0, len(media), 188)]


def test_packets_sent_twice_announced_jumps_and_marked_damage():
    data = random.Random(2).randbytes(120_000)
    plain = packets_of(ts.pack(data))
    twice = [q for i, p in enumerate(plain) for q in ([p, p] if i % 7 == 3 and p[1] & 0x1F == 1 else [p])]
    s = ts.unpack(b"".join(map(bytes, twice)))
    assert s.payload == data and s.gaps == 0 and s.repeated == len(twice) - len(plain) > 3
    # the writer announces a jump of the counter
    jump, own = [bytearray(p) for p in plain], 0
    at = [i for i, p in enumerate(jump) if (p[1] & 0x1F) << 8 | p[2] == ts.ES_PID and p[1] & 0x40 and p[3] & 0x20][1]
    for p in jump[at:]:
        if (p[1] & 0x1F) << 8 | p[2] == ts.ES_PID:
            p[3] = p[3] & 0xF0 | (p[3] + 5) & 0x0F
            own += 1
    jump[at][5] |= 0x80
    s = ts.unpack(b"".join(map(bytes, jump)))
    assert own and s.payload == data and (s.gaps, s.marked) == (0, 1)
    # a packet marked as damaged is left out, and leaves a gap
    hurt = [bytearray(p) for p in plain]
    hurt[10][1] |= 0x80
    s = ts.unpack(b"".join(map(bytes, hurt)))
    assert s.damaged == 1 and s.gaps == 1 and len(s.payload) < len(data)
    scrambled = [bytearray(p) for p in plain]
    for p in scrambled[2:]:
        p[3] |= 0x80
    with pytest.raises(ValueError):
        ts.unpack(b"".join(map(bytes, scrambled)))


def table_packets(pid, raw, counter=0):
    """Sections that may be longer than a packet."""
    raw, out = b"\x00" + raw, []
    for i in range(0, len(raw), 184):
        head = bytes([0x47, (0x40 if i == 0 else 0) | pid >> 8, pid & 0xFF, 0x10 | (counter + i // 184) % 16])
        out.append(head + raw[i : i + 184].ljust(184, b"\xff"))
    return out


def test_long_tables_versions_and_several_programs():
    """Two programs; the map of one has descriptors over three packets and a newer version that names another stream."""
    one, two = (random.Random(k).randbytes(3_000) for k in (3, 4))
    streams = {0x200: packets_of(ts.pack(one))[2:], 0x300: packets_of(ts.pack(two))[2:]}
    for pid, own in streams.items():
        for p in own:
            p[1], p[2] = p[1] & 0xE0 | pid >> 8, pid & 0xFF
    entry = lambda number, pid: number.to_bytes(2, "big") + (0xE000 | pid).to_bytes(2, "big")
    pat = ts._section(0x00, 1, entry(0, 0x10) + entry(7, 0x1001) + entry(9, 0x1002))

    def pmt(number, pid, descriptors, version=0):
        body = (0xE000 | pid).to_bytes(2, "big") + (0xF000 | len(descriptors)).to_bytes(2, "big") + descriptors + bytes([6]) + (0xE000 | pid).to_bytes(2, "big") + b"\xf0\x00"
        raw = bytearray(ts._section(0x02, number, body)[:-4])
        raw[5] = raw[5] & 0xC1 | version << 1
        return bytes(raw) + ts.section_crc(bytes(raw)).to_bytes(4, "big")

    long = b"".join(bytes([0x80 + k % 100, 18]) + bytes(18) for k in range(20))
    packets = table_packets(0, pat) + table_packets(0x1001, pmt(7, 0x300, long)) + table_packets(0x1002, pmt(9, 0x300, b""))
    packets += table_packets(0x1001, pmt(7, 0x200, long, 1), 3) + table_packets(0, pat, 1) + [bytes(p) for own in zip(*streams.values()) for p in own]
    media = b"".join(packets)
    assert ts.programs(media) == {7: [(0x200, 6)], 9: [(0x300, 6)]}
    assert ts.unpack(media).payload == one == ts.unpack(media, 7).payload and ts.unpack(media, 9).payload == two
    assert ts.unpack(media).gaps == 0
    for wrong in ({"program": 8}, {"program": 7, "pid": 0x300}):
        with pytest.raises(ValueError):
            ts.unpack(media, **wrong)
    hurt = bytearray(media)
    hurt[188 + 100] ^= 1  # in the first map of program 7; its second version still holds
    assert ts.unpack(bytes(hurt)).payload == one and ts.unpack(bytes(hurt)).damaged == 1


def test_frames(spark):
    rows = [(1, "abc", 5), (2, None, 5), (3, "", 5), (4, "ü" * 40_000, 5), (1, "abc", 6), (5, "a" * 64, 5), (None, "x", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, media long")
    got = ts.read_media(ts.write_media(df)).collect()
    assert len(got) == len(rows)
    texts = {r[0]: (r[1] or "").encode() for r in rows}
    for r in got:
        raw = texts[r.doc_id]
        payload = raw.ljust(max(64, -(-len(raw) // 64) * 64), b"\0")
        assert (r.n_bytes, r.payload_bytes) == (len(raw), len(payload))
        assert r.payload_sha256 == hashlib.sha256(payload).hexdigest() and r.tail_crc32 == zlib.crc32(payload[-64:])
        media = ts.pack(payload)
        assert (r.media_bytes, r.media_sha256) == (len(media), hashlib.sha256(media).hexdigest())
        assert r.continuity_errors == 0
    same = [r for r in got if r.doc_id in (2, 3)]
    assert same[0].feature == same[1].feature and same[0].media_sha256 == same[1].media_sha256
    assert ts.read_media(ts.write_media(df.where("false"))).count() == 0
