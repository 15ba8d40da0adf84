import hashlib
import random

from graphparts.llm import media_ts as m


def test_round_trip_of_every_length():
    r = random.Random(1)
    for n in [*range(0, 400), 4095, 4096, 4097, 40_000]:
        payload = m.padded(r.randbytes(n)) if n % 3 else r.randbytes(n + 1)
        data = m.mux(payload)
        s = m.demux(data)
        assert s.payload[m.DATA_PID] == payload and len(data) % 188 == 0
        assert (s.counter_errors, s.table_errors, s.skipped) == (0, 0, 0) and all(u.complete for u in s.units)


def test_timestamps_and_points():
    s = m.demux(m.mux(bytes(m.UNIT * 20)))
    assert [u.pts for u in s.units] == [n * m.UNIT_TICKS for n in range(20)]
    assert [n for n, u in enumerate(s.units) if u.random_access] == [0, 8, 16]
    assert [u.offset for u in s.units] == [n * m.UNIT for n in range(20)]
    assert s.programs == {1: m.PMT_PID} and s.streams == {m.DATA_PID: m.STREAM_TYPE} and s.clocks == 3


def test_damage_is_seen():
    data = m.mux(random.Random(2).randbytes(20_000))
    lost = m.demux(data[: 188 * 9] + data[188 * 10 :])
    assert lost.counter_errors == 1 and sum(not u.complete for u in lost.units) == 1
    twice = m.demux(data[: 188 * 10] + data[188 * 9 :])
    assert twice.counter_errors == 0 and twice.payload == m.demux(data).payload
    noisy = m.demux(b"\x01\x02" + data + b"\x47\x00")
    assert noisy.skipped == 4 and noisy.payload == m.demux(data).payload
    broken = bytearray(data)
    broken[10] ^= 1
    assert m.demux(bytes(broken)).table_errors == 1
    assert m.demux(b"").units == []


def test_checksum_known_value():
    assert m.section_crc(b"123456789") == 0x0376E6E7


def test_query_digests(spark):
    texts = [None, "", "a" * 64, "ñ" * 5000, "a" * 64]
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id bigint, text string, feature string")
    rows = sorted(m.media_digests(df).collect())
    for r, t in zip(rows, texts, strict=True):
        p = m.padded((t or "").encode())
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (len((t or "").encode()), len(p), hashlib.sha256(p).hexdigest())
        assert len(p) % 64 == 0 and p
    assert rows[2][1:] == rows[4][1:]
    assert m.media_digests(df.limit(0)).collect() == []
    full = m.with_media(df).collect()
    assert {hashlib.sha256(r.media).hexdigest() for r in full} == {r.media_sha256 for r in rows} and full[0].text == texts[full[0].doc_id]


def packets(pid, body, counter=0):
    """``body`` cut into packets of one pid, the last filled by an adaptation field."""
    out, first = b"", True
    while body or first:
        part, body = body[:184], body[184:]
        fill = 184 - len(part)
        field = b"" if not fill else bytes([fill - 1]) + (b"\0" + b"\xff" * (fill - 2) if fill > 1 else b"")
        out += bytes([0x47, (0x40 if first else 0) | pid >> 8, pid & 255, (0x30 if field else 0x10) | counter & 15]) + field + part
        counter, first = counter + 1, False
    return out


def section(table, number, body):
    head = bytes([table, 0xB0 | (len(body) + 9) >> 8, (len(body) + 9) & 255, number >> 8, number & 255, 0xC1, 0, 0]) + body
    c = 0xFFFFFFFF
    for b in head:  # bit by bit, apart from the table of the module
        for k in range(7, -1, -1):
            top = (c >> 31) ^ (b >> k & 1)
            c = (c << 1) & 0xFFFFFFFF ^ (0x04C11DB7 if top else 0)
    return head + c.to_bytes(4, "big")


def test_another_writer_with_long_tables_and_two_streams():
    streams = {0x200 + k: 0x1B if k % 2 else 0x0F for k in range(60)}
    pmt = (0xE200).to_bytes(2, "big") + b"\xf0\x00" + b"".join(bytes([t]) + (0xE000 | p).to_bytes(2, "big") + b"\xf0\x03\x0a\x01\x65" for p, t in streams.items())
    pat = b"".join(n.to_bytes(2, "big") + (0xE000 | 0x100 + n).to_bytes(2, "big") for n in (0, 1, 7))
    data = packets(0, b"\0" + section(0, 1, pat)) + packets(0x101, b"\0" + section(2, 1, pmt)) + packets(0x107, b"\0" + section(2, 7, b"\xe3\x00\xf0\x00") + section(2, 7, b"\xe3\x00\xf0\x00\x06\xe3\x00\xf0\x00") + b"\xff" * 9)
    assert len(section(2, 1, pmt)) > 2 * 184
    pes = lambda body, pts: b"\0\0\1\xe0" + (8 + len(body)).to_bytes(2, "big") + b"\x80\x80\x05" + m._stamp(2, pts) + body
    data += packets(0x200, pes(b"a" * 300, 9)) + packets(0x201, pes(b"b" * 7, 2**33 - 1)) + packets(0x200, pes(b"c", 10), 2)
    s = m.demux(data)
    assert s.programs == {1: 0x101, 7: 0x107} and s.streams == streams | {0x300: 6} and (s.table_errors, s.counter_errors) == (0, 0)
    assert s.payload == {0x200: b"a" * 300 + b"c", 0x201: b"b" * 7}
    assert sorted((u.pid, u.pts, u.offset, u.length) for u in s.units) == [(0x200, 9, 0, 300), (0x200, 10, 300, 1), (0x201, 2**33 - 1, 0, 7)]
    cut = data[: 188 * 2] + data[188 * 3 :]  # one packet of the long table is lost
    assert m.demux(cut).table_errors >= 1


def plain_payload(data):
    """The data stream's bytes by a reader that knows this one layout only."""
    out = b""
    for at in range(0, len(data), 188):
        p = data[at : at + 188]
        if ((p[1] & 31) << 8 | p[2]) != m.DATA_PID:
            continue
        body = p[5 + p[4] :] if p[3] & 0x20 else p[4:]
        out += body[14:] if p[1] & 0x40 else body
    return out


def test_stored_columns_against_a_plain_reader(spark):
    texts = [None, "", "ab", "long text " * 200_000, "long text " * 200_000]
    df = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)], "doc_id bigint, text string, media_units int")
    for r in m.with_media(df).collect():
        want = m.padded((texts[r.doc_id] or "").encode())
        assert plain_payload(r.media) == want
        assert [u.offset for u in r.media_units] == list(range(0, len(want), m.UNIT)) and sum(u.length for u in r.media_units) == len(want)
    got = {r.doc_id: r for r in m.media_digests(df).collect()}
    assert got[3][1:] == got[4][1:] and got[3].n_units == -(-got[3].payload_bytes // m.UNIT) and got[3].n_points == -(-got[3].n_units // m.UNITS_PER_POINT)
