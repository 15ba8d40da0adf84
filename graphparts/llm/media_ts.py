"""Media columns in MPEG transport streams.

``mux`` stores a payload as 188-byte transport packets: program association and map
tables, then packetised elementary stream (PES) units with presentation timestamps, clock
references and random-access marks. ``demux`` reads such streams back, those of other writers
included: it joins tables that span packets, verifies their checksums, follows continuity counters,
reassembles the elementary packets of every stream and lists their timestamps and random-access
points. Not read: packets of other lengths than 188 bytes, scrambled payloads, and tables other than
the program association and map tables.

Defined results: a null text is the empty text; an empty payload is stored as 64 zero
bytes; equal texts give equal bytes. Bytes that are no packet are skipped up to the next
sync byte and counted; a unit whose continuity broke is returned and marked incomplete; a table cut short
is counted as an error. Repeated rows get a stream each; an empty table gives an empty table; other columns
pass :func:`with_media`, where columns named like its results are replaced; a very long text is one long stream.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.llm.common import crc32, mapped, utf8, written

# Fixed values of the format.
PACKET, SYNC, BODY = 188, 0x47, 184
PAT_PID, NULL_PID = 0x0000, 0x1FFF
CLOCK = 90_000

# Choices of this writer.
PMT_PID, DATA_PID, PROGRAM, STREAM_TYPE, STREAM_ID = 0x1000, 0x0100, 1, 0x06, 0xBD
UNIT, UNIT_TICKS, UNITS_PER_POINT = 4096, CLOCK // 25, 8


def _section_crc_table() -> list[int]:
    out = []
    for byte in range(256):
        c = byte << 24
        for _ in range(8):
            c = ((c << 1) ^ 0x04C11DB7 if c & 0x80000000 else c << 1) & 0xFFFFFFFF
        out.append(c)
    return out


_CRC = _section_crc_table()


def section_crc(data: bytes) -> int:
    c = 0xFFFFFFFF
    for b in data:
        c = ((c << 8) & 0xFFFFFFFF) ^ _CRC[(c >> 24) ^ b]
    return c


def _section(table_id: int, number: int, body: bytes) -> bytes:
    length = 5 + len(body) + 4
    head = bytes([table_id, 0xB0 | length >> 8, length & 255, number >> 8, number & 255, 0xC1, 0, 0]) + body
    return head + section_crc(head).to_bytes(4, "big")


def _table_packet(pid: int, counter: int, section: bytes) -> bytes:
    return bytes([SYNC, 0x40 | pid >> 8, pid & 255, 0x10 | counter & 15, 0]) + section + b"\xff" * (BODY - 1 - len(section))


_PAT = _section(0, 1, PROGRAM.to_bytes(2, "big") + (0xE000 | PMT_PID).to_bytes(2, "big"))
_PMT = _section(2, PROGRAM, (0xE000 | DATA_PID).to_bytes(2, "big") + b"\xf0\x00" + bytes([STREAM_TYPE]) + (0xE000 | DATA_PID).to_bytes(2, "big") + b"\xf0\x00")


def _stamp(mark: int, t: int) -> bytes:
    return bytes([mark << 4 | (t >> 29 & 14) | 1, t >> 22 & 255, (t >> 14 & 254) | 1, t >> 7 & 255, (t << 1 & 254) | 1])


def _unstamp(b: bytes) -> int:
    return (b[0] >> 1 & 7) << 30 | b[1] << 22 | (b[2] >> 1) << 15 | b[3] << 7 | b[4] >> 1


def mux(payload: bytes) -> bytes:
    """``payload`` as a transport stream of one program with one private data stream."""
    out, counter, tables = [], 0, 0
    for n, at in enumerate(range(0, len(payload), UNIT)):
        data = payload[at : at + UNIT]
        ticks = n * UNIT_TICKS % (1 << 33)
        point = n % UNITS_PER_POINT == 0
        if point:
            out += _table_packet(PAT_PID, tables, _PAT), _table_packet(PMT_PID, tables, _PMT)
            tables += 1
        unit = b"\0\0\1" + bytes([STREAM_ID]) + (8 + len(data)).to_bytes(2, "big") + b"\x80\x80\x05" + _stamp(2, ticks) + data
        place = 0
        while place < len(unit):
            field_ = b""
            if point and not place:  # random access, with the clock reference
                field_ = b"\x50" + (ticks << 15 | 0x3F << 9).to_bytes(6, "big")
            room = BODY - (1 + len(field_) if field_ else 0)
            left = len(unit) - place
            if left < room:
                fill = BODY - left - 1
                field_ = field_ or (b"\0" if fill else b"")
                field_ += b"\xff" * (fill - len(field_))
                adapted = bytes([fill]) + field_
            else:
                adapted = bytes([len(field_)]) + field_ if field_ else b""
            take = BODY - len(adapted)
            out.append(bytes([SYNC, (0 if place else 0x40) | DATA_PID >> 8, DATA_PID & 255, (0x30 if adapted else 0x10) | counter]) + adapted + unit[place : place + take])
            counter = (counter + 1) & 15
            place += take
    return b"".join(out)


@dataclass
class Unit:
    """One reassembled elementary packet; ``offset`` is its place in the stream's payload."""

    pid: int
    pts: int | None
    dts: int | None
    offset: int
    length: int
    random_access: bool
    complete: bool


@dataclass
class Stream:
    programs: dict[int, int] = field(default_factory=dict)  # number -> map table's pid
    streams: dict[int, int] = field(default_factory=dict)  # pid -> type
    packets: int = 0
    skipped: int = 0
    counter_errors: int = 0
    table_errors: int = 0
    clocks: int = 0
    units: list[Unit] = field(default_factory=list)
    payload: dict[int, bytes] = field(default_factory=dict)


def _tables(s: Stream, pid: int, section: bytes) -> None:
    if len(section) < 12:
        s.table_errors += 1
        return
    end = 3 + ((section[1] & 15) << 8 | section[2])
    if end > len(section) or section_crc(section[:end]):
        s.table_errors += 1
        return
    body = section[8 : end - 4]
    if pid == PAT_PID and section[0] == 0:
        for i in range(0, len(body) - 3, 4):
            if number := body[i] << 8 | body[i + 1]:
                s.programs[number] = (body[i + 2] & 31) << 8 | body[i + 3]
    elif section[0] == 2 and len(body) >= 4:
        i = 4 + ((body[2] & 15) << 8 | body[3])
        while i + 5 <= len(body):
            s.streams[(body[i + 1] & 31) << 8 | body[i + 2]] = body[i]
            i += 5 + ((body[i + 3] & 15) << 8 | body[i + 4])


def demux(data: bytes) -> Stream:
    """Read a transport stream of 188-byte packets back; tables may span packets, and packets may hold several."""
    s = Stream()
    counters: dict[int, int] = {}
    pending: dict[int, list] = {}  # pid -> [parts, random access, whole so far]
    parts: dict[int, list[bytes]] = {}
    sizes: dict[int, int] = {}
    previous: dict[int, bytes] = {}
    sections: dict[int, bytearray] = {}  # pid -> what has come of an unfinished table

    def table_bytes(pid: int, body: bytes, begins: bool) -> None:
        """Add a packet's body to the tables of ``pid``; every complete one is read."""
        if begins and body:
            if pid in sections:
                sections[pid] += body[1 : 1 + body[0]]
                whole(pid)
                if sections.pop(pid, None):
                    s.table_errors += 1  # it ended before its length
            sections[pid] = bytearray(body[1 + body[0] :])
        elif pid in sections:
            sections[pid] += body
        whole(pid)

    def whole(pid: int) -> None:
        held = sections.get(pid)
        while held:
            if held[0] == 0xFF:  # stuffing up to the next table
                break
            if len(held) < 3 or len(held) < (end := 3 + ((held[1] & 15) << 8 | held[2])):
                return
            _tables(s, pid, bytes(held[:end]))
            del held[:end]
        sections.pop(pid, None)

    def close(pid: int) -> None:
        if pid not in pending:
            return
        pieces, point, whole = pending.pop(pid)
        unit = b"".join(pieces)
        if len(unit) < 6 or unit[:3] != b"\0\0\1":
            s.counter_errors += 1
            return
        declared = unit[4] << 8 | unit[5]
        head, pts, dts = 6, None, None
        if len(unit) >= 9 and unit[6] & 0xC0 == 0x80:
            head = 9 + unit[8]
            if unit[7] & 0x80 and len(unit) >= 14:
                pts = dts = _unstamp(unit[9:14])
            if unit[7] & 0xC0 == 0xC0 and len(unit) >= 19:
                dts = _unstamp(unit[14:19])
        end = 6 + declared if declared else len(unit)
        body = unit[head:end]
        s.units.append(Unit(pid, pts, dts, sizes.get(pid, 0), len(body), point, whole and end <= len(unit)))
        parts.setdefault(pid, []).append(body)
        sizes[pid] = sizes.get(pid, 0) + len(body)

    at, n = 0, len(data)
    while at + PACKET <= n:
        if data[at] != SYNC:
            found = data.find(b"\x47", at + 1)
            step = (found if found >= 0 else n) - at
            s.skipped += step
            at += step
            continue
        b1, b3 = data[at + 1], data[at + 3]
        pid = (b1 & 31) << 8 | data[at + 2]
        control, counter = b3 >> 4 & 3, b3 & 15
        s.packets += 1
        start, point, jump = at + 4, False, False
        if control & 2:
            length = data[start]
            if length:
                flags = data[start + 1]
                point, jump = bool(flags & 0x40), bool(flags & 0x80)
                s.clocks += flags >> 4 & 1
            start += 1 + length
        stop = at + PACKET
        at = stop
        if pid == NULL_PID or not control & 1:
            continue
        last = counters.get(pid)
        if last is not None and not jump and counter != (last + 1) & 15:
            if counter == last and previous.get(pid) == data[stop - PACKET : stop]:
                continue  # the format allows a packet to be sent twice
            s.counter_errors += 1
            if pid in pending:
                pending[pid][2] = False
            if sections.pop(pid, None):
                s.table_errors += 1
        counters[pid] = counter
        previous[pid] = data[stop - PACKET : stop]
        body = data[start:stop]
        if pid == PAT_PID or pid in s.programs.values():
            table_bytes(pid, body, bool(b1 & 0x40))
            continue
        if b1 & 0x40:
            close(pid)
            pending[pid] = [[body], point, True]
        elif pid in pending:
            pending[pid][0].append(body)
    s.skipped += n - at
    s.table_errors += len(sections)
    for pid in list(pending):
        close(pid)
    s.payload = {pid: b"".join(p) for pid, p in parts.items()}
    return s


def padded(raw: bytes) -> bytes:
    """``raw`` with zero bytes up to a positive multiple of 64."""
    return raw + bytes(-len(raw) % 64 if raw else 64)


def feature(s: Stream) -> str:
    """What the container tells about its content, as one line."""
    points = [u for u in s.units if u.random_access]
    stamps = [u.pts for u in s.units if u.pts is not None]
    return ";".join(
        [
            "programs=" + ",".join(f"{a}:{b}" for a, b in sorted(s.programs.items())),
            "streams=" + ",".join(f"{a}:{b}" for a, b in sorted(s.streams.items())),
            f"packets={s.packets}",
            f"units={len(s.units)}",
            f"incomplete={sum(not u.complete for u in s.units)}",
            f"counter_errors={s.counter_errors}",
            f"table_errors={s.table_errors}",
            f"clocks={s.clocks}",
            f"pts={min(stamps)}-{max(stamps)}" if stamps else "pts=",
            f"points={len(points)}",
        ]
    )


_UNITS = "array<struct<pid:int,pts:bigint,dts:bigint,offset:bigint,length:bigint,random_access:boolean,complete:boolean>>"


def with_media(df: DataFrame, text: str = "text", carry: list[str] | None = None) -> DataFrame:
    """Every row with ``media`` (the stored stream) and ``media_units`` (timestamps and random-access points).

    ``carry`` names the columns that stay, all by default. Columns named like the results are replaced.
    """
    keep = [c for c in (df.columns if carry is None else carry) if c not in ("media", "media_units")]
    read = list(dict.fromkeys([*keep, text]))
    kept = df.select(*(F.col(f"`{c}`") for c in read))
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema if f.name in keep), "media binary", f"media_units {_UNITS}"])

    def run(batch: pa.RecordBatch) -> dict:
        media = [mux(padded(utf8(t))) for t in batch.column(read.index(text)).to_pylist()]
        return {c: batch.column(read.index(c)) for c in keep} | {"media": media, "media_units": [[vars(u) for u in demux(m).units] for m in media]}

    return mapped(kept, run, schema)


def media_digests(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Store every text as a media column with its units, read the stored columns back, and return digests and features."""
    plain = df.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text"))
    plain = plain.withColumn("n_bytes", F.coalesce(F.octet_length("text"), F.lit(0)).cast("bigint"))
    stored = written(with_media(plain, "text", ["doc_id", "n_bytes"]), "media")

    def run(batch: pa.RecordBatch) -> dict:
        out: dict = {k: [] for k in ("payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature")}
        for media in batch.column(2).to_pylist():
            stream = demux(media)
            payload = stream.payload[DATA_PID]
            for k, v in zip(out, (len(payload), hashlib.sha256(payload).hexdigest(), crc32(payload[-64:]), len(media), hashlib.sha256(media).hexdigest(), feature(stream)), strict=True):
                out[k].append(v)
        return {"doc_id": batch.column(0), "n_bytes": batch.column(1), "n_units": batch.column(3), "n_points": batch.column(4), "last_pts": batch.column(5)} | out

    units = F.col("media_units")
    about = [F.size(units).alias("n_units"), F.size(F.filter(units, lambda u: u["random_access"])).alias("n_points"), F.array_max(F.transform(units, lambda u: u["pts"])).alias("last_pts")]
    return mapped(
        stored.select("doc_id", "n_bytes", "media", *about),
        run,
        "doc_id bigint, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string, n_units int, n_points int, last_pts bigint",
    )
