"""MPEG transport streams as a media column: muxing bytes into packets, and demuxing packets back.

A payload becomes one elementary stream of private data: access units of a fixed number of 8-bit samples, each
in one packetised elementary stream (PES) packet with a presentation time, split over 188-byte transport packets
with continuity counters. The program tables open the stream, and access units at a fixed distance are random-access
points that carry a clock reference. The demuxer trusts the tables alone: it finds the program map through the
association table, checks both checksums, follows the elementary stream's counters (a repeated packet is skipped,
a gap is counted), reassembles the packets and returns times, random-access points and samples.

Defined results: null counts as an empty payload; an empty payload gives a stream of tables only unless it is padded;
equal payloads give equal streams; a stream that is cut or damaged yields the units that are whole, with its errors counted.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import ship

# Fixed values of the transport stream format.
PACKET, SYNC, BODY = 188, 0x47, 184
PAT_PID, NULL_PID = 0, 0x1FFF
PRIVATE_STREAM, PRIVATE_PES = 0x06, 0xBD
CLOCK = 90_000
CRC_POLYNOMIAL = 0x04C11DB7

# Choices of this muxer.
PMT_PID, DATA_PID, PROGRAM, STREAM_ID = 0x100, 0x101, 1, 1
RATE = 48_000
UNIT = 4_608
RANDOM_ACCESS_EVERY = 8
PAD_TO, PAD_BYTE = 576, 0xFF


def _crc_table() -> list[int]:
    out = []
    for i in range(256):
        c = i << 24
        for _ in range(8):
            c = (c << 1) ^ CRC_POLYNOMIAL if c & 0x80000000 else c << 1
        out.append(c & 0xFFFFFFFF)
    return out


_CRC = _crc_table()


def section_crc(data: bytes) -> int:
    """The tables' checksum: most significant bit first, starting from all ones."""
    c = 0xFFFFFFFF
    for b in data:
        c = ((c << 8) & 0xFFFFFFFF) ^ _CRC[(c >> 24) ^ b]
    return c


def _section(table: int, ident: int, body: bytes) -> bytes:
    head = bytes([table]) + struct.pack(">HHBBB", 0xB000 | (len(body) + 9), ident, 0xC1, 0, 0) + body
    return head + struct.pack(">I", section_crc(head))


def _table_packet(pid: int, section: bytes) -> bytes:
    data = struct.pack(">BHB", SYNC, 0x4000 | pid, 0x10) + b"\0" + section
    return data.ljust(PACKET, b"\xff")


_TABLES = _table_packet(PAT_PID, _section(0, STREAM_ID, struct.pack(">HH", PROGRAM, 0xE000 | PMT_PID))) + _table_packet(
    PMT_PID, _section(2, PROGRAM, struct.pack(">HH", 0xE000 | DATA_PID, 0xF000) + struct.pack(">BHH", PRIVATE_STREAM, 0xE000 | DATA_PID, 0xF000))
)
_HEADS = [struct.pack(">BHB", SYNC, DATA_PID, 0x10 | c) for c in range(16)]


def _stamp(mark: int, t: int) -> bytes:
    return bytes([mark << 4 | (t >> 29) & 0x0E | 1]) + struct.pack(">HH", (t >> 14) & 0xFFFE | 1, (t << 1) & 0xFFFE | 1)


def _adapted(start: int, counter: int, fields: bytes, data: bytes) -> bytes:
    """One packet with an adaptation field stuffed so that ``data`` ends at the packet's end."""
    room = BODY - len(data)
    area = b"" if room == 1 else (fields or b"\0").ljust(room - 1, b"\xff")
    return struct.pack(">BHBB", SYNC, start << 14 | DATA_PID, 0x30 | counter, room - 1) + area + data


def mux(payload: bytes, unit: int = UNIT, random_access_every: int = RANDOM_ACCESS_EVERY) -> bytes:
    """A single-program transport stream that holds ``payload`` in units of ``unit`` bytes."""
    out, counter = [_TABLES], 0
    for n, at in enumerate(range(0, len(payload), unit)):
        data = payload[at : at + unit]
        time = at * CLOCK // RATE & 0x1FFFFFFFF
        pes = b"\0\0\1" + struct.pack(">BHBBB", PRIVATE_PES, len(data) + 8, 0x84, 0x80, 5) + _stamp(2, time) + data
        fields = b""
        if n % random_access_every == 0:
            fields = b"\x50" + struct.pack(">IH", time >> 1, (time & 1) << 15 | 0x7E00)
        first = min(len(pes), BODY - 1 - len(fields) if fields else BODY)
        out.append(_adapted(1, counter, fields, pes[:first]) if fields or first < BODY else struct.pack(">BHB", SYNC, 0x4000 | DATA_PID, 0x10 | counter) + pes[:first])
        counter = (counter + 1) & 15
        last = first + (len(pes) - first) // BODY * BODY
        for i in range(first, last, BODY):
            out.append(_HEADS[counter] + pes[i : i + BODY])
            counter = (counter + 1) & 15
        if last < len(pes):
            out.append(_adapted(0, counter, b"", pes[last:]))
            counter = (counter + 1) & 15
    return b"".join(out)


@dataclass
class Stream:
    """What a demuxed stream holds: one entry of ``times``, ``sizes`` and ``random_access`` for each unit."""

    payload: bytes = b""
    times: list[int] = field(default_factory=list)
    sizes: list[int] = field(default_factory=list)
    random_access: list[int] = field(default_factory=list)
    packets: int = 0
    gaps: int = 0
    repeats: int = 0
    table_errors: int = 0
    programs: dict[int, int] = field(default_factory=dict)
    stream_types: dict[int, int] = field(default_factory=dict)


def _read_section(data: bytes) -> bytes | None:
    """A section without its checksum; None if it is cut or the checksum is wrong."""
    s = data[1 + data[0] :] if data else b""
    size = 3 + (struct.unpack(">H", s[1:3])[0] & 0xFFF) if len(s) >= 3 else 0
    return s[: size - 4] if 12 <= size <= len(s) and section_crc(s[:size]) == 0 else None


def demux(media: bytes) -> Stream:
    out, maps, wanted = Stream(), set(), set()
    open_: dict[int, list[bytes]] = {}
    marks: dict[int, bool] = {}
    counters: dict[int, int] = {}
    parts: list[bytes] = []

    def finish(pid: int) -> None:
        pes = b"".join(open_.pop(pid, []))
        if len(pes) < 9 or pes[:3] != b"\0\0\1":
            return
        size, head = struct.unpack(">H", pes[4:6])[0], 9 + pes[8]
        data = pes[head : 6 + size] if size else pes[head:]
        if size and len(pes) < 6 + size:
            return
        a, b, c = (pes[9], *struct.unpack(">HH", pes[10:14])) if pes[7] & 0x80 else (0, 0, 0)
        if marks.get(pid):
            out.random_access.append(len(out.times))
        out.times.append((a & 0x0E) << 29 | (b >> 1) << 15 | c >> 1)
        out.sizes.append(len(data))
        parts.append(data)

    for at in range(0, len(media) - PACKET + 1, PACKET):
        if media[at] != SYNC:
            out.table_errors += 1
            continue
        out.packets += 1
        b1, flags = media[at + 1], media[at + 3]
        pid, start = (b1 & 0x1F) << 8 | media[at + 2], b1 & 0x40
        if pid == NULL_PID or not flags & 0x10:
            continue
        body, marked = at + 4, False
        if flags & 0x20:
            size = media[body]
            marked = size > 0 and bool(media[body + 1] & 0x40)
            body += 1 + size
        if pid in wanted:
            before, now = counters.get(pid), flags & 15
            counters[pid] = now
            if before is not None and now != (before + 1) & 15:
                if now == before:
                    out.repeats += 1
                    continue
                out.gaps += 1
                open_.pop(pid, None)
            if start:
                finish(pid)
                open_[pid], marks[pid] = [media[body : at + PACKET]], marked
            elif pid in open_:
                open_[pid].append(media[body : at + PACKET])
        elif start and (pid == PAT_PID or pid in maps):
            s = _read_section(media[body : at + PACKET])
            if s is None:
                out.table_errors += 1
            elif s[0] == 0 and pid == PAT_PID:
                for i in range(8, len(s) - 3, 4):
                    number, target = struct.unpack(">HH", s[i : i + 4])
                    if number:
                        out.programs[number] = target & 0x1FFF
                        maps.add(target & 0x1FFF)
            elif s[0] == 2 and pid in maps:
                i = 12 + (struct.unpack(">H", s[10:12])[0] & 0xFFF)
                while i + 5 <= len(s):
                    kind, target, more = struct.unpack(">BHH", s[i : i + 5])
                    out.stream_types[target & 0x1FFF] = kind
                    wanted.add(target & 0x1FFF)
                    i += 5 + (more & 0xFFF)
    for pid in list(open_):
        finish(pid)
    out.payload = b"".join(parts)
    return out


def pad(data: bytes, to: int = PAD_TO) -> bytes:
    """``data`` filled up to a positive multiple of ``to``."""
    return data + bytes([PAD_BYTE]) * (-len(data) % to or (0 if data else to))


def feature(s: Stream) -> str:
    """Counts, span of time and random-access points of a demuxed stream, and the samples' mean and crossings of the middle."""
    import numpy as np

    x = np.frombuffer(s.payload, dtype=np.uint8)
    mean = int(x.sum(dtype=np.int64)) * 1000 // max(len(x), 1)
    crossings = int(np.count_nonzero((x[1:] >= 128) != (x[:-1] >= 128)))
    ends = (s.times[0], s.times[-1]) if s.times else (-1, -1)
    return f"packets={s.packets};units={len(s.times)};first_pts={ends[0]};last_pts={ends[1]};random_access={len(s.random_access)};gaps={s.gaps};repeats={s.repeats};table_errors={s.table_errors};mean_milli={mean};crossings={crossings}"


def store_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, n_bytes, media``: each text's UTF-8, padded and muxed."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw = [(t.as_py() or "").encode() for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(r) for r in raw], pa.int64()), pa.array([mux(pad(r)) for r in raw], pa.binary())], names=[id_col, "n_bytes", "media"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_bytes bigint, media binary")


def index_media(stored: DataFrame, id_col: str = "doc_id", media_col: str = "media") -> DataFrame:
    """``id_col`` with the stream's units: presentation times, sizes, random-access units, packets, gaps, repeats, table errors."""
    ship(stored.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [demux(m.as_py() or b"") for m in batch.column(1)]
            longs = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array([getattr(s, n) for s in found], longs) for n in ("times", "sizes", "random_access")), *(pa.array([getattr(s, n) for s in found], pa.int64()) for n in ("packets", "gaps", "repeats", "table_errors"))],
                names=[id_col, "pts", "sizes", "random_access", "packets", "gaps", "repeats", "table_errors"],
            )

    kind = stored.schema[id_col].dataType.simpleString()
    return stored.select(id_col, media_col).mapInArrow(run, f"`{id_col}` {kind}, pts array<bigint>, sizes array<bigint>, random_access array<bigint>, packets bigint, gaps bigint, repeats bigint, table_errors bigint")


def round_trip_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Each text stored as a stream, read back from the stored bytes, and described; one row for each row."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols: list[list] = [[] for _ in range(7)]
            for t in batch.column(1):
                raw = (t.as_py() or "").encode()
                media = mux(pad(raw))
                back = demux(media)
                for c, v in zip(cols, (len(raw), len(back.payload), hashlib.sha256(back.payload).hexdigest(), zlib.crc32(back.payload[-32:]), len(media), hashlib.sha256(media).hexdigest(), feature(back)), strict=True):
                    c.append(v)
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names=[id_col, "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string")
