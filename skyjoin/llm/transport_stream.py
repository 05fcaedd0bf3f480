"""MPEG transport streams (ISO/IEC 13818-1): writing, parsing and storing them in media columns.

Reading: packets are found by their sync bytes, program tables (PAT, PMT) are parsed across packets and checked by CRC,
continuity counters are checked by the standard's rules, elementary packets are reassembled by PID, and each keeps its
time stamps and whether it starts at a random-access point. Writing gives one program with one private stream whose access
units carry the payload; all but the units' last packets are laid out as a numpy matrix.

Edge cases: an empty payload gives tables alone; bytes before sync and after the last whole packet are skipped and counted;
duplicate packets are dropped once; a gap in a counter without a discontinuity flag is an error and damages the open
elementary packet, which is then marked; scrambled and null packets carry nothing; null texts count as empty, equal texts have equal
streams, rows are stored one by one; extra columns are ignored; an empty table gives an empty one.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, returning, text_bytes

PACKET, SYNC, NULL_PID = 188, 0x47, 0x1FFF
PMT_PID, DATA_PID, PROGRAM = 0x1000, 0x0101, 1
#: Stream type and id of private data in elementary packets.
PRIVATE_TYPE, PRIVATE_ID = 0x06, 0xBD
#: Payload is padded to this multiple; an access unit carries so many of them; 90 kHz ticks between units (25 a second).
BLOCK, UNIT, TICKS = 576, 10 * 576, 3600
#: A random-access point stands at every so many units.
RANDOM_ACCESS = 8
PES_HEAD = 14


@lru_cache(maxsize=1)
def _crc_table() -> list[int]:
    out = []
    for n in range(256):
        c = n << 24
        for _ in range(8):
            c = (c << 1) ^ (0x04C11DB7 if c & 0x80000000 else 0)
        out.append(c & 0xFFFFFFFF)
    return out


def crc32_mpeg(data: bytes) -> int:
    """The CRC of program tables: most significant bit first, no final inversion. Zero over a section with its CRC."""
    c, rows = 0xFFFFFFFF, _crc_table()
    for b in data:
        c = ((c << 8) & 0xFFFFFFFF) ^ rows[(c >> 24) ^ b]
    return c


def section(table: int, number: int, body: bytes) -> bytes:
    out = bytes([table]) + (0xB000 | (len(body) + 9)).to_bytes(2, "big") + number.to_bytes(2, "big") + b"\xc1\x00\x00" + body
    return out + crc32_mpeg(out).to_bytes(4, "big")


def table_packet(pid: int, sec: bytes) -> bytes:
    body = b"\x00" + sec
    if len(body) > PACKET - 4:
        raise ValueError("a written table fits one packet")
    return bytes([SYNC, 0x40 | pid >> 8, pid & 255, 0x10]) + body + b"\xff" * (PACKET - 4 - len(body))


@lru_cache(maxsize=1)
def tables() -> bytes:
    pat = section(0, 1, PROGRAM.to_bytes(2, "big") + (0xE000 | PMT_PID).to_bytes(2, "big"))
    pmt = section(2, PROGRAM, (0xE000 | DATA_PID).to_bytes(2, "big") + b"\xf0\x00" + bytes([PRIVATE_TYPE]) + (0xE000 | DATA_PID).to_bytes(2, "big") + b"\xf0\x00")
    return table_packet(0, pat) + table_packet(PMT_PID, pmt)


def stamp(ticks: int, mark: int = 2) -> bytes:
    t = ticks % (1 << 33)
    return bytes([mark << 4 | t >> 29 & 14 | 1, t >> 22 & 255, t >> 14 & 254 | 1, t >> 7 & 255, t << 1 & 254 | 1])


def read_stamp(b: bytes) -> int:
    return (b[0] >> 1 & 7) << 30 | b[1] << 22 | (b[2] >> 1) << 15 | b[3] << 7 | b[4] >> 1


def reference_clock(ticks: int) -> bytes:
    base = ticks % (1 << 33)
    return (base << 15 | 0x7E00).to_bytes(6, "big")


def _unit(data: bytes, number: int, counter: int) -> bytes:
    """The packets of one access unit: clock and flags in its first packet, stuffing in its first or last."""
    pes = b"\x00\x00\x01" + bytes([PRIVATE_ID]) + (len(data) + 8).to_bytes(2, "big") + b"\x84\x80\x05" + stamp(number * TICKS) + data
    flags = 0x10 | (0x40 if number % RANDOM_ACCESS == 0 else 0)
    first = bytes([flags]) + reference_clock(number * TICKS)
    room = PACKET - 5 - len(first)
    if len(pes) <= room:
        first += b"\xff" * (room - len(pes))
        room = len(pes)
    head = bytes([SYNC, 0x40 | DATA_PID >> 8, DATA_PID & 255, 0x30 | counter & 15, len(first)]) + first + pes[:room]
    rest = pes[room:]
    whole, left = divmod(len(rest), PACKET - 4)
    rows = np.empty((whole, PACKET), np.uint8)
    rows[:, 0], rows[:, 1], rows[:, 2] = SYNC, DATA_PID >> 8, DATA_PID & 255
    rows[:, 3] = 0x10 | (np.arange(counter + 1, counter + 1 + whole) & 15)
    rows[:, 4:] = np.frombuffer(rest, np.uint8, whole * (PACKET - 4)).reshape(whole, PACKET - 4)
    out = head + rows.tobytes()
    if left:
        pad = PACKET - 5 - left
        field_ = b"" if pad == 0 else b"\x00" + b"\xff" * (pad - 1)
        out += bytes([SYNC, DATA_PID >> 8, DATA_PID & 255, 0x30 | (counter + 1 + whole) & 15, pad]) + field_ + rest[whole * (PACKET - 4) :]
    return out


def write_stream(payload: bytes) -> bytes:
    """A transport stream that carries the payload: tables before every random-access point, then its access units."""
    out, counter = [], 0
    for number, at in enumerate(range(0, len(payload), UNIT)):
        if number % RANDOM_ACCESS == 0:
            shift = number // RANDOM_ACCESS & 15  # the tables' own counters
            rows = np.frombuffer(tables(), np.uint8).reshape(2, PACKET).copy()
            rows[:, 3] |= shift
            out.append(rows.tobytes())
        unit = _unit(payload[at : at + UNIT], number, counter)
        counter += len(unit) // PACKET
        out.append(unit)
    return b"".join(out) or tables()


@dataclass
class Elementary:
    """One reassembled elementary packet."""

    pid: int
    stream_id: int
    data: bytes
    pts: int | None = None
    dts: int | None = None
    random_access: bool = False
    packet: int = 0
    damaged: bool = False


@dataclass
class Stream:
    """What a parsed transport stream holds."""

    packets: int = 0
    skipped: int = 0
    programs: dict[int, int] = field(default_factory=dict)
    streams: dict[int, int] = field(default_factory=dict)
    units: list[Elementary] = field(default_factory=list)
    counter_errors: int = 0
    duplicates: int = 0
    table_errors: int = 0
    clocks: int = 0

    def payload(self, pid: int | None = None) -> bytes:
        pid = min(self.streams, default=None) if pid is None else pid
        return b"".join(u.data for u in self.units if u.pid == pid)

    def index(self) -> list[tuple[int, int | None, int]]:
        """(packet, time stamp, bytes before it) of each random-access point."""
        out, before = [], 0
        for u in self.units:
            if u.random_access:
                out.append((u.packet, u.pts, before))
            before += len(u.data)
        return out


def _packets(data: bytes) -> tuple[np.ndarray, int]:
    """The packet matrix from the first place where sync bytes repeat, and the bytes skipped."""
    flat = np.frombuffer(data, np.uint8)
    for start in range(min(PACKET, max(1, len(flat) - PACKET + 1))):
        n = (len(flat) - start) // PACKET
        if n and (flat[start : start + n * PACKET : PACKET] == SYNC)[: min(n, 5)].all():
            return flat[start : start + n * PACKET].reshape(n, PACKET), len(flat) - n * PACKET
    return flat[:0].reshape(0, PACKET), len(flat)


def _elementary(pid: int, raw: bytes, packet: int, access: bool, damaged: bool) -> Elementary | None:
    if len(raw) < 9 or raw[:3] != b"\x00\x00\x01":
        return None
    length, flags, head = int.from_bytes(raw[4:6], "big"), raw[7] >> 6, raw[8]
    pts = read_stamp(raw[9:14]) if flags & 2 and len(raw) >= 14 else None
    dts = read_stamp(raw[14:19]) if flags == 3 and len(raw) >= 19 else pts
    end = 6 + length if length else len(raw)
    return Elementary(pid, raw[3], raw[9 + head : end], pts, dts, access, packet, damaged or len(raw) < end)


def read_stream(data: bytes) -> Stream:
    """Parses a transport stream; packets of damaged synchronisation are counted as counter errors by their gap."""
    out = Stream()
    rows, out.skipped = _packets(data)
    rows = rows[(rows[:, 0] == SYNC) & (rows[:, 1] & 0x80 == 0)]
    out.packets = len(rows)
    pids = (rows[:, 1].astype(np.int32) & 0x1F) << 8 | rows[:, 2]
    starts, kinds, counters, sizes = rows[:, 1] & 0x40 != 0, rows[:, 3] >> 4 & 3, rows[:, 3] & 15, rows[:, 4]
    field_ = kinds & 2 != 0
    offset = np.where(kinds & 1 == 0, PACKET, np.where(field_, 5 + sizes.astype(np.int32), 4))
    offset[(rows[:, 3] & 0xC0) != 0] = PACKET  # scrambled
    flags = np.where(field_ & (sizes > 0), rows[:, 5], 0)
    out.clocks = int((flags & 0x10 != 0).sum())
    held = {pid: np.flatnonzero(pids == pid) for pid in np.unique(pids).tolist() if pid != NULL_PID}
    for pid in held:
        at = held[pid]
        at = at[kinds[at] & 1 == 1]
        step = (counters[at][1:].astype(np.int32) - counters[at][:-1]) & 15
        same = np.append(False, step == 0)
        for i in np.flatnonzero(same):
            same[i] = bool((rows[at[i]] == rows[at[i - 1]]).all()) and not same[i - 1]
        out.duplicates += int(same.sum())
        at = at[~same]
        step = (counters[at][1:].astype(np.int32) - counters[at][:-1]) & 15
        broken = np.append(False, (step != 1) & (flags[at][1:] & 0x80 == 0))
        out.counter_errors += int(broken.sum())
        held[pid] = (at, broken)

    def sections(pid: int):
        buffer = b""
        for i, bad in zip(*held.get(pid, ((), ())), strict=True):
            body = rows[i, offset[i] :].tobytes()
            if bad:
                buffer = b""
            if starts[i] and body:
                buffer, body = (buffer + body[1 : 1 + body[0]], body[1 + body[0] :])
                yield from whole(buffer)
                buffer = b""
            elif not buffer:
                continue
            buffer += body
            while len(buffer) >= 3 and buffer[0] != 255 and len(buffer) >= (n := 3 + (int.from_bytes(buffer[1:3], "big") & 0xFFF)):
                yield from whole(buffer[:n])
                buffer = buffer[n:]

    def whole(sec: bytes):
        if len(sec) < 3 or sec[0] == 255:
            return
        n = 3 + (int.from_bytes(sec[1:3], "big") & 0xFFF)
        if len(sec) < n:
            return
        if crc32_mpeg(sec[:n]):
            out.table_errors += 1
        else:
            yield sec[:n]

    done: set[bytes] = set()
    for sec in sections(0):
        if sec in done or sec[0] != 0:
            continue
        done.add(sec)
        for i in range(8, len(sec) - 4, 4):
            if program := int.from_bytes(sec[i : i + 2], "big"):
                out.programs[program] = int.from_bytes(sec[i + 2 : i + 4], "big") & 0x1FFF
    for pid in sorted(set(out.programs.values())):
        for sec in sections(pid):
            if sec in done or sec[0] != 2:
                continue
            done.add(sec)
            i = 12 + (int.from_bytes(sec[10:12], "big") & 0xFFF)
            while i + 5 <= len(sec) - 4:
                out.streams[int.from_bytes(sec[i + 1 : i + 3], "big") & 0x1FFF] = sec[i]
                i += 5 + (int.from_bytes(sec[i + 3 : i + 5], "big") & 0xFFF)
    for pid in sorted(out.streams):
        at, broken = held.get(pid, (np.zeros(0, int), np.zeros(0, bool)))
        begins = np.flatnonzero(starts[at])
        for a, b in zip(begins, np.append(begins[1:], len(at)), strict=True):
            own, bad = at[a:b], bool(broken[a + 1 : b].any())
            plain = offset[own] == 4
            # Whole packets after the first are cut out of the matrix together.
            if len(own) > 2 and plain[1:-1].all():
                raw = rows[own[0], offset[own[0]] :].tobytes() + rows[own[1:-1], 4:].tobytes() + rows[own[-1], offset[own[-1]] :].tobytes()
            else:
                raw = b"".join(rows[i, offset[i] :].tobytes() for i in own)
            if unit := _elementary(pid, raw, int(own[0]), bool(flags[own[0]] & 0x40), bad):
                out.units.append(unit)
    out.units.sort(key=lambda u: u.packet)
    return out


def padded(text: bytes) -> bytes:
    """The text with bytes 255 up to a positive multiple of BLOCK."""
    return text + b"\xff" * (max(1, -(-len(text) // BLOCK)) * BLOCK - len(text))


def feature(s: Stream, payload: bytes) -> str:
    """Packets, elementary packets, errors, time span, number of random-access points, and the payload's byte entropy and mean."""
    counts = np.bincount(np.frombuffer(payload, np.uint8), minlength=256)
    share = counts[counts > 0] / max(1, len(payload))
    entropy = float(-(share * np.log2(share)).sum()) + 0.0
    last = s.units[-1].pts if s.units else None
    mean = float((counts * np.arange(256)).sum() / max(1, len(payload)))
    return f"ts;packets={s.packets};units={len(s.units)};clocks={s.clocks};errors={s.counter_errors + s.table_errors};last_pts={last};access={len(s.index())};entropy={entropy:.4f};mean={mean:.3f}"


STORED = "doc_id long, n_bytes long, media binary, payload binary, feature string, programs int, packets int, counter_errors int, access_points array<struct<packet:int,pts:long,offset:long>>, last_pts long"
_POINTS = pa.list_(pa.struct([("packet", pa.int32()), ("pts", pa.int64()), ("offset", pa.int64())]))


def stored_media(docs: DataFrame) -> DataFrame:
    """Each text stored as a transport stream: the stream itself, and what reading it back gives, with all its random-access points.

    Null texts count as empty. The payload is the bytes read back, never those that went in.
    """

    def run(batches):
        names = re.findall(r"(?:^|, )(\w+) ", STORED)
        for whole in batches:
            for batch in chunks(whole, 1):
                rows = []
                for text in text_bytes(batch.column(1)):
                    media = write_stream(padded(text))
                    s = read_stream(media)
                    back = s.payload()
                    points = [{"packet": p, "pts": t, "offset": at} for p, t, at in s.index()]
                    rows.append((len(text), media, back, feature(s, back), len(s.programs), s.packets, s.counter_errors, points, s.units[-1].pts if s.units else None))
                columns = list(zip(*rows, strict=True)) if rows else [[]] * (len(names) - 1)
                kinds = [pa.int64(), pa.binary(), pa.binary(), pa.string(), pa.int32(), pa.int32(), pa.int32(), _POINTS, pa.int64()]
                yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], names)

    return docs.selectExpr("cast(doc_id AS long) AS doc_id", "text").mapInArrow(returning(run), STORED)


def media_columns(docs: DataFrame) -> DataFrame:
    """What op3 returns: digests of the stored streams and of the payloads read back, a feature line, the parsed counts and the index."""
    return stored_media(docs).select(
        "doc_id", "n_bytes",
        F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha2("payload", 256).alias("payload_sha256"),
        F.crc32(F.expr("substring(payload, greatest(1, octet_length(payload) - 31), 32)")).alias("tail_crc32"),
        F.octet_length("media").cast("long").alias("media_bytes"), F.sha2("media", 256).alias("media_sha256"),
        "feature", "programs", "packets", "counter_errors", F.size("access_points").alias("random_access_points"), "last_pts", "access_points",
    )


def access_units(media: DataFrame) -> DataFrame:
    """A table (doc_id, media binary) of streams, to one row for each elementary packet with its time stamps and flags."""
    schema = "doc_id long, unit int, pid int, pts long, dts long, random_access boolean, damaged boolean, n_bytes int, packet int"

    def run(batches):
        names = [f.split()[0] for f in schema.split(", ")]
        for batch in batches:
            rows = [(i, k, u.pid, u.pts, u.dts, u.random_access, u.damaged, len(u.data), u.packet) for i, m in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) for k, u in enumerate(read_stream(m or b"").units)]
            kinds = [pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.bool_(), pa.bool_(), pa.int32(), pa.int32()]
            yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], k) for j, k in enumerate(kinds)], names)

    return media.selectExpr("cast(doc_id AS long) AS doc_id", "media").mapInArrow(returning(run), schema)
