"""Media columns in MPEG transport streams.

``store`` turns each payload into a transport stream of 188-byte packets:
program association and program map tables with their checksums before every
random-access point, and packetised elementary packets ("units") of up to
``unit_bytes`` with a presentation timestamp each. ``read`` parses the tables,
checks the continuity counters, reassembles the units and returns the payload
with timestamps and random-access points.

Defined results: a null or empty text is 64 zero bytes of payload; the stored
form depends on the text only. Damaged streams are reported by counters
(continuity, table checksum) and by null payloads when no stream is found.
"""

from __future__ import annotations

import hashlib
import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices, spool

PACKET, SYNC, BLOCK = 188, 0x47, 64
PAT_PID, PMT_PID, DATA_PID, PROGRAM = 0x0000, 0x1000, 0x0100, 1
PRIVATE_DATA, PRIVATE_STREAM = 0x06, 0xBD
#: Ticks of the 90 kHz clock between units, and units between random-access points.
UNIT_TICKS, UNITS_PER_ENTRY, UNIT_BYTES = 3600, 4, 16384


def _crc_table() -> list[int]:
    table = []
    for i in range(256):
        c = i << 24
        for _ in range(8):
            c = (c << 1) ^ (0x04C11DB7 if c & 0x80000000 else 0)
        table.append(c & 0xFFFFFFFF)
    return table


_CRC = _crc_table()


def section_crc(data: bytes) -> int:
    """CRC-32 of program tables (most significant bit first, no final inversion)."""
    c = 0xFFFFFFFF
    for b in data:
        c = ((c << 8) & 0xFFFFFFFF) ^ _CRC[(c >> 24) ^ b]
    return c


def _section(table_id: int, number: int, body: bytes) -> bytes:
    size = len(body) + 9
    head = bytes([table_id, 0xB0 | size >> 8, size & 0xFF, number >> 8, number & 0xFF, 0xC1, 0, 0])
    return head + body + section_crc(head + body).to_bytes(4, "big")


_PAT = _section(0x00, 1, bytes([PROGRAM >> 8, PROGRAM & 0xFF, 0xE0 | PMT_PID >> 8, PMT_PID & 0xFF]))
_PMT = _section(
    0x02, PROGRAM, bytes([0xE0 | DATA_PID >> 8, DATA_PID & 0xFF, 0xF0, 0, PRIVATE_DATA, 0xE0 | DATA_PID >> 8, DATA_PID & 0xFF, 0xF0, 0])
)


def _table_packet(pid: int, section: bytes, counter: int) -> bytes:
    return (bytes([SYNC, 0x40 | pid >> 8, pid & 0xFF, 0x10 | counter & 15, 0]) + section).ljust(PACKET, b"\xff")


def _stamp(pts: int) -> bytes:
    return bytes([0x21 | pts >> 29 & 0x0E, pts >> 22 & 0xFF, 0x01 | pts >> 14 & 0xFE, pts >> 7 & 0xFF, 0x01 | pts << 1 & 0xFE])


def _unit_packets(unit: bytes, pts: int, entry: bool, counter: int) -> np.ndarray:
    """One elementary packet as rows of 188 bytes."""
    head = b"\x00\x00\x01" + bytes([PRIVATE_STREAM]) + (len(unit) + 8).to_bytes(2, "big") + b"\x84\x80\x05" + _stamp(pts)
    data = np.frombuffer(head + unit, dtype=np.uint8)
    room = 182 if entry else 184
    rest = max(0, len(data) - room)
    n = 1 + -(-rest // 184)
    rows = np.full((n, PACKET), 0xFF, dtype=np.uint8)
    rows[:, 0], rows[:, 1], rows[:, 2] = SYNC, DATA_PID >> 8, DATA_PID & 0xFF
    rows[:, 3] = 0x10 | (counter + np.arange(n)) & 15
    rows[0, 1] |= 0x40
    full = rest // 184
    if full:
        rows[1 : 1 + full, 4:] = data[room : room + full * 184].reshape(full, 184)
    ends = [(0, data[:room], 0x40 if entry else 0)]
    if n - 1 > full:
        ends.append((n - 1, data[room + full * 184 :], 0))
    for k, part, flags in ends:
        gap = 184 - len(part)
        if gap:
            rows[k, 3] |= 0x20
            rows[k, 4] = gap - 1
            if gap > 1:
                rows[k, 5] = flags
        rows[k, 4 + gap :] = part
    return rows


def pad(data: bytes) -> bytes:
    """Zero bytes up to a positive multiple of 64."""
    return data.ljust(max(BLOCK, -(-len(data) // BLOCK) * BLOCK), b"\0")


def mux(payload: bytes, unit_bytes: int = UNIT_BYTES) -> bytes:
    """The payload as a transport stream."""
    out, counter = [], 0
    for k, at in enumerate(range(0, len(payload), unit_bytes)):
        entry = k % UNITS_PER_ENTRY == 0
        if entry:
            turn = k // UNITS_PER_ENTRY
            out += [_table_packet(PAT_PID, _PAT, turn), _table_packet(PMT_PID, _PMT, turn)]
        rows = _unit_packets(payload[at : at + unit_bytes], k * UNIT_TICKS % (1 << 33), entry, counter)
        counter += len(rows)
        out.append(rows.tobytes())
    return b"".join(out)


@dataclass
class Stream:
    """What a transport stream holds."""

    payload: bytes | None = None
    packets: int = 0
    counter_errors: int = 0
    table_errors: int = 0
    #: (timestamp, payload offset, bytes, whether playing can start here) of each unit
    units: list[tuple[int, int, int, bool]] = field(default_factory=list)

    def describe(self) -> str:
        entries = ",".join(f"{t}@{at}" for t, at, _, start in self.units if start)
        last = self.units[-1][0] if self.units else ""
        return f"packets={self.packets};units={len(self.units)};last_pts={last};entries={entries};counter_errors={self.counter_errors};table_errors={self.table_errors}"


def _read_section(rows: np.ndarray, offsets: np.ndarray, found: Stream, table_id: int) -> bytes | None:
    got = None
    for row, at in zip(rows, offsets):
        data = row[at:].tobytes()
        data = data[1 + data[0] :] if data else b""
        size = ((data[1] & 0x0F) << 8 | data[2]) + 3 if len(data) > 3 else 0
        if size < 12 or size > len(data) or data[0] != table_id or section_crc(data[:size]):
            found.table_errors += 1
        else:
            got = data[8 : size - 4]
    return got


def demux(media: bytes | None) -> Stream:
    """Parse tables, check counters, reassemble the units of the first private data stream."""
    found = Stream()
    if not media or len(media) % PACKET:
        return found
    rows = np.frombuffer(media, dtype=np.uint8).reshape(-1, PACKET)
    rows = rows[rows[:, 0] == SYNC]
    found.packets = len(rows)
    pid = (rows[:, 1].astype(int) & 0x1F) << 8 | rows[:, 2]
    extra = rows[:, 3] & 0x20 != 0
    offset = np.where(extra, 5 + rows[:, 4].astype(int), 4)
    table = pid == PAT_PID
    body = _read_section(rows[table], offset[table], found, 0x00)
    if body is None:
        return found
    pmt_pid = (body[2] & 0x1F) << 8 | body[3]
    table = pid == pmt_pid
    body = _read_section(rows[table], offset[table], found, 0x02)
    if body is None:
        return found
    at, data_pid = 4 + ((body[2] & 0x0F) << 8 | body[3]), None
    while at + 5 <= len(body) and data_pid is None:
        if body[at] == PRIVATE_DATA:
            data_pid = (body[at + 1] & 0x1F) << 8 | body[at + 2]
        at += 5 + ((body[at + 3] & 0x0F) << 8 | body[at + 4])
    for one in np.unique(pid):
        counters = rows[(pid == one) & (rows[:, 3] & 0x10 != 0), 3] & 15
        found.counter_errors += int(((np.diff(counters.astype(int)) - 1) % 16 != 0).sum())
    mine = (pid == data_pid) & (rows[:, 3] & 0x10 != 0)
    data, begin = rows[mine], offset[mine]
    starts = np.nonzero(data[:, 1] & 0x40)[0]
    flags = np.where(extra[mine] & (data[:, 4] > 0), data[:, 5], 0)
    flat = data[np.arange(PACKET) >= begin[:, None]].tobytes()
    ends = np.concatenate([[0], np.cumsum(PACKET - begin)])
    parts, size = [], 0
    for s, e in zip(starts, [*starts[1:], len(data)]):
        unit = flat[ends[s] : ends[e]]
        if unit[:3] != b"\x00\x00\x01" or len(unit) < 14:
            found.table_errors += 1
            continue
        t = unit[9:14]
        pts = (t[0] >> 1 & 7) << 30 | t[1] << 22 | t[2] >> 1 << 15 | t[3] << 7 | t[4] >> 1
        part = unit[9 + unit[8] : 6 + int.from_bytes(unit[4:6], "big")]
        found.units.append((pts, size, len(part), bool(flags[s] & 0x40)))
        parts.append(part)
        size += len(part)
    found.payload = b"".join(parts)
    return found


def _store_batches(unit_bytes: int):
    def run(batches):
        for batch in slices(batches, 128):
            texts = [t or b"" for t in batch.column(1).to_pylist()]
            media = [mux(pad(t), unit_bytes) for t in texts]
            sizes = pa.array([len(t) for t in texts], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), sizes, pa.array(media, pa.binary())], names=["doc_id", "n_bytes", "media"])

    return run


def store(docs: DataFrame, unit_bytes: int = UNIT_BYTES) -> DataFrame:
    """doc_id, n_bytes (of the text in UTF-8), media (transport stream) of every row."""
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    return picked.mapInArrow(_store_batches(unit_bytes), "doc_id long, n_bytes long, media binary")


_READ = (
    "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, "
    "units array<struct<pts:bigint,offset:bigint,bytes:bigint,random_access:boolean>>"
)


def _read_batches(batches):
    unit = pa.struct([("pts", pa.int64()), ("offset", pa.int64()), ("bytes", pa.int64()), ("random_access", pa.bool_())])
    for batch in slices(batches, 128):
        rows = []
        for media in batch.column(2).to_pylist():
            s = demux(media)
            p = s.payload
            rows.append((
                None if p is None else len(p), None if p is None else hashlib.sha256(p).hexdigest(), None if p is None else zlib.crc32(p[-BLOCK:]),
                None if media is None else len(media), None if media is None else hashlib.sha256(media).hexdigest(), s.describe(),
                [dict(zip(("pts", "offset", "bytes", "random_access"), u)) for u in s.units],
            ))
        kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.list_(unit)]
        columns = [pa.array(c, k) for c, k in zip(zip(*rows), kinds)]
        names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "units"]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *columns], names=names)


def read(stored: DataFrame) -> DataFrame:
    """Digests, timestamps and random-access points of stored streams, from their bytes alone."""
    return stored.select("doc_id", "n_bytes", "media").mapInArrow(_read_batches, _READ)


def stored_and_read(docs: DataFrame) -> DataFrame:
    """Store every row's text in the shared folder, then read the stored streams."""
    return read(spool(store(docs), "media"))
