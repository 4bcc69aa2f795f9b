"""WARC archives in seekable Zstandard bundles.

``write`` stores one record per page: a response with the whole payload, or a
revisit that refers to the response with the same payload. Records are grouped
into independent Zstandard frames; a bundle ends with a seek table (skippable
frame, readable by any seekable-format reader, and ignored by plain
decompressors). The returned index maps each record to its bundle, frame and offset
within the frame. ``read`` opens bundles through the seek table, decompresses
only the frames asked for, parses the records and verifies digests.

Bundles are named by task attempt and only those in the committed index
count, so a lost executor or a repeated task leaves at most an unused file. The
folder has to be one that all executors reach (any file system pyarrow opens).

Defined results: null html is an empty payload; of equal payloads of at least
``min_bytes``, the smallest page_id is the response (repeated rows of that
page_id are all responses), null ids come last and refer to it; where all ids
of a payload are null, all are responses. Null urls are left out of the record.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid

import pyarrow as pa
import pyarrow.fs
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import shared_dir, slices, spool

#: Fixed values of the seekable format.
SKIPPABLE, SEEKABLE = 0x184D2A5E, 0x8F92EAB1
FRAME_BYTES, BUNDLE_BYTES, LEVEL = 1 << 18, 1 << 26, 3
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
_INDEX = "page_id long, bundle string, frame int, at long, length long"
_READ = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long"


def digest32(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def build_record(page_id, url, payload: bytes, refers_to=None, revisit=False, date="2024-01-01T00:00:00Z") -> bytes:
    """One record; a revisit has the payload's digest and length but not the payload."""
    block = HTTP if revisit else HTTP + payload
    fields = [
        ("WARC-Type", "revisit" if revisit else "response"),
        ("WARC-Record-ID", f"<urn:x-page:{'' if page_id is None else page_id}>"),
        ("WARC-Date", date),
        ("WARC-Payload-Digest", f"sha1:{digest32(payload)}"),
        ("X-Payload-Length", len(payload)),
        ("Content-Type", "application/http; msgtype=response"),
        ("Content-Length", len(block)),
    ]
    if url is not None:
        fields.append(("WARC-Target-URI", url.replace("\r", "%0D").replace("\n", "%0A")))
    if revisit:
        fields += [("WARC-Profile", PROFILE), ("WARC-Refers-To", f"<urn:x-page:{refers_to}>")]
    head = "".join(f"{k}: {v}\r\n" for k, v in fields)
    return b"WARC/1.1\r\n" + head.encode() + b"\r\n" + block + b"\r\n\r\n"


def parse_record(data: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields and payload (empty for a revisit) of one record."""
    head, _, rest = data.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if lines[0] != "WARC/1.1":
        raise ValueError("not a WARC record")
    fields = dict(x.split(": ", 1) for x in lines[1:])
    block = rest[: int(fields["Content-Length"])]
    return fields, block.partition(b"\r\n\r\n")[2]


class BundleWriter:
    """Independent frames, then the seek table."""

    def __init__(self, out, level: int = LEVEL, frame_bytes: int = FRAME_BYTES):
        self._out, self._limit = out, frame_bytes
        self._zstd = zstandard.ZstdCompressor(level=level)
        self._frames: list[tuple[int, int]] = []
        self._held: list[bytes] = []
        self._size = self.written = 0

    def add(self, record: bytes) -> tuple[int, int]:
        """(frame, offset within the decompressed frame) of the record."""
        if self._size and self._size + len(record) > self._limit:
            self._flush()
        place = len(self._frames), self._size
        self._held.append(record)
        self._size += len(record)
        return place

    def _flush(self) -> None:
        if self._held:
            frame = self._zstd.compress(b"".join(self._held))
            self._out.write(frame)
            self._frames.append((len(frame), self._size))
            self.written += len(frame)
            self._held, self._size = [], 0

    def close(self) -> None:
        self._flush()
        table = b"".join(struct.pack("<II", *f) for f in self._frames) + struct.pack("<IBI", len(self._frames), 0, SEEKABLE)
        self._out.write(struct.pack("<II", SKIPPABLE, len(table)) + table)
        self._out.close()


class BundleReader:
    """Frames by number, through the seek table at the end."""

    def __init__(self, source):
        self._in = source
        end = source.size()
        source.seek(end - 9)
        n, flags, magic = struct.unpack("<IBI", source.read(9))
        if magic != SEEKABLE:
            raise ValueError("no seek table")
        width = 12 if flags & 0x80 else 8
        source.seek(end - 9 - n * width)
        table = source.read(n * width)
        self.frames, at = [], 0
        for k in range(n):
            packed, plain = struct.unpack_from("<II", table, k * width)
            self.frames.append((at, packed, plain))
            at += packed
        self._zstd = zstandard.ZstdDecompressor()

    def frame(self, k: int) -> bytes:
        at, packed, plain = self.frames[k]
        self._in.seek(at)
        return self._zstd.decompress(self._in.read(packed), max_output_size=max(plain, 1))


def _open(uri: str):
    if uri.startswith("file:/") and not uri.startswith("file://"):
        uri = "file://" + uri[5:]
    return pyarrow.fs.FileSystem.from_uri(uri if "://" in uri else "file://" + uri)


def _write_batches(folder: str, frame_bytes: int, bundle_bytes: int):
    def run(batches):
        fs, root = _open(folder)
        task = TaskContext.get()
        name = f"{task.partitionId():06d}-{task.taskAttemptId()}"
        writer, number = None, 0
        for batch in slices(batches, 512):
            rows = []
            for page_id, url, html, first, revisit in zip(*(c.to_pylist() for c in batch.columns)):
                if writer is None:
                    bundle = f"pages-{name}-{number:04d}.warc.zst"
                    writer = BundleWriter(fs.open_output_stream(f"{root}/{bundle}", compression=None), frame_bytes=frame_bytes)
                    number += 1
                record = build_record(page_id, url, html or b"", first, bool(revisit))
                rows.append((page_id, bundle, *writer.add(record), len(record)))
                if writer.written >= bundle_bytes:
                    writer.close()
                    writer = None
            yield pa.RecordBatch.from_arrays(
                [pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.string(), pa.int32(), pa.int64(), pa.int64()))],
                names=["page_id", "bundle", "frame", "at", "length"],
            )
        if writer is not None:
            writer.close()

    return run


def plan_records(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """page_id, url, html (bytes), first_id, revisit of every page.

    Only payloads that occur more than once enter the table that is joined, so
    pages are not shuffled while it is small; above the broadcast threshold the
    join is sorted, with hot payloads split.
    """
    html = F.coalesce(F.col("html").cast("binary"), F.lit(b""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), html.alias("html"))
    rows = rows.withColumn("sha", F.sha1("html"))
    again = rows.where(F.length("html") >= min_bytes).groupBy("sha").agg(F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("n"))
    again = spool(again.where("n > 1").select(F.col("sha").alias("again"), "first_id"), "again")
    planned = rows.join(again, F.col("sha") == F.col("again"), "left")
    revisit = F.col("again").isNotNull() & F.col("first_id").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first_id"))
    return planned.select("page_id", "url", "html", "first_id", revisit.alias("revisit"))


def write(
    pages: DataFrame, folder: str | None = None, min_bytes: int = 0, frame_bytes: int = FRAME_BYTES, bundle_bytes: int = BUNDLE_BYTES
) -> tuple[str, DataFrame]:
    """Write the bundles; returns their folder and the index of all records."""
    folder = folder or f"{shared_dir(pages.sparkSession)}/warc-{uuid.uuid4().hex}"
    fs, root = _open(folder)
    fs.create_dir(root, recursive=True)
    return folder, spool(plan_records(pages, min_bytes).mapInArrow(_write_batches(folder, frame_bytes, bundle_bytes), _INDEX), "index")


def _number(field: str | None):
    digits = field.removeprefix("<urn:x-page:").removesuffix(">") if field else ""
    return int(digits) if digits not in ("", "None") else None


def _read_batches(folder: str):
    def run(batches):
        fs, root = _open(folder)
        source, opened, held = None, None, (None, b"")
        for batch in slices(batches, 512):
            rows = []
            for bundle, frame, at, length in zip(*(batch.column(k).to_pylist() for k in range(1, 5))):
                if bundle != opened:
                    source, opened, held = BundleReader(fs.open_input_file(f"{root}/{bundle}")), bundle, (None, b"")
                if held[0] != frame:
                    held = frame, source.frame(frame)
                fields, payload = parse_record(held[1][at : at + length])
                digest = fields["WARC-Payload-Digest"].removeprefix("sha1:")
                revisit = fields["WARC-Type"] == "revisit"
                if not revisit and (digest32(payload) != digest or len(payload) != int(fields["X-Payload-Length"])):
                    raise ValueError(f"damaged record in {bundle}, frame {frame}")
                rows.append((
                    _number(fields["WARC-Record-ID"]), fields.get("WARC-Target-URI"), int(fields["X-Payload-Length"]), digest,
                    fields["WARC-Type"], _number(fields.get("WARC-Refers-To")),
                ))
            kinds = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64())
            names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to"]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=names)

    return run


def read(folder: str, index: DataFrame, frames_a_task: int = 16) -> DataFrame:
    """The indexed records, read back; runs of neighbouring frames stay in one task."""
    dealt = index.repartition("bundle", F.floor(F.col("frame") / frames_a_task)).sortWithinPartitions("bundle", "frame", "at")
    return dealt.mapInArrow(_read_batches(folder), _READ)
