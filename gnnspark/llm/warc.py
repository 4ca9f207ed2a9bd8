"""WARC archives in seekable Zstandard bundles.

A bundle holds independent frames, each a group of records, then a skippable frame with the index (record identifier, frame, offset inside
the frame) and the seek table of the public seekable format: sizes of every frame and a fixed footer. One record can be
read by decompressing one frame.

Of records with equal payloads the one with the largest page id is a response, and the others are revisits that refer to it. Payload groups are found on narrow rows: digests are
counted before the shuffle, and only digests that repeat are joined back: broadcast while their counted rows are few (so payloads are not shuffled), else by a join whose hot digests are
split at run time.

Bundles are written by tasks into the shared folder under a temporary name and renamed, so a task that is run again replaces its own
bundle; any file system that pyarrow opens by URI will do. A bundle is cut at ``bundle_bytes`` of payload, a frame at ``frame_bytes``, so memory is bounded by one frame
or one record.

Defined results: null html is an empty payload; a null page id is written as none and is a response; rows with equal id and payload are all written, all with that record type (the
largest id of a payload is a response even when repeated); an empty table gives no bundle and no rows. Only the named columns are read.
"""

from __future__ import annotations

import base64
import hashlib
import posixpath
import struct
from collections.abc import Iterator
from dataclasses import dataclass
from urllib.parse import quote

import pyarrow as pa
import zstandard
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .state import checkpointed, map_in_arrow

# Fixed values of the seekable format: skippable frame magic for the seek table, its footer magic, and the magic of our index frame.
SEEK_MAGIC, FOOTER_MAGIC, INDEX_MAGIC = 0x184D2A5E, 0x8F92EAB1, 0x184D2A50

#: Digests that repeat are broadcast up to so many rows of about 100 bytes.
BROADCAST_ROWS = 50_000


@dataclass(frozen=True)
class Record:
    """What a WARC record says; ``payload`` is empty for a revisit."""

    page_id: int | None
    url: str | None
    kind: str
    payload: bytes
    payload_bytes: int
    digest: str
    refers_to: int | None

    @property
    def record_id(self) -> str:
        return f"<urn:page:{'none' if self.page_id is None else self.page_id}>"


def digest_of(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def to_warc(r: Record, date: str = "2024-01-01T00:00:00Z") -> bytes:
    head = [
        "WARC/1.1",
        f"WARC-Type: {r.kind}",
        f"WARC-Record-ID: {r.record_id}",
        f"WARC-Date: {date}",
        f"WARC-Target-URI: {quote(r.url or '', safe=':/?#[]@!$&()*+,;=%~.-_')}",
        f"WARC-Payload-Digest: sha1:{r.digest}",
        f"X-Payload-Length: {r.payload_bytes}",
        "Content-Type: text/html; charset=utf-8",
        f"Content-Length: {len(r.payload)}",
    ]
    if r.kind == "revisit":
        head[4:4] = ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{r.refers_to}>"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + r.payload + b"\r\n\r\n"


def from_warc(data: bytes, at: int = 0) -> tuple[Record, int]:
    """The record that starts at ``at``, and where the next one starts."""
    end = data.index(b"\r\n\r\n", at)
    fields = dict(line.split(": ", 1) for line in data[at:end].decode().split("\r\n")[1:])
    size = int(fields["Content-Length"])
    page = lambda key: None if key not in fields or "none" in fields[key] else int(fields[key].rstrip(">").rpartition(":")[2])
    body = data[end + 4 : end + 4 + size]
    record = Record(page("WARC-Record-ID"), fields["WARC-Target-URI"], fields["WARC-Type"], body, int(fields["X-Payload-Length"]), fields["WARC-Payload-Digest"].removeprefix("sha1:"), page("WARC-Refers-To"))
    return record, end + 4 + size + 4


class BundleWriter:
    """Frames, then the index frame and the seek table, to one file."""

    def __init__(self, out, level: int = 3, frame_bytes: int = 1 << 20):
        self.out, self.frame_bytes = out, frame_bytes
        self.zstd = zstandard.ZstdCompressor(level=level)
        self.frames: list[tuple[int, int]] = []
        self.index: list[str] = []
        self.buffer, self.size, self.payload = [], 0, 0

    def add(self, r: Record) -> None:
        data = to_warc(r)
        if self.size and self.size + len(data) > self.frame_bytes:
            self.flush()
        self.index.append(f"{r.record_id}\t{len(self.frames)}\t{self.size}\n")
        self.buffer.append(data)
        self.size += len(data)
        self.payload += len(data)

    def flush(self) -> None:
        if self.size:
            packed = self.zstd.compress(b"".join(self.buffer))
            self.out.write(packed)
            self.frames.append((len(packed), self.size))
            self.buffer, self.size = [], 0

    def close(self) -> None:
        self.flush()
        index = self.zstd.compress("".join(self.index).encode())
        index = struct.pack("<II", INDEX_MAGIC, len(index)) + index
        self.out.write(index)
        frames = [*self.frames, (len(index), 0)]
        table = b"".join(struct.pack("<II", *f) for f in frames) + struct.pack("<IBI", len(frames), 0, FOOTER_MAGIC)
        self.out.write(struct.pack("<II", SEEK_MAGIC, len(table)) + table)
        self.out.close()


class Bundle:
    """Random access to a bundle through its seek table."""

    def __init__(self, source):
        self.source = source
        size = source.size()
        count, _, magic = struct.unpack("<IBI", self._read(size - 9, 9))
        if magic != FOOTER_MAGIC:
            raise ValueError("no seek table at the end of the file")
        table = self._read(size - 9 - 8 * count, 8 * count)
        self.frames, at = [], 0
        for i in range(count):
            packed, plain = struct.unpack_from("<II", table, 8 * i)
            self.frames.append((at, packed, plain))
            at += packed
        self.zstd = zstandard.ZstdDecompressor()

    def _read(self, at: int, n: int) -> bytes:
        self.source.seek(at)
        return self.source.read(n)

    def frame(self, i: int) -> bytes:
        at, packed, plain = self.frames[i]
        return self.zstd.decompress(self._read(at, packed), max_output_size=plain)

    def index(self) -> dict[str, tuple[int, int]]:
        """record identifier -> (frame, offset inside the frame); of repeated identifiers the last."""
        at, packed, _ = self.frames[-1]
        lines = self.zstd.decompressobj().decompress(self._read(at + 8, packed - 8)).decode()
        return {k: (int(f), int(o)) for k, f, o in (line.split("\t") for line in lines.splitlines())}

    def record(self, record_id: str) -> Record:
        frame, offset = self.index()[record_id]
        return from_warc(self.frame(frame), offset)[0]

    def records(self) -> Iterator[Record]:
        for i in range(len(self.frames) - 1):
            data, at = self.frame(i), 0
            while at < len(data):
                r, at = from_warc(data, at)
                yield r


def opened(uri: str):
    """(file system, path) of a URI or a local path."""
    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{posixpath.abspath(uri)}")


def plan_records(pages: DataFrame, id_col: str = "page_id", url: str = "url", html: str = "html", least_bytes: int = 0) -> DataFrame:
    """(page_id, url, payload, refers_to): what to write; ``refers_to`` is null for responses."""
    payload = F.coalesce(F.col(html), F.lit("")).cast("binary")
    told = pages.select(F.col(id_col).alias("page_id"), F.col(url).alias("url"), payload.alias("payload"))
    sized = told.select("page_id", F.sha1("payload").alias("sha"), F.octet_length("payload").alias("n")).where(F.col("n") >= least_bytes)
    repeated = checkpointed(sized.groupBy("sha", "n").agg(F.max("page_id").alias("top"), F.count("*").alias("times")).where("times > 1 and top is not null").select("sha", F.col("n").alias("size"), "top"))
    keyed = told.withColumn("__sha", F.sha1("payload"))
    near = F.broadcast(repeated) if repeated.count() <= BROADCAST_ROWS else repeated
    joined = keyed.join(near, (F.col("__sha") == F.col("sha")) & (F.octet_length("payload") == F.col("size")), "left")
    refers = F.when(F.col("page_id") < F.col("top"), F.col("top"))
    return joined.select("page_id", "url", "payload", refers.alias("refers_to"))


def write_bundles(records: DataFrame, folder: str, bundle_bytes: int = 64 << 20, frame_bytes: int = 1 << 20, level: int = 3) -> DataFrame:
    """Write the rows of :func:`plan_records`; a row (path, records, bytes) for each bundle. Runs when the result is used: use it once."""

    def apply(batches):
        store, root = opened(folder)
        store.create_dir(root, recursive=True)
        task, n, writer, name, count = TaskContext.get(), 0, None, None, 0

        def finish():
            writer.close()
            store.move(f"{name}.{task.taskAttemptId()}.tmp", name)
            return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([count]), pa.array([writer.payload])], names=["path", "records", "bytes"])

        for batch in batches:
            for row in batch.to_pylist():
                if writer is None:
                    name, count, n = f"{root}/part-{task.partitionId():06d}-{n:04d}.warc.zst", 0, n + 1
                    writer = BundleWriter(store.open_output_stream(f"{name}.{task.taskAttemptId()}.tmp"), level, frame_bytes)
                full = row["payload"]
                again = row["refers_to"] is not None
                writer.add(Record(row["page_id"], row["url"], "revisit" if again else "response", b"" if again else full, len(full), digest_of(full), row["refers_to"]))
                count += 1
                if writer.payload >= bundle_bytes:
                    yield finish()
                    writer = None
        if writer is not None:
            yield finish()

    return map_in_arrow(records, apply, "path string, records long, bytes long")


def read_bundles(bundles: DataFrame, folder: str, payloads: bool = False) -> DataFrame:
    """(page_id, url, record_type, refers_to, payload_bytes, payload_digest [, payload]) of every record in bundles listed as ``path``.

    Frames are decompressed one by one; responses are checked against their digest.
    """
    names = ["page_id", "url", "record_type", "refers_to", "payload_bytes", "payload_digest", *(["payload"] if payloads else [])]
    types = [pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), *([pa.binary()] if payloads else [])]

    def apply(batches):
        store, _ = opened(folder)

        def out(rows):
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=names)

        for batch in batches:
            for path in batch.column(0).to_pylist():
                rows, held = [], 0
                with store.open_input_file(path) as f:
                    for r in Bundle(f).records():
                        if r.kind == "response" and (digest_of(r.payload), len(r.payload)) != (r.digest, r.payload_bytes):
                            raise ValueError(f"payload of {r.record_id} does not match its digest")
                        rows.append((r.page_id, r.url, r.kind, r.refers_to, r.payload_bytes, r.digest, *([r.payload] if payloads else [])))
                        held += len(r.payload) if payloads else 1
                        if held >= (16 << 20 if payloads else 20_000):
                            yield out(rows)
                            rows, held = [], 0
                if rows:
                    yield out(rows)

    schema = "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string" + (", payload binary" if payloads else "")
    return bundles.select("path").mapInArrow(apply, schema)


def archive(pages: DataFrame, folder: str, id_col: str = "page_id", url: str = "url", html: str = "html", least_bytes: int = 0, bundle_bytes: int = 64 << 20) -> DataFrame:
    """Write all pages into ``folder`` and return the manifest (path, records, bytes), written before this returns."""
    return checkpointed(write_bundles(plan_records(pages, id_col, url, html, least_bytes), folder, bundle_bytes))
