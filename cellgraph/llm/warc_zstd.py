"""WARC archives in seekable Zstandard bundles.

Layout of a bundle file: independent Zstandard frames, each holding a group of whole WARC
records, then a skippable frame with the seek table (compressed and decompressed size of
each frame) and its nine-byte footer.  A bundle therefore reads as a plain ``.warc.zst``
for any Zstandard tool, while one record costs one frame to read.  The record index maps a
record to (bundle, frame, offset inside the decompressed frame, length).

Writing is safe against lost and repeated tasks: a task writes to a name of its own and
renames when complete, and only files that the committed index names are ever read.
"""

from __future__ import annotations

import hashlib
import io
import struct
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .storage import materialise, shared_dir

# Fixed values of the Zstandard seekable format.
SKIPPABLE_MAGIC = 0x184D2A5E
SEEKABLE_MAGIC = 0x8F92EAB1
FOOTER = struct.Struct("<IBI")
ENTRY = struct.Struct("<II")
SKIP_HEADER = struct.Struct("<II")

HTTP_HEAD = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
DATE = "1970-01-01T00:00:00Z"

INDEX_SCHEMA = "record_id long, bundle string, frame int, frame_offset long, record_bytes long"
READ_SCHEMA = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"


def seek_table(frames: list[tuple[int, int]]) -> bytes:
    """Skippable frame with (compressed, decompressed) sizes and the footer."""
    body = b"".join(ENTRY.pack(*x) for x in frames) + FOOTER.pack(len(frames), 0, SEEKABLE_MAGIC)
    return SKIP_HEADER.pack(SKIPPABLE_MAGIC, len(body)) + body


class BundleWriter:
    """Groups records into frames of about ``frame_bytes`` and closes with the seek table."""

    def __init__(self, sink, frame_bytes: int = 1 << 20, level: int = 3):
        self.sink, self.frame_bytes = sink, frame_bytes
        self.packer = zstandard.ZstdCompressor(level=level, write_checksum=True)
        self.frames: list[tuple[int, int]] = []
        self.pending, self.pending_bytes, self.written = [], 0, 0

    def add(self, record: bytes) -> tuple[int, int]:
        """(frame, offset in the decompressed frame) of the record."""
        if self.pending_bytes and self.pending_bytes + len(record) > self.frame_bytes:
            self._flush()
        at = len(self.frames), self.pending_bytes
        self.pending.append(record)
        self.pending_bytes += len(record)
        return at

    def _flush(self) -> None:
        if self.pending:
            packed = self.packer.compress(b"".join(self.pending))
            self.sink.write(packed)
            self.frames.append((len(packed), self.pending_bytes))
            self.written += len(packed)
            self.pending, self.pending_bytes = [], 0

    def close(self) -> None:
        self._flush()
        self.sink.write(seek_table(self.frames))


class BundleReader:
    """Random access to a bundle through its footer; ``source`` is seekable."""

    def __init__(self, source):
        self.source = source
        size = source.seek(0, io.SEEK_END) if not hasattr(source, "size") else source.size()
        source.seek(size - FOOTER.size)
        count, _, magic = FOOTER.unpack(source.read(FOOTER.size))
        if magic != SEEKABLE_MAGIC:
            raise ValueError("no seek table at the end of the bundle")
        source.seek(size - FOOTER.size - count * ENTRY.size)
        table = np.frombuffer(source.read(count * ENTRY.size), dtype="<u4").reshape(-1, 2).astype(np.int64)
        self.sizes = table
        self.starts = np.concatenate([[0], np.cumsum(table[:, 0])]) if count else np.zeros(1, np.int64)

    def __len__(self) -> int:
        return len(self.sizes)

    def frame(self, k: int) -> bytes:
        self.source.seek(int(self.starts[k]))
        packed = self.source.read(int(self.sizes[k, 0]))
        return zstandard.ZstdDecompressor().decompress(packed, max_output_size=int(self.sizes[k, 1]))

    def record(self, frame: int, offset: int, length: int) -> bytes:
        return self.frame(frame)[offset : offset + length]


def _header(value) -> str:
    """One header line's value: line breaks in it would end the header."""
    return "" if value is None else "".join(c if c not in "\r\n" else " " for c in str(value))


def render_record(page_id, url, payload: bytes, digest: str, refers_to) -> bytes:
    """A WARC/1.1 record: the whole payload for a response, headers alone for a revisit."""
    kind = "response" if refers_to is None else "revisit"
    block = HTTP_HEAD + payload if refers_to is None else HTTP_HEAD
    lines = [
        "WARC/1.1",
        f"WARC-Type: {kind}",
        f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>",
        f"WARC-Date: {DATE}",
        f"WARC-Target-URI: {_header(url)}",
        f"WARC-Payload-Digest: sha256:{digest}",
        f"Payload-Length: {len(payload)}",
        "Content-Type: application/http; msgtype=response",
    ]
    if refers_to is not None:
        lines.append(f"WARC-Refers-To: <urn:page:{refers_to}>")
        lines.append("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")
    lines.append(f"Content-Length: {len(block)}")
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_records(frame: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, block) of each record of a decompressed frame."""
    at = 0
    while at < len(frame):
        end = frame.index(b"\r\n\r\n", at)
        head = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in frame[at:end].decode().split("\r\n")[1:])
        start = end + 4
        stop = start + int(head["Content-Length"])
        yield head, frame[start:stop]
        at = stop + 4


def _number(urn: str):
    digits = urn.removeprefix("<urn:page:").removesuffix(">")
    return int(digits) if digits else None


def plan_revisits(pages: DataFrame, id_col="page_id", url_col="url", payload_col="html", min_bytes: int = 100) -> DataFrame:
    """Each page with its digest and, for repeats of a payload, the page it refers to.

    Null payloads are empty.  Payloads of fewer than ``min_bytes`` bytes never become
    revisits.  The smallest id of a payload is its response; a row that repeats that id is a
    response too, since a record can't refer to itself.  Rows without an id stay responses.
    Copies are folded in every map task before the shuffle; the join back is an ordinary
    equi-join on the digest, whose hot keys adaptive execution can split.
    """
    body = F.coalesce(F.col(payload_col).cast("string"), F.lit(""))
    rows = pages.select(
        F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), body.alias("payload"), F.sha2(body.cast("binary"), 256).alias("digest"), F.octet_length(body).cast("long").alias("n"),
    )
    narrow = rows.filter(F.col("n") >= min_bytes).groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count("*").alias("copies")).filter("copies > 1").drop("copies")
    refers = F.when((F.col("first_id") != F.col("page_id")) & (F.col("n") >= min_bytes), F.col("first_id"))
    return rows.join(narrow, "digest", "left").select("page_id", "url", "payload", "digest", refers.alias("refers_to"))


def write_bundles(plan: DataFrame, folder: str, frame_bytes: int = 1 << 20, bundle_bytes: int = 256 << 20, level: int = 3) -> DataFrame:
    """Write bundles under ``folder``; the record index (``INDEX_SCHEMA``), one row a record.

    Evaluating the result writes the files, so materialise it once before reading from it.
    """

    def write(batches):
        store, root = fs.FileSystem.from_uri(folder)
        store.create_dir(root, recursive=True)
        out, sink, rows, part = None, None, [], None

        def finish():
            out.close()
            sink.close()
            store.move(f"{root}/{part}.part", f"{root}/{part}.warc.zst")
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 4
            return pa.RecordBatch.from_arrays(
                [pa.array(columns[0], pa.int64()), pa.array([f"{part}.warc.zst"] * len(rows), pa.string()), pa.array(columns[1], pa.int32()), pa.array(columns[2], pa.int64()), pa.array(columns[3], pa.int64())],
                names=["record_id", "bundle", "frame", "frame_offset", "record_bytes"],
            )

        for batch in batches:
            for page_id, url, payload, digest, refers_to in zip(*(batch.column(k) for k in range(5)), strict=True):
                if out is None:
                    part, rows = uuid.uuid4().hex, []
                    sink = store.open_output_stream(f"{root}/{part}.part")
                    out = BundleWriter(sink, frame_bytes, level)
                record = render_record(page_id.as_py(), url.as_py(), payload.as_py().encode(), digest.as_py(), refers_to.as_py())
                rows.append((page_id.as_py(), *out.add(record), len(record)))
                if out.written >= bundle_bytes:
                    yield finish()
                    out = None
        if out is not None:
            yield finish()

    return plan.select("page_id", "url", "payload", "digest", "refers_to").mapInArrow(write, INDEX_SCHEMA)


def read_bundles(spark: SparkSession, index: DataFrame, folder: str) -> DataFrame:
    """Every record of every bundle the index names; response payloads are hashed anew and
    must match the digest in their header."""

    def read(batches):
        store, root = fs.FileSystem.from_uri(folder)
        for batch in batches:
            for name in batch.column(0).to_pylist():
                with store.open_input_file(f"{root}/{name}") as source:
                    reader = BundleReader(source)
                    for k in range(len(reader)):
                        rows = []
                        for head, block in parse_records(reader.frame(k)):
                            digest, n = head["WARC-Payload-Digest"].removeprefix("sha256:"), int(head["Payload-Length"])
                            if head["WARC-Type"] == "response":
                                payload = block[len(HTTP_HEAD) :]
                                if len(payload) != n or hashlib.sha256(payload).hexdigest() != digest:
                                    raise ValueError(f"payload of {head['WARC-Record-ID']} in {name} differs from its digest")
                            refers = head.get("WARC-Refers-To")
                            rows.append((_number(head["WARC-Record-ID"]), n, digest, head["WARC-Type"], None if refers is None else _number(refers)))
                        kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64())
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=[c.split()[0] for c in READ_SCHEMA.split(", ")])

    names = index.select("bundle").distinct()
    # one archive a task: left alone, a few names would be gathered into a single task
    return names.repartition(max(1, min(names.count(), 20_000))).mapInArrow(read, READ_SCHEMA)


def fetch(folder: str, bundle: str, frame: int, frame_offset: int, record_bytes: int) -> bytes:
    """One record by its index entry: one footer and one frame are read."""
    store, root = fs.FileSystem.from_uri(folder)
    with store.open_input_file(f"{root}/{bundle}") as source:
        return BundleReader(source).record(frame, frame_offset, record_bytes)


def archive_pages(pages: DataFrame, folder: str | None = None, **options) -> tuple[DataFrame, DataFrame, str]:
    """(records read back, record index, folder) of all pages."""
    spark = pages.sparkSession
    folder = folder or shared_dir(spark, "warc")
    index = materialise(write_bundles(plan_revisits(pages), f"{folder}/bundles", **options), f"{folder}/index")
    return read_bundles(spark, index, f"{folder}/bundles"), index, f"{folder}/bundles"


def op9_warc_seekable(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    return archive_pages(pages)[0]


ORACLE_SQL = """
WITH p AS (
  SELECT page_id, encode(coalesce(html, '')) AS body FROM pages
), d AS (
  SELECT page_id, octet_length(body)::BIGINT AS payload_bytes, sha256(body) AS payload_digest FROM p
), f AS (
  SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first_id FROM d
)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 100 AND first_id <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 100 AND first_id <> page_id THEN first_id END AS refers_to
FROM f
"""
