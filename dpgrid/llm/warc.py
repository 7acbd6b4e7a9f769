"""WARC archives as seekable Zstandard bundles.

Records are grouped into independent frames; a skippable frame at the end of the file lists the compressed and plain
size of each frame (the public seekable layout), so any frame can be found from the file's tail and read alone. An
index table maps each record to file, frame and offset within the plain frame.

Of records with equal payloads of at least ``REVISIT_BYTES`` bytes the one with the largest page id keeps the payload; the
others become revisit records that name it. Equality is decided by SHA-1 and length in the JVM; only (digest, largest id) of
repeated payloads is joined back, and adaptive execution splits a digest that many pages share.

Edge cases: a null html is an empty payload; a null url is written as an empty target; line breaks in urls are escaped;
rows that repeat the largest page id of their payload are all responses; null page ids are written and read back as null and
never own a payload unless all ids of the group are null; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import struct
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpgrid.llm.arrow import chunks, column, out, strings
from dpgrid.llm.shared_files import write_bytes
from dpgrid.plans.scratch import materialise, new_path

REVISIT_BYTES = 1000
#: Plain bytes after which a frame ends, and compressed bytes after which a file ends.
FRAME_BYTES, FILE_BYTES = 256 << 10, 64 << 20
#: Fixed values of the public seekable layout.
SKIPPABLE, SEEK_MAGIC = 0x184D2A5E, 0x8F92EAB1
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"
_BREAKS = re.compile(r"[\r\n]")


class BundleWriter:
    """Frames of records and the closing seek table, in memory up to a file's size."""

    def __init__(self, level: int = 3, frame_bytes: int = FRAME_BYTES):
        self.zip, self.frame_bytes = zstandard.ZstdCompressor(level=level), frame_bytes
        self.frames: list[bytes] = []
        self.sizes: list[tuple[int, int]] = []
        self.open: list[bytes] = []
        self.at = self.written = 0

    def add(self, record: bytes) -> tuple[int, int]:
        """Append a record; its frame number and offset there."""
        where = len(self.frames), self.at
        self.open.append(record)
        self.at += len(record)
        if self.at >= self.frame_bytes:
            self.end_frame()
        return where

    def end_frame(self) -> None:
        if self.open:
            packed = self.zip.compress(b"".join(self.open))
            self.frames.append(packed)
            self.sizes.append((len(packed), self.at))
            self.written += len(packed)
            self.open, self.at = [], 0

    def close(self) -> bytes:
        self.end_frame()
        table = b"".join(struct.pack("<II", *s) for s in self.sizes) + struct.pack("<IBI", len(self.sizes), 0, SEEK_MAGIC)
        return b"".join([*self.frames, struct.pack("<II", SKIPPABLE, len(table)), table])


class Bundle:
    """Random access to a bundle's frames."""

    def __init__(self, data: bytes):
        count, flags, magic = struct.unpack_from("<IBI", data, len(data) - 9)
        if magic != SEEK_MAGIC:
            raise ValueError("no seek table")
        wide = 12 if flags & 0x80 else 8
        self.data, self.sizes, self.starts, at = data, [], [], 0
        for k in range(count):
            packed, plain = struct.unpack_from("<II", data, len(data) - 9 - wide * (count - k))
            self.starts.append(at)
            self.sizes.append((packed, plain))
            at += packed

    def frame(self, k: int) -> bytes:
        packed, plain = self.sizes[k]
        return zstandard.ZstdDecompressor().decompress(memoryview(self.data)[self.starts[k] : self.starts[k] + packed], max_output_size=plain)

    def record(self, frame: int, offset: int) -> tuple[dict[str, str], bytes]:
        """Headers and block of one record, found by the index."""
        return next(records(self.frame(frame)[offset:]))


def records(plain: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and block of each record in a plain frame."""
    at = 0
    while at < len(plain):
        end = plain.index(b"\r\n\r\n", at)
        head = dict(line.split(": ", 1) for line in plain[at:end].decode("utf-8").split("\r\n")[1:])
        size = int(head["Content-Length"])
        yield head, plain[end + 4 : end + 4 + size]
        at = end + 4 + size + 4


def name_of(page_id: int | None) -> str:
    return f"<urn:page:{'' if page_id is None else page_id}>"


def id_of(name: str) -> int | None:
    return int(name[10:-1]) if len(name) > 11 else None


def record_bytes(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, revisit: bool) -> bytes:
    """One response or revisit record; a revisit keeps the HTTP head, which tells the payload's length."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    target = _BREAKS.sub(lambda m: f"%{ord(m[0]):02X}", url or "")
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: {name_of(page_id)}", f"WARC-Target-URI: {target}", f"WARC-Date: {DATE}", f"WARC-Payload-Digest: sha1:{digest}"]
    if revisit:
        head += [f"WARC-Refers-To: {name_of(refers_to)}", f"WARC-Profile: {PROFILE}"]
    body = http if revisit else http + payload
    head += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(body)}"]
    return b"".join(["\r\n".join(head).encode(), b"\r\n\r\n", body, b"\r\n\r\n"])


def with_owners(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``page_id, url, html, digest, owner``: owner is the page that keeps a repeated long payload, else null."""
    plain = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.coalesce(F.col(html_col).cast("string"), F.lit("")).alias("html"))
    size, digest = F.octet_length("html").cast("long"), F.sha1(F.col("html").cast("binary"))
    repeated = materialise(
        plain.select("page_id", size.alias("size"), digest.alias("digest"))
        .where(F.col("size") >= REVISIT_BYTES)
        .groupBy("digest", "size")
        .agg(F.max("page_id").alias("owner"), F.count(F.lit(1)).alias("n"))
        .where("n > 1")
        .select("digest", "size", "owner"),
        "repeated_payloads",
    )
    return plain.withColumns({"digest": digest, "size": size}).join(repeated, ["digest", "size"], "left").drop("size")


def write_bundles(pages: DataFrame, out_dir: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Write the archives to ``out_dir``; returns the index ``page_id, file, frame, offset``."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number, bundle = TaskContext.get().partitionId(), 0, BundleWriter()
        ids, frames, offsets = [], [], []

        def close():
            nonlocal number, bundle
            name = f"part-{part:08d}-{number:06d}.warc.zst"
            write_bytes(f"{out_dir}/{name}", bundle.close())
            made = out(["page_id", "file", "frame", "offset"], pa.array(ids, pa.int64()), [name] * len(ids), pa.array(frames, pa.int32()), pa.array(offsets, pa.int64()))
            number, bundle = number + 1, BundleWriter()
            for x in (ids, frames, offsets):
                x.clear()
            return made

        for piece in chunks(batches, "html"):
            payloads = [h or b"" for h in column(piece, "html").cast(pa.binary()).to_pylist()]
            for page, url, payload, digest, owner in zip(strings(piece, "page_id"), strings(piece, "url"), payloads, strings(piece, "digest"), strings(piece, "owner"), strict=True):
                revisit = owner is not None and owner != page
                frame, offset = bundle.add(record_bytes(page, url, payload, digest, owner, revisit))
                ids.append(page)
                frames.append(frame)
                offsets.append(offset)
                if bundle.written >= FILE_BYTES:
                    yield close()
        if ids:
            yield close()

    return materialise(with_owners(pages, id_col, url_col, html_col).mapInArrow(write, "page_id long, file string, frame int, offset long"), "warc_index")


def read_bundles(spark: SparkSession, out_dir: str) -> DataFrame:
    """One row per record of all archives: page_id, payload_bytes, payload_digest, record_type, refers_to."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in column(batch, "content"):
                bundle = Bundle(content.as_py())
                for k in range(len(bundle.sizes)):
                    rows = []
                    for head, block in records(bundle.frame(k)):
                        http, _, payload = block.partition(b"\r\n\r\n")
                        size = int(re.search(rb"\r\nContent-Length: (\d+)", http)[1])
                        digest = head["WARC-Payload-Digest"].removeprefix("sha1:")
                        kind = head["WARC-Type"]
                        if kind == "response" and (len(payload) != size or hashlib.sha1(payload).hexdigest() != digest):
                            raise ValueError(f"damaged record {head['WARC-Record-ID']}")
                        rows.append((id_of(head["WARC-Record-ID"]), size, digest, kind, id_of(head.get("WARC-Refers-To", name_of(None)))))
                    cols = list(zip(*rows, strict=True))
                    yield out(["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"], pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), cols[2], cols[3], pa.array(cols[4], pa.int64()))

    files = spark.read.format("binaryFile").schema("path string, modificationTime timestamp, length long, content binary").option("pathGlobFilter", "*.warc.zst").load(out_dir)
    return files.select("content").mapInArrow(read, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def archive(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Write all pages to archives in the shared folder, and read the archives back."""
    spark = pages.sparkSession
    where = new_path(spark, "warc")
    path = spark._jvm.org.apache.hadoop.fs.Path(where)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).mkdirs(path)
    write_bundles(pages, where, id_col, url_col, html_col)
    return read_bundles(spark, where)
