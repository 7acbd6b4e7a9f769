"""Token-id files: ids bit-packed at the vocabulary's width, with block offsets for random access.

Layout of a file (all integers little-endian)::

    magic "DPTOKEN1" | bits u32 | block u32 | documents u64 | tokens u64
    document ids i64[documents] | id is present u8[documents] | first token u64[documents + 1]
    byte offset of each block u64[blocks + 1]     (from the start of the packed part)
    packed blocks: ``block`` ids of ``bits`` bits each, low bit first, padded to a byte per block

Files are named in document order (part, then number within the part). Documents are ranged by id, so
the files of a run, read in name order, hold all ids in ascending document order.

Edge cases: a null or empty text has only the end id; rows with a null id come first; rows that repeat an
id are all stored, side by side; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dpgrid.llm.arrow import ENCODE_BYTES, chunks, column, out, strings
from dpgrid.llm.shared_files import write_bytes
from dpgrid.llm.tokens import library_encoder, vocabulary_size
from dpgrid.plans.scratch import materialise, new_path

MAGIC = b"DPTOKEN1"
HEAD = struct.Struct("<8sIIQQ")
#: Ids in a block, and ids after which a task begins another file.
BLOCK, FILE_TOKENS = 4096, 1 << 24


def bits_for(vocabulary: int) -> int:
    """Least number of bits that holds every id below ``vocabulary``."""
    return max(1, int(vocabulary - 1).bit_length())


def pack(ids: np.ndarray, bits: int) -> bytes:
    """Ids → consecutive ``bits``-bit fields, low bit first, padded to whole bytes."""
    if bits in (8, 16, 32):
        return ids.astype(f"<u{bits // 8}").tobytes()
    return np.packbits((ids[:, None].astype(np.uint32) >> np.arange(bits, dtype=np.uint32)) & 1 == 1, bitorder="little").tobytes()


def unpack(data, count: int, bits: int) -> np.ndarray:
    """Inverse of ``pack`` for ``count`` ids, as uint32."""
    if bits in (8, 16, 32):
        return np.frombuffer(data, f"<u{bits // 8}", count).astype(np.uint32)
    flat = np.unpackbits(np.frombuffer(data, np.uint8), count=count * bits, bitorder="little").reshape(count, bits)
    return flat.astype(np.uint32) @ (np.uint32(1) << np.arange(bits, dtype=np.uint32))


def file_bytes(doc_ids: list[int | None], rows: list[np.ndarray], bits: int, block: int = BLOCK) -> bytes:
    """One file of the layout above."""
    ids = np.concatenate(rows) if rows else np.empty(0, np.uint32)
    first = np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype("<u8")
    packed = [pack(ids[i : i + block], bits) for i in range(0, len(ids), block)]
    offsets = np.concatenate([[0], np.cumsum([len(p) for p in packed])]).astype("<u8")
    known = np.array([d is not None for d in doc_ids], np.uint8)
    names = np.array([d or 0 for d in doc_ids], "<i8")
    return b"".join([HEAD.pack(MAGIC, bits, block, len(rows), len(ids)), names.tobytes(), known.tobytes(), first.tobytes(), offsets.tobytes(), *packed])


class TokenFile:
    """Random access to one file's bytes."""

    def __init__(self, data: bytes):
        self.data = memoryview(data)
        magic, self.bits, self.block, self.documents, self.tokens = HEAD.unpack_from(data)
        if magic != MAGIC:
            raise ValueError("not a token file")
        at, n = HEAD.size, self.documents
        self.doc_ids = np.frombuffer(data, "<i8", n, at)
        self.known = np.frombuffer(data, np.uint8, n, at + 8 * n).astype(bool)
        self.first = np.frombuffer(data, "<u8", n + 1, at + 9 * n).astype(np.int64)
        blocks = -(-self.tokens // self.block)
        self.offsets = np.frombuffer(data, "<u8", blocks + 1, at + 17 * n + 8).astype(np.int64)
        self.start = at + 17 * n + 8 + 8 * (blocks + 1)

    def read(self, lo: int, hi: int) -> np.ndarray:
        """Ids ``lo`` to ``hi`` of the file; only the blocks that hold them are unpacked."""
        if hi <= lo:
            return np.empty(0, np.uint32)
        b0, b1 = lo // self.block, (hi - 1) // self.block
        parts = [
            unpack(self.data[self.start + self.offsets[b] : self.start + self.offsets[b + 1]], min(self.block, self.tokens - b * self.block), self.bits)
            for b in range(b0, b1 + 1)
        ]
        return np.concatenate(parts)[lo - b0 * self.block : hi - b0 * self.block]

    def document(self, k: int) -> np.ndarray:
        return self.read(int(self.first[k]), int(self.first[k + 1]))


def write_token_files(docs: DataFrame, out_dir: str, tokenizer: str, end_id: int, id_col: str = "doc_id", text_col: str = "text", file_tokens: int = FILE_TOKENS) -> DataFrame:
    """Encode ``docs`` and write the files to ``out_dir``; returns the manifest (file, documents, tokens)."""
    bits = bits_for(max(vocabulary_size(tokenizer), end_id + 1))

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part, number = library_encoder(tokenizer), TaskContext.get().partitionId(), 0
        ids: list[int | None] = []
        rows: list[np.ndarray] = []
        held, end = 0, np.array([end_id], np.uint32)

        def close():
            nonlocal number, held
            name = f"part-{part:08d}-{number:06d}.tok"
            write_bytes(f"{out_dir}/{name}", file_bytes(ids, rows, bits))
            made = out(["file", "documents", "tokens"], [name], [len(rows)], [held])
            number, held = number + 1, 0
            ids.clear()
            rows.clear()
            return made

        for piece in chunks(batches, "text", ENCODE_BYTES):
            for doc, row in zip(strings(piece, "doc_id"), encode(strings(piece, "text")), strict=True):
                ids.append(doc)
                rows.append(np.concatenate([row, end]))
                held += len(rows[-1])
                if held >= file_tokens:
                    yield close()
        encode.cache.clear()  # the worker lives on, and with it what it knows
        if rows:
            yield close()

    ordered = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))
    return materialise(ordered.mapInArrow(write, "file string, documents long, tokens long"), "token_manifest")


def read_token_files(spark: SparkSession, out_dir: str, manifest: DataFrame) -> DataFrame:
    """Documents of the files: ``doc_id, start, n_tokens, ids_crc32``; start counts over all files before."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, content in zip(column(batch, "path"), column(batch, "content"), strict=True):
                file = TokenFile(content.as_py())
                n = file.documents
                crc = np.fromiter((zlib.crc32(file.document(k).astype("<u4").tobytes()) for k in range(n)), np.int64, n)
                doc = pa.array(file.doc_ids.astype(np.int64), mask=~file.known)
                yield out(["file", "doc_id", "local", "n_tokens", "ids_crc32"], [path.as_py().rpartition("/")[2]] * n, doc, file.first[:-1], np.diff(file.first), crc)

    files = spark.read.format("binaryFile").schema("path string, modificationTime timestamp, length long, content binary").option("pathGlobFilter", "*.tok").load(out_dir)
    rows = files.select("path", "content").mapInArrow(read, "file string, doc_id long, local long, n_tokens long, ids_crc32 long")
    # One row per file: a few hundred bytes for each 16 million ids, so a single ordered task is enough.
    before = manifest.select("file", (F.sum("tokens").over(Window.orderBy("file").rowsBetween(Window.unboundedPreceding, 0)) - F.col("tokens")).alias("before"))
    return rows.join(before, "file").select("doc_id", (F.col("before") + F.col("local")).alias("start"), "n_tokens", "ids_crc32")


def token_files(docs: DataFrame, tokenizer: str, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Write all documents' ids to files in the shared folder, and read the files back."""
    spark = docs.sparkSession
    where = new_path(spark, "token_files")
    spark_path = spark._jvm.org.apache.hadoop.fs.Path(where)
    spark_path.getFileSystem(spark._jsc.hadoopConfiguration()).mkdirs(spark_path)
    manifest = write_token_files(docs, where, tokenizer, end_id, id_col, text_col)
    return read_token_files(spark, where, manifest)
