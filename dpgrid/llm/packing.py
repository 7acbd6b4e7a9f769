"""Concatenate and cut: all documents end to end, cut into windows of fixed length.

Pass one encodes each document where it lies, counts ids from the start of its partition, and writes
the ids to the shared folder. Totals per partition, summed in order of the partitions, give every document its
global offset. Pass two cuts the documents at the multiples of the window length, in the JVM: a document
over a boundary gets a piece on either side. Only the last window can be short.

Edge cases: a null or empty text is its end id alone; repeated rows are packed as often as they occur;
null ids are carried; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dpgrid.llm.arrow import ENCODE_BYTES, chunks, column, out, strings
from dpgrid.llm.tokens import library_encoder
from dpgrid.plans.scratch import materialise

WINDOW = 1024


def encoded(docs: DataFrame, tokenizer: str, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pass one: ``part, local, doc_id, n, ids`` (ids as little-endian uint32), materialised."""

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        library, part, at, end = library_encoder(tokenizer), TaskContext.get().partitionId(), 0, np.array([end_id], np.uint32)
        for piece in chunks(batches, "text", ENCODE_BYTES):
            rows = [np.concatenate([row, end]) for row in library(strings(piece, "text"))]
            sizes = np.array([len(r) for r in rows], np.int64)
            starts = at + np.cumsum(sizes) - sizes
            at += int(sizes.sum())
            yield out(["part", "local", "doc_id", "n", "ids"], np.full(len(rows), part, np.int32), starts, column(piece, "doc_id"), sizes, pa.array([r.astype("<u4").tobytes() for r in rows], pa.binary()))
        library.cache.clear()  # the worker lives on, and with it what it knows

    plain = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return materialise(plain.mapInArrow(encode, "part int, local long, doc_id long, n long, ids binary"), "encoded")


def concatenate_and_cut(rows: DataFrame, window: int = WINDOW) -> DataFrame:
    """Pass two: one row per piece of the table that ``encoded`` wrote."""
    totals = rows.groupBy("part").agg(F.sum("n").alias("total"))
    # One row of two numbers per input partition; summed in one task and small enough to broadcast.
    before = totals.select("part", (F.sum("total").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, 0)) - F.col("total")).alias("before"))
    placed = rows.join(F.broadcast(before), "part").select("doc_id", "n", "ids", (F.col("before") + F.col("local")).alias("g"))
    w = F.lit(window)

    def piece(s):
        lo, hi = F.greatest(s * w, F.col("g")), F.least((s + 1) * w, F.col("g") + F.col("n"))
        start, length = lo - F.col("g"), hi - lo
        ids = F.substring(F.col("ids"), (start * 4 + 1).cast("int"), (length * 4).cast("int"))
        return F.struct(start.alias("start"), length.alias("length"), F.crc32(ids).alias("ids_crc32"), s.alias("sequence_id"), (lo - s * w).alias("offset"))

    windows = F.sequence(F.floor(F.col("g") / w), F.floor((F.col("g") + F.col("n") - 1) / w))
    return placed.select("doc_id", F.col("n").alias("doc_tokens"), F.explode(F.transform(windows, piece)).alias("p")).select(
        "doc_id", "p.start", "p.length", "p.ids_crc32", "doc_tokens", "p.sequence_id", "p.offset"
    )


def pack_documents(docs: DataFrame, tokenizer: str, end_id: int = 0, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of all documents: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    return concatenate_and_cut(encoded(docs, tokenizer, end_id, id_col, text_col), window)
