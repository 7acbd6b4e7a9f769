"""Embedding near-duplicates: sign hashing in several tables, exact cosine, connected components.

Equal vectors of a label become one class with a count, so copies cost one row. Random hyperplanes give each class a sign
code in each table; classes that agree in a table's whole code (and label and length) are compared exactly, in double precision, as blocks
of a matrix product. Small buckets travel in packs; one beyond a block is dealt as pairs of fixed-size blocks, so no task holds a
whole bucket. A pair that meets in several tables counts only in the first. Blocks return sums of partners per vector and a
spanning forest of the links, never the pairs.

The number of bits follows the number of classes, and the number of tables follows the bits, so that a pair at
the threshold is missed with a probability of at most ``MISS`` whatever the size. Products are cheap beside sending a vector to
one more table, so codes are short and buckets wide.

Edge cases: vectors that are null, empty, zero, or hold null or non-finite components, and rows without a label, link with nothing;
they and unlinked vectors are their own component; equal vectors link; rows that repeat a vec_id count each as a partner;
null ids get no component; a long vector is compared whole; pairs whose cosine as computed in doubles is the threshold link;
an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpgrid.llm.arrow import column, out
from dpgrid.plans.graph import connected_components
from dpgrid.plans.scratch import drop_tables, materialise

THRESHOLD, MISS = 0.98, 1e-5
#: Classes in a block of a bucket, and classes that a bucket would hold on average if all had one label.
BLOCK, BUCKET = 2048, 2048
#: Numbers in a pack of small buckets, about.
PACK = 1 << 20


def plan(classes: int, threshold: float = THRESHOLD, miss: float = MISS) -> tuple[int, int]:
    """Bits of a code and number of tables for so many classes."""
    bits = int(min(30, max(4, math.ceil(math.log2(max(2, classes / BUCKET))))))
    agree = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, math.ceil(math.log(miss) / math.log(1 - agree))


def planes(length: int, tables: int, bits: int, seed: int = 11) -> np.ndarray:
    """Normals of all hyperplanes, one per column; the same for a length wherever they are drawn."""
    return np.random.default_rng([seed, length]).standard_normal((length, tables * bits))


def codes(x: np.ndarray, tables: int, bits: int) -> np.ndarray:
    """Sign code of each row in each table."""
    side = (x @ planes(x.shape[1], tables, bits) > 0).reshape(len(x), tables, bits)
    return side @ (1 << np.arange(bits, dtype=np.int64))


def forest(a: np.ndarray, b: np.ndarray) -> list[tuple[int, int]]:
    """Edges that join the same vertices as ``a - b``, without cycles."""
    root: dict[int, int] = {}

    def top(v: int) -> int:
        while (up := root.get(v, v)) != v:
            root[v] = root.get(up, up)
            v = up
        return v

    kept = []
    for x, y in zip(a.tolist(), b.tolist(), strict=True):
        p, q = top(x), top(y)
        if p != q:
            root[max(p, q)] = min(p, q)
            kept.append((x, y))
    return kept


def _flat(values: pa.Array) -> np.ndarray:
    return values.flatten().to_numpy(zero_copy_only=False)


def compare(ids: np.ndarray, weight: np.ndarray, x: np.ndarray, code: np.ndarray, block: np.ndarray, first: int, second: int, table: int, threshold: float) -> tuple[dict[int, int], list[tuple[int, int]]]:
    """Partners per class and joining edges between two blocks of a bucket (or within one)."""
    x = x / np.abs(x).max(1, keepdims=True)
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    left, right = np.flatnonzero(block == first), np.flatnonzero(block == second)
    linked: list[tuple[np.ndarray, np.ndarray]] = []
    for lo in range(0, len(left), BLOCK):  # blocks are of expected size BLOCK; their parts bound the product
        rows = left[lo : lo + BLOCK]
        for k in range(0, len(right), BLOCK):
            cols = right[k : k + BLOCK]
            i, j = np.nonzero(x[rows] @ x[cols].T >= threshold)
            i, j = rows[i], cols[j]
            if first == second:
                i, j = i[i < j], j[i < j]
            if table and len(i):
                new = ~(code[i, :table] == code[j, :table]).any(1)
                i, j = i[new], j[new]
            linked.append((i, j))
    i, j = (np.concatenate(z) if z else np.empty(0, np.int64) for z in zip(*linked, strict=True)) if linked else (np.empty(0, np.int64),) * 2
    total = np.bincount(i, weight[j], len(ids)) + np.bincount(j, weight[i], len(ids))
    return {int(ids[k]): int(total[k]) for k in np.flatnonzero(total)}, forest(ids[i], ids[j])


def embedding_components(vectors: DataFrame, threshold: float = THRESHOLD, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label") -> DataFrame:
    """One row per vector: vec_id, n_links, component_id, kept."""
    plain = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(label_col).alias("label"), F.col(vector_col).alias("v"))
    if plain.schema["v"].dataType.elementType.typeName() != "float":  # floats travel as they are; all arithmetic is in doubles
        plain = plain.withColumn("v", F.transform("v", lambda e: e.cast("double")))
    number = plain.schema["v"].dataType.simpleString()
    sound = F.col("label").isNotNull() & (F.size("v") > 0) & F.forall("v", lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < float("inf"))) & F.exists("v", lambda e: e != 0)
    good = materialise(plain.where(F.coalesce(sound & F.col("vec_id").isNotNull(), F.lit(False))).select("vec_id", "label", "v", F.xxhash64("label", "v").alias("h")), "vectors")
    classes = materialise(good.groupBy("label", "h", "v").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("n")), "vector_classes")
    bits, tables = plan(classes.count(), threshold)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            v = column(batch, "v")
            sizes = np.diff(v.offsets.to_numpy())
            flat, ends = _flat(v), np.cumsum(sizes)
            made = np.empty((batch.num_rows, tables), np.int32)
            for size in np.unique(sizes):
                rows = np.flatnonzero(sizes == size)
                x = flat[(ends[rows] - size)[:, None] + np.arange(size)].astype(np.float64)
                with np.errstate(over="ignore", invalid="ignore"):
                    made[rows] = codes(x / np.abs(x).max(1, keepdims=True), tables, bits)
            yield out(["rep", "n", "label", "v", "code"], *(column(batch, c) for c in ("rep", "n", "label", "v")), pa.array(list(made), pa.list_(pa.int32())))

    kind = good.schema["label"].dataType.simpleString()
    coded = materialise(classes.select("rep", "n", "label", "v").mapInArrow(encode, f"rep long, n long, label {kind}, v {number}, code array<int>"), "vector_codes")
    key = F.xxhash64("label", F.size("v"), "table", "c")
    places = coded.select("rep", F.posexplode("code").alias("table", "c"), "label", "v")
    buckets = materialise(places.groupBy(key.alias("bucket"), "table").agg(F.count(F.lit(1)).alias("size"), F.max(F.size("v")).alias("length")).where("size > 1"), "buckets")
    small = F.col("size") <= BLOCK
    packs = max(1, -(-(buckets.where(small).agg(F.sum(F.col("size") * F.col("length"))).first()[0] or 0) // PACK))
    # A row's bucket, then its block of the bucket, then all pairs that this block has with another: ids only, until dealt.
    many = F.when(small, 1).otherwise(F.ceil(F.col("size") / BLOCK)).cast("int")
    slim = places.select("rep", "table", key.alias("bucket")).join(buckets.drop("length"), ["bucket", "table"]).withColumn("block", F.pmod(F.xxhash64("rep"), many).cast("int"))
    pack = F.when(small, F.pmod(F.xxhash64("bucket"), F.lit(packs))).otherwise(F.col("bucket"))
    seats = materialise(
        slim.select("rep", "bucket", "table", small.alias("small"), pack.alias("pack"), "block", F.explode(F.sequence(F.lit(0), many - 1)).alias("other")).select(
            "rep", "bucket", "table", "small", "pack", "block", F.least("block", "other").alias("first"), F.greatest("block", "other").alias("second")
        ),
        "vector_seats",
    )
    dealt = seats.join(coded.select("rep", "n", "v", "code"), "rep")

    def pairs(group: pa.Table) -> pa.Table:
        group = group.sort_by("bucket").combine_chunks()
        get = lambda c: group[c].to_numpy()
        bucket, table, ids, weight, block = (get(c) for c in ("bucket", "table", "rep", "n", "block"))
        first, second = group["first"][0].as_py(), group["second"][0].as_py()
        code = group["code"].combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
        v = group["v"].combine_chunks()
        flat, ends = v.flatten().to_numpy(), np.concatenate([[0], np.cumsum(pc.list_value_length(v).to_numpy())])
        total: dict[int, int] = {}
        links: list[tuple[int, int]] = []
        edges = np.flatnonzero(np.concatenate([[True], (bucket[1:] != bucket[:-1]) | (table[1:] != table[:-1])]))
        for lo, hi in zip(edges, [*edges[1:], len(ids)], strict=True):
            x = flat[ends[lo] : ends[hi]].reshape(hi - lo, -1).astype(np.float64)
            sums, found = compare(ids[lo:hi], weight[lo:hi], x, code[lo:hi], block[lo:hi], first, second, int(table[lo]), threshold)
            links += found
            for k, n in sums.items():
                total[k] = total.get(k, 0) + n
        rows = [(k, None, n) for k, n in total.items()] + [(a, b, 0) for a, b in links]
        a, b, n = zip(*rows, strict=True) if rows else ((), (), ())
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "links": pa.array(n, pa.int64())})

    found = materialise(dealt.groupBy("pack", "small", "first", "second").applyInArrow(pairs, "a long, b long, links long"), "vector_links")
    sums = found.where("b is null").groupBy("a").agg(F.sum("links").alias("others"))
    joined = connected_components(found.where("b is not null"), "a", "b")
    facts = materialise(
        classes.select("rep", "label", "h", "v", "n").join(sums.withColumnRenamed("a", "rep"), "rep", "left").join(joined.withColumnRenamed("vertex", "rep"), "rep", "left")
        .select("label", "h", "v", (F.col("n") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"), F.coalesce("component", "rep").alias("component_id")),
        "vector_facts",
    )
    drop_tables(facts.sparkSession, classes, coded, buckets, seats, found, joined)
    # Members find their class by equal label, hash and components; the hash alone would do but for collisions.
    own = good.join(facts, ["label", "h", "v"]).select("vec_id", "n_links", "component_id")
    rest = plain.where(~F.coalesce(sound & F.col("vec_id").isNotNull(), F.lit(False))).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return own.unionByName(rest).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))
