"""Line deduplication over a sharded minimal perfect hash.

A first pass sends each document's distinct line hashes (two 64-bit halves of a 128-bit hash) to a map-side
combined count. Lines found in enough documents go, by hash, into shards; each shard becomes a minimal
perfect hash with three arrays beside it: fingerprint (the other hash half), number of documents, and largest
document id. Shards are files in the shared folder. The second pass gathers the line hashes of many documents, sorts them by
shard, and maps or fetches each shard that they need once; documents are never joined with lines and never move.

The perfect hash is a cascade of bit arrays: a key that meets no other key at its place of a level owns
that bit, the rest go on to the next level; a key's number is the rank of its bit.

Edge cases: a null or empty text is one empty line; a row is a document, so repeated rows count each; null ids are
never the largest; ties do not arise within a document, whose lines all stay if it holds the largest id; a text or line of any
length is hashed whole; an empty table gives no rows; other columns pass through, except those named as the result's columns.
"""

from __future__ import annotations

import json
import mmap
from collections import OrderedDict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dpgrid.llm.arrow import SPACES, chunks, column, out
from dpgrid.llm.shared_files import read_bytes, write_bytes
from dpgrid.plans.scratch import materialise, new_path

MIN_CHARS, MIN_DOCS = 20, 3
#: Keys a shard holds on average; least number of shards.
SHARD_KEYS, LEAST_SHARDS = 250_000, 16
#: Bytes of fetched shards and number of mapped ones that a worker keeps open between probes.
FETCHED_BYTES, MAPPED = 256 << 20, 256
#: Text bytes whose lines are looked up together: each shard is opened once for so many.
PROBE_BYTES = 16 << 20
_SPACES = SPACES.encode()


def mixed(keys: np.ndarray, salt: int) -> np.ndarray:
    """A fresh 64-bit hash of each key for each salt."""
    with np.errstate(over="ignore"):
        x = keys + np.uint64((salt * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & (2**64 - 1))
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


class PerfectHash:
    """Minimal perfect hash of distinct 64-bit keys."""

    def __init__(self, levels: list[np.ndarray], ranks: list[np.ndarray], rest: np.ndarray, first_rest: int):
        self.levels, self.ranks, self.rest, self.first_rest = levels, ranks, rest, first_rest

    @classmethod
    def build(cls, keys: np.ndarray, gamma: float = 2.0, most_levels: int = 40) -> PerfectHash:
        levels, ranks, count, left = [], [], 0, keys
        while len(left) and len(levels) < most_levels:
            words = max(1, int(gamma * len(left) + 63) // 64)
            place = mixed(left, len(levels)) % np.uint64(words * 64)
            hits = np.bincount(place.astype(np.int64), minlength=words * 64)
            bits = np.packbits(hits == 1, bitorder="little").view("<u8")
            each = np.bitwise_count(bits).astype(np.int64)
            levels.append(bits)
            ranks.append((count + np.cumsum(each) - each).astype(np.int64))
            count += int(each.sum())
            left = left[hits[place.astype(np.int64)] > 1]
        return cls(levels, ranks, np.sort(left), count)

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        """The key's number, or for an unknown key any number or -1."""
        got = np.full(len(keys), -1, np.int64)
        open_ = np.arange(len(keys))
        for salt, (bits, rank) in enumerate(zip(self.levels, self.ranks, strict=True)):
            if not len(open_):
                return got
            place = mixed(keys[open_], salt) % np.uint64(len(bits) * 64)
            word, bit = (place >> np.uint64(6)).astype(np.int64), place & np.uint64(63)
            row = bits[word]
            hit = (row >> bit) & np.uint64(1) == 1
            below = row[hit] & ((np.uint64(1) << bit[hit]) - np.uint64(1))
            got[open_[hit]] = rank[word[hit]] + np.bitwise_count(below)
            open_ = open_[~hit]
        if len(open_) and len(self.rest):
            at = np.minimum(np.searchsorted(self.rest, keys[open_]), len(self.rest) - 1)
            same = self.rest[at] == keys[open_]
            got[open_[same]] = self.first_rest + at[same]
        return got


def shard_bytes(keys: np.ndarray, prints: np.ndarray, counts: np.ndarray, last: np.ndarray) -> bytes:
    """A shard's file: a JSON head (padded to 8 bytes, its length first), then the arrays."""
    order = PerfectHash.build(keys)
    at = order(keys)
    placed = [np.empty(len(keys), d) for d in ("<u8", "<u4", "<i8")]
    for array, values in zip(placed, (prints, np.minimum(counts, 2**32 - 1), last), strict=True):
        array[at] = values
    parts = [*order.levels, *order.ranks, order.rest, *placed]
    kinds = [str(p.dtype.newbyteorder("<").str) for p in parts]
    head = json.dumps({"levels": len(order.levels), "first_rest": order.first_rest, "kinds": kinds, "sizes": [len(p) for p in parts]}).encode()
    head += b" " * (-len(head) % 8)
    return b"".join([len(head).to_bytes(8, "little"), head, *(p.tobytes() + b"\0" * (-p.nbytes % 8) for p in parts)])


class Shard:
    def __init__(self, data):
        size = int.from_bytes(data[:8], "little")
        head, at, parts = json.loads(bytes(data[8 : 8 + size])), 8 + size, []
        for kind, n in zip(head["kinds"], head["sizes"], strict=True):
            parts.append(np.frombuffer(data, kind, n, at))
            at += -(-parts[-1].nbytes // 8) * 8
        k = head["levels"]
        self.hash = PerfectHash(parts[:k], parts[k : 2 * k], parts[2 * k], head["first_rest"])
        self.prints, self.counts, self.last = parts[2 * k + 1 :]

    def probe(self, keys: np.ndarray, prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Number of documents (0: not in the index) and largest document id of each line."""
        at = self.hash(keys)
        ok = at >= 0
        ok[ok] = self.prints[at[ok]] == prints[ok]
        counts, last = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64)
        counts[ok], last[ok] = self.counts[at[ok]], self.last[at[ok]]
        return counts, last


class LineIndex:
    """All shards of a folder; opened when first probed."""

    def __init__(self, where: str, shards: int):
        self.where, self.shards, self.open, self.held = where, shards, OrderedDict(), 0

    def shard(self, k: int) -> Shard:
        if k in self.open:
            self.open.move_to_end(k)
            return self.open[k][0]
        uri = f"{self.where}/shard-{k:08d}.mph"
        if uri.startswith("file:"):
            with open("/" + uri[5:].lstrip("/"), "rb") as f:
                got = Shard(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)), 0
        else:
            data = read_bytes(uri)
            got = Shard(data), len(data)
        self.open[k] = got
        self.held += got[1]
        while (self.held > FETCHED_BYTES or len(self.open) > MAPPED) and len(self.open) > 1:
            self.held -= self.open.popitem(last=False)[1][1]
        return got[0]

    def probe(self, keys: np.ndarray, prints: np.ndarray, present: set[int]) -> tuple[np.ndarray, np.ndarray]:
        counts, last = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64)
        if not len(keys):
            return counts, last
        home = shard_of(keys, self.shards)
        order = np.argsort(home, kind="stable")
        edges = np.flatnonzero(np.diff(home[order], prepend=-1))
        for lo, hi in zip(edges, [*edges[1:], len(order)], strict=True):
            rows = order[lo:hi]
            if int(home[rows[0]]) in present:
                counts[rows], last[rows] = self.shard(int(home[rows[0]])).probe(keys[rows], prints[rows])
        return counts, last


def shard_of(keys: np.ndarray, shards: int) -> np.ndarray:
    return ((keys >> np.uint64(32)) * np.uint64(shards) >> np.uint64(32)).astype(np.int64)


def key_of(line: bytes) -> bytes:
    """Blanks off both ends, A-Z to lower case (UTF-8 bytes of other letters are untouched)."""
    return line.strip(_SPACES).lower()


def long_enough(key: bytes, chars: int) -> bool:
    return len(key) >= chars and (len(key) >= 4 * chars or len(key.decode("utf-8", "replace")) >= chars)


def _hashes(keys: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    both = np.frombuffer(b"".join(map(xxhash.xxh3_128_digest, keys)), ">u8").astype(np.uint64).reshape(-1, 2)
    return both[:, 0], both[:, 1]


def _texts(batch: pa.RecordBatch, text: str) -> list[bytes]:
    return [t or b"" for t in column(batch, text).cast(pa.binary()).to_pylist()]


def line_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """Per distinct line key: hash halves, number of documents, largest document id."""

    def lines(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in chunks(batches, "text"):
            keys, sizes = [], []
            for text in _texts(piece, "text"):
                own = {k for line in text.split(b"\n") if long_enough(k := key_of(line), min_chars)}
                keys += own
                sizes.append(len(own))
            if keys:
                a, b = _hashes(keys)
                doc = column(piece, "doc_id").take(pa.array(np.repeat(np.arange(len(sizes)), sizes)))
                yield out(["a", "b", "doc_id"], a.view(np.int64), b.view(np.int64), doc)

    plain = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return plain.mapInArrow(lines, "a long, b long, doc_id long").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n_docs"), F.max("doc_id").alias("last_doc"))


def build_index(counts: DataFrame, min_docs: int = MIN_DOCS) -> tuple[str, int, set[int]]:
    """Write the shards of all lines in at least ``min_docs`` documents; (folder, shards, shards with keys)."""
    spark = counts.sparkSession
    kept = materialise(counts.where(F.col("n_docs") >= min_docs), "frequent_lines")
    shards = max(LEAST_SHARDS, -(-kept.count() // SHARD_KEYS))
    where = new_path(spark, "line_index")

    def build(group: pa.Table) -> pa.Table:
        col = lambda name: group[name].to_numpy()
        k = group["shard"][0].as_py()
        last = group["last_doc"].fill_null(np.iinfo(np.int64).min).to_numpy()
        data = shard_bytes(col("a").view(np.uint64), col("b").view(np.uint64), col("n_docs"), last)
        write_bytes(f"{where}/shard-{k:08d}.mph", data)
        return pa.table({"shard": [k], "keys": [group.num_rows]})

    # The same arithmetic as shard_of: the upper 32 bits, scaled.
    shard = F.shiftrightunsigned(F.shiftrightunsigned("a", 32) * F.lit(shards), 32).alias("shard")
    made = kept.select(shard, "a", "b", "n_docs", "last_doc").groupBy("shard").applyInArrow(build, "shard long, keys long")
    return where, shards, {r["shard"] for r in made.collect()}  # a number per shard


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS) -> DataFrame:
    """``docs`` with repeated lines taken out of the text, and columns ``n_lines`` (before) and ``n_dropped``."""
    where, shards, present = build_index(line_counts(docs, id_col, text_col, min_chars), min_docs)
    passed = [f for f in docs.schema.fields if f.name not in ("n_lines", "n_dropped")]
    schema = T.StructType([T.StructField(f.name, T.StringType() if f.name == text_col else f.dataType) for f in passed] + [T.StructField("n_lines", T.LongType()), T.StructField("n_dropped", T.LongType())])

    def hashed(piece: pa.RecordBatch) -> tuple[np.ndarray, ...]:
        """Row, place in the row, and hash halves of all lines that are long enough."""
        owner, place, keys = [], [], []
        for i, text in enumerate(_texts(piece, text_col)):
            for j, line in enumerate(text.split(b"\n")):
                if long_enough(k := key_of(line), min_chars):
                    owner.append(i)
                    place.append(j)
                    keys.append(k)
        return np.array(owner, np.int64), np.array(place, np.int64), *(_hashes(keys) if keys else (np.empty(0, np.uint64),) * 2)

    def finish(piece: pa.RecordBatch, owner: np.ndarray, place: np.ndarray, found: np.ndarray, last: np.ndarray) -> pa.RecordBatch:
        """The piece without the lines that the index condemns."""
        ids = column(piece, id_col).cast(pa.int64())
        known, mine = np.asarray(ids.is_valid()), ids.fill_null(0).to_numpy(zero_copy_only=False)
        gone = np.flatnonzero((found >= min_docs) & ~(known[owner] & (last == mine[owner])))
        doomed: dict[int, set[int]] = {}
        for x in gone:
            doomed.setdefault(int(owner[x]), set()).add(int(place[x]))
        texts = _texts(piece, text_col)
        kept = [b"\n".join(line for j, line in enumerate(t.split(b"\n")) if j not in doomed[i]) if i in doomed else t for i, t in enumerate(texts)]
        cols = {name: column(piece, name) for name in piece.schema.names} | {text_col: pa.array([k.decode("utf-8", "replace") for k in kept], pa.string())}
        cols |= {"n_lines": pa.array([t.count(b"\n") + 1 for t in texts], pa.int64()), "n_dropped": pa.array([len(doomed.get(i, ())) for i in range(len(texts))], pa.int64())}
        return out([*cols], *cols.values())

    def clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = LineIndex(where, shards)

        def flush(held: list) -> Iterator[pa.RecordBatch]:
            found, last = index.probe(*(np.concatenate([h[k] for _, h in held]) for k in (2, 3)), present)
            at = 0
            for piece, (owner, place, a, _) in held:
                yield finish(piece, owner, place, found[at : at + len(a)], last[at : at + len(a)])
                at += len(a)

        held, size = [], 0
        for piece in chunks(batches, text_col):
            held.append((piece, hashed(piece)))
            size += column(piece, text_col).nbytes
            if size >= PROBE_BYTES:
                yield from flush(held)
                held, size = [], 0
        if held:
            yield from flush(held)

    return docs.select(*[f.name for f in passed]).mapInArrow(clean, schema)
