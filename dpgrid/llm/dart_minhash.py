"""MinHash near-duplicates with darts: weighted signatures, bands, exact check, connected components.

Every element of the universe owns an endless, hashed shower of darts over (weight, rank), one per unit of area on
average. A set hits the darts that lie below its element's weight; each dart belongs to a hashed coordinate, and a
coordinate keeps the hit dart of least rank. Two sets then agree in a coordinate with the probability of their weighted
Jaccard similarity. The plane is cut into dyadic cells whose darts follow from a hash of (element, cell), so only the cells
below a rank that some darts per coordinate are expected to reach are looked at: work grows with set size plus
coordinates, not with their product.

Texts are lower-cased, and their windows of five words are hashed to 64 bits (a shorter text is one window). A window's weight
is how often the text holds it, so similarity is that of weighted sets: the sum of lesser weights over the sum of greater ones.
Texts of equal words form a class whose least document id stands for it. Representatives that agree in a band
share a bucket; of buckets with the same members one is kept. Buckets are compared exactly, as products of 0/1 blocks in which the
second, third, ... occurrence of a window is an element of its own, which makes weighted similarity plain; a block returns edges that
join the linked documents, never all pairs. Blocks and packs are bounded in members and in elements. A very large bucket first meets
some pivots: Jaccard distance is a metric, so members that a pivot links, and that lie further from every unlinked member than
a link reaches, are settled by that one comparison each. No candidate of a bucket is lost.

Edge cases: null, empty and wordless texts are their own class and link with nothing; ties do not matter, as all members of a
component get its least id; a row is told by its id and its text, so rows that share an id and differ in text are judged apart, and
equal rows alike; rows without an id have no component and are kept; a very long text is one set, compared in a task with at most
a block of others; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpgrid.llm.arrow import chunks, column, out, strings
from dpgrid.llm.embedding_dedup import forest
from dpgrid.plans.graph import connected_components
from dpgrid.plans.scratch import drop_tables, materialise

#: Words in a shingle; similarity of a link; bands of rows each (a pair at 0.8 is missed once in 17,000).
WORDS, THRESHOLD, BANDS, ROWS = 5, 0.8, 32, 6
#: Members in a block, columns of a 0/1 block, and members beyond which a bucket meets pivots first.
BLOCK, COLUMNS, LARGE = 256, 2048, 4096
#: Elements of a block or a pack on average; a single longer text is a block of its own.
ELEMENTS = 2_000_000
#: Bytes of text that are sketched together: their darts live at once.
SKETCH_BYTES = 1_000_000
#: Rank below which the first cell lies: 2 ** -FINE.
FINE = 7
_GOLD = np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


@lru_cache(maxsize=64)
def poisson_cdf(mean: float) -> np.ndarray:
    """Cumulative probabilities of 0, 1, 2, ... events."""
    top = int(mean + 12 * mean**0.5 + 20)
    k = np.arange(top + 1)
    logs = k * np.log(mean) - mean - np.concatenate([[0.0], np.cumsum(np.log(k[1:]))])
    return np.cumsum(np.exp(logs))


def rank_cell(j: int) -> tuple[float, float]:
    """Lower end and width of rank cell ``j``: [0, 2^-FINE), then doubling."""
    return (0.0, 2.0**-FINE) if j == 0 else (2.0 ** (j - 1 - FINE), 2.0 ** (j - 1 - FINE))


def weight_cell(i: int) -> tuple[float, float]:
    """Lower end and width of weight cell ``i``: [0, 1), then doubling."""
    return (0.0, 1.0) if i == 0 else (2.0 ** (i - 1), 2.0 ** (i - 1))


def signatures(elements: np.ndarray, weights: np.ndarray | None, sizes: np.ndarray, k: int) -> np.ndarray:
    """Dart signatures of sets laid end to end; ``weights=None`` means one each.

    ``sizes`` counts the elements of each set. Returns (sets, k) uint64; the row of an empty set is all ones.
    """
    n = len(sizes)
    least = np.full(n * k, np.uint64(2**64 - 1))
    if not len(elements):
        return least.reshape(n, k)
    owner = np.repeat(np.arange(n), sizes)
    total = np.bincount(owner, weights, n)
    with np.errstate(divide="ignore"):
        reach = np.log2((k * np.log(k) + 4 * k) / np.maximum(total, 1e-300))
    last = np.maximum(np.ceil(reach).astype(np.int64) + FINE, 0)  # last rank cell of each set
    last[total <= 0] = -1
    tallest = 0 if weights is None else int(max(0, np.floor(np.log2(max(weights.max(), 1))) + 1))
    j = 0
    while j <= last.max():
        _throw(least, elements, weights, owner, last[owner] >= j, j, tallest, k)
        if j == last.max():  # a set with an empty coordinate looks further
            bare = (least.reshape(n, k) == np.uint64(2**64 - 1)).any(1) & (last >= 0)
            behind = bare & (last < j)
            if behind.any():
                for step in range(int(last[behind].min()) + 1, j + 1):
                    _throw(least, elements, weights, owner, (behind & (last < step))[owner], step, tallest, k)
                bare = (least.reshape(n, k) == np.uint64(2**64 - 1)).any(1) & (last >= 0)
                last[behind] = j
            last[bare] = j + 1
        j += 1
    return least.reshape(n, k)


def _throw(least: np.ndarray, elements: np.ndarray, weights: np.ndarray | None, owner: np.ndarray, who: np.ndarray, j: int, tallest: int, k: int) -> None:
    """Add the darts of rank cell ``j`` of the elements in ``who`` to the least darts per coordinate."""
    rows = np.flatnonzero(who)
    _, rank_width = rank_cell(j)
    for i in range(tallest + 1):
        low, weight_width = weight_cell(i)
        at = rows if weights is None else rows[weights[rows] > low]
        if not len(at):
            continue
        with np.errstate(over="ignore"):
            seed = mix(elements[at] + _GOLD * np.uint64(1 + j * 64 + i))
        u = (seed >> np.uint64(11)).astype(np.float64) * 2.0**-53
        count = np.searchsorted(poisson_cdf(rank_width * weight_width), u, side="right")
        hit = np.flatnonzero(count)
        count = count[hit]
        ends = np.cumsum(count)
        if not len(ends):
            continue
        number = np.arange(ends[-1]) - np.repeat(ends - count, count)
        who_ = np.repeat(at[hit], count)
        with np.errstate(over="ignore"):
            dart = mix(np.repeat(seed[hit], count) + (number.astype(np.uint64) + np.uint64(1)) * np.uint64(0xD1B54A32D192ED03))
        if weights is not None and (weights[at] < low + weight_width).any():  # else all darts of the cell lie below the weight
            more = mix(dart ^ np.uint64(0xA0761D6478BD642F))
            inside = low + weight_width * ((more >> np.uint64(11)).astype(np.float64) * 2.0**-53) < weights[who_]
            dart, who_ = dart[inside], who_[inside]
        coordinate = ((dart >> np.uint64(32)) * np.uint64(k) >> np.uint64(32)).astype(np.int64)
        rank = (np.uint64(j) << np.uint64(56)) | ((mix(dart) >> np.uint64(8)))
        np.minimum.at(least, owner[who_] * k + coordinate, rank)


def bands_of(sig: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """One 64-bit key per band, different between bands."""
    sig = sig.reshape(len(sig), bands, rows)
    key = np.broadcast_to(mix(np.arange(1, bands + 1, dtype=np.uint64) * _GOLD), sig.shape[:2]).copy()
    with np.errstate(over="ignore"):
        for r in range(rows):
            key = mix(key * np.uint64(31) + sig[:, :, r])
    return key.view(np.int64)


class Shingler:
    """Texts → distinct 64-bit shingle hashes, with a bounded cache of word hashes."""

    def __init__(self, words: int = WORDS, most: int = 100_000):
        self.words, self.most, self.seen = words, most, {}

    def tokens(self, text: str | None) -> list[bytes]:
        return text.lower().encode("utf-8", "surrogatepass").split() if text else []

    def hashes(self, words: list[bytes]) -> np.ndarray:
        seen = self.seen
        if len(seen) > self.most:
            seen.clear()
        return np.fromiter((seen[w] if w in seen else seen.setdefault(w, xxhash.xxh3_64_intdigest(w)) for w in words), np.uint64, len(words))

    def all(self, h: np.ndarray) -> np.ndarray:
        """Hashes of all windows of a word row; of the whole row if it is shorter."""
        w = min(self.words, len(h))
        made = np.zeros(len(h) - w + 1, np.uint64)
        with np.errstate(over="ignore"):
            for i in range(w):
                made = mix(made * np.uint64(3) + h[i : len(h) - w + 1 + i] + np.uint64(i + 1))
        return made

    def __call__(self, text: str | None) -> tuple[list[bytes], np.ndarray, np.ndarray]:
        """Words, distinct window hashes, and how often each occurs."""
        words = self.tokens(text)
        if not words:
            return words, np.empty(0, np.uint64), np.empty(0, np.int64)
        return words, *np.unique(self.all(self.hashes(words)), return_counts=True)


def occurrences(windows: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """One element per occurrence: plain similarity of such sets is the weighted one of ``windows``."""
    if len(counts) == counts.sum():
        return windows
    number = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    with np.errstate(over="ignore"):
        later = mix(np.repeat(windows, counts) + number.astype(np.uint64) * _GOLD)
    return np.where(number == 0, np.repeat(windows, counts), later)


def _plain(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("h"))


def sketch(plain: DataFrame, bands: int = BANDS, rows: int = ROWS, words: int = WORDS) -> DataFrame:
    """Per row ``doc_id, text, h`` with words: doc_id, h, two halves of a hash of its words, band keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(words)
        for piece in chunks(batches, "text", SKETCH_BYTES):
            sets, weights, prints, some = [], [], [], []
            for i, text in enumerate(strings(piece, "text")):
                own, shingles, w = shingler(text)
                if own:
                    some.append(i)
                    sets.append(shingles)
                    weights.append(w)
                    prints.append(xxhash.xxh3_128_digest(b" ".join(own)))
            if some:
                sig = signatures(np.concatenate(sets), np.concatenate(weights).astype(np.float64), np.array([len(s) for s in sets]), bands * rows)
                half, at = np.frombuffer(b"".join(prints), "<i8").reshape(-1, 2), pa.array(some)
                yield out(["doc_id", "h", "f1", "f2", "bands"], column(piece, "doc_id").take(at), column(piece, "h").take(at), half[:, 0].copy(), half[:, 1].copy(), pa.array(list(bands_of(sig, bands, rows)), pa.list_(pa.int64())))

    return plain.where("doc_id is not null").mapInArrow(run, "doc_id long, h long, f1 long, f2 long, bands array<long>")


def shingle_sets(texts: DataFrame, words: int = WORDS) -> DataFrame:
    """Per row ``member, text`` with words: member, hashes of its windows' occurrences. Equal members in a row count once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler, last = Shingler(words), None
        for piece in chunks(batches, "text"):
            members, sets = [], []
            for member, text in zip(strings(piece, "member"), strings(piece, "text"), strict=True):
                if member != last:
                    members.append(member)
                    sets.append(occurrences(*shingler(text)[1:]).view(np.int64))
                last = member
            yield out(["member", "shingles"], pa.array(members, pa.int64()), pa.array(sets, pa.list_(pa.int64())))

    return texts.select("member", "text").mapInArrow(run, "member long, shingles array<long>").where(F.size("shingles") > 0)


def similarities(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """``pairs(a, b)`` with their exact Jaccard similarity ``sim``."""
    left, right = sets.select(F.col("member").alias("a"), F.col("shingles").alias("x")), sets.select(F.col("member").alias("b"), F.col("shingles").alias("y"))
    both = F.size(F.array_intersect("x", "y"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", (both / (F.size("x") + F.size("y") - both)).alias("sim"))


def intersections(sets: list[np.ndarray], left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Sizes of the intersections of each set in ``left`` with each in ``right``, as products of 0/1 blocks."""
    use = np.unique(np.concatenate([left, right]))
    sizes = np.array([len(sets[i]) for i in use])
    _, col, count = np.unique(np.concatenate([sets[i] for i in use]), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(len(use)), sizes)
    shared = count > 1  # what one set alone holds meets nothing
    number = np.cumsum(shared) - 1
    keep = shared[col]
    row, col = row[keep], number[col[keep]]
    a, b = np.searchsorted(use, left), np.searchsorted(use, right)
    made = np.zeros((len(left), len(right)), np.float32)
    order = np.argsort(col, kind="stable")
    row, col = row[order], col[order]
    for lo in range(0, int(number[-1]) + 1 if len(number) else 0, COLUMNS):
        i, j = np.searchsorted(col, [lo, lo + COLUMNS])
        block = np.zeros((len(use), COLUMNS), np.float32)
        block[row[i:j], col[i:j] - lo] = 1
        made += block[a] @ block[b].T
    return made


def joining(ids: np.ndarray, sets: list[np.ndarray], left: np.ndarray, right: np.ndarray, threshold: float) -> list[tuple[int, int]]:
    """Edges without cycles that join the same ids as all links between ``left`` and ``right`` (positions; equal for one block)."""
    sizes = np.array([len(s) for s in sets], np.float64)
    both = intersections(sets, left, right)
    total = sizes[left][:, None] + sizes[right][None, :] - both
    i, j = np.nonzero(both >= threshold * total - 1e-9)
    i, j = left[i], right[j]
    apart = i != j
    return forest(ids[i[apart]], ids[j[apart]])


def _compare(group: pa.Table, threshold: float) -> pa.Table:
    """All buckets of a pack of small ones, or one pair of blocks of a large one."""
    group = group.sort_by("bucket").combine_chunks()
    bucket, member, block = (group[c].to_numpy() for c in ("bucket", "member", "block"))
    first, second = group["first"][0].as_py(), group["second"][0].as_py()
    held = group["shingles"].combine_chunks()
    flat, ends = held.flatten().to_numpy(), np.concatenate([[0], np.cumsum(pc.list_value_length(held).to_numpy())])
    sets = [flat[ends[i] : ends[i + 1]] for i in range(len(member))]
    found: list[tuple[int, int]] = []
    edges = np.flatnonzero(np.diff(bucket, prepend=bucket[0] - 1))
    for lo, hi in zip(edges, [*edges[1:], len(bucket)], strict=True):
        rows = np.arange(lo, hi)
        left, right = rows[block[lo:hi] == first], rows[block[lo:hi] == second]
        for i in range(0, len(left), BLOCK):
            for k in range(0, len(right), BLOCK):
                found += joining(member, sets, left[i : i + BLOCK], right[k : k + BLOCK], threshold)
    a, b = zip(*dict.fromkeys(found), strict=True) if found else ((), ())
    return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})


def _thinned(seats: DataFrame, sets: DataFrame, threshold: float, large: int, turns: int = 3) -> tuple[DataFrame, list[DataFrame]]:
    """Seats whose links are not yet settled after some pivots of the large buckets, and links found on the way."""
    known: list[DataFrame] = []
    for _ in range(turns):
        wide = materialise(seats.where(F.col("n") > large), "wide_seats")
        if wide.isEmpty():
            break
        heads = materialise(wide.groupBy("bucket").agg(F.min("member").alias("pivot")), "pivots")
        held = materialise(wide.join(heads, "bucket").where("member <> pivot").select("bucket", "member", "pivot"), "pivot_seats")
        sims = materialise(similarities(held.select(F.col("member").alias("a"), F.col("pivot").alias("b")).distinct(), sets), "pivot_sims")
        known.append(sims.where(F.col("sim") >= threshold).select("a", "b"))
        seen = materialise(held.join(sims.select(F.col("a").alias("member"), F.col("b").alias("pivot"), "sim"), ["member", "pivot"]).select("bucket", "member", "sim"), "seat_sims")
        # The nearest unlinked member; linked ones further from it, by the metric, than one link reaches are settled.
        near = materialise(seen.where(F.col("sim") < threshold).groupBy("bucket").agg(F.max("sim").alias("near")), "nearest")
        rest = materialise(seen.join(near, "bucket").where((F.col("sim") < threshold) | (F.col("sim") <= F.col("near") + (1 - threshold) + 1e-9)).select("bucket", "member").distinct(), "rest_seats")
        sizes = materialise(rest.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "rest_sizes")
        left = materialise(seats.where(F.col("n") <= large).unionByName(rest.join(sizes, "bucket").select("bucket", "member", "n")), "seats")
        drop_tables(seats.sparkSession, seats, wide, heads, held, seen, near, rest, sizes)
        seats = left
    return seats, known


def _dealt(seats: DataFrame, sets: DataFrame) -> DataFrame:
    """Seats as packs of small buckets and pairs of blocks of large ones, each bounded in members and elements."""
    sized = seats.join(sets.select("member", F.size("shingles").alias("m")), "member").groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.sum("m").alias("e"))
    small = (F.col("n") <= BLOCK // 2) & (F.col("e") <= ELEMENTS // 2)
    sized = materialise(sized.withColumn("small", small), "bucket_sizes")
    members, elements = sized.where("small").agg(F.sum("n"), F.sum("e")).first()
    packs = max(1, -(-(members or 0) // BLOCK), -(-(elements or 0) // ELEMENTS))
    many = F.least(F.col("n"), F.greatest(F.ceil(F.col("n") / BLOCK), F.ceil(F.col("e") / ELEMENTS))).cast("int")
    return (
        seats.select("bucket", "member").join(sized.select("bucket", "small", F.when(F.col("small"), 1).otherwise(many).alias("many")), "bucket")
        .withColumn("pack", F.when(F.col("small"), F.pmod(F.xxhash64("bucket"), F.lit(packs))).otherwise(F.col("bucket")))
        .withColumn("block", F.pmod(F.xxhash64("member", "bucket"), F.col("many")).cast("int"))
        .select("*", F.explode(F.sequence(F.lit(0), F.col("many") - 1)).alias("other"))
        .select("bucket", "member", "block", "pack", "small", F.least("block", "other").alias("first"), F.greatest("block", "other").alias("second"))
    )


def links(reps: DataFrame, classes: DataFrame, plain: DataFrame, threshold: float = THRESHOLD, words: int = WORDS, large: int = LARGE) -> DataFrame:
    """Links ``a, b`` that join the same classes as all pairs of a bucket with at least ``threshold``.

    ``reps(member, bands)``; ``classes(v, copy_of, copy_h)`` names the row that stands for a member; ``plain(doc_id, h, text)`` holds its text.
    """
    places = reps.select("member", F.explode("bands").alias("bucket"))
    h = F.xxhash64("member")
    # A member has one seat in a bucket, however many rows bring it there: pairs of equal hashes would cancel.
    sized = places.distinct().groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.bit_xor(h).alias("x"), F.bit_xor(F.xxhash64("member", F.lit(1))).alias("y")).where("n > 1")
    # Near copies meet in most bands: of buckets with the same members one is enough.
    buckets = materialise(sized.groupBy("n", "x", "y").agg(F.min("bucket").alias("bucket")).select("bucket", "n"), "buckets")
    seats = materialise(places.join(buckets, "bucket").distinct(), "seats")
    # Sort-merge whatever the size: neither the ids nor the texts have a bound, and small inputs should show what large ones cost.
    asked = classes.join(seats.select(F.col("member").alias("v")).distinct(), "v").select(F.col("v").alias("member"), F.col("copy_of").alias("doc_id"), F.col("copy_h").alias("h"))
    sets = materialise(shingle_sets(plain.join(asked.hint("merge"), ["doc_id", "h"]), words), "shingle_sets")
    seats, known = _thinned(seats, sets, threshold, large)
    found = _dealt(seats, sets).join(sets, "member").groupBy("pack", "small", "first", "second").applyInArrow(lambda group: _compare(group, threshold), "a long, b long")
    for k in known:
        found = found.union(k)
    made = materialise(found, "near_links")
    # All that ``found`` reads was written here; the sets of windows take more room than the texts.
    drop_tables(made.sparkSession, buckets, found)
    return made


def _resolved(plain: DataFrame, threshold: float, bands: int, rows: int, words: int) -> tuple[DataFrame, DataFrame]:
    """Sketches ``doc_id, h, f1, f2``, and facts of their classes: ``f1, f2, copy_of, copy_h, component_id, chief``.

    ``copy_of, copy_h`` tell the least row of a class; the chief of a component is its class of least such id.
    """
    sketched = materialise(sketch(plain, bands, rows, words), "sketches")
    first = F.min(F.struct("doc_id", "h")).alias("first")
    classes = materialise(sketched.groupBy("f1", "f2").agg(first).select("f1", "f2", F.col("first.doc_id").alias("copy_of"), F.col("first.h").alias("copy_h"), F.monotonically_increasing_id().alias("v")), "text_classes")
    heads = classes.select("f1", "f2", F.col("copy_of").alias("doc_id"), F.col("copy_h").alias("h"), F.col("v").alias("member"))
    reps = sketched.join(heads, ["doc_id", "h", "f1", "f2"]).select("member", "bands")
    near = links(reps, classes, plain, threshold, words)
    joined = connected_components(near, "a", "b").withColumnRenamed("vertex", "v")
    # Written, so that the join below meets two plain shuffles, and a component of many classes can be split.
    chiefs = materialise(joined.join(classes.select("v", "copy_of"), "v").groupBy("component").agg(F.min(F.struct("copy_of", "v")).alias("c")), "component_chiefs")
    linked = joined.join(chiefs, "component").select("v", F.col("c.copy_of").alias("component_id"), (F.col("v") == F.col("c.v")).alias("chief"))
    facts = classes.join(linked, "v", "left").select("f1", "f2", "copy_of", "copy_h", F.coalesce("component_id", "copy_of").alias("component_id"), F.coalesce("chief", F.lit(True)).alias("chief"))
    made = materialise(facts, "class_facts")
    drop_tables(made.sparkSession, near, chiefs, joined, classes)
    return sketched.select("doc_id", "h", "f1", "f2"), made


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, words: int = WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: doc_id, copy_of (least id of equal words), component_id, kept."""
    plain = _plain(docs, id_col, text_col)
    sketched, facts = _resolved(plain, threshold, bands, rows, words)
    found = sketched.join(facts, ["f1", "f2"]).select("doc_id", "copy_of", "component_id")
    wordless = plain.where(F.col("doc_id").isNull() | F.coalesce(~F.col("text").rlike(r"[^\x20\x09-\x0D]"), F.lit(True))).select("doc_id", F.col("doc_id").alias("copy_of"), F.col("doc_id").alias("component_id"))
    return found.unionByName(wordless).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def drop_near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, words: int = WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one row of each component: a row of the chief class with its least id.

    Rows equal in id and text count once; rows without an id or without a word all stay as they are.
    """
    sketched, facts = _resolved(_plain(docs, id_col, text_col), threshold, bands, rows, words)
    heads = facts.where("chief").select("f1", "f2", F.col("copy_of").alias("_id"), F.col("copy_h").alias("_h"))
    stays = F.coalesce((F.col("doc_id") == F.col("_id")) & (F.col("h") == F.col("_h")), F.lit(False))
    # One line per row that goes, and per kept row that occurs more than once: as many as there are copies.
    lines = sketched.join(heads, ["f1", "f2"], "left").groupBy(F.col("doc_id").alias("_id"), F.col("h").alias("_h")).agg(F.max(stays).alias("stays"), F.count(F.lit(1)).alias("n"))
    marked = materialise(lines.where("not stays or n > 1").select("_id", "_h", "stays"), "marked_rows")
    keyed = docs.withColumns({"_id": F.col(id_col).cast("long"), "_h": F.xxhash64(F.col(text_col).cast("string"))})
    made = keyed.join(marked.hint("merge"), ["_id", "_h"], "left_anti")
    twins = marked.where("stays")
    if not twins.isEmpty():
        made = made.unionByName(keyed.join(twins.drop("stays").hint("merge"), ["_id", "_h"], "left_semi").dropDuplicates(["_id", "_h"]))
    return made.select(*docs.columns)
