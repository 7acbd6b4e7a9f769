"""Private descriptions of a point set, from which synthetic points are drawn.

A description is a frame of boxes, ``eps_i, rep, leaf, lo0, hi0, lo1, hi1, ..., cnt`` with real, possibly negative counts. Grids whose size follows
from the budget are counted once per budget, not once per repetition. Every publisher takes the ``source`` of its draws and the ``sensitivity`` of
a count to the neighbour rule (2 where neighbours replace a record). All of them are plans of column expressions, joins and grouped sums;
the many draws of adaptive leaves and synthetic points are made by Arrow batch.
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from itertools import product
from urllib.parse import unquote

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dpgrid.functions import batch as batch_draws
from dpgrid.functions.keyed import LEAST, MOST, gumbel, keyed_uniform, laplace
from dpgrid.operators.grid import GridSpec, cell_of, coordinates, index_of, inside, linear
from dpgrid.operators.privacy import RUN
from dpgrid.operators.quantize import densify, quantize
from dpgrid.plans.scratch import materialise

#: Constant of the published grid-size rules; budget share of the first level.
RULE, SPLIT = 10.0, 0.5
#: Synthetic points that one row of the sampler expands to at most.
DRAWS = 1_000_000
#: Points held at once while they are drawn; entries of the dense tables in which a task adds up its cells.
HELD, TALLIED = 1 << 18, 1 << 22
#: Draws and rows of compact points that a tile of top cells stands for on average, at most.
TILE_DRAWS, TILE_POINTS = 1 << 19, 1 << 17
#: Bytes of a file of compact points that a task reads whole, at most.
MOST_BYTES = 1 << 26
#: Repetitions of a top cell and their noisy counts travel as the bytes of such lines, which the JVM passes on unread.
REPS_OF = np.dtype([("rep", "<i4"), ("v", "<f8")])


def _box(spec: GridSpec, indexes: Sequence[Column], g: Sequence[Column | int]) -> list[Column]:
    made = []
    for a, (i, k) in enumerate(zip(indexes, g, strict=True)):
        width = F.lit(spec.hi[a] - spec.lo[a]) / k
        made += [(F.lit(spec.lo[a]) + i * width).alias(f"lo{a}"), (F.lit(spec.lo[a]) + (i + 1) * width).alias(f"hi{a}")]
    return made


def _budgets(runs: DataFrame, n: float, rule) -> DataFrame:
    """``eps_i, eps, m`` with the grid side that ``rule(n, eps)`` gives."""
    rows = runs.select("eps_i", "eps").distinct().collect()  # one line per budget
    return runs.sparkSession.createDataFrame([(r["eps_i"], r["eps"], int(rule(n, r["eps"]))) for r in rows], "eps_i int, eps double, m int")


def uniform_side(n: float, eps: float) -> int:
    return max(1, math.floor(math.sqrt(n * eps / RULE) + 0.5))


def adaptive_side(n: float, eps: float) -> int:
    return max(10, math.ceil(0.25 * math.sqrt(n * eps / RULE)))


def _side_cell(cols: Sequence[str], spec: GridSpec, m: str) -> Column:
    made = None
    for c, lo, hi in zip(cols, spec.lo, spec.hi, strict=True):
        i = F.greatest(F.least(F.floor((F.col(c) - lo) * F.col(m) / (hi - lo)), F.col(m) - 1), F.lit(0))
        made = i if made is None else made * F.col(m) + i
    return made.cast("long")


def _unrolled(cell: Column, m: Column, n: int) -> list[Column]:
    made = []
    for _ in range(n):
        made.append(F.pmod(cell, m))
        cell = F.floor(cell / m)
    return [c.cast("long") for c in reversed(made)]


def publish_uniform(df: DataFrame, cols: Sequence[str], spec: GridSpec, runs: DataFrame, key: str, n_hint: float | None = None, source: str = "keyed", sensitivity: int = 1) -> DataFrame:
    """One grid whose side follows from the number of points and the budget."""
    pts = inside(df, list(cols), spec).select(*cols)
    n = n_hint if n_hint is not None else pts.count()
    sides = _budgets(runs, n, uniform_side)
    counts = pts.crossJoin(F.broadcast(sides)).groupBy("eps_i", _side_cell(cols, spec, "m").alias("leaf")).agg(F.count(F.lit(1)).alias("c"))
    power = F.pow(F.col("m"), F.lit(spec.n)).cast("long")
    domain = sides.select("eps_i", "eps", "m", F.explode(F.sequence(F.lit(0).cast("long"), power - 1)).alias("leaf"))
    full = domain.join(counts, ["eps_i", "leaf"], "left").join(F.broadcast(runs.select(*RUN)), "eps_i")
    noisy = F.coalesce("c", F.lit(0)) + laplace(keyed_uniform(key, "ugrid", *RUN, "leaf", source=source), sensitivity / F.col("eps"))
    at = _unrolled(F.col("leaf"), F.col("m").cast("long"), spec.n)
    return full.select(*RUN, "leaf", *_box(spec, at, [F.col("m")] * spec.n), noisy.alias("cnt"))


def compact_points(df: DataFrame, cols: Sequence[str], spec: GridSpec, by: Sequence[str] = ()) -> DataFrame:
    """``by..., cols..., weight``: equal points as one row with their number, points of a cell together, so that later counts combine where they are read.

    With ``by`` columns the points without sound coordinates stay as well.
    """
    # A generator keeps the later steps from being merged with the formulas of the coordinates, which would then be worked out again at each mention.
    placed = df.select(*by, F.inline(F.array(F.struct(*cols))))
    pts = (placed if by else inside(placed, list(cols), spec)).select(*by, *cols, cell_of(list(cols), spec).alias("_cell")).repartition(_deal(df), "_cell")
    made = pts.groupBy("_cell", *by, *cols).agg(F.count(F.lit(1)).alias("weight"))
    return materialise(made.select(*by, *cols, "weight"), "agrid_points")


def compact_counts(compact: DataFrame, cols: Sequence[str], spec: GridSpec) -> DataFrame:
    """``quantize`` of the points that ``compact`` stands for, written once."""
    return materialise(inside(compact, list(cols), spec).groupBy(cell_of(list(cols), spec).alias("cell")).agg(F.sum("weight").alias("cnt")), "counts")


def _deal(df: DataFrame) -> int:
    """Parts for rows whose size says nothing about the work they stand for."""
    return 4 * df.sparkSession.sparkContext.defaultParallelism


def publish_adaptive(df: DataFrame, cols: Sequence[str], spec: GridSpec, runs: DataFrame, key: str, n_hint: float | None = None, source: str = "keyed", sensitivity: int = 1, compact: bool = False) -> DataFrame:
    """Two levels: a coarse grid with half the budget, then each cell split as its noisy count deserves, with least-squares agreement.

    The leaves of a top cell are an array from draw to agreement: runs times leaves are never shuffled, sorted or written. ``compact`` says that
    ``df`` comes from ``compact_points``.
    """
    dealt, tiles = _adaptive_tiles(df, cols, spec, runs, key, n_hint, source, sensitivity, compact)
    full = dealt.mapInArrow(_with_noise(tiles), "eps_i int, rep int, top long, m int, m2 int, v double, us array<double>, total double")
    both = full.select(*RUN, "top", "m", "m2", "v", "total", F.posexplode("us").alias("inner", "u"))
    kappa = F.pow(F.col("m2"), F.lit(spec.n)).cast("long")
    a, b = SPLIT**2, (1 - SPLIT) ** 2
    parent = (a * kappa * F.col("v") + b * F.col("total")) / (b + a * kappa)
    top_at = _unrolled(F.col("top"), F.col("m").cast("long"), spec.n)
    in_at = _unrolled(F.col("inner"), F.col("m2").cast("long"), spec.n)
    fine = [t * F.col("m2") + i for t, i in zip(top_at, in_at, strict=True)]
    return both.select(*RUN, F.concat_ws(".", "top", "inner").alias("leaf"), *_box(spec, fine, [F.col("m") * F.col("m2")] * spec.n), (F.col("u") + (parent - F.col("total")) / kappa).alias("cnt"))


def adaptive_counts(df: DataFrame, cols: Sequence[str], spec: GridSpec, runs: DataFrame, key: str, n_hint: float | None = None, source: str = "keyed", sensitivity: int = 1, compact: bool = False) -> DataFrame:
    """``drawn_counts`` of ``publish_adaptive``, the same numbers: leaves become cells where their noise is drawn, and never are rows.

    Only a leaf across a border that stands for more than ``DRAWS`` points leaves its task, to be dealt in shares.
    """
    boxes = ", ".join(f"lo{a} double, hi{a} double" for a in range(spec.n))
    dealt, tiles = _adaptive_tiles(df, cols, spec, runs, key, n_hint, source, sensitivity, compact)
    made = dealt.mapInArrow(_leaf_cells(tiles), f"eps_i int, rep int, cell long, n long, leaf string, {boxes}, cnt double")
    made = materialise(made, "agrid_cells")
    cells = made.where("leaf is null").select(*RUN, "cell", F.col("n").alias("cnt"))
    large = drawn_counts(made.where("leaf is not null").drop("cell", "n"), key, spec, source)
    return cells.unionByName(large).groupBy(*RUN, "cell").agg(F.sum("cnt").alias("cnt"))


@dataclass(frozen=True)
class _Tiles:
    """How the top cells of all budgets are dealt to tasks: by the tile of space that holds their middle, ``tiles`` a side, each with the points of its top cells.

    A budget is a line ``eps_i, eps, m, reps``. A point travels, as a ``point`` of a row of bytes, to the tile of each top cell it lies in: mostly the same one.
    """

    cols: tuple[str, ...]
    spec: GridSpec
    budgets: tuple[tuple[int, float, int, tuple[int, ...]], ...]
    tiles: int
    key: str
    source: str
    sensitivity: int

    @property
    def point(self) -> np.dtype:
        return np.dtype([*[(f"x{a}", "<f8") for a in range(self.spec.n)], ("weight", "<i8")])

    def tops(self, x: np.ndarray, m: int, a: int) -> np.ndarray:
        """Top cell on an axis, as ``_side_cell`` has it."""
        lo, hi = self.spec.lo[a], self.spec.hi[a]
        return np.clip(np.floor((x - lo) * float(m) / (hi - lo)), 0, m - 1).astype(np.int64)

    def first(self, tile: int, m: int) -> int:
        """The first top cell of an axis whose middle lies in that tile or beyond."""
        return -((self.tiles - 2 * m * tile) // (2 * self.tiles))

    def deal(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Arrow function: points by tile, many in a row."""
        held, size = [], 0
        for batch in batches:
            met = np.empty(batch.num_rows, self.point)
            for name, c in zip(self.point.names, (*self.cols, "weight"), strict=True):
                met[name] = batch.column(c).to_numpy(zero_copy_only=False)
            held, size = [*held, met], size + len(met)
            if size >= HELD:
                yield self._dealt(np.concatenate(held))
                held, size = [], 0
        if size:
            yield self._dealt(np.concatenate(held))

    def deal_files(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Arrow function: the same from whole Parquet files, ``content``."""
        for batch in batches:
            for content in batch.column("content"):
                table = pq.ParquetFile(pa.BufferReader(content.as_buffer()))
                yield from self.deal(table.iter_batches(HELD, columns=[*self.cols, "weight"], use_threads=False))

    def _dealt(self, points: np.ndarray) -> pa.RecordBatch:
        tiles = np.zeros((len(self.budgets), len(points)), np.int64)
        for a in range(self.spec.n):
            x = np.ascontiguousarray(points[f"x{a}"])
            for own, (_, _, m, _) in zip(tiles, self.budgets, strict=True):
                own *= self.tiles
                own += (2 * self.tops(x, m, a) + 1) * self.tiles // (2 * m)
        same = (tiles == tiles[:1]).all(0)
        alone, apart = np.flatnonzero(same), np.flatnonzero(~same)
        tile, at = np.divmod(np.unique(tiles[:, apart] * len(points) + apart), len(points))
        tile, at = np.concatenate([tiles[0, alone], tile]), np.concatenate([alone, at])
        order = np.argsort(tile, kind="stable")
        tile, sent = tile[order], points[at[order]]
        first = np.flatnonzero(np.concatenate([[True], tile[1:] != tile[:-1]]))
        ends = np.append(first, len(tile)) * self.point.itemsize
        packed = pa.Array.from_buffers(pa.binary(), len(first), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(sent.tobytes())])
        return pa.RecordBatch.from_arrays([pa.array(tile[first]), packed], names=["tile", "points"])

    def rows(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Top cells of one tile after another, of input that comes in order of tile: those that split alike as a row, with the true counts ``held`` of its leaves."""
        tile, parts = None, []
        for batch in batches:
            for t, some in zip(batch.column("tile").to_pylist(), batch.column("points"), strict=True):
                if t != tile and tile is not None:
                    yield from self._split(tile, parts)
                    parts = []
                tile = t
                if some.is_valid:
                    parts.append(np.frombuffer(some.as_buffer(), self.point))
        if tile is not None:
            yield from self._split(tile, parts)

    def _split(self, tile: int, parts: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        n, points = self.spec.n, np.concatenate([np.empty(0, self.point), *parts])
        at_tile = np.unravel_index(tile, (self.tiles,) * n)
        xs, weight = [np.ascontiguousarray(points[f"x{a}"]) for a in range(n)], points["weight"].astype(np.float64)
        lines, own, met, begin = [], [], [], 0
        for eps_i, eps, m, _ in self.budgets:
            span = [(self.first(int(t), m), self.first(int(t) + 1, m)) for t in at_tile]
            shape = tuple(b - a for a, b in span)
            top = np.zeros((1,) * n, np.int64)
            for a, (lo, hi) in enumerate(span):
                top = top * m + np.arange(lo, hi).reshape([-1 if i == a else 1 for i in range(n)])
            axes = [self.tops(x, m, a) for a, x in enumerate(xs)]
            here = np.ones(len(points), bool)
            for at, (lo, hi) in zip(axes, span, strict=True):
                here &= (at >= lo) & (at < hi)
            here = np.flatnonzero(here)
            axes = [at[here] for at in axes]
            local = np.zeros(len(here), np.int64)
            for at, (lo, _), k in zip(axes, span, shape, strict=True):
                local = local * k + at - lo
            c = np.bincount(local, weight[here], top.size).astype(np.int64)
            lines.append((np.full(top.size, eps_i, np.int32), np.full(top.size, eps), np.full(top.size, m, np.int32), top.ravel(), c))
            own.append((m, here, axes, begin + local))
            begin += top.size
        if not begin:
            return
        tops = pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*lines, strict=True)], names=["eps_i", "eps", "m", "top", "c"])
        reps = {eps_i: list(some) for eps_i, _, _, some in self.budgets}
        rows = pa.Table.from_batches(list(_noisy_tops(self.key, self.source, self.sensitivity, reps)(iter([tops])))).combine_chunks().to_batches(max_chunksize=None)[0]
        m2 = rows.column("m2").to_numpy().astype(np.int64)
        size = m2**n
        start = np.concatenate([[0], np.cumsum(size)])
        # The rows of a top cell follow one another, in the order of the cells.
        row_m, row_top, row_eps = (rows.column(x).to_numpy() for x in ("m", "top", "eps_i"))
        new = np.concatenate([[True], (row_top[1:] != row_top[:-1]) | (row_eps[1:] != row_eps[:-1])])
        first = np.flatnonzero(new)
        many = np.diff(np.append(first, len(new)))
        true = np.zeros(int(start[-1]))
        for m, here, axes, top in own:
            copies = many[top]
            of, row = np.arange(len(here)), first[top]
            if copies.max(initial=1) > 1:
                of = np.repeat(of, copies)
                row = row[of] + np.arange(len(of)) - (np.cumsum(copies) - copies)[of]
            side = m2[row]
            inner = np.zeros(len(of), np.int64)
            for a in range(n):
                lo, hi = self.spec.lo[a], self.spec.hi[a]
                width = (hi - lo) / float(m)
                part = np.clip(np.floor((xs[a][here] - (lo + axes[a] * width))[of] / width * side), 0, side - 1).astype(np.int64)
                inner = inner * side + part
            if len(of):
                low, high = int(start[row.min()]), int(start[row.max() + 1])
                true[low:high] += np.bincount(start[row] - low + inner, weight[here][of], high - low)
        held = pa.LargeListArray.from_arrays(pa.array(start), pa.array(true))
        scale = self.sensitivity / (rows.column("eps").to_numpy() * (1 - SPLIT))
        yield pa.RecordBatch.from_arrays([*[rows.column(x) for x in ("eps_i", "top", "m", "m2", "reps")], held, pa.array(scale)], names=["eps_i", "top", "m", "m2", "reps", "held", "scale"])


def _whole_files(pts: DataFrame, cols: Sequence[str]) -> DataFrame | None:
    """``content`` of the Parquet files that hold just the rows of ``pts``, if it is such a table of doubles in files of ordinary size.

    Spark hands rows to Python one by one, at several times the cost of reading them there from a file.
    """
    plain = pts._jdf.queryExecution().optimizedPlan().getClass().getSimpleName() == "LogicalRelation"
    if not plain or any(dict(pts.dtypes)[c] != "double" for c in cols):
        return None
    paths = [unquote(f) for f in pts.inputFiles()]
    if not paths or not all(f.endswith(".parquet") for f in paths):
        return None
    files = pts.sparkSession.read.format("binaryFile").load(paths)
    return files.select("content") if files.agg(F.max("length")).first()[0] <= MOST_BYTES else None


def _adaptive_tiles(df: DataFrame, cols: Sequence[str], spec: GridSpec, runs: DataFrame, key: str, n_hint: float | None, source: str, sensitivity: int, compact: bool) -> tuple[DataFrame, _Tiles]:
    """``tile, points``, the tiles of a part in order, and how to read them: top and leaf counts are made where their noise is drawn, so neither is a row."""
    pts = df if compact else compact_points(df, cols, spec)
    weight, rows = pts.agg(F.sum("weight"), F.count(F.lit(1))).first()
    n = n_hint if n_hint is not None else (weight or 0)
    lines: dict[tuple[int, float], list[int]] = {}
    for r in runs.select(*RUN, "eps").collect():  # a run is a line of parameters
        lines.setdefault((r["eps_i"], r["eps"]), []).append(r["rep"])
    budgets = tuple((i, eps, int(adaptive_side(n, eps)), tuple(reps)) for (i, eps), reps in sorted(lines.items()))
    draws = sum((m**spec.n + n * eps * (1 - SPLIT) / (RULE / 2)) * len(reps) for _, eps, m, reps in budgets)
    tiles = max(1, min(math.ceil(max(draws / TILE_DRAWS, rows / TILE_POINTS) ** (1 / spec.n)), *[m for _, _, m, _ in budgets]))
    how = _Tiles(tuple(cols), spec, budgets, tiles, key, source, sensitivity)
    files = _whole_files(pts, cols)
    if files is not None:
        dealt = files.mapInArrow(how.deal_files, "tile long, points binary")
    else:
        dealt = pts.select(*[F.col(c).cast("double").alias(c) for c in cols], "weight").mapInArrow(how.deal, "tile long, points binary")
    bare = df.sparkSession.range(tiles**spec.n).select(F.col("id").alias("tile"), F.lit(None).cast("binary").alias("points"))  # tiles without points have noise too
    parts = max(2 * _deal(df), math.ceil(rows / (4 * TILE_POINTS)))
    return dealt.unionByName(bare).repartition(parts, "tile").sortWithinPartitions("tile"), how


def _noisy_tops(key: str, source: str, sensitivity: int, lines: dict[int, list[int]]):
    """Arrow function: noisy counts ``v`` of top cells for the repetitions ``lines`` of their budgets, those that split a cell into ``m2`` parts a side as one row."""
    size, reps = np.zeros(max(lines, default=0) + 1, np.int64), np.array([x for e in sorted(lines) for x in lines[e]], np.int64)
    for e, some in lines.items():
        size[e] = len(some)
    begin = np.cumsum(size) - size
    places = [f"{e}|{x}" for e in sorted(lines) for x in lines[e]]

    def split(batch: pa.RecordBatch) -> pa.RecordBatch:
        eps_i, eps, m, top, c = (batch.column(x).to_numpy(zero_copy_only=False) for x in ("eps_i", "eps", "m", "top", "c"))
        own = size[eps_i]
        of = np.repeat(np.arange(len(own)), own)
        line = np.arange(len(of)) + (begin[eps_i] - np.cumsum(own) + own)[of]
        u = batch_draws.uniforms(key, "agrid1", pa.array(places, pa.string()), line, top[of], source)
        v = np.nan_to_num(c.astype(np.float64))[of] + batch_draws.laplace(u, (sensitivity / (eps * SPLIT))[of])
        m2 = np.maximum(1, np.ceil(np.sqrt(np.maximum(v, 0.0) * (eps * (1 - SPLIT))[of] / (RULE / 2)))).astype(np.int64)
        order = np.lexsort((m2, of))
        of, m2 = of[order], m2[order]
        first = np.flatnonzero(np.concatenate([np.ones(min(1, len(of)), bool), (of[1:] != of[:-1]) | (m2[1:] != m2[:-1])]))
        met = np.empty(len(of), REPS_OF)
        met["rep"], met["v"] = reps[line[order]], v[order]
        ends = (np.append(first, len(of)) * REPS_OF.itemsize).astype(np.int32)
        packed = pa.Array.from_buffers(pa.binary(), len(first), [None, pa.py_buffer(ends), pa.py_buffer(met.tobytes())])
        at = of[first]
        return pa.RecordBatch.from_arrays([pa.array(eps_i[at]), pa.array(eps[at]), pa.array(m[at]), pa.array(top[at]), pa.array(m2[first], pa.int32()), packed], names=["eps_i", "eps", "m", "top", "m2", "reps"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = max(1, HELD // max(1, int(size.max())))
        for batch in batches:
            for at in range(0, batch.num_rows, step):
                yield split(batch.slice(at, step))

    return add


def _unpacked(packed: pa.Array) -> np.ndarray:
    """The ``REPS_OF`` lines of an array of their bytes, one value after another."""
    wide = packed.cast(pa.large_binary())
    ends = np.frombuffer(wide.buffers()[1], np.int64)[wide.offset : wide.offset + len(wide) + 1]
    return np.frombuffer(wide.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]].view(REPS_OF)


@dataclass
class _Leaves:
    """Top cells of runs, an entry each, and their leaves one after another: entry, number within it, and noisy count.

    Repetitions of a row split a cell alike: ``shape`` is a leaf's place among the leaves of the rows, whose cells, grids and sides are ``tops``, ``grids`` and ``sides``;
    ``of`` is the row of an entry.
    """

    eps_i: np.ndarray
    rep: np.ndarray
    top: np.ndarray
    m: np.ndarray
    m2: np.ndarray
    v: np.ndarray
    place: pa.Array
    size: np.ndarray
    total: np.ndarray
    row: np.ndarray
    inner: np.ndarray
    us: np.ndarray
    shape: np.ndarray
    of: np.ndarray
    tops: np.ndarray
    grids: np.ndarray
    sides: np.ndarray


def _noisy_leaves(batch: pa.RecordBatch, n: int, key: str, source: str) -> Iterator[_Leaves]:
    """The leaves of a batch, so many top cells at a time that about ``HELD`` leaves are held."""
    side = batch.column("m2").to_numpy(zero_copy_only=False).astype(np.int64) ** n
    load = side * (pc.binary_length(batch.column("reps")).to_numpy(zero_copy_only=False) // REPS_OF.itemsize + 1)
    upto, first = np.cumsum(load), 0
    while first < len(load):
        last = max(first + 1, int(np.searchsorted(upto, upto[first] - load[first] + HELD, "right")))
        yield _noisy(batch.slice(first, last - first), n, key, source)
        first = last


def _noisy(batch: pa.RecordBatch, n: int, key: str, source: str) -> _Leaves:
    reps, held = batch.column("reps"), batch.column("held")
    of = np.repeat(np.arange(len(reps)), pc.binary_length(reps).to_numpy(zero_copy_only=False) // REPS_OF.itemsize)
    eps_i, top, m, m2, scale = (batch.column(c).to_numpy(zero_copy_only=False)[of] for c in ("eps_i", "top", "m", "m2", "scale"))
    runs = _unpacked(reps)
    rep, v = np.ascontiguousarray(runs["rep"]), np.ascontiguousarray(runs["v"])
    place = pc.binary_join_element_wise(*[pa.array(x).cast(pa.string()) for x in (eps_i, rep, top)], "|")
    own = batch.column("m2").to_numpy(zero_copy_only=False).astype(np.int64) ** n
    begin = np.cumsum(own) - own
    true = held.flatten().to_numpy()
    size = own[of]
    row, start = np.repeat(np.arange(len(size)), size), np.cumsum(size) - size
    inner = np.arange(len(row)) - np.repeat(start, size)
    shape = inner + np.repeat(begin[of], size)
    us = true[shape] + batch_draws.laplace(batch_draws.uniforms(key, "agrid2", place, row, inner, source), np.repeat(scale, size))
    return _Leaves(eps_i, rep, top, m, m2, v, place, size, np.bincount(row, us, len(size)), row, inner, us, shape, of, *(batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("top", "m", "m2")))


def _with_noise(tiles: _Tiles):
    """Arrow function: noise on the leaf counts of each top cell, and their sum."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tiles.rows(batches):
            for x in _noisy_leaves(batch, tiles.spec.n, tiles.key, tiles.source):
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(x.size)]), pa.int32()), pa.array(x.us, pa.float64()))
                yield pa.RecordBatch.from_arrays([*map(pa.array, (x.eps_i, x.rep, x.top, x.m, x.m2, x.v)), lists, pa.array(x.total, pa.float64())], names=[*RUN, "top", "m", "m2", "v", "us", "total"])

    return add


def _part(x: np.ndarray, spec: GridSpec, a: int) -> np.ndarray:
    """``index_of`` for arrays, in doubles."""
    return np.clip(np.floor((x - spec.lo[a]) * float(spec.g[a]) / (spec.hi[a] - spec.lo[a])), 0, spec.g[a] - 1)


class _Tally:
    """Counts by run and cell: dense tables that a task adds to until they would grow too large, else what each call adds."""

    def __init__(self, cells: int):
        self.cells, self.tables = cells, {}

    def add(self, eps_i: np.ndarray, rep: np.ndarray, entry: np.ndarray, cell: np.ndarray, n: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
        """Adds ``n`` to cells of the runs ``eps_i[entry], rep[entry]``. Yields rows only where they cannot be held."""
        if not len(cell):
            return
        run = eps_i.astype(np.int64) << 32 | rep.astype(np.int64)
        lines, line = np.unique(run, return_inverse=True)  # of entries, which are few beside what they hold
        line = line[entry]
        if (len(self.tables) + len(lines)) * self.cells > TALLIED:
            yield from self.rows()
        if len(lines) * self.cells <= TALLIED:
            met = np.bincount(line * self.cells + cell, n, len(lines) * self.cells).reshape(len(lines), self.cells)
            for x, own in zip(lines.tolist(), met, strict=True):
                self.tables[x] = self.tables[x] + own.astype(np.int64) if x in self.tables else own.astype(np.int64)
            return
        order = np.lexsort((cell, line))
        line, cell, n = line[order], cell[order], n[order]
        first = np.flatnonzero(np.concatenate([[True], (line[1:] != line[:-1]) | (cell[1:] != cell[:-1])]))
        yield lines[line[first]] >> 32, lines[line[first]] & 0xFFFFFFFF, cell[first], np.add.reduceat(n, first)

    def rows(self) -> Iterator[tuple[np.ndarray, ...]]:
        """What is held, which is then forgotten."""
        for x, own in self.tables.items():
            cell = np.flatnonzero(own)
            yield np.full(len(cell), x >> 32), np.full(len(cell), x & 0xFFFFFFFF), cell, own[cell]
        self.tables = {}


def _drawn(key: str, spec: GridSpec, source: str, places: pa.Array, known: np.ndarray, lo: list[np.ndarray], hi: list[np.ndarray], done: np.ndarray, points: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Box and cell of the points ``done + 1`` to ``done + points`` of each box; the part of an axis is ``known`` or, where NaN, drawn."""
    upto, first = np.cumsum(points), 0
    while first < len(points):  # so many boxes at a time that about ``HELD`` points are held
        last = max(first + 1, int(np.searchsorted(upto, upto[first] - points[first] + HELD, "right")))
        size = points[first:last]
        row = np.repeat(np.arange(first, last), size)
        j = done[row] + 1 + np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)
        cell = np.zeros(len(row), np.int64)
        for a in range(spec.n):
            at = known[a][row]
            open_ = np.flatnonzero(np.isnan(at))
            box = row[open_]
            x = lo[a][box] + (hi[a] - lo[a])[box] * batch_draws.uniforms(key, f"synth_x{a}", places[first:last], box - first, j[open_], source)
            at[open_] = _part(x, spec, a)
            cell = cell * spec.g[a] + at.astype(np.int64)
        yield row, cell
        first = last


def _leaf_boxes(top: np.ndarray, m: np.ndarray, side: np.ndarray, spec: GridSpec) -> tuple[np.ndarray, list[np.ndarray], list[np.ndarray]]:
    """Boxes of all leaves of top cells, one after another, and by axis the part that holds every draw, NaN where the draw decides."""
    size = side**spec.n
    row = np.repeat(np.arange(len(size)), size)
    rest, above = np.arange(len(row)) - (np.cumsum(size) - size)[row], top
    known, lo, hi = np.empty((spec.n, len(row))), [np.empty(0)] * spec.n, [np.empty(0)] * spec.n
    for d in reversed(range(spec.n)):
        above, t = np.divmod(above, m)
        i = rest % side[row]
        rest = rest // side[row] if d else rest
        fine, width = (t * side)[row] + i, ((spec.hi[d] - spec.lo[d]) / (m * side))[row]
        lo[d], hi[d] = spec.lo[d] + fine * width, spec.lo[d] + (fine + 1) * width
        least, most = (_part(lo[d] + (hi[d] - lo[d]) * u, spec, d) for u in (LEAST, MOST))
        known[d] = np.where(least == most, least, np.nan)
    return known, lo, hi


def _leaf_cells(tiles: _Tiles):
    """Arrow function: cells of the points that the leaves of top cells stand for, and the leaves too large to draw in one task."""
    key, spec, source = tiles.key, tiles.spec, tiles.source
    n, boxes = spec.n, [f"{x}{a}" for a in range(spec.n) for x in ("lo", "hi")]
    names = [*RUN, "cell", "n", "leaf", *boxes, "cnt"]

    def told(eps_i: np.ndarray, rep: np.ndarray, cell: np.ndarray, total: np.ndarray) -> pa.RecordBatch:
        none = [pa.nulls(len(cell), pa.string()), *[pa.nulls(len(cell), pa.float64()) for _ in (*boxes, "cnt")]]
        return pa.RecordBatch.from_arrays([pa.array(eps_i, pa.int32()), pa.array(rep, pa.int32()), pa.array(cell, pa.int64()), pa.array(np.asarray(total).astype(np.int64)), *none], names=names)

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally = _Tally(spec.cells)
        for batch in tiles.rows(batches):
            for x in _noisy_leaves(batch, n, key, source):
                yield from one(x, tally)
        for made in tally.rows():
            yield told(*made)

    def one(x: _Leaves, tally: _Tally) -> Iterator[pa.RecordBatch]:
        a, b = SPLIT**2, (1 - SPLIT) ** 2
        parent = (a * x.size * x.v + b * x.total) / (b + a * x.size)
        change = (parent - x.total) / x.size
        whole = x.us + np.repeat(change, x.size)
        np.maximum(whole, 0.0, whole)
        whole += 0.5
        np.floor(whole, whole)
        known, lo, hi = _leaf_boxes(x.tops, x.grids, x.sides, spec)
        certain = ~np.isnan(known).any(0)
        place = np.where(certain, np.ravel_multi_index(tuple(np.where(certain, known, 0).astype(np.int64)), spec.g), -1)
        begin = np.cumsum(x.sides**n) - x.sides**n
        least = np.minimum.reduceat(place, begin)
        within = ((least >= 0) & (least == np.maximum.reduceat(place, begin)))[x.of]
        # The leaves of a top cell that lies in one cell count together.
        held = np.bincount(x.row, whole, len(x.size))
        at = np.flatnonzero(within & (held > 0))
        for made in tally.add(x.eps_i, x.rep, at, least[x.of[at]], held[at]):
            yield told(*made)
        some = np.flatnonzero(np.repeat(~within, x.size) & (whole > 0))
        row, inner, whole, shape = x.row[some], x.inner[some], whole[some].astype(np.int64), x.shape[some]
        place = place[shape]
        sure = place >= 0
        for made in tally.add(x.eps_i, x.rep, row[sure], place[sure], whole[sure]):
            yield told(*made)
        open_ = np.flatnonzero(~sure)
        across = whole[open_] > DRAWS
        large, open_ = open_[across], open_[~across]
        if len(large):
            leaf = [f"{t}.{i}" for t, i in zip(x.top[row[large]].tolist(), inner[large].tolist(), strict=True)]
            empty = [pa.nulls(len(large), pa.int64())] * 2
            yield pa.RecordBatch.from_arrays([pa.array(x.eps_i[row[large]], pa.int32()), pa.array(x.rep[row[large]], pa.int32()), *empty, pa.array(leaf, pa.string()), *[pa.array(z[d][shape[large]]) for d in range(n) for z in (lo, hi)], pa.array((x.us[some] + change[row])[large])], names=names)
        at, own = row[open_], shape[open_]
        places = pc.binary_join_element_wise(x.place.take(pa.array(at)), pa.array(inner[open_]).cast(pa.string()), ".")
        for box, cell in _drawn(key, spec, source, places, known[:, own], [z[own] for z in lo], [z[own] for z in hi], np.zeros(len(open_), np.int64), whole[open_]):
            for made in tally.add(x.eps_i, x.rep, at[box], cell, np.ones(len(cell), np.int64)):
                yield told(*made)

    return cells


def _shift(x: Column, bits: Column | int) -> Column:
    return F.call_function("shiftright", x, bits if isinstance(bits, Column) else F.lit(bits))


def _tree_weights(height: int, fan: int) -> tuple[list[float], list[list[float]]]:
    """Budget shares of the levels, and what a node of level ``j`` adds to the gap of its ancestor at level ``m``.

    The best estimate of a node is a mix of its own noisy count and the sum of its children's estimates, weighted by their variances. The gap of a
    node is its estimate less that sum. Both are sums over descendants, with a weight per pair of levels.
    """
    raw = [2 ** (i / 3) for i in range(height + 1)]
    shares = [x / sum(raw) for x in raw]
    own, below, var = [0.0] * height + [1.0], [0.0] * (height + 1), 1 / shares[height] ** 2
    for i in range(height - 1, -1, -1):
        children, mine = fan * var, 1 / shares[i] ** 2
        own[i], below[i], var = children / (children + mine), mine / (children + mine), children * mine / (children + mine)
    to = [[0.0] * (height + 1) for _ in range(height + 1)]
    for m in range(height):
        to[m][m], chain = own[m], below[m] - 1
        for j in range(m + 1, height + 1):
            to[j][m] = chain * own[j]
            chain *= below[j]
    return shares, to


def publish_quadtree(df: DataFrame, cols: Sequence[str], spec: GridSpec, runs: DataFrame, key: str, height: int | None = None, source: str = "keyed", sensitivity: int = 1) -> DataFrame:
    """Complete tree of halvings: geometric budgets growing toward the leaves, weighted averages upward, mean consistency downward.

    Without ``height`` the leaves are at least as fine as the grid. Both passes over the tree are linear, so each is one explosion of nodes to their
    ancestors and one grouped sum: a leaf is its noisy count plus its share of the gap of each ancestor.
    """
    h = height if height is not None else math.ceil(math.log2(max(spec.g)))
    n, side = spec.n, 2**h
    fine = GridSpec(spec.lo, spec.hi, (side,) * n)
    fine.dense_cells()
    shares, to = _tree_weights(h, 2**n)
    spark = df.sparkSession
    domain = None
    for i, share in enumerate(shares):
        part = spark.range(2 ** (i * n)).select(F.lit(i).alias("level"), F.lit(share).alias("share"), F.col("id").alias("node"))
        domain = part if domain is None else domain.unionByName(part)

    def parts(node: Column, level: Column | int) -> list[Column]:
        """Coordinates of a node: its number is the row of their bits."""
        bits = level if isinstance(level, Column) else F.lit(level)
        return [F.pmod(_shift(node, bits * (n - 1 - a)), F.call_function("shiftleft", F.lit(1).cast("long"), bits)) for a in range(n)]

    def joined_bits(at: list[Column], level: Column) -> Column:
        made = at[0]
        for c in at[1:]:
            made = F.call_function("shiftleft", made, level) + c
        return made

    levels = F.explode(F.sequence(F.lit(0), F.lit(h))).alias("level")
    cells = quantize(df, cols, fine).select("cnt", "cell", levels)
    node = joined_bits([_shift(c, h - F.col("level")) for c in parts(F.col("cell"), h)], F.col("level"))
    sums = cells.groupBy("level", node.alias("node")).agg(F.sum("cnt").alias("c"))
    noisy = domain.join(sums, ["level", "node"], "left").crossJoin(F.broadcast(runs))
    draw = laplace(keyed_uniform(key, "quad", *RUN, "level", "node", source=source), sensitivity / (F.col("eps") * F.col("share")))
    noisy = materialise(noisy.select(*RUN, "level", "node", (F.coalesce("c", F.lit(0)) + draw).alias("v")), "tree_nodes")

    def with_ancestors(rows: DataFrame) -> DataFrame:
        rows = rows.select("*", F.explode(F.sequence(F.lit(0), F.least(F.col("level"), F.lit(h - 1)))).alias("m"))
        up = F.col("level") - F.col("m")
        return rows.withColumn("anc", joined_bits([_shift(c, up) for c in parts(F.col("node"), F.col("level"))], F.col("m")))

    leaves = noisy.where(F.col("level") == h)
    if h:
        weight = F.element_at(F.array(*[F.lit(x) for row in to for x in row]), (F.col("level") * (h + 1) + F.col("m") + 1).cast("int"))
        gaps = materialise(with_ancestors(noisy).groupBy(*RUN, "m", "anc").agg(F.sum(F.col("v") * weight).alias("gap")), "tree_gaps")
        part = F.col("gap") / F.pow(F.lit(2.0**n), h - F.col("m"))
        leaves = with_ancestors(leaves).join(gaps, [*RUN, "m", "anc"]).groupBy(*RUN, "node").agg((F.max("v") + F.sum(part)).alias("v"))
    return leaves.select(*RUN, F.col("node").alias("leaf"), *_box(spec, parts(F.col("node"), h), [F.lit(side)] * n), F.col("v").alias("cnt"))


def publish_kd(df: DataFrame, cols: Sequence[str], spec: GridSpec, runs: DataFrame, key: str, height: int = 6, median_share: float = 0.3, source: str = "keyed", sensitivity: int = 1) -> DataFrame:
    """Axes in turn, split at private medians drawn by the exponential mechanism over cell borders; noisy leaf counts.

    A level is a grouped sum of each box's cells along the axis, a running sum over those few places, and a maximum; cells carry the borders of their box.
    """
    n = spec.n
    at = coordinates(F.col("cell"), spec.g)
    cells = densify(quantize(df, cols, spec), spec).crossJoin(F.broadcast(runs)).select(*RUN, "eps", "cnt", F.lit(0).cast("long").alias("box"), *[x for a in range(n) for x in (at[a].alias(f"c{a}"), F.lit(0).cast("long").alias(f"from{a}"), F.lit(spec.g[a]).cast("long").alias(f"to{a}"))])
    for level in range(height):
        a = level % n
        line = cells.groupBy(*RUN, "eps", "box", f"to{a}", f"c{a}").agg(F.sum("cnt").alias("s"))
        own = Window.partitionBy(*RUN, "box")
        below = F.sum("s").over(own.orderBy(f"c{a}").rowsBetween(Window.unboundedPreceding, 0))
        cut = (F.col(f"c{a}") + 1).alias("cut")
        line = line.select(*RUN, "eps", "box", f"to{a}", cut, (-F.abs(below - F.sum("s").over(own) / 2)).alias("score")).where(F.col("cut") < F.col(f"to{a}"))
        worth = F.col("eps") * F.lit(median_share / height / (2 * sensitivity)) * F.col("score") + gumbel(keyed_uniform(key, "kd", *RUN, F.lit(level), "box", "cut", source=source))
        cuts = materialise(line.groupBy(*RUN, "box").agg(F.max_by("cut", worth).alias("cut")), "kd_cuts")
        right = F.coalesce(F.col(f"c{a}") >= F.col("cut"), F.lit(False))
        split = cells.join(cuts, [*RUN, "box"], "left")
        split = split.withColumns({"box": F.col("box") * 2 + right.cast("long"), f"from{a}": F.when(right, F.col("cut")).otherwise(F.col(f"from{a}")), f"to{a}": F.when(right, F.col(f"to{a}")).otherwise(F.coalesce("cut", f"to{a}"))})
        cells = materialise(split.drop("cut"), "kd_cells")
    ends = [x for a in range(n) for x in (f"from{a}", f"to{a}")]
    boxes = cells.groupBy(*RUN, "eps", "box", *ends).agg(F.sum("cnt").alias("c"))
    noisy = F.col("c") + laplace(keyed_uniform(key, "kdleaf", *RUN, "box", source=source), sensitivity / (F.col("eps") * (1 - median_share)))
    place = lambda x, a: F.lit(spec.lo[a]) + F.col(x) * F.lit((spec.hi[a] - spec.lo[a]) / spec.g[a])
    return boxes.select(*RUN, F.col("box").alias("leaf"), *[x for a in range(n) for x in (place(f"from{a}", a).alias(f"lo{a}"), place(f"to{a}", a).alias(f"hi{a}"))], noisy.alias("cnt"))


def publish_wavelet(df: DataFrame, cols: Sequence[str], spec: GridSpec, runs: DataFrame, key: str, source: str = "keyed", sensitivity: int = 1) -> DataFrame:
    """Noise on weighted Haar coefficients along every axis, then the inverse; axes are padded to powers of two.

    The transform is linear, so a cell is its clean count plus the signed noise of the coefficients whose support holds it: one per combination of
    scales. Each cell draws those by their own keys in one projection; no coefficient is ever materialised.
    """
    n = spec.n
    wide = [1 << max(0, (k - 1).bit_length()) for k in spec.g]
    rho = math.prod(1 + math.log2(k) for k in wide)
    scales = [[0, *[1 << i for i in range(k.bit_length() - 1)]] for k in wide]  # 0: the mean; else how many coefficients the scale has
    terms = F.array(*[F.struct(*[F.lit(s).cast("long").alias(f"s{a}") for a, s in enumerate(each)], F.lit(float(math.prod(k / max(s, 1) for k, s in zip(wide, each, strict=True)))).alias("weight")) for each in product(*scales)])
    at = coordinates(F.col("cell"), spec.g)

    def signed(total: Column, t: Column) -> Column:
        places, sign = [], F.lit(1.0)
        for a, k in enumerate(wide):
            s = t[f"s{a}"]
            places.append(s + F.floor(at[a] * s / k).cast("long"))  # coefficient on this axis; 0 is the mean
            sign = sign * F.when((s > 0) & (F.floor(at[a] * s * 2 / k) % 2 == 1), -1.0).otherwise(1.0)
        return total + sign * laplace(keyed_uniform(key, "wave", *RUN, *places, source=source), F.lit(2 * rho * sensitivity) / F.col("eps") / t["weight"])

    dense = densify(quantize(df, cols, spec), spec).crossJoin(F.broadcast(runs))
    return dense.select(*RUN, F.col("cell").alias("leaf"), *_box(spec, at, list(map(F.lit, spec.g))), (F.col("cnt") + F.aggregate(terms, F.lit(0.0), signed)).alias("cnt"))


def publish_marginals(df: DataFrame, cols: Sequence[str], spec: GridSpec, runs: DataFrame, key: str, source: str = "keyed", sensitivity: int = 1) -> DataFrame:
    """``eps_i, rep, marginal, i0.., cnt``: the cube of all marginals of the cell table, the budget shared equally among them.

    Coordinates that a marginal sums over are null; ``marginal`` is the grouping number.
    """
    dense = densify(quantize(df, cols, spec), spec)
    at = dense.select("cnt", *[c.alias(f"i{a}") for a, c in enumerate(coordinates(F.col("cell"), spec.g))])
    names = [f"i{a}" for a in range(spec.n)]
    cube = at.cube(*names).agg(F.sum("cnt").alias("c"), F.grouping_id().cast("int").alias("marginal"))
    place = F.concat_ws(",", *[F.coalesce(F.col(x).cast("string"), F.lit("*")) for x in names])
    noisy = F.col("c") + laplace(keyed_uniform(key, "cube", *RUN, place, source=source), float(sensitivity * 2**spec.n) / F.col("eps"))
    return cube.crossJoin(F.broadcast(runs)).select(*RUN, "marginal", *names, noisy.alias("cnt"))


def publish_contingency(df: DataFrame, cols: Sequence[str], spec: GridSpec, runs: DataFrame, key: str, source: str = "keyed", sensitivity: int = 1) -> DataFrame:
    """The full contingency table of the cells themselves, with noise on each."""
    from dpgrid.operators.privacy import private_quantize

    noisy = private_quantize(quantize(df, cols, spec), spec, runs, key, 1.0, sensitivity, source=source)
    return noisy.select(*RUN, F.col("cell").alias("leaf"), *_box(spec, coordinates(F.col("cell"), spec.g), list(map(F.lit, spec.g))), F.col("cnt_noisy").alias("cnt"))


PUBLISHERS = {"contingency": publish_contingency, "uniform": publish_uniform, "adaptive_grid": publish_adaptive, "quadtree": publish_quadtree, "kd": publish_kd, "wavelet": publish_wavelet}


def sample_boxes(leaves: DataFrame, key: str, n: int = 2, source: str = "keyed") -> DataFrame:
    """Synthetic points ``eps_i, rep, leaf, j, x0, x1..``: counts rounded, negatives to nothing, uniform places in the box.

    Large boxes are first cut into shares, so that one row never expands without bound, and the few, small rows are dealt to all
    cores before they expand: their size on disk says nothing about the points they stand for.
    """
    whole = F.floor(F.greatest(F.col("cnt"), F.lit(0.0)) + 0.5).cast("long")
    shares = leaves.withColumn("whole", whole).where("whole > 0").withColumn("share", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("whole") - 1) / DRAWS).cast("long"))))
    shares = shares.repartition(4 * leaves.sparkSession.sparkContext.defaultParallelism, *RUN, "leaf", "share")
    each = shares.select("*", F.explode(F.sequence(F.col("share") * DRAWS + 1, F.least((F.col("share") + 1) * DRAWS, F.col("whole")))).alias("j"))
    xs = [(F.col(f"lo{a}") + (F.col(f"hi{a}") - F.col(f"lo{a}")) * keyed_uniform(key, f"synth_x{a}", *RUN, "leaf", "j", source=source)).alias(f"x{a}") for a in range(n)]
    return each.select(*RUN, "leaf", "j", *xs)


def drawn_counts(leaves: DataFrame, key: str, spec: GridSpec, source: str = "keyed") -> DataFrame:
    """``eps_i, rep, cell, cnt`` of the points of ``sample_boxes``, without drawing those whose cell is certain.

    A place grows with its draw, in floating point too. Where the least and the largest draw fall into the same part of an axis, all do: such
    axes need no draw, and a box that lies in one cell counts whole. Only boxes across a border draw points, the same ones.
    """
    keys, span = [*RUN, "leaf"], [x for a in range(spec.n) for x in (f"lo{a}", f"hi{a}")]
    part = lambda a, u: index_of(F.col(f"lo{a}") + (F.col(f"hi{a}") - F.col(f"lo{a}")) * u, spec.lo[a], spec.hi[a], spec.g[a])
    whole = F.floor(F.greatest(F.col("cnt"), F.lit(0.0)) + 0.5).cast("long")
    rows = leaves.withColumn("whole", whole).where("whole > 0")
    for a in range(spec.n):
        rows = rows.withColumn(f"p{a}", F.when(part(a, F.lit(LEAST)) == part(a, F.lit(MOST)), part(a, F.lit(LEAST))))
    known = [F.col(f"p{a}") for a in range(spec.n)]
    open_ = F.lit(False)
    for p in known:
        open_ = open_ | p.isNull()
    across = lambda x: F.when(open_, F.col(x)).alias(x)
    # Boxes within a cell add up by cell; the others stay apart, a row each.
    met = rows.groupBy(*RUN, *[across(x) for x in ("leaf", *span)], *[f"p{a}" for a in range(spec.n)]).agg(F.sum("whole").alias("whole"))
    share = F.explode(F.when(open_, F.sequence(F.lit(0).cast("long"), F.floor((F.col("whole") - 1) / DRAWS).cast("long"))).otherwise(F.array(F.lit(0).cast("long"))))
    dealt = met.withColumn("share", share).repartition(_deal(leaves), *keys, "share")
    lines = dealt.select(*RUN, F.concat_ws("|", *keys).alias("place"), *span, *[f"p{a}" for a in range(spec.n)], "whole", (F.col("share") * DRAWS).alias("done"))
    return lines.mapInArrow(_draw_cells(key, spec, source), "eps_i int, rep int, cell long, cnt long").groupBy(*RUN, "cell").agg(F.sum("cnt").alias("cnt"))


def _draw_cells(key: str, spec: GridSpec, source: str):
    """Arrow function: counts by cell of boxes in one cell and of the points drawn for the others."""

    def told(eps_i: np.ndarray, rep: np.ndarray, cell: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(eps_i, pa.int32()), pa.array(rep, pa.int32()), pa.array(cell, pa.int64()), pa.array(np.asarray(n).astype(np.int64))], names=[*RUN, "cell", "cnt"])

    def draw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally = _Tally(spec.cells)
        for batch in batches:
            col = {c: batch.column(c).to_numpy(zero_copy_only=False) for c in batch.schema.names if c != "place"}
            known = np.stack([col[f"p{a}"].astype(np.float64) for a in range(spec.n)])  # NaN where the draw decides
            sure = ~np.isnan(known).any(0)
            for made in tally.add(col["eps_i"], col["rep"], np.flatnonzero(sure), np.ravel_multi_index(tuple(known[:, sure].astype(np.int64)), spec.g), col["whole"][sure]):
                yield told(*made)
            open_ = np.flatnonzero(~sure)
            places = batch.column("place").take(pa.array(open_))
            done = col["done"][open_].astype(np.int64)
            points = np.minimum(col["whole"][open_] - done, DRAWS).astype(np.int64)
            lo, hi = ([col[f"{x}{a}"][open_] for a in range(spec.n)] for x in ("lo", "hi"))
            for box, cell in _drawn(key, spec, source, places, known[:, open_], lo, hi, done, points):
                for made in tally.add(col["eps_i"], col["rep"], open_[box], cell, np.ones(len(cell), np.int64)):
                    yield told(*made)
        for made in tally.rows():
            yield told(*made)

    return draw


def areal_counts(leaves: DataFrame, spec: GridSpec) -> DataFrame:
    """``eps_i, rep, cell, cnt``: rounded counts shared out by overlap with the cells, without drawing any point.

    Shares are rounded to 2^-20, so that later sums are exact and ties do not depend on the order of addition.
    """
    made = leaves.withColumn("whole", F.floor(F.greatest(F.col("cnt"), F.lit(0.0)) + 0.5)).where("whole > 0")
    names = []
    for a in range(spec.n):
        lo, hi, g = spec.lo[a], spec.hi[a], spec.g[a]
        step = (hi - lo) / g
        first = index_of(F.col(f"lo{a}") + 1e-12 * (hi - lo), lo, hi, g)
        last = index_of(F.col(f"hi{a}") - 1e-12 * (hi - lo), lo, hi, g)
        made = made.withColumn(f"_i{a}", F.explode(F.sequence(first, last)))
        over = F.least(F.col(f"hi{a}"), lo + (F.col(f"_i{a}") + 1) * step) - F.greatest(F.col(f"lo{a}"), lo + F.col(f"_i{a}") * step)
        made = made.withColumn(f"_f{a}", F.greatest(over, F.lit(0.0)) / (F.col(f"hi{a}") - F.col(f"lo{a}")))
        names.append(f"_i{a}")
    share = F.col("whole")
    for a in range(spec.n):
        share = share * F.col(f"_f{a}")
    return made.groupBy(*RUN, linear([F.col(x) for x in names], spec.g).alias("cell")).agg((F.round(F.sum(share) * 2.0**20) / 2.0**20).alias("cnt"))


def range_count(leaves: DataFrame, boxes: DataFrame, n: int = 2) -> DataFrame:
    """``eps_i, rep, box, estimate`` for ``boxes(box, qlo0, qhi0, ...)``: counts times overlapping share, negative ones included."""
    hit, share = F.lit(True), F.col("cnt")
    for a in range(n):
        hit = hit & (F.col(f"lo{a}") < F.col(f"qhi{a}")) & (F.col(f"hi{a}") > F.col(f"qlo{a}"))
        share = share * (F.least(f"hi{a}", f"qhi{a}") - F.greatest(f"lo{a}", f"qlo{a}")) / (F.col(f"hi{a}") - F.col(f"lo{a}"))
    return leaves.join(F.broadcast(boxes), hit).groupBy(*RUN, "box").agg(F.sum(share).alias("estimate"))
