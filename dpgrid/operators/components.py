"""Connected components of significant cells.

``local`` labels each run's cells in one grouped task, for up to a few million cells a run. ``iterate`` contracts a distributed edge list.
``tiled`` labels tiles of the grid apart, and contracts only the edges that cross tile borders: the way for very large grids. ``auto`` takes the
first up to ``LOCAL_CELLS`` cells of the grid and the last beyond; all give the same labels.
A component's label is its least cell number.
"""

from __future__ import annotations

from collections.abc import Sequence
from itertools import product

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dpgrid.operators.grid import coordinates, linear
from dpgrid.plans.graph import connected_components as graph_components

#: Runs are numbered below this in vertex ids.
_RUNS = 100_000
#: Cells of a grid that one task labels.
LOCAL_CELLS = 4_000_000


def offsets(n: int, adjacency: str = "face") -> list[tuple[int, ...]]:
    """Steps to the neighbours of larger number: half of all neighbours, as edges are undirected."""
    if adjacency not in ("face", "full"):
        raise ValueError(f"adjacency {adjacency!r}")
    steps = [s for s in product((-1, 0, 1), repeat=n) if any(s) and (adjacency == "full" or sum(map(abs, s)) == 1)]
    return [s for s in steps if s > (0,) * n]


def label_array(cells: np.ndarray, g: tuple[int, ...], adjacency: str = "face", periodic: bool = False) -> np.ndarray:
    """Least cell number of each cell's component, by pointer jumping over sorted cells."""
    if not len(cells):
        return cells
    order = np.argsort(cells)
    own = cells[order]
    at = np.stack(np.unravel_index(own, g), 1)
    a, b = [], []
    for step in offsets(len(g), adjacency):
        to = at + step
        if periodic:
            to %= g
            ok = np.ones(len(own), bool)
        else:
            ok = ((to >= 0) & (to < g)).all(1)
        number = np.ravel_multi_index(tuple(np.where(ok[:, None], to, 0).T), g)
        pos = np.minimum(np.searchsorted(own, number), len(own) - 1)
        hit = np.flatnonzero(ok & (own[pos] == number))
        a.append(hit)
        b.append(pos[hit])
    a, b = np.concatenate(a), np.concatenate(b)
    root = np.arange(len(own))
    while True:
        new = root.copy()
        np.minimum.at(new, root[a], root[b])
        np.minimum.at(new, root[b], root[a])
        while not np.array_equal(new, new[new]):
            new = new[new]
        if np.array_equal(new, root):
            break
        root = new
    out = np.empty_like(cells)
    out[order] = own[root]
    return out


def _run_number(by: Sequence[str]):
    made = F.lit(0).cast("long")
    for c in by:
        made = made * _RUNS + F.col(c).cast("long")
    return made


def edges(cells: DataFrame, g: tuple[int, ...], by: Sequence[str] = (), adjacency: str = "face", periodic: bool = False) -> DataFrame:
    """``by..., a, b`` of adjacent cells: a join of the cells with their own shifted numbers."""
    at = coordinates(F.col("wcell"), g)
    steps = F.explode(F.array(*[F.struct(*[F.lit(x).alias(f"s{i}") for i, x in enumerate(s)]) for s in offsets(len(g), adjacency)]))
    shifted = cells.select(*by, F.col("wcell").alias("a"), *[c.alias(f"_i{i}") for i, c in enumerate(at)], steps.alias("s"))
    to = [F.col(f"_i{i}") + F.col(f"s.s{i}") for i in range(len(g))]
    if periodic:
        to = [F.pmod(t, F.lit(k)) for t, k in zip(to, g, strict=True)]
    else:
        for t, k in zip(to, g, strict=True):
            shifted = shifted.where((t >= 0) & (t < k))
    return shifted.select(*by, "a", linear(to, g).alias("b")).join(cells.select(*by, F.col("wcell").alias("b")), [*by, "b"]).select(*by, "a", "b")


def connected_components(cells: DataFrame, g: tuple[int, ...], by: Sequence[str] = (), adjacency: str = "face", strategy: str = "local", periodic: bool = False, tile: int = 1024) -> DataFrame:
    """``cells`` with column ``cluster``. ``by`` columns are integers when the strategy is not ``local``. ``periodic`` joins opposite borders of the grid."""
    if strategy == "auto":
        strategy = "local" if int(np.prod(g, dtype=np.int64)) <= LOCAL_CELLS else "tiled"
    if strategy == "local":
        schema = T.StructType([f for f in cells.schema.fields if f.name != "cluster"] + [T.StructField("cluster", T.LongType())])

        def label(pdf: pd.DataFrame) -> pd.DataFrame:
            return pdf.assign(cluster=label_array(pdf["wcell"].to_numpy(np.int64), g, adjacency, periodic))

        return cells.groupBy(*by).applyInPandas(label, schema)
    size = int(np.prod(g))
    if strategy == "iterate":
        joined = edges(cells, g, by, adjacency, periodic)
        run = _run_number(by) * size
        found = graph_components(joined.select((run + F.col("a")).alias("a"), (run + F.col("b")).alias("b")), "a", "b")
        keyed = cells.withColumn("vertex", run + F.col("wcell"))
        return keyed.join(found, "vertex", "left").withColumn("cluster", F.coalesce(F.col("component") % size, F.col("wcell"))).drop("vertex", "component")
    if strategy == "tiled":
        tiles = [F.floor(c / tile).cast("long") for c in coordinates(F.col("wcell"), g)]
        wide = tuple(-(-k // tile) for k in g)
        inner = connected_components(cells.withColumn("_tile", linear(tiles, wide)), g, [*by, "_tile"], adjacency)
        # Labels of a tile are cells of that tile, so they serve as vertices; only border cells can have outer edges.
        names = inner.select(*by, "wcell", "cluster", "_tile")
        rim = None
        for c, k in zip(coordinates(F.col("wcell"), g), g, strict=True):
            side = (c % tile == 0) | (c % tile == tile - 1) | (c == k - 1) if k > tile or periodic else F.lit(False)
            rim = side if rim is None else rim | side
        border = names.where(rim)
        across = edges(border, g, by, adjacency, periodic).join(border.select(*by, F.col("wcell").alias("a"), F.col("cluster").alias("ca")), [*by, "a"]).join(border.select(*by, F.col("wcell").alias("b"), F.col("cluster").alias("cb")), [*by, "b"])
        run = _run_number(by) * size
        found = graph_components(across.where("ca <> cb").select((run + F.col("ca")).alias("a"), (run + F.col("cb")).alias("b")), "a", "b")
        joined = inner.withColumn("vertex", run + F.col("cluster")).join(found, "vertex", "left")
        return joined.withColumn("cluster", F.coalesce(F.col("component") % size, F.col("cluster"))).drop("vertex", "component", "_tile")
    raise ValueError(f"strategy {strategy!r}")
