"""Counting points per cell: one scan of the coordinate columns, then only cells travel."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpgrid.operators.grid import GridSpec, cell_of, inside, index_of, linear


def quantize(df: DataFrame, cols: Sequence[str], spec: GridSpec, by: Sequence[str] = (), out_of_bounds: str = "clamp") -> DataFrame:
    """``by..., cell, cnt`` of the non-empty cells; null and NaN coordinates are left out."""
    return inside(df, list(cols), spec, out_of_bounds).groupBy(*by, cell_of(list(cols), spec).alias("cell")).agg(F.count(F.lit(1)).alias("cnt"))


def quantize_vec(df: DataFrame, vec: str, spec: GridSpec, by: Sequence[str] = ()) -> DataFrame:
    """The same for points held in an array column; its first ``n`` elements are the coordinates."""
    at = [F.element_at(vec, a + 1).cast("double") for a in range(spec.n)]
    sound = df.where((F.size(vec) >= spec.n) & ~F.exists(F.slice(vec, 1, spec.n), lambda e: e.isNull() | F.isnan(e)))
    cell = linear([index_of(x, lo, hi, g) for x, lo, hi, g in zip(at, spec.lo, spec.hi, spec.g, strict=True)], spec.g)
    return sound.groupBy(*by, cell.alias("cell")).agg(F.count(F.lit(1)).alias("cnt"))


def occupied_cells(df: DataFrame, cols: Sequence[str], spec: GridSpec, approximate: bool = False) -> DataFrame:
    """One row, ``occupied``: how many cells hold a point, exactly or by a sketch of constant size."""
    cell = cell_of(list(cols), spec)
    return inside(df, list(cols), spec).agg((F.approx_count_distinct(cell) if approximate else F.count_distinct(cell)).alias("occupied"))


def densify(counts: DataFrame, spec: GridSpec, runs: DataFrame | None = None, by: Sequence[str] = ()) -> DataFrame:
    """Every cell (of every run), empty ones with 0."""
    domain = counts.sparkSession.range(spec.dense_cells()).withColumnRenamed("id", "cell")
    if runs is not None:
        domain = domain.crossJoin(F.broadcast(runs))  # a run is a line of parameters
    return domain.join(counts, [*by, "cell"], "left").withColumn("cnt", F.coalesce("cnt", F.lit(0)))


def bounds_from_data(df: DataFrame, cols: Sequence[str], g: Sequence[int]) -> GridSpec:
    """Bounds as the least and largest coordinates. Not private: for the non-private algorithm only."""
    row = df.agg(*[f(c).alias(f"{n}{i}") for i, c in enumerate(cols) for n, f in (("lo", F.min), ("hi", F.max))]).first()
    return GridSpec(tuple(float(row[f"lo{i}"]) for i in range(len(cols))), tuple(float(row[f"hi{i}"]) for i in range(len(cols))), tuple(g))


def bound_contribution(df: DataFrame, user: str, cap: int, key: str, row_id: str) -> DataFrame:
    """At most ``cap`` rows per individual, chosen by keyed draw: then one individual changes counts by at most ``cap``."""
    from pyspark.sql import Window

    from dpgrid.functions.keyed import keyed_uniform

    order = Window.partitionBy(user).orderBy(keyed_uniform(key, "cap", row_id), row_id)
    return df.withColumn("_place", F.row_number().over(order)).where(F.col("_place") <= cap).drop("_place")
