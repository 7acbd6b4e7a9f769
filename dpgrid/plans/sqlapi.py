"""SQL surface: scalar functions, table functions, pandas functions and a helper that registers a clustering as a view."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dpgrid.operators import methods
from dpgrid.operators.grid import GridSpec
from dpgrid.operators.privacy import runs_frame

#: Name, arguments, result and body of each SQL function.
FUNCTIONS = (
    ("laplace_noise", "u DOUBLE, b DOUBLE", "DOUBLE", "-b * signum(u - 0.5e0) * ln(1e0 - 2e0 * abs(u - 0.5e0))"),
    ("cell_index", "x DOUBLE, lo DOUBLE, hi DOUBLE, g BIGINT", "BIGINT", "greatest(least(floor((x - lo) * g / (hi - lo)), g - 1), 0)"),
    ("cell_id", "i0 BIGINT, i1 BIGINT, g1 BIGINT", "BIGINT", "i0 * g1 + i1"),
    ("haar_block", "cell BIGINT, g1 BIGINT", "BIGINT", "(cell div g1) div 2 * ((g1 + 1) div 2) + (cell % g1) div 2"),
)


def register_sql(spark: SparkSession) -> None:
    """Create the SQL functions and table functions in the session."""
    for name, args, made, body in FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {made} RETURN {body}")
    spark.udtf.register("grid_neighbors", neighbors_udtf())
    spark.udtf.register("boxes_to_points", boxes_udtf())


def neighbors_udtf():
    """Table function: numbers of the cells next to a cell of a two-dimensional grid."""

    class Neighbors:
        def eval(self, cell: int, rows: int, cols: int, full: bool):
            i, j = divmod(cell, cols)
            for a in (-1, 0, 1):
                for b in (-1, 0, 1):
                    if (a or b) and (full or not (a and b)) and 0 <= i + a < rows and 0 <= j + b < cols:
                        yield ((i + a) * cols + j + b,)

    return F.udtf(Neighbors, returnType="neighbor: bigint")


def boxes_udtf():
    """Table function: evenly placed points of a box, as many as its rounded count."""

    class Boxes:
        def eval(self, lo0: float, hi0: float, lo1: float, hi1: float, cnt: float):
            n = int(max(cnt, 0.0) + 0.5)
            for k in range(n):
                yield lo0 + (hi0 - lo0) * ((k + 0.5) / n), lo1 + (hi1 - lo1) * ((k * 0.6180339887498949 + 0.5) % 1.0)

    return F.udtf(Boxes, returnType="x0: double, x1: double")


def cell_udf(spec: GridSpec):
    """Arrow-batched cell number of array points, for dimensions beyond what is comfortable as columns; null for unsound points."""
    lo, step, g = np.array(spec.lo), np.array(spec.g) / (np.array(spec.hi) - np.array(spec.lo)), np.array(spec.g)

    @F.pandas_udf(T.LongType())
    def cell(points: pd.Series) -> pd.Series:
        ok = points.map(lambda p: p is not None and len(p) >= len(g) and all(x is not None and x == x for x in p[: len(g)]))
        made = pd.Series([None] * len(points), dtype="Int64", index=points.index)
        if ok.any():
            x = np.stack([np.asarray(p[: len(g)], float) for p in points[ok]])
            made[ok] = np.ravel_multi_index(tuple(np.clip(np.floor((x - lo) * step), 0, g - 1).astype(int).T), tuple(g))
        return made

    return cell


def log_sum_exp():
    """Grouped aggregate: ln of the sum of exponentials, without overflow."""

    @F.pandas_udf(T.DoubleType())
    def lse(v: pd.Series) -> float:
        top = v.max()
        return float(top + np.log(np.exp(v - top).sum()))

    return lse


def weighted_entropy():
    """Grouped aggregate: bits of a column of class weights."""

    @F.pandas_udf(T.DoubleType())
    def entropy(w: pd.Series) -> float:
        share = w[w > 0] / w.sum()
        return float(-(share * np.log2(share)).sum())

    return entropy


def sql_cluster(spark: SparkSession, view: str, result: str, cols: Sequence[str], spec: GridSpec, p: float, method: str = "nonprivate", eps: float = 1.0, key: str = "", **how) -> DataFrame:
    """Cluster the points of a view and register the labelled cells as the temporary view ``result``."""
    made = methods.release(spark.table(view), list(cols), spec, p, runs_frame(spark, [eps]), key, method, **how)
    made.cells.createOrReplaceTempView(result)
    return made.cells
