"""Ranks and cuts of the average band.

Only positive values are ranked. A value histogram stands for the sorted list: on clean Haar values it has far fewer rows than
the grid, and every rank follows from one window over it per run. For very large bands ``bracket_cut`` finds the same order
statistic without a total sort.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dpgrid.plans.scratch import materialise

_GUARD = 1e-9


def top_count(positives: Column | str, p: Column | float, rounding: str = "ceil") -> Column:
    """How many values stay when the lowest share ``p`` of the positives goes."""
    x = (F.lit(1.0) - (F.lit(float(p)) if isinstance(p, (int, float)) else p)) * (F.col(positives) if isinstance(positives, str) else positives)
    made = {"ceil": F.ceil(x - _GUARD), "floor": F.floor(x + _GUARD), "round": F.floor(x + 0.5)}[rounding]
    return F.greatest(made, F.lit(0)).cast("long")


def value_histogram(band: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """``by..., w, mult, rank_ge``: distinct positive values, their multiplicity, and how many values are at least as large."""
    hist = band.where(F.col("w") > 0).groupBy(*by, "w").agg(F.count(F.lit(1)).alias("mult"))
    down = Window.partitionBy(*by).orderBy(F.col("w").desc()).rowsBetween(Window.unboundedPreceding, 0)
    return hist.withColumn("rank_ge", F.sum("mult").over(down))


def count_signs(band: DataFrame, coarse_cells: int, by: Sequence[str] = ()) -> DataFrame:
    """``by..., n_pos, n_nonpos``; cells that a sparse band lacks are zeros and so not positive."""
    made = band.groupBy(*by).agg(F.sum(F.when(F.col("w") > 0, 1).otherwise(0)).cast("long").alias("n_pos"))
    return made.withColumn("n_nonpos", F.lit(coarse_cells) - F.col("n_pos"))


def cut_at(band: DataFrame, ranks: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """``by..., n_pos, k, d`` with ``d`` the ``k``-th largest positive value, for ``ranks`` = ``by..., n_pos, k``; null for k = 0."""
    hist = value_histogram(band, by)
    joined = ranks.join(hist, list(by), "left") if by else ranks.crossJoin(hist)
    d = F.max(F.when(F.col("rank_ge") >= F.col("k"), F.col("w")))
    return joined.groupBy(*by, "n_pos", "k").agg(d.alias("d")).withColumn("d", F.when(F.col("k") > 0, F.col("d")))


def percentile_cut(band: DataFrame, p: float, by: Sequence[str] = (), rounding: str = "ceil", drop: DataFrame | None = None) -> DataFrame:
    """``by..., n_pos, k, d`` of the rank rule; ``drop`` (``by..., r``) takes that many least positives off first, all but one at most.

    Counts, ranks and the cut come from one histogram, so the band is read once.
    """
    hist = value_histogram(band, by).withColumn("n_pos", F.sum("mult").over(Window.partitionBy(*by)))
    ranked = _with_rank(hist, p, by, rounding, drop)
    d = F.max(F.when((F.col("k") > 0) & (F.col("rank_ge") >= F.col("k")), F.col("w")))
    return ranked.groupBy(*by, "n_pos", "k").agg(d.alias("d"))


def _with_rank(rows: DataFrame, p: float, by: Sequence[str], rounding: str, drop: DataFrame | None) -> DataFrame:
    """Column ``k`` from ``n_pos`` and the run's ``drop``."""
    left = F.col("n_pos")
    if drop is not None:
        lines = F.broadcast(drop.select(*by, "r"))  # one number per run
        rows = rows.join(lines, list(by)) if by else rows.crossJoin(lines)
        left = left - F.least(F.greatest(F.col("r"), F.lit(0)), F.greatest(left - 1, F.lit(0)))
    return rows.withColumn("k", F.least(F.col("n_pos"), top_count(left, p, rounding)))


#: Steps of the quantile sketch; a bracket is some of them wide.
STEPS = 500


def bracket_cut(band: DataFrame, p: float, by: Sequence[str] = (), rounding: str = "ceil", drop: DataFrame | None = None, accuracy: int = 20_000) -> DataFrame:
    """The same as ``percentile_cut`` in two passes: a quantile sketch per run brackets the rank, then exact ranks within the bracket alone.

    No task holds more of a run than the sketch or the bracket, which has less than a hundredth of its values but for ties.
    """
    pos = band.where(F.col("w") > 0)
    runs = pos.groupBy(*by).agg(F.count(F.lit(1)).alias("n_pos"), F.percentile_approx("w", [i / STEPS for i in range(STEPS + 1)], accuracy).alias("q")).where("n_pos > 0")
    share = (1 - F.col("k") / F.col("n_pos")) * STEPS
    below, above = F.floor(share).cast("int"), F.least(F.ceil(share).cast("int") + 2, F.lit(STEPS + 1))
    lines = _with_rank(runs, p, by, rounding, drop).select(*by, "n_pos", "k", F.when(below < 1, 0.0).otherwise(F.element_at("q", F.greatest(below, F.lit(1)))).alias("lo"), F.element_at("q", above).alias("hi"))
    lines = F.broadcast(materialise(lines, "brackets"))  # a line per run
    near = pos.join(lines, list(by)) if by else pos.crossJoin(lines)
    # What lies above the bracket is one row of a null value, which comes first.
    hist = near.where(F.col("w") >= F.col("lo")).groupBy(*by, "n_pos", "k", F.when(F.col("w") <= F.col("hi"), F.col("w")).alias("v")).agg(F.count(F.lit(1)).alias("mult"))
    down = Window.partitionBy(*by).orderBy(F.col("v").desc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    d = F.max(F.when((F.col("k") > 0) & (F.col("rank_ge") >= F.col("k")), F.col("v")))
    return hist.withColumn("rank_ge", F.sum("mult").over(down)).groupBy(*by, "n_pos", "k").agg(d.alias("d"))


def keep_cells(band: DataFrame, cut: DataFrame, by: Sequence[str] = (), ties: str = "inclusive") -> DataFrame:
    """Cells of the band at or above (``strict``: above) their run's cut; cuts are a row per run and travel to the cells."""
    runs = F.broadcast(cut.select(*by, "d"))
    joined = band.join(runs, list(by)) if by else band.crossJoin(runs)
    test = F.col("w") >= F.col("d") if ties == "inclusive" else F.col("w") > F.col("d")
    return joined.where((F.col("w") > 0) & test).drop("d")


def significant_cells(band: DataFrame, p: float | None = None, k: int | None = None, d: float | None = None, by: Sequence[str] = (), ties: str = "inclusive", rounding: str = "ceil") -> tuple[DataFrame, DataFrame]:
    """(cells kept, cut) by percentile ``p``, rank ``k`` or value ``d``."""
    if sum(x is not None for x in (p, k, d)) != 1:
        raise ValueError("give one of p, k and d")
    if p is not None:
        if not 0 <= p < 1:
            raise ValueError("p is a share from 0 to below 1")
        cut = percentile_cut(band, p, by, rounding)
    else:
        n = band.where(F.col("w") > 0).groupBy(*by).agg(F.count(F.lit(1)).alias("n_pos"))
        if k is not None:
            cut = cut_at(band, n.withColumn("k", F.least(F.col("n_pos"), F.lit(k).cast("long"))), by)
        else:
            kept = band.where((F.col("w") > 0) & (F.col("w") >= d)).groupBy(*by).agg(F.count(F.lit(1)).alias("k"))
            cut = (n.join(kept, list(by), "left") if by else n.crossJoin(kept)).withColumn("k", F.coalesce("k", F.lit(0))).withColumn("d", F.lit(float(d)))
    return keep_cells(band, cut, by, ties), cut


def rank_intervals(band: DataFrame, by: Sequence[str] = (), upper: float | None = None) -> DataFrame:
    """``by..., rank, lo, hi``: half-open intervals (lo, hi] between neighbouring distinct positive values.

    ``rank`` counts the values at least ``hi``. With a public ``upper`` bound an interval of rank 0 reaches from the largest value to it.
    """
    hist = value_histogram(band, by)
    down = Window.partitionBy(*by).orderBy(F.col("w").desc())
    made = hist.select(*by, F.col("rank_ge").alias("rank"), F.coalesce(F.lead("w").over(down), F.lit(0.0)).alias("lo"), F.col("w").alias("hi"))
    if upper is None:
        return made
    top = hist.groupBy(*by).agg(F.max("w").alias("lo")).where(F.col("lo") < upper)
    return made.unionByName(top.select(*by, F.lit(0).cast("long").alias("rank"), "lo", F.lit(float(upper)).alias("hi")))
