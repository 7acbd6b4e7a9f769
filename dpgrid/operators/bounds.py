"""Theory of the releases: expected shifts of the cut rank and utility bounds. Owner side: all of it reads clean statistics."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def tail(x: Column) -> Column:
    """Probability that four unit Laplace draws sum to at most -x, for x >= 0."""
    return F.exp(-x) * (48 + 33 * x + 9 * x * x + x * x * x) / 96


def theta(band: DataFrame, eps: Column | float, level: int = 1, variant: str = "consistent") -> Column:
    """Aggregate: expected number of positive coefficients (2-D Haar, level 1) that noise turns non-positive.

    The noise of a coefficient is half a sum of four draws of scale 1/eps; ``variant="undivided"`` leaves out the half.
    """
    e = F.lit(float(eps)) if isinstance(eps, (int, float)) else eps
    return F.sum(F.when(F.col("w") > 0, tail((2.0 if variant == "consistent" else 1.0) * e * F.col("w"))).otherwise(0.0))


def expected_rank_shift(p: float, n_nonpos: Column, theta_: Column) -> Column:
    """Expected excess of the noisy-counts rank over the clean one."""
    return (1 - p) * (n_nonpos / 2 - theta_)


def statistics(band: DataFrame, runs: DataFrame, p: float, coarse_cells: int) -> DataFrame:
    """``eps_i, eps, n_pos, n_nonpos, k, w_max, w_k, theta`` of the clean band, a line per budget."""
    from dpgrid.operators.threshold import percentile_cut

    budgets = runs.select("eps_i", "eps").distinct()
    cut = percentile_cut(band, p)
    top = band.agg(F.max("w").alias("w_max"))
    th = band.crossJoin(F.broadcast(budgets)).groupBy("eps_i", "eps").agg(theta(band, F.col("eps")).alias("theta"))
    return th.crossJoin(cut).crossJoin(top).select("eps_i", "eps", "n_pos", (F.lit(coarse_cells) - F.col("n_pos")).alias("n_nonpos"), "k", "w_max", F.col("d").alias("w_k"), "theta")


def _clamped(lo: Column, hi: Column) -> tuple[Column, Column]:
    edge = lambda c: F.greatest(F.least(c, F.col("n_pos").cast("double")), F.lit(1.0)).cast("long")
    return edge(F.floor(lo)).alias("k_min"), edge(F.ceil(hi)).alias("k_max")


def _gamma(eps: Column, omega: float, tight: bool) -> Column:
    """Half-width that all noise of all coefficients stays within, with probability 1 - omega."""
    draws = 4 * (F.col("n_pos") + F.col("n_nonpos"))
    return (4.0 if tight else 8.0) / eps * F.log(draws / omega)


def _binomial(omega: float) -> Column:
    return F.sqrt(F.col("n_nonpos") * math.log(1 / omega) / 2)


def bounds_noisy_counts(stats: DataFrame, p: float, omega: float, tight: bool = False) -> DataFrame:
    z, s = F.col("n_nonpos") / 2, _binomial(omega)
    lo, hi = F.col("k") + (1 - p) * (z - s - F.col("theta")), F.col("k") + (1 - p) * (z + s - F.col("theta"))
    return stats.select("eps_i", *_clamped(lo, hi), _gamma(F.col("eps"), omega, tight).alias("gamma"), F.lit((1 - omega) ** 2).alias("probability"))


def bounds_trimmed(stats: DataFrame, p: float, omega: float, alpha: float = 0.9, tight: bool = False) -> DataFrame:
    s, beta = _binomial(omega), (1.0 if tight else 2.0) / (F.col("eps") * (1 - alpha)) * math.log(1 / omega)
    lo, hi = F.col("k") + (1 - p) * (-s - F.col("theta") - beta), F.col("k") + (1 - p) * (s - F.col("theta") + beta)
    return stats.select("eps_i", *_clamped(lo, hi), _gamma(F.col("eps") * alpha, omega, tight).alias("gamma"), F.lit((1 - omega) ** 3).alias("probability"))


def bounds_sampled_cut(stats: DataFrame, p: float, omega: float, alpha: float = 0.7, tight: bool = False) -> DataFrame:
    """May be empty of information: the widths hold the whole list; they are clamped to it."""
    e2 = F.col("eps") * (1 - alpha)
    gap = F.greatest(F.abs(F.col("w_max") - F.col("w_k")), F.lit(1e-12))
    down = F.col("n_pos") - F.col("k") - 1 + 2.0 / e2 * F.log(gap / (F.abs(F.col("w_k")) * omega))
    up = F.col("k") - 2 + 2.0 / e2 * F.log(F.abs(F.col("w_k")) / (gap * omega))
    return stats.select("eps_i", *_clamped(F.col("k") - down, F.col("k") + up), _gamma(F.col("eps") * alpha, omega, tight).alias("gamma"), F.lit((1 - omega) ** 3).alias("probability"))


def prefer_method(stats: DataFrame) -> DataFrame:
    """Which of the two threshold techniques has the tighter bound, by the sign of ln(w_k / (w_max - w_k))."""
    sign = F.log(F.col("w_k") / F.greatest(F.col("w_max") - F.col("w_k"), F.lit(1e-12)))
    return stats.select("eps_i", sign.alias("indicator"), F.when(sign < 0, "sampled_cut").otherwise("trimmed").alias("tighter"))


def verify_bounds(clean: DataFrame, bounds: DataFrame, released: DataFrame, runs: DataFrame) -> DataFrame:
    """``eps_i, rep, must, must_kept, must_not, must_not_dropped, holds`` of the claims that the bounds make about clean cells."""
    from dpgrid.operators.threshold import value_histogram

    hist = value_histogram(clean)
    at = lambda k: F.max(F.when(F.col("rank_ge") >= F.col(k), F.col("w")))
    edge = bounds.crossJoin(hist).groupBy("eps_i", "gamma").agg(at("k_min").alias("w_hi"), at("k_max").alias("w_lo"))
    lines = runs.select("eps_i", "rep").join(F.broadcast(edge), "eps_i")
    cells = lines.crossJoin(clean.where("w > 0")).join(released.select("eps_i", "rep", "wcell", F.lit(1).alias("out")), ["eps_i", "rep", "wcell"], "left")
    must, never = F.col("w") > F.col("w_hi") + F.col("gamma"), F.col("w") < F.col("w_lo") - F.col("gamma")
    count = lambda c: F.sum(F.when(c, 1).otherwise(0)).cast("long")
    made = cells.groupBy("eps_i", "rep").agg(
        count(must).alias("must"), count(must & F.col("out").isNotNull()).alias("must_kept"), count(never).alias("must_not"), count(never & F.col("out").isNull()).alias("must_not_dropped")
    )
    return made.withColumn("holds", (F.col("must") == F.col("must_kept")) & (F.col("must_not") == F.col("must_not_dropped")))
