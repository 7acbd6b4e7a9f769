"""Budgets, private counts, and the exponential mechanism."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dpgrid.functions.keyed import geometric, gumbel, keyed_uniform, laplace
from dpgrid.operators.grid import GridSpec, coordinates, linear
from dpgrid.operators.quantize import densify


@dataclass
class Ledger:
    """Spending of one release: sequential parts add up, disjoint parts count once at their largest."""

    total: float
    entries: list[tuple[str, float, str]] = field(default_factory=list)

    def spend(self, eps: float, label: str, kind: str = "sequential") -> float:
        if eps <= 0:
            raise ValueError("a budget part is positive")
        if self.spent() + eps > self.total * (1 + 1e-12):
            raise ValueError(f"{label}: {self.spent() + eps} exceeds the budget {self.total}")
        self.entries.append((label, float(eps), kind))
        return eps

    def parallel(self, parts: Sequence[float], label: str) -> float:
        """Mechanisms on disjoint records cost as much as the dearest."""
        return self.spend(max(parts), label, "parallel")

    def spent(self) -> float:
        return sum(e for _, e, _ in self.entries)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.entries, "label string, eps double, kind string")


def runs_frame(spark: SparkSession, eps: Sequence[float], reps: int = 1) -> DataFrame:
    """``eps_i, rep, eps``: one line per budget and repetition."""
    return spark.createDataFrame([(i, r, float(e)) for i, e in enumerate(eps) for r in range(reps)], "eps_i int, rep int, eps double")


RUN = ("eps_i", "rep")


def count_noise(key: str, scale: Column, *parts: Column | str, noise: str = "laplace", source: str = "keyed") -> Column:
    if noise == "laplace":
        return laplace(keyed_uniform(key, "count", *parts, source=source), scale)
    if noise == "geometric":
        return geometric(keyed_uniform(key, "count", *parts, source=source), keyed_uniform(key, "count2", *parts, source=source), scale)
    raise ValueError(f"noise {noise!r}")


def private_quantize(counts: DataFrame, spec: GridSpec, runs: DataFrame, key: str, share: float = 1.0, sensitivity: int = 1, noise: str = "laplace", source: str = "keyed") -> DataFrame:
    """``eps_i, rep, cell, cnt_noisy``: every cell of every run with its own draw, empty cells too."""
    domain = densify(counts.select("cell", "cnt"), spec)
    scale = F.lit(float(sensitivity)) / (F.col("eps") * F.lit(float(share)))
    return domain.crossJoin(F.broadcast(runs)).select(*RUN, "cell", (F.col("cnt") + count_noise(key, scale, *RUN, "cell", noise=noise, source=source)).alias("cnt_noisy"))


def private_haar(counts: DataFrame, spec: GridSpec, runs: DataFrame, key: str, share: float = 1.0, sensitivity: int = 1, level: int = 1, noise: str = "laplace", source: str = "keyed") -> DataFrame:
    """``eps_i, rep, wcell, w``: noisy average band with noise and transform in one projection.

    The same draws as ``private_quantize`` followed by the Haar step, but each block sums its own cells' draws, so a run costs
    as many rows as the band has cells and no exchange beyond the clean counts' own.
    """
    wide, side = spec.coarse(level), 2**level
    from dpgrid.operators.wavelet import wavelet_transform

    clean = wavelet_transform(counts, spec, "haar", level).withColumn("w", F.col("w") * 2.0 ** (spec.n * level / 2))
    blocks = counts.sparkSession.range(_size(wide)).withColumnRenamed("id", "wcell").join(clean, "wcell", "left").withColumn("w", F.coalesce("w", F.lit(0.0)))
    at = coordinates(F.col("wcell"), wide)
    scale = F.lit(float(sensitivity)) / (F.col("eps") * F.lit(float(share)))
    total = F.col("w")
    for k in range(side**spec.n):
        inner, rest = [], k
        for _ in range(spec.n):
            inner.append(rest % side)
            rest //= side
        inner.reverse()
        place = [a * side + b for a, b in zip(at, inner, strict=True)]
        draw = count_noise(key, scale, *RUN, linear(place, spec.g), noise=noise, source=source)
        odd = [p < g for p, g in zip(place, spec.g, strict=True) if g % side]
        for o in odd:
            draw = F.when(o, draw).otherwise(0.0)
        total = total + draw
    return blocks.crossJoin(F.broadcast(runs)).select(*RUN, "wcell", (total / 2.0 ** (spec.n * level / 2)).alias("w"))


def _size(g: tuple[int, ...]) -> int:
    made = 1
    for k in g:
        made *= k
    return made


def noisy_nonpositive(nonpos: DataFrame, runs: DataFrame, key: str, share: float, sensitivity: int = 1, source: str = "keyed") -> DataFrame:
    """``eps_i, rep, z_noisy`` from the one-row ``nonpos(n_nonpos)`` of the clean band."""
    scale = F.lit(float(sensitivity)) / (F.col("eps") * F.lit(float(share)))
    return nonpos.crossJoin(F.broadcast(runs)).select(*RUN, (F.col("n_nonpos") + laplace(keyed_uniform(key, "z", *RUN, source=source), scale)).alias("z_noisy"))


def exponential_mechanism(candidates: DataFrame, score: Column, weight: Column, u: Column, eps: Column, sensitivity: float, by: Sequence[str], keep: Sequence[str]) -> DataFrame:
    """One candidate per run, drawn with probability proportional to weight times exp(eps * score / (2 * sensitivity)).

    The candidate of largest log weight plus a Gumbel draw has just that law, so a plain maximum per run does it.
    """
    ranked = candidates.where(weight > 0).withColumn("_v", F.log(weight) + eps * score / (2.0 * sensitivity) + gumbel(u))
    return ranked.groupBy(*by).agg(F.max_by(F.struct(*keep), "_v").alias("_c")).select(*by, "_c.*")


def exponential_cut(intervals: DataFrame, k: DataFrame, runs: DataFrame, key: str, share: float, sensitivity: int = 1, sampler: str = "gumbel", source: str = "keyed") -> DataFrame:
    """``eps_i, rep, k_priv, d``: a rank interval near rank k, then a uniform point in it.

    ``intervals`` as ``rank_intervals`` makes them for the clean band, ``k`` the one-row clean rank. ``sampler="cumulative"`` inverts
    the cumulative weights instead, with the largest log weight taken off first.
    """
    eps = F.col("eps") * F.lit(float(share))
    cands = intervals.crossJoin(k.select("k")).crossJoin(F.broadcast(runs))
    score = -F.abs(F.col("rank") - F.col("k")).cast("double")
    width = F.col("hi") - F.col("lo")
    if sampler == "gumbel":
        won = exponential_mechanism(cands, score, width, keyed_uniform(key, "gumbel", *RUN, "rank", source=source), eps, sensitivity, RUN, ["rank", "lo", "hi"])
    elif sampler == "cumulative":
        v = cands.where(width > 0).withColumn("_v", F.log(width) + eps * score / (2.0 * sensitivity))
        whole = Window.partitionBy(*RUN)
        v = v.withColumn("_e", F.exp(F.col("_v") - F.max("_v").over(whole)))
        upto = whole.orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
        v = v.withColumn("_t", F.sum("_e").over(upto) / F.sum("_e").over(whole)).where(F.col("_t") >= keyed_uniform(key, "pick", *RUN, source=source))
        won = v.groupBy(*RUN).agg(F.min_by(F.struct("rank", "lo", "hi"), "_t").alias("_c")).select(*RUN, "_c.*")
    else:
        raise ValueError(f"sampler {sampler!r}")
    return won.select(*RUN, F.col("rank").alias("k_priv"), (F.col("lo") + (F.col("hi") - F.col("lo")) * keyed_uniform(key, "within", *RUN, source=source)).alias("d"))
