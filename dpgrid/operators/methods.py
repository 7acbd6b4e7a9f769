"""The clustering algorithm and its private releases.

Every release takes a frame of runs (budget and repetition per line), so a whole sweep is one plan. Frames of cells
hold releasable columns only; clean ranks and counts stay in the owner's diagnostics.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpgrid.operators.components import connected_components
from dpgrid.operators.grid import GridSpec, block_of, cell_of, coordinates, inside
from dpgrid.operators.privacy import RUN, Ledger, exponential_cut, noisy_nonpositive, private_haar, private_quantize
from dpgrid.operators.quantize import quantize
from dpgrid.operators.threshold import bracket_cut, count_signs, keep_cells, percentile_cut, rank_intervals, significant_cells
from dpgrid.operators.wavelet import get_wavelet, sensitivity_count, sensitivity_rank, sensitivity_z, wavelet_transform
from dpgrid.plans.scratch import materialise


#: Cells of a band beyond which its cut is found within a bracket.
LARGE_BAND = 2_000_000


@dataclass
class Clustering:
    """Labelled cells ``by..., wcell, w, cluster`` and the cut ``by..., n_pos, k, d``."""

    cells: DataFrame
    cut: DataFrame
    band: DataFrame
    spec: GridSpec
    level: int = 1


@dataclass
class PrivateClustering:
    """``cells``: run, wcell, cluster. ``cut``: run, k_priv, d_priv. ``band`` (noisy) and ``owner`` stay with the owner."""

    cells: DataFrame
    cut: DataFrame
    band: DataFrame
    ledger: Ledger
    spec: GridSpec
    owner: DataFrame | None = None
    level: int = 1


@dataclass(frozen=True)
class Options:
    wavelet: str = "haar"
    level: int = 1
    adjacency: str = "face"
    ties: str = "inclusive"
    rounding: str = "ceil"
    strategy: str = "auto"
    neighbor: str = "add_remove"
    noise: str = "laplace"
    source: str = "keyed"


def cluster_band(band: DataFrame, spec: GridSpec, p: float, by: Sequence[str] = (), o: Options = Options()) -> Clustering:
    cells, cut = significant_cells(band, p=p, by=by, ties=o.ties, rounding=o.rounding)
    return Clustering(connected_components(cells, spec.coarse(o.level), by, o.adjacency, o.strategy), cut, band, spec, o.level)


def cluster_counts_matrix(counts: DataFrame, spec: GridSpec, p: float, by: Sequence[str] = (), o: Options = Options(), value: str = "cnt") -> Clustering:
    return cluster_band(wavelet_transform(counts, spec, o.wavelet, o.level, value, by), spec, p, by, o)


def cluster_grid(df: DataFrame, cols: Sequence[str], spec: GridSpec, p: float, by: Sequence[str] = (), o: Options = Options()) -> Clustering:
    """The non-private algorithm: count, low-pass, cut at the percentile, join adjacent cells."""
    return cluster_counts_matrix(quantize(df, cols, spec, by), spec, p, by, o)


def assign_points(df: DataFrame, cells: DataFrame, cols: Sequence[str], spec: GridSpec, level: int = 1, by: Sequence[str] = ()) -> DataFrame:
    """Points with the cluster of their cell, -1 for noise. Labels are as many as the grid has cells at most, so they travel.

    Above a size that Spark would broadcast by itself the hint is left to the optimizer.
    """
    placed = inside(df, list(cols), spec).withColumn("wcell", block_of(cell_of(list(cols), spec), spec, level))
    size = 1
    for k in spec.coarse(level):
        size *= k
    labels = cells.select(*by, "wcell", "cluster")
    labels = F.broadcast(labels) if size <= 2_000_000 else labels
    return placed.join(labels, [*by, "wcell"], "left").withColumn("cluster", F.coalesce("cluster", F.lit(-1).cast("long")))


def cluster_profile(cells: DataFrame, spec: GridSpec, level: int = 1, by: Sequence[str] = ()) -> DataFrame:
    """Per cluster: cells, mass, bounding box and mass centre in cell coordinates."""
    at = coordinates(F.col("wcell"), spec.coarse(level))
    rows = cells.select(*by, "cluster", "w", *[c.alias(f"w{a}") for a, c in enumerate(at)])
    boxes = [x for a in range(spec.n) for x in (F.min(f"w{a}").alias(f"min{a}"), F.max(f"w{a}").alias(f"max{a}"), (F.sum(F.col(f"w{a}") * F.col("w")) / F.sum("w")).alias(f"centre{a}"))]
    return rows.groupBy(*by, "cluster").agg(F.count(F.lit(1)).alias("cells"), F.sum("w").alias("mass"), *boxes)


def ascii_map(cells: DataFrame, spec: GridSpec, level: int = 1) -> DataFrame:
    """``line, picture`` of a two-dimensional clustering, a letter per cluster (in order of label) and a dot for noise."""
    from pyspark.sql import Window

    rows, cols = spec.coarse(level)
    marked = cells.select("wcell", (F.dense_rank().over(Window.orderBy("cluster")) - 1).alias("i")).withColumn("mark", F.char(65 + F.col("i") % 26))
    domain = cells.sparkSession.range(rows * cols).withColumnRenamed("id", "wcell")
    full = domain.join(marked, "wcell", "left").select(F.floor(F.col("wcell") / cols).cast("long").alias("line"), "wcell", F.coalesce("mark", F.lit(".")).alias("mark"))
    cell = F.array_sort(F.collect_list(F.struct("wcell", "mark")))
    return full.groupBy("line").agg(F.array_join(F.transform(cell, lambda s: s["mark"]), "").alias("picture"))


def _drawn_band(*args) -> DataFrame:
    """The noisy band, drawn once and written: ranking and selection read numbers instead of hashing again."""
    return materialise(_noisy_band(*args), "noisy_band")


def _noisy_band(counts: DataFrame, spec: GridSpec, runs: DataFrame, key: str, share: float, o: Options) -> DataFrame:
    s = sensitivity_count(o.neighbor)
    if get_wavelet(o.wavelet).haar:
        return private_haar(counts, spec, runs, key, share, s, o.level, o.noise, o.source)
    noisy = private_quantize(counts, spec, runs, key, share, s, o.noise, o.source)
    return wavelet_transform(noisy, spec, o.wavelet, o.level, "cnt_noisy", RUN)


def _noisy_cut(band: DataFrame, spec: GridSpec, p: float, o: Options, drop: DataFrame | None = None) -> DataFrame:
    """Noisy values are all different, so a run's ranks come from a sort of its band: whole for ordinary grids, of a narrow bracket beyond ``LARGE_BAND`` cells.

    Both give the same cut.
    """
    cut = bracket_cut if _coarse_cells(spec, o.level) > LARGE_BAND else percentile_cut
    return cut(band, p, RUN, o.rounding, drop)


def _coarse_cells(spec: GridSpec, level: int) -> int:
    made = 1
    for k in spec.coarse(level):
        made *= k
    return made


def _released(kept: DataFrame, cut: DataFrame, band: DataFrame, ledger: Ledger, spec: GridSpec, o: Options, owner: DataFrame | None = None) -> PrivateClustering:
    labelled = connected_components(kept, spec.coarse(o.level), RUN, o.adjacency, o.strategy)
    return PrivateClustering(labelled.select(*RUN, "wcell", "cluster"), cut, band, ledger, spec, owner, o.level)


def _counts(df: DataFrame, cols: Sequence[str], spec: GridSpec) -> DataFrame:
    """Clean counts, written once: every branch and run reads the few cells, not the points."""
    return materialise(quantize(df, cols, spec), "counts")


def release_noisy_counts(counts: DataFrame, spec: GridSpec, p: float, runs: DataFrame, key: str, o: Options = Options()) -> PrivateClustering:
    """Noise on the counts only; rank and cut read the noisy band."""
    ledger = Ledger(1.0)
    ledger.parallel([1.0], "counts")
    band = _drawn_band(counts, spec, runs, key, 1.0, o)
    cut = _noisy_cut(band, spec, p, o)
    return _released(keep_cells(band, cut, RUN, o.ties), cut.select(*RUN, F.col("k").alias("k_priv"), F.col("d").alias("d_priv")), band, ledger, spec, o)


def release_trimmed(counts: DataFrame, spec: GridSpec, p: float, runs: DataFrame, key: str, alpha: float = 0.9, o: Options = Options(), trim_rounding: str = "floor") -> PrivateClustering:
    """Noisy counts, and half a noisy count of non-positive clean cells off the small end of the noisy rank list.

    ``trim_rounding`` turns the half into a whole number: ``floor``, ``round`` or ``ceil``. At least one positive value stays.
    """
    if not 0 < alpha < 1:
        raise ValueError("the split lies between 0 and 1")
    ledger = Ledger(1.0)
    ledger.parallel([alpha], "counts")
    ledger.spend(1 - alpha, "non-positive count")
    band = _drawn_band(counts, spec, runs, key, alpha, o)
    clean = count_signs(wavelet_transform(counts, spec, o.wavelet, o.level), _coarse_cells(spec, o.level))
    z = noisy_nonpositive(clean, runs, key, 1 - alpha, sensitivity_z(o.wavelet, spec.n, o.neighbor), o.source)
    whole = {"floor": F.floor, "ceil": F.ceil, "round": lambda x: F.floor(x + 0.5)}[trim_rounding]
    drop = z.select(*RUN, whole(F.col("z_noisy") / 2).cast("long").alias("r"))
    cut = _noisy_cut(band, spec, p, o, drop)
    return _released(keep_cells(band, cut, RUN, o.ties), cut.select(*RUN, F.col("k").alias("k_priv"), F.col("d").alias("d_priv")), band, ledger, spec, o)


def release_sampled_cut(counts: DataFrame, spec: GridSpec, p: float, runs: DataFrame, key: str, alpha: float = 0.7, upper: float | None = None, sampler: str = "gumbel", o: Options = Options()) -> PrivateClustering:
    """Noisy counts, and a cut value drawn near the clean rank by the exponential mechanism.

    Without ``upper`` the range of the cut ends at the largest clean value, which is data; a public bound makes the release strictly private.
    """
    if not 0 < alpha < 1:
        raise ValueError("the split lies between 0 and 1")
    ledger = Ledger(1.0)
    ledger.parallel([alpha], "counts")
    ledger.spend(1 - alpha, "cut")
    band = _drawn_band(counts, spec, runs, key, alpha, o)
    clean = wavelet_transform(counts, spec, o.wavelet, o.level)
    k = percentile_cut(clean, p, (), o.rounding)
    drawn = exponential_cut(rank_intervals(clean, (), upper), k, runs, key, 1 - alpha, sensitivity_rank(o.wavelet, spec.n, o.neighbor), sampler, o.source)
    return _released(keep_cells(band, drawn, RUN, "strict"), drawn.select(*RUN, "k_priv", F.col("d").alias("d_priv")), band, ledger, spec, o)


def release_ablation(counts: DataFrame, spec: GridSpec, p: float, runs: DataFrame, key: str, which: str, alpha: float = 0.7, o: Options = Options()) -> PrivateClustering:
    """One noise source alone: ``clean_counts`` with a drawn cut, or ``clean_cut`` on noisy counts. Not private; for analysis."""
    clean = wavelet_transform(counts, spec, o.wavelet, o.level)
    cut = percentile_cut(clean, p, (), o.rounding)
    if which == "clean_counts":
        drawn = exponential_cut(rank_intervals(clean), cut, runs, key, 1 - alpha, sensitivity_rank(o.wavelet, spec.n, o.neighbor), "gumbel", o.source)
        band = clean.crossJoin(F.broadcast(runs.select(*RUN)))
        kept = keep_cells(band, drawn, RUN, "strict")
        out = drawn.select(*RUN, "k_priv", F.col("d").alias("d_priv"))
    elif which == "clean_cut":
        band = _drawn_band(counts, spec, runs, key, alpha, o)
        lines = runs.select(*RUN).crossJoin(cut.select("k", "d"))
        kept = keep_cells(band, lines, RUN, o.ties)
        out = lines.select(*RUN, F.col("k").alias("k_priv"), F.col("d").alias("d_priv"))
    else:
        raise ValueError(f"ablation {which!r}")
    return _released(kept, out, band, Ledger(1.0), spec, o)


def release_synthetic(df: DataFrame, cols: Sequence[str], spec: GridSpec, p: float, runs: DataFrame, key: str, publisher: str = "adaptive_grid", synth: str = "points", o: Options = Options(), **how) -> PrivateClustering:
    """Publish a noisy description privately, draw synthetic points (or fractional counts) from it, and cluster those."""
    from dpgrid.operators import publish

    if o.noise != "laplace":
        raise ValueError("publishers draw Laplace noise")
    ledger = Ledger(1.0)
    ledger.spend(1.0, publisher)
    if synth not in ("points", "areal"):
        raise ValueError(f"synthesis {synth!r}")
    how |= {"source": o.source, "sensitivity": sensitivity_count(o.neighbor)}
    if publisher == "adaptive_grid" and synth == "points":
        counts = publish.adaptive_counts(df, list(cols), spec, runs, key, **how)
    else:
        leaves = publish.PUBLISHERS[publisher](df, list(cols), spec, runs, key, **how)
        counts = publish.drawn_counts(leaves, key, spec, o.source) if synth == "points" else publish.areal_counts(leaves, spec)
    made = cluster_counts_matrix(materialise(counts, "synthetic_counts"), spec, p, RUN, o)
    return PrivateClustering(made.cells.select(*RUN, "wcell", "cluster"), made.cut.select(*RUN, F.col("k").alias("k_priv"), F.col("d").alias("d_priv")), made.band, ledger, spec, None, o.level)


def release(df: DataFrame, cols: Sequence[str], spec: GridSpec, p: float, runs: DataFrame, key: str, method: str, **how) -> Clustering | PrivateClustering:
    """Any method by name: ``nonprivate``, ``synthetic``, ``noisy_counts``, ``trimmed``, ``sampled_cut``."""
    if method == "nonprivate":
        return cluster_grid(df, cols, spec, p, **how)
    if method == "synthetic":
        return release_synthetic(df, cols, spec, p, runs, key, **how)
    made = {"noisy_counts": release_noisy_counts, "trimmed": release_trimmed, "sampled_cut": release_sampled_cut}[method]
    return made(_counts(df, cols, spec), spec, p, runs, key, **how)
