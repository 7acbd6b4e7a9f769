"""Accuracy of private clusterings against the true one.

True labels come as ``wcell, cluster``, private ones per run. Everything that grows with the grid is a join and a grouped count; only the table
of overlaps, a line per pair of clusters that share a cell, enters a grouped task, one per run.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpgrid.functions.keyed import keyed_below, keyed_uniform
from dpgrid.operators.assignment import assign
from dpgrid.operators.privacy import RUN


def overlaps(truth: DataFrame, runs_labels: DataFrame, by: Sequence[str] = RUN) -> DataFrame:
    """``by..., a, b, o``: cells that true cluster a and private cluster b share."""
    t = truth.select("wcell", F.col("cluster").alias("a"))
    return runs_labels.select(*by, "wcell", F.col("cluster").alias("b")).join(t, "wcell").groupBy(*by, "a", "b").agg(F.count(F.lit(1)).alias("o"))


def sizes(labels: DataFrame, name: str, by: Sequence[str] = ()) -> DataFrame:
    return labels.groupBy(*by, F.col("cluster").alias(name)).agg(F.count(F.lit(1)).alias(f"n_{name}"))


def cluster_distance(truth: DataFrame, runs_labels: DataFrame, by: Sequence[str] = RUN) -> DataFrame:
    """``by..., a, b, o, n_a, n_b, distance`` of overlapping pairs: the larger of the two one-sided differences."""
    o = overlaps(truth, runs_labels, by).join(sizes(truth, "a"), "a").join(sizes(runs_labels, "b", by), [*by, "b"])
    return o.withColumn("distance", F.greatest(F.col("n_a") - F.col("o"), F.col("n_b") - F.col("o"))).select(*by, "a", "b", "o", "n_a", "n_b", "distance")


def set_matching(n_a: np.ndarray, n_b: np.ndarray, o: np.ndarray) -> float:
    """Least total distance of a one-to-one matching; clusters left over on either side cost their size."""
    k = max(len(n_a), len(n_b))
    if not k:
        return 0.0
    a, b, both = np.zeros(k), np.zeros(k), np.zeros((k, k))
    a[: len(n_a)], b[: len(n_b)] = n_a, n_b
    both[: o.shape[0], : o.shape[1]] = o
    cost = np.maximum(a[:, None] - both, b[None, :] - both)
    return float(cost[np.arange(k), assign(cost)].sum())


def grid_cluster_dissimilarity(truth: DataFrame, runs_labels: DataFrame, runs: DataFrame, by: Sequence[str] = RUN) -> DataFrame:
    """``by..., cost, gcd``: matching cost, and the same over the number of true cells. Null without true cells.

    ``runs`` lists all runs, so that a run without any private cell counts too (its dissimilarity is 1).
    """
    t = sizes(truth, "a").select(F.lit(0).alias("kind"), F.col("a"), F.lit(None).cast("long").alias("b"), F.col("n_a").alias("n"))
    lines = runs.select(*by).crossJoin(F.broadcast(t))
    p = sizes(runs_labels, "b", by).select(*by, F.lit(1).alias("kind"), F.lit(None).cast("long").alias("a"), F.col("b"), F.col("n_b").alias("n"))
    o = overlaps(truth, runs_labels, by).select(*by, F.lit(2).alias("kind"), "a", "b", F.col("o").alias("n"))

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        a, b, both = (pdf[pdf["kind"] == k] for k in (0, 1, 2))
        ai, bi = {int(x): i for i, x in enumerate(a["a"])}, {int(x): i for i, x in enumerate(b["b"])}
        m = np.zeros((len(ai), len(bi)))
        for x, y, n in zip(both["a"], both["b"], both["n"], strict=True):
            m[ai[int(x)], bi[int(y)]] = n
        cost = set_matching(a["n"].to_numpy(float), b["n"].to_numpy(float), m)
        total = float(a["n"].sum())
        return pd.DataFrame([{**{c: pdf[c].iloc[0] for c in by}, "cost": cost, "gcd": cost / total if total else None}])

    kinds = ", ".join(f"{c} int" for c in by)
    return lines.unionByName(p).unionByName(o).groupBy(*by).applyInPandas(solve, f"{kinds}, cost double, gcd double")


def cell_confusion(truth: DataFrame, runs_labels: DataFrame, runs: DataFrame, coarse_cells: int, by: Sequence[str] = RUN) -> DataFrame:
    """``by..., hit, false_positive, false_negative, true_negative, grid_dissimilarity`` of significant cells."""
    t = runs.select(*by).crossJoin(truth.select("wcell", F.lit(1).alias("t")))
    both = t.join(runs_labels.select(*by, "wcell", F.lit(1).alias("p")), [*by, "wcell"], "full_outer")
    count = lambda c: F.sum(F.when(c, 1).otherwise(0)).cast("long")
    made = both.groupBy(*by).agg(
        count(F.col("t").isNotNull() & F.col("p").isNotNull()).alias("hit"), count(F.col("t").isNull()).alias("false_positive"), count(F.col("p").isNull()).alias("false_negative")
    )
    rest = F.lit(coarse_cells) - F.col("hit") - F.col("false_positive") - F.col("false_negative")
    return made.withColumn("true_negative", rest).withColumn("grid_dissimilarity", (F.col("false_positive") + F.col("false_negative")) / (F.col("hit") + F.col("false_negative")))


def rank_error(k_true: DataFrame, cuts: DataFrame) -> DataFrame:
    """``eps_i, rep, k, k_priv, rank_error`` from the one-row clean ``k`` and each run's ``k_priv``."""
    return cuts.crossJoin(F.broadcast(k_true.select("k"))).select(*RUN, "k", "k_priv", (F.abs(F.col("k_priv") - F.col("k")) / F.col("k")).alias("rank_error"))


def f_measure(truth: DataFrame, runs_labels: DataFrame, runs: DataFrame, by: Sequence[str] = RUN, weights: DataFrame | None = None) -> DataFrame:
    """``by..., f``: per true cluster the best harmonic mean over private ones, weighted by its size.

    Cells count one each, or as ``weights(wcell, weight)`` says (points of the cell).
    """
    unit = F.lit(1.0)
    t, p = truth.select("wcell", F.col("cluster").alias("a")), runs_labels.select(*by, "wcell", F.col("cluster").alias("b"))
    if weights is not None:
        t, p, unit = t.join(weights, "wcell"), p.join(weights, "wcell"), F.col("weight")
    na, nb = t.groupBy("a").agg(F.sum(unit).alias("na")), p.groupBy(*by, "b").agg(F.sum(unit).alias("nb"))
    o = p.join(t.select("wcell", "a"), "wcell").groupBy(*by, "a", "b").agg(F.sum(unit).alias("o"))
    best = o.join(F.broadcast(na), "a").join(nb, [*by, "b"]).groupBy(*by, "a").agg(F.max(2 * F.col("o") / (F.col("na") + F.col("nb"))).alias("best"))
    every = runs.select(*by).crossJoin(F.broadcast(na)).join(best, [*by, "a"], "left")
    return every.groupBy(*by).agg((F.sum(F.col("na") * F.coalesce("best", F.lit(0.0))) / F.sum("na")).alias("f"))


def cluster_counts(truth: DataFrame, runs_labels: DataFrame, runs: DataFrame, by: Sequence[str] = RUN) -> DataFrame:
    """``by..., clusters_true, clusters_private``."""
    t = truth.agg(F.count_distinct("cluster").alias("clusters_true"))
    p = runs_labels.groupBy(*by).agg(F.count_distinct("cluster").alias("clusters_private"))
    return runs.select(*by).join(p, list(by), "left").crossJoin(t).select(*by, "clusters_true", F.coalesce("clusters_private", F.lit(0)).alias("clusters_private"))


def split_points(df: DataFrame, key: str, share: float = 0.9, point_id: str = "point_id") -> DataFrame:
    """Points with ``train``: true for about that share, by keyed draw."""
    return df.withColumn("train", keyed_below(share, key, "split", point_id))


def sample_share(df: DataFrame, key: str, share: float, point_id: str = "point_id") -> DataFrame:
    """About that share of the points, each by its own keyed draw: a filter, whatever the size."""
    return df.where(keyed_below(share, key, "share", point_id))


def sample_points(df: DataFrame, key: str, n: int, point_id: str = "point_id") -> DataFrame:
    """The ``n`` points of least keyed draw: the same whatever the partitioning."""
    return df.orderBy(keyed_uniform(key, "sample", point_id), point_id).limit(n)


def contingency(predictions: DataFrame, by: Sequence[str] = RUN, weight: str | None = None) -> DataFrame:
    """``by..., pred_t, pred_p, n`` of test samples; ``weight`` names a column of how many samples a row stands for."""
    return predictions.groupBy(*by, "pred_t", "pred_p").agg((F.sum(weight) if weight else F.count(F.lit(1))).alias("n"))


def class_matching_dissimilarity(predictions: DataFrame, by: Sequence[str] = RUN, weight: str | None = None) -> DataFrame:
    """``by..., agreed, total, cmd``: one minus the best one-to-one agreement of predicted classes."""

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        a, ai = np.unique(pdf["pred_t"].to_numpy(), return_inverse=True)
        b, bi = np.unique(pdf["pred_p"].to_numpy(), return_inverse=True)
        m = np.zeros((max(len(a), len(b)),) * 2)
        np.add.at(m, (ai, bi), pdf["n"].to_numpy(float))
        agreed, total = float(m[np.arange(len(m)), assign(-m)].sum()), float(pdf["n"].sum())
        return pd.DataFrame([{**{c: pdf[c].iloc[0] for c in by}, "agreed": agreed, "total": total, "cmd": 1 - agreed / total}])

    return contingency(predictions, by, weight).groupBy(*by).applyInPandas(solve, ", ".join(f"{c} int" for c in by) + ", agreed double, total double, cmd double")


def pair_disagreement(predictions: DataFrame, by: Sequence[str] = RUN, weight: str | None = None) -> DataFrame:
    """``by..., ppd``: share of sample pairs on which the classifiers disagree about being of one class.

    Pairs are counted from the contingency table, so cost is linear in samples. Null below two samples.
    """
    pairs = lambda c: F.sum(F.col(c) * (F.col(c) - 1) / 2)
    n = contingency(predictions, by, weight)
    a = n.groupBy(*by, "pred_t").agg(F.sum("n").alias("m")).groupBy(*by).agg(pairs("m").alias("pa"))
    b = n.groupBy(*by, "pred_p").agg(F.sum("n").alias("m")).groupBy(*by).agg(pairs("m").alias("pb"))
    both = n.groupBy(*by).agg(pairs("n").alias("pn"), F.sum("n").alias("total")).join(a, list(by)).join(b, list(by))
    every = F.col("total") * (F.col("total") - 1) / 2
    return both.select(*by, F.when(F.col("total") > 1, (F.col("pa") + F.col("pb") - 2 * F.col("pn")) / every).alias("ppd"))


def pair_disagreement_exact(predictions: DataFrame, by: Sequence[str] = RUN, point_id: str = "point_id") -> DataFrame:
    """The same by listing all pairs; for tests on a few hundred samples."""
    a, b = predictions.alias("a"), predictions.alias("b")
    same = [F.col(f"a.{c}") == F.col(f"b.{c}") for c in by]
    cond = F.col(f"a.{point_id}") < F.col(f"b.{point_id}")
    for s in same:
        cond = cond & s
    differ = (F.col("a.pred_t") == F.col("b.pred_t")) != (F.col("a.pred_p") == F.col("b.pred_p"))
    return a.join(b, cond).groupBy(*[F.col(f"a.{c}").alias(c) for c in by]).agg(F.avg(differ.cast("double")).alias("ppd"))


def pair_flip_bound(k: int, n: int) -> float:
    """Largest share of pairs that ``k`` differing samples out of ``n`` can change."""
    return (k * (k - 1) / 2 + k * (n - k)) / (n * (n - 1) / 2)


def flip_counts(clean: DataFrame, noisy: DataFrame, by: Sequence[str] = RUN) -> DataFrame:
    """``by..., became_positive, became_nonpositive``: coefficients whose sign class the noise changed. ``noisy`` has every cell."""
    c = clean.select("wcell", F.col("w").alias("v"))
    both = noisy.join(c, "wcell", "left")
    was = F.coalesce(F.col("v"), F.lit(0.0)) > 0
    count = lambda x: F.sum(F.when(x, 1).otherwise(0)).cast("long")
    return both.groupBy(*by).agg(count(~was & (F.col("w") > 0)).alias("became_positive"), count(was & (F.col("w") <= 0)).alias("became_nonpositive"))


def neighbour_audit(counts: DataFrame, other: DataFrame, spec, wavelet: str = "haar", level: int = 1) -> DataFrame:
    """How far two neighbouring count matrices lie apart: sum of count changes, changed coefficients, change of the non-positive number."""
    from dpgrid.operators.wavelet import wavelet_transform

    m = counts.select("cell", F.col("cnt").alias("c")).join(other.select("cell", F.col("cnt").alias("d")), "cell", "full_outer")
    moved = m.agg(F.sum(F.abs(F.coalesce("c", F.lit(0)) - F.coalesce("d", F.lit(0)))).alias("count_change"))
    a = wavelet_transform(counts, spec, wavelet, level).select("wcell", F.col("w").alias("v"))
    b = wavelet_transform(other, spec, wavelet, level).select("wcell", F.col("w").alias("x"))
    v, x = F.coalesce("v", F.lit(0.0)), F.coalesce("x", F.lit(0.0))
    w = a.join(b, "wcell", "full_outer").agg(
        F.sum(F.when(F.abs(v - x) > 1e-9, 1).otherwise(0)).cast("long").alias("changed"), F.abs(F.sum((v > 1e-9).cast("int") - (x > 1e-9).cast("int"))).cast("long").alias("nonpositive_change")
    )
    return moved.crossJoin(w)
