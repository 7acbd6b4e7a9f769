"""Decision trees that learn cluster labels from cell coordinates.

Binary splits at midpoints, chosen by gain ratio among splits of at least average gain, and pruned by a pessimistic error estimate. A tree's rows
are the significant cells of one run, so trees of all runs grow in parallel, one grouped task each, whatever the number of points. The result
is the leaves as boxes of cell coordinates; as splits lie between cells, predicting by cell equals predicting by point.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpgrid.operators.grid import GridSpec, coordinates
from dpgrid.operators.privacy import RUN

#: Normal deviate of the pruning confidence of a quarter.
_DEVIATE = 0.6744897501960817


def _entropy(counts: np.ndarray) -> np.ndarray:
    """Bits per row of class counts."""
    total = counts.sum(-1, keepdims=True)
    share = np.divide(counts, total, out=np.zeros_like(counts, dtype=float), where=total > 0)
    return -(share * np.log2(np.where(share > 0, share, 1))).sum(-1)


def _pessimistic(errors: float, n: float) -> float:
    """Upper estimate of a leaf's errors."""
    if n == 0:
        return 0.0
    f, z = errors / n, _DEVIATE
    return n * (f + z * z / (2 * n) + z * math.sqrt(f / n - f * f / n + z * z / (4 * n * n))) / (1 + z * z / n)


def best_split(x: np.ndarray, y: np.ndarray, classes: int, min_leaf: int = 2, criterion: str = "gain_ratio") -> tuple[int, float] | None:
    """(feature, cut) or None. ``y`` holds class numbers."""
    n, found = len(y), []
    whole = _entropy(np.bincount(y, minlength=classes).astype(float))
    for a in range(x.shape[1]):
        order = np.argsort(x[:, a], kind="stable")
        v, hot = x[order, a], np.zeros((n, classes))
        hot[np.arange(n), y[order]] = 1
        left = hot.cumsum(0)[:-1]
        k = np.arange(1, n)
        ok = (v[1:] > v[:-1]) & (k >= min_leaf) & (n - k >= min_leaf)
        if not ok.any():
            continue
        right = left[-1] + hot[-1] - left
        gain = whole - (k * _entropy(left) + (n - k) * _entropy(right)) / n
        info = _entropy(np.stack([k, n - k], 1).astype(float))
        for i in np.flatnonzero(ok & (gain > 1e-12)):
            found.append((gain[i], info[i], a, (v[i] + v[i + 1]) / 2))
    if not found:
        return None
    gains = np.array([f[0] for f in found])
    score = gains if criterion == "gain" else np.where(gains >= gains.mean() - 1e-12, gains / np.array([f[1] for f in found]), -1)
    _, _, a, cut = found[int(score.argmax())]
    return a, cut


def grow(x: np.ndarray, labels: np.ndarray, min_leaf: int = 2, max_depth: int = 30, prune: bool = True, criterion: str = "gain_ratio") -> list[tuple[np.ndarray, np.ndarray, int, int]]:
    """Leaves ``(lo, hi, label, rows)``: a point belongs where lo < x <= hi."""
    names, y = np.unique(labels, return_inverse=True)
    k, n = len(names), x.shape[1]

    def build(rows: np.ndarray, lo: np.ndarray, hi: np.ndarray, depth: int):
        own = np.bincount(y[rows], minlength=k)
        top = int(own.argmax())
        leaf = [(lo, hi, int(names[top]), len(rows))]
        worst = _pessimistic(len(rows) - own[top], len(rows))
        if own[top] == len(rows) or len(rows) < 2 * min_leaf or depth >= max_depth:
            return leaf, worst
        split = best_split(x[rows], y[rows], k, min_leaf, criterion)
        if split is None:
            return leaf, worst
        a, cut = split
        left = x[rows, a] <= cut
        lh, rl = hi.copy(), lo.copy()
        lh[a], rl[a] = cut, cut
        l_leaves, l_err = build(rows[left], lo, lh, depth + 1)
        r_leaves, r_err = build(rows[~left], rl, hi, depth + 1)
        if prune and worst <= l_err + r_err + 1e-9:
            return leaf, worst
        return l_leaves + r_leaves, l_err + r_err

    if not len(y):
        return []
    return build(np.arange(len(y)), np.full(n, -np.inf), np.full(n, np.inf), 0)[0]


def fit_tree(cells: DataFrame, g: tuple[int, ...], by: Sequence[str] = RUN, min_leaf: int = 2, max_depth: int = 30, prune: bool = True, criterion: str = "gain_ratio") -> DataFrame:
    """``by..., node, lo0, hi0, .., label, rows``: the leaves of each run's tree."""
    n = len(g)

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("wcell")
        x = np.stack(np.unravel_index(pdf["wcell"].to_numpy(np.int64), g), 1).astype(float)
        rows = [{**{c: pdf[c].iloc[0] for c in by}, "node": i, **{f"lo{a}": lo[a] for a in range(n)}, **{f"hi{a}": hi[a] for a in range(n)}, "label": lab, "rows": m} for i, (lo, hi, lab, m) in enumerate(grow(x, pdf["cluster"].to_numpy(), min_leaf, max_depth, prune, criterion))]
        return pd.DataFrame(rows)

    schema = ", ".join([*(f"{c} int" for c in by), "node int", *(f"lo{a} double" for a in range(n)), *(f"hi{a} double" for a in range(n)), "label long", "rows long"])
    return cells.select(*by, "wcell", "cluster").groupBy(*by).applyInPandas(fit, schema).select(*by, "node", *[x for a in range(n) for x in (f"lo{a}", f"hi{a}")], "label", "rows")


def predict_cells(tree: DataFrame, spec: GridSpec, level: int = 1, by: Sequence[str] = RUN) -> DataFrame:
    """``by..., wcell, pred`` for every cell: each leaf lists the cells of its box, so no pair of cell and leaf is ever compared."""
    g = spec.coarse(level)
    rows = tree
    for a, k in enumerate(g):
        first = F.greatest(F.floor(F.greatest(F.col(f"lo{a}"), F.lit(-1.0))) + 1, F.lit(0)).cast("long")
        last = F.least(F.floor(F.least(F.col(f"hi{a}"), F.lit(float(k)))), F.lit(k - 1)).cast("long")
        rows = rows.where(first <= last).withColumn(f"_i{a}", F.explode(F.sequence(first, last)))
    from dpgrid.operators.grid import linear

    return rows.select(*by, linear([F.col(f"_i{a}") for a in range(len(g))], g).alias("wcell"), F.col("label").alias("pred"))


def predictions(test: DataFrame, true_tree: DataFrame, run_trees: DataFrame, runs: DataFrame, spec: GridSpec, level: int = 1, by: Sequence[str] = RUN) -> DataFrame:
    """The rows of ``test`` per run with ``pred_t, pred_p``; ``test`` has ``wcell``, and best a row per cell with the number of its samples.

    Samples of a cell share their predictions, so lines are cells times runs then. A run without a tree predicts -1.
    """
    t = predict_cells(true_tree, spec, level, ()).select("wcell", F.col("pred").alias("pred_t"))
    p = predict_cells(run_trees, spec, level, by).select(*by, "wcell", F.col("pred").alias("pred_p"))
    lines = test.crossJoin(F.broadcast(runs.select(*by)))
    minus = F.lit(-1).cast("long")
    return lines.join(t, "wcell", "left").join(p, [*by, "wcell"], "left").withColumns({"pred_t": F.coalesce("pred_t", minus), "pred_p": F.coalesce("pred_p", minus)})


def training_rows(cells: DataFrame, g: tuple[int, ...]) -> DataFrame:
    """Cells with their coordinates as columns, for other learners."""
    return cells.select("*", *[c.alias(f"w{a}") for a, c in enumerate(coordinates(F.col("wcell"), g))])
