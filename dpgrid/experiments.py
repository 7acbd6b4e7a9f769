"""Experiment workloads: measures by method and budget over repeated runs, and the smaller studies, as registered queries."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpgrid.catalog import EPS, KEY, ORACLES, QUERIES, REPS, SWEEP, SWEEP_REPS, _clustered, band, clean, coarse, counts, kept_counts, np_cells, private_sql, pts, r6, register, runs, sweep, technique
from dpgrid.operators import bounds as bo
from dpgrid.operators import measures as me
from dpgrid.operators import methods as mt
from dpgrid.operators import publish as pu
from dpgrid.operators import tree as tr
from dpgrid.operators.components import connected_components
from dpgrid.operators.grid import GridSpec, block_of, cell_of, coordinates, inside, unit
from dpgrid.operators.privacy import RUN, runs_frame
from dpgrid.operators.quantize import occupied_cells, quantize
from dpgrid.operators.threshold import percentile_cut, significant_cells
from dpgrid.operators.wavelet import wavelet_transform
from dpgrid.plans import duck
from dpgrid.plans.duck import Query, num
from dpgrid.plans.scratch import materialise, new_path
from dpgrid.sources.workloads import WORKLOADS
from dpgrid.streaming import windows as win

METHODS = ("synthetic", "noisy_counts", "trimmed", "sampled_cut")
SHORT = {"synthetic": "SYN", "noisy_counts": "NQ", "trimmed": "TRIM", "sampled_cut": "CUT"}
OMEGA = 0.05


def truth(s: SparkSession, d: str, w: str) -> DataFrame:
    return materialise(np_cells(s, d, w).select("wcell", "cluster", "w"), "truth")


def report(rows: DataFrame, metric: str, lines: DataFrame) -> DataFrame:
    """Mean, spread and range by method and budget, over repetitions."""
    named = rows.join(F.broadcast(lines.select("eps_i", "eps").distinct()), "eps_i")
    a = [f(metric) for f in (F.avg, F.stddev_samp, F.min, F.max)]
    return named.groupBy("method", "eps").agg(*[r6(x, n) for x, n in zip(a, ("mean", "sd", "least", "most"), strict=True)], F.count(metric).alias("runs"))


def together(make: Callable[..., DataFrame], what: Iterable) -> DataFrame:
    """Union of ``make(x)``, each written by a thread of its own: a plan stays small, and the short jobs of one fill the cores that another leaves idle."""
    with ThreadPoolExecutor(8) as pool:
        return reduce(DataFrame.unionByName, pool.map(lambda x: materialise(make(x), "measured"), what))


def kept_points(s: SparkSession, d: str, w: str) -> tuple[DataFrame, DataFrame]:
    """The workload's counts and its compact points, from one pass over its tables."""
    wl = WORKLOADS[w]
    compact = pu.compact_points(wl.points(s, d), wl.cols, wl.spec)
    return pu.compact_counts(compact, wl.cols, wl.spec), compact


def each_method(s: SparkSession, d: str, w: str, lines: DataFrame, measure, methods=METHODS, counts: DataFrame | None = None, compact: DataFrame | None = None, **how) -> DataFrame:
    """Union over methods of what ``measure(released)`` makes of each; they share one count of the points."""
    counts, compact = kept_points(s, d, w) if counts is None else (counts, compact)

    def one(m: str) -> DataFrame:
        return measure(technique(s, d, w, m, lines, counts, compact, **how)).withColumn("method", F.lit(SHORT[m]))

    return together(one, methods)


def _measures() -> None:
    spec, g = WORKLOADS["w2"].spec, WORKLOADS["w2"].spec.coarse(1)
    sub = lambda q, body: "(" + q.select(body) + ")"
    names = METHODS
    per = " UNION ALL ".join(f"SELECT '{SHORT[m]}' AS method, * FROM {sub(private_sql('w2', m, list(SWEEP), SWEEP_REPS), 'SELECT p.eps_i, p.rep, p.k_priv, r.eps FROM pcut p JOIN runs r USING (eps_i, rep)')} x" for m in names)
    k = sub(clean("w2").cut(0.10), "SELECT k FROM cut")
    register("rank_error_sweep_w2", _rank_errors, f"SELECT method, eps, round(avg(abs(k_priv - k) / k), 6) AS mean_error, round(avg(k_priv), 6) AS mean_k FROM ({per}) q CROSS JOIN {k} c GROUP BY method, eps")
    labelled = lambda: private_sql("w2", "trimmed").components(g, "kept", "plab", RUN).cut(0.10, "band", "tcut").keep("band", "tcut", "tkept").components(g, "tkept", "tlab")
    over = labelled().add("o", "SELECT p.eps_i, p.rep, t.cluster AS a, p.cluster AS b, count(*) AS o FROM plab p JOIN tlab t USING (wcell) GROUP BY ALL").add("na", "SELECT cluster AS a, count(*) AS n_a FROM tlab GROUP BY 1").add("nb", "SELECT eps_i, rep, cluster AS b, count(*) AS n_b FROM plab GROUP BY ALL")
    register("gcd_overlap_w2", lambda s, d: me.cluster_distance(truth(s, d, "w2"), technique(s, d, "w2", "trimmed").cells), over.select("SELECT eps_i, rep, a, b, o, n_a, n_b, greatest(n_a - o, n_b - o) AS distance FROM o JOIN na USING (a) JOIN nb USING (eps_i, rep, b)"))
    register("fmeasure_w2", lambda s, d: me.f_measure(truth(s, d, "w2"), technique(s, d, "w2", "trimmed").cells, runs(s)).select(*RUN, r6("f")), over.select("SELECT eps_i, rep, round(sum(n_a * best) / sum(n_a), 6) AS f FROM (SELECT eps_i, rep, a, n_a, max(2e0 * coalesce(o, 0) / (n_a + coalesce(n_b, 0))) AS best FROM na CROSS JOIN (SELECT eps_i, rep FROM runs) r LEFT JOIN o USING (eps_i, rep, a) LEFT JOIN nb USING (eps_i, rep, b) GROUP BY ALL) q GROUP BY eps_i, rep"))
    register("confusion_w2", lambda s, d: me.cell_confusion(truth(s, d, "w2"), technique(s, d, "w2", "trimmed").cells, runs(s), coarse("w2")).select(*RUN, "hit", "false_positive", "false_negative", "true_negative", r6("grid_dissimilarity")), labelled().add("tt", "SELECT r.eps_i, r.rep, t.wcell FROM tlab t CROSS JOIN runs r").select(f"SELECT eps_i, rep, count(*) FILTER (WHERE a = 1 AND b = 1) AS hit, count(*) FILTER (WHERE a IS NULL) AS false_positive, count(*) FILTER (WHERE b IS NULL) AS false_negative, {coarse('w2')} - count(*) AS true_negative, round(count(*) FILTER (WHERE a IS NULL OR b IS NULL) * 1e0 / count(*) FILTER (WHERE a = 1), 6) AS grid_dissimilarity FROM (SELECT *, 1 AS a FROM tt) x FULL JOIN (SELECT eps_i, rep, wcell, 1 AS b FROM plab) y USING (eps_i, rep, wcell) GROUP BY eps_i, rep"))
    counts_sql = " UNION ALL ".join(f"SELECT '{SHORT[m]}' AS method, * FROM {sub(private_sql('w2', m).components(g, by=RUN), 'SELECT eps_i, rep, count(DISTINCT cluster) AS clusters_private FROM lab GROUP BY ALL')} x" for m in names)
    register("cluster_counts_sweep", lambda s, d: each_method(s, d, "w2", runs(s), lambda m: me.cluster_counts(truth(s, d, "w2"), m.cells, runs(s))), f"SELECT method, eps_i, rep, clusters_true, clusters_private FROM ({counts_sql}) q CROSS JOIN {sub(_clustered('w2'), 'SELECT count(DISTINCT cluster) AS clusters_true FROM lab')} t")
    register("flips_w2", lambda s, d: me.flip_counts(band(s, d, "w2"), technique(s, d, "w2", "noisy_counts").band), clean("w2").runs(list(EPS), REPS).noisy_band(spec, KEY).select("SELECT eps_i, rep, count(*) FILTER (WHERE coalesce(b.w, 0) <= 0 AND n.w > 0) AS became_positive, count(*) FILTER (WHERE b.w > 0 AND n.w <= 0) AS became_nonpositive FROM nband n LEFT JOIN band b USING (wcell) GROUP BY eps_i, rep"))
    x = "(2e0 * eps * w)"
    tail = f"exp(-{x}) * (48 + 33 * {x} + 9 * {x} * {x} + {x} * {x} * {x}) / 96"
    stats = clean("w2").runs(list(EPS), REPS).cut(0.10).add("th", f"SELECT eps_i, eps, sum({tail}) AS theta FROM (SELECT DISTINCT eps_i, eps FROM runs) r CROSS JOIN band WHERE w > 0 GROUP BY ALL").add("st", f"SELECT eps_i, eps, n_pos, {coarse('w2')} - n_pos AS n_nonpos, k, d AS w_k, (SELECT max(w) FROM band) AS w_max, theta FROM th CROSS JOIN cut")
    st = lambda s, d, w="w2": bo.statistics(band(s, d, w), runs(s), WORKLOADS[w].p, coarse(w))
    register("theta_w2", lambda s, d: st(s, d).select("eps_i", "n_pos", F.col("n_nonpos").cast("long").alias("n_nonpos"), "k", r6("theta"), r6(bo.expected_rank_shift(0.10, F.col("n_nonpos"), F.col("theta")), "expected_shift")), stats.select("SELECT eps_i, n_pos, n_nonpos, k, round(theta, 6) AS theta, round(0.9e0 * (n_nonpos / 2e0 - theta), 6) AS expected_shift FROM st"))
    edge = lambda lo, hi, e: f"SELECT eps_i, CAST(greatest(least(floor({lo}), n_pos), 1) AS BIGINT) AS k_min, CAST(greatest(least(ceil({hi}), n_pos), 1) AS BIGINT) AS k_max, round(8e0 / ({e}) * ln(4 * (n_pos + n_nonpos) / {num(OMEGA)}), 6) AS gamma FROM st"
    wide = f"sqrt(n_nonpos * ln(1e0 / {num(OMEGA)}) / 2e0)"
    lines = lambda f: lambda s, d: f(st(s, d), 0.10, OMEGA).select("eps_i", "k_min", "k_max", r6("gamma"))
    register("bounds_nq_w2", lines(bo.bounds_noisy_counts), stats.select(edge(f"k + 0.9e0 * (n_nonpos / 2e0 - {wide} - theta)", f"k + 0.9e0 * (n_nonpos / 2e0 + {wide} - theta)", "eps")))
    beta = f"2e0 / (eps * 0.1e0) * ln(1e0 / {num(OMEGA)})"
    register("bounds_trim_w2", lines(bo.bounds_trimmed), stats.select(edge(f"k + 0.9e0 * (-{wide} - theta - {beta})", f"k + 0.9e0 * ({wide} - theta + {beta})", "eps * 0.9e0")))
    e2, gap = "(eps * 0.3e0)", "greatest(abs(w_max - w_k), 1e-12)"
    register("bounds_cut_w2", lines(bo.bounds_sampled_cut), stats.select(edge(f"k - (n_pos - k - 1 + 2e0 / {e2} * ln({gap} / (abs(w_k) * {num(OMEGA)})))", f"k + (k - 2 + 2e0 / {e2} * ln(abs(w_k) / ({gap} * {num(OMEGA)})))", "eps * 0.7e0")))
    register("prefer_method_w2", lambda s, d: bo.prefer_method(st(s, d)).select("eps_i", r6("indicator"), "tighter"), stats.select("SELECT eps_i, round(ln(w_k / greatest(w_max - w_k, 1e-12)), 6) AS indicator, CASE WHEN ln(w_k / greatest(w_max - w_k, 1e-12)) < 0 THEN 'sampled_cut' ELSE 'trimmed' END AS tighter FROM st"))
    cell = duck.block_sql("cell", spec)
    pred = labelled().add("pp", f"SELECT r.eps_i, r.rep, coalesce(t.cluster, -1) AS a, coalesce(l.cluster, -1) AS b, count(*) AS n FROM (SELECT {cell} AS wcell FROM (SELECT {duck.cell_sql(['x0', 'x1'], spec)} AS cell FROM pts) z) p CROSS JOIN (SELECT eps_i, rep FROM runs) r LEFT JOIN tlab t USING (wcell) LEFT JOIN plab l USING (eps_i, rep, wcell) GROUP BY ALL")
    pairs = lambda key: f"(SELECT eps_i, rep, sum(m * (m - 1) / 2e0) AS v FROM (SELECT eps_i, rep, sum(n) AS m FROM pp GROUP BY eps_i, rep{key}) z GROUP BY ALL)"
    register("ppd_w2", lambda s, d: me.pair_disagreement(_labels_as_predictions(s, d), weight="n").select(*RUN, r6("ppd")), pred.select(f"SELECT eps_i, rep, round((x.v + y.v - 2 * z.v) / t.v, 6) AS ppd FROM {pairs(', a')} x JOIN {pairs(', b')} y USING (eps_i, rep) JOIN {pairs(', a, b')} z USING (eps_i, rep) JOIN {pairs('')} t USING (eps_i, rep)"))
    register("cmd_w2", lambda s, d: me.class_matching_dissimilarity(_labels_as_predictions(s, d), weight="n").select(*RUN, "agreed", "total", r6("cmd")))
    for w in ("w1", "w2", "w3", "w4"):
        register(f"gcd_sweep_{w}", lambda s, d, w=w: each_method(s, d, w, runs(s), lambda m: me.grid_cluster_dissimilarity(truth(s, d, w), m.cells, runs(s))).select("method", *RUN, "cost", r6("gcd")))


def _cut_errors(s: SparkSession, d: str, w: str, lines: DataFrame) -> DataFrame:
    """Rank error of all techniques' runs; the clean rank and the techniques read one count of the points."""
    counts, compact = kept_points(s, d, w)
    k = materialise(percentile_cut(wavelet_transform(counts, WORKLOADS[w].spec), WORKLOADS[w].p), "clean_cut")
    return each_method(s, d, w, lines, lambda m: me.rank_error(k, m.cut), counts=counts, compact=compact)


def _rank_errors(s: SparkSession, d: str) -> DataFrame:
    lines = sweep(s)
    rows = _cut_errors(s, d, "w2", lines)
    return rows.join(F.broadcast(lines.select("eps_i", "eps").distinct()), "eps_i").groupBy("method", "eps").agg(r6(F.avg("rank_error"), "mean_error"), r6(F.avg("k_priv"), "mean_k"))


def _labels_as_predictions(s: SparkSession, d: str) -> DataFrame:
    """True and private label of every cell that holds points, with their number ``n``; noise is a class of its own."""
    wl = WORKLOADS["w2"]
    placed = wl.points(s, d).groupBy(block_of(cell_of(wl.cols, wl.spec), wl.spec).alias("wcell")).agg(F.count(F.lit(1)).alias("n"))
    minus = F.lit(-1).cast("long")
    t = truth(s, d, "w2").select("wcell", F.col("cluster").alias("pred_t"))
    p = technique(s, d, "w2", "trimmed").cells.withColumnRenamed("cluster", "pred_p")
    lines = placed.crossJoin(F.broadcast(runs(s).select(*RUN))).join(t, "wcell", "left").join(p, [*RUN, "wcell"], "left")
    return lines.withColumns({"pred_t": F.coalesce("pred_t", minus), "pred_p": F.coalesce("pred_p", minus)})


@dataclass
class Split:
    """Compact points to train on, their counts, the true clusters of these, and the ``n`` test points of each cell; the last two are still being made."""

    train: DataFrame
    counts: DataFrame
    true: Future[DataFrame]
    test: Future[DataFrame]


def split_workload(s: SparkSession, d: str, w: str) -> Split:
    wl = WORKLOADS[w]
    parts = pu.compact_points(me.split_points(wl.points(s, d), KEY), wl.cols, wl.spec, ["train"])
    train = materialise(inside(parts.where("train"), wl.cols, wl.spec).select(*wl.cols, "weight"), "train_points")  # a table of its own is dealt by file
    test = parts.where(~F.col("train")).groupBy(block_of(cell_of(wl.cols, wl.spec), wl.spec).alias("wcell")).agg(F.sum("weight").alias("n"))
    counts = pu.compact_counts(train, wl.cols, wl.spec)
    aside = ThreadPoolExecutor(2)  # the techniques do not wait for these
    true = aside.submit(lambda: materialise(mt.cluster_counts_matrix(counts, wl.spec, wl.p).cells, "truth"))
    made = Split(train, counts, true, aside.submit(materialise, test, "test_cells"))
    aside.shutdown(wait=False)
    return made


def classifier_predictions(s: SparkSession, d: str, w: str, lines: DataFrame, method: str, split: Split | None = None) -> DataFrame:
    """Predictions of trees trained on the cells of nine tenths of the points, for the cells of the other tenth and its ``n`` points in each."""
    wl, split = WORKLOADS[w], split_workload(s, d, w) if split is None else split
    train, counts = split.train, split.counts
    if method == "synthetic":
        made = mt.release_synthetic(train, wl.cols, wl.spec, wl.p, lines, KEY, compact=True)
    else:
        made = {"noisy_counts": mt.release_noisy_counts, "trimmed": mt.release_trimmed, "sampled_cut": mt.release_sampled_cut}[method](counts, wl.spec, wl.p, lines, KEY)
    g = wl.spec.coarse(1)
    return tr.predictions(split.test.result(), tr.fit_tree(split.true.result(), g, ()), tr.fit_tree(made.cells, g), lines, wl.spec)


def _report_sql(parts: dict[str, str], metric: str) -> str:
    """``report`` over a SELECT of ``eps, metric`` per method."""
    every = " UNION ALL ".join(f"SELECT '{m}' AS method, eps, {metric} FROM ({q}) x{i}" for i, (m, q) in enumerate(parts.items()))
    return f"SELECT method, eps, round(avg({metric}), 6) AS mean, round(stddev_samp({metric}), 6) AS sd, round(min({metric}), 6) AS least, round(max({metric}), 6) AS most, count({metric}) AS runs FROM ({every}) q GROUP BY method, eps"


def _rank_sql(w: str, m: str, eps, reps: int) -> str:
    q = private_sql(w, m, list(eps), reps).cut(WORKLOADS[w].p, "band", "rcut")
    return q.select("SELECT eps, abs(k_priv - k) * 1e0 / k AS rank_error FROM pcut JOIN runs USING (eps_i, rep) CROSS JOIN (SELECT k FROM rcut) c")


def _both_labels(w: str, m: str, eps, reps: int) -> Query:
    g, p = WORKLOADS[w].spec.coarse(1), WORKLOADS[w].p
    return private_sql(w, m, list(eps), reps).components(g, "kept", "plab", RUN).cut(p, "band", "tcut").keep("band", "tcut", "tkept").components(g, "tkept", "tlab")


def _f_sql(w: str, m: str, eps, reps: int) -> str:
    q = _both_labels(w, m, eps, reps).add("o", "SELECT p.eps_i, p.rep, t.cluster AS a, p.cluster AS b, count(*) AS o FROM plab p JOIN tlab t USING (wcell) GROUP BY ALL").add("na", "SELECT cluster AS a, count(*) AS n_a FROM tlab GROUP BY 1").add("nb", "SELECT eps_i, rep, cluster AS b, count(*) AS n_b FROM plab GROUP BY ALL")
    best = "SELECT eps_i, rep, a, max(2e0 * o / (n_a + n_b)) AS best FROM o JOIN na USING (a) JOIN nb USING (eps_i, rep, b) GROUP BY ALL"
    return q.select(f"SELECT eps, sum(n_a * coalesce(best, 0e0)) / sum(n_a) AS f FROM runs CROSS JOIN na LEFT JOIN ({best}) z USING (eps_i, rep, a) GROUP BY eps_i, rep, eps")


def _clusters_sql(w: str, m: str, eps, reps: int) -> str:
    q = private_sql(w, m, list(eps), reps).components(WORKLOADS[w].spec.coarse(1), "kept", "plab", RUN)
    return q.select("SELECT eps, coalesce(c, 0) AS clusters_private FROM runs LEFT JOIN (SELECT eps_i, rep, count(DISTINCT cluster) AS c FROM plab GROUP BY ALL) z USING (eps_i, rep)")


def _every(fn, w: str, eps=SWEEP, reps: int = SWEEP_REPS) -> dict[str, str]:
    return {SHORT[m]: fn(w, m, eps, reps) for m in METHODS}


def _tail_sql() -> str:
    x = "(2e0 * eps * w)"
    return f"exp(-{x}) * (48 + 33 * {x} + 9 * {x} * {x} + {x} * {x} * {x}) / 96"


def _edges_sql(m: str, p: float) -> tuple[str, str, str]:
    """Lower and upper rank and half-width of a method's bound, over the columns of ``st``."""
    one, ln_omega = num(1 - p), f"ln(1e0 / {num(OMEGA)})"
    wide = f"sqrt(n_nonpos * {ln_omega} / 2e0)"
    gamma = lambda e: f"8e0 / (eps * {num(e)}) * ln(4 * (n_pos + n_nonpos) / {num(OMEGA)})"
    if m == "noisy_counts":
        return f"k + {one} * (n_nonpos / 2e0 - {wide} - theta)", f"k + {one} * (n_nonpos / 2e0 + {wide} - theta)", gamma(1.0)
    if m == "trimmed":
        beta = f"2e0 / (eps * {num(1 - 0.9)}) * {ln_omega}"
        return f"k + {one} * (-{wide} - theta - {beta})", f"k + {one} * ({wide} - theta + {beta})", gamma(0.9)
    e2, gap = f"(eps * {num(1 - 0.7)})", "greatest(abs(w_max - w_k), 1e-12)"
    return f"k - (n_pos - k - 1 + 2e0 / {e2} * ln({gap} / (abs(w_k) * {num(OMEGA)})))", f"k + (k - 2 + 2e0 / {e2} * ln(abs(w_k) / ({gap} * {num(OMEGA)})))", gamma(0.7)


def _bounds_sql(w: str, m: str) -> str:
    wl = WORKLOADS[w]
    lo, hi, gamma = _edges_sql(m, wl.p)
    q = private_sql(w, m, [0.5, 1.0, 2.0], SWEEP_REPS).cut(wl.p, "band", "bcut")
    q.add("th", f"SELECT eps_i, eps, sum({_tail_sql()}) AS theta FROM (SELECT DISTINCT eps_i, eps FROM runs) r CROSS JOIN band WHERE w > 0 GROUP BY ALL")
    q.add("st", f"SELECT eps_i, eps, n_pos, {coarse(w)} - n_pos AS n_nonpos, k, d AS w_k, (SELECT max(w) FROM band) AS w_max, theta FROM th CROSS JOIN bcut")
    q.add("ed", f"SELECT eps_i, greatest(least(floor({lo}), n_pos), 1) AS k_min, greatest(least(ceil({hi}), n_pos), 1) AS k_max, {gamma} AS gamma FROM st")
    q.add("rk", "SELECT w, sum(mult) OVER (ORDER BY w DESC) AS r FROM (SELECT w, count(*) AS mult FROM band WHERE w > 0 GROUP BY w) z")
    q.add("eg", "SELECT eps_i, gamma, max(w) FILTER (WHERE r >= k_min) AS w_hi, max(w) FILTER (WHERE r >= k_max) AS w_lo FROM ed CROSS JOIN rk GROUP BY ALL")
    q.add("ce", "SELECT r.eps_i, r.rep, b.w > w_hi + gamma AS must, b.w < w_lo - gamma AS never, k.wcell IS NOT NULL AS out FROM runs r JOIN eg USING (eps_i) CROSS JOIN band b LEFT JOIN kept k ON k.eps_i = r.eps_i AND k.rep = r.rep AND k.wcell = b.wcell WHERE b.w > 0")
    each = "SELECT eps_i, rep, count(*) FILTER (WHERE must) AS must, count(*) FILTER (WHERE never) AS must_not, count(*) FILTER (WHERE (must AND NOT out) OR (never AND out)) = 0 AS holds FROM ce GROUP BY ALL"
    return q.select(f"SELECT '{w}' AS workload, '{SHORT[m]}' AS method, round(avg(CASE WHEN holds THEN 1e0 ELSE 0e0 END), 6) AS coverage, CAST(sum(must) AS BIGINT) AS must, CAST(sum(must_not) AS BIGINT) AS must_not FROM ({each}) y")


def _experiments() -> None:
    facts = " UNION ALL ".join(f"SELECT '{w}' AS workload, * FROM ({_clustered(w).select(f'SELECT c.n_pos, {coarse(w)} - c.n_pos AS n_nonpos, c.k, (SELECT count(DISTINCT cluster) FROM lab) AS clusters FROM cut c')}) x" for w in ("w1", "w2", "w3", "w4"))
    register("exp_nonprivate", _nonprivate, facts)
    for w in ("w1", "w2", "w3", "w4"):
        register(f"exp_rank_error_{w}", lambda s, d, w=w: report(_cut_errors(s, d, w, sweep(s)), "rank_error", sweep(s)), _report_sql(_every(_rank_sql, w), "rank_error"))
        register(f"exp_dissimilarity_{w}", lambda s, d, w=w: _with_truth(s, d, w, sweep(s), lambda t, m, lines: me.grid_cluster_dissimilarity(t, m.cells, lines), "gcd"))
        register(f"exp_fmeasure_{w}", lambda s, d, w=w: _with_truth(s, d, w, sweep(s), lambda t, m, lines: me.f_measure(t, m.cells, lines), "f"), _report_sql(_every(_f_sql, w), "f"))
        register(f"exp_classifier_{w}", lambda s, d, w=w: _classifier(s, d, w, runs_frame(s, SWEEP, SWEEP_REPS)))
    register("exp_alpha_trim", lambda s, d: _alphas(s, d, "w1", mt.release_trimmed, (0.01, 0.1, 0.3, 0.5, 0.7, 0.9, 0.99)))
    register("exp_alpha_cut", lambda s, d: _alphas(s, d, "w1", mt.release_sampled_cut, (0.1, 0.3, 0.5, 0.7, 0.9)))
    register("exp_grid_size", _grid_sizes)
    register("exp_wavelets", _wavelet_study)
    register("exp_bridge_record", bridge_record, _bridge_sql())
    register("exp_synthetic_merge", lambda s, d: _with_truth(s, d, "w1", runs_frame(s, [0.5, 1.0], SWEEP_REPS), lambda t, m, lines: me.cluster_counts(t, m.cells, lines), "clusters_private"), _report_sql(_every(_clusters_sql, "w1", (0.5, 1.0)), "clusters_private"))
    x = "(2e0 * eps * w)"
    tail = f"exp(-{x}) * (48 + 33 * {x} + 9 * {x} * {x} + {x} * {x} * {x}) / 96"
    theory = private_sql("w2", "noisy_counts", list(SWEEP), SWEEP_REPS).cut(0.10, "band", "ccut").add("th", f"SELECT eps_i, eps, sum({tail}) AS theta FROM (SELECT DISTINCT eps_i, eps FROM runs) r CROSS JOIN band WHERE w > 0 GROUP BY ALL").add("mk", "SELECT eps_i, avg(k_priv) AS mean_k FROM pcut GROUP BY eps_i")
    register("exp_theory_nq", _theory, theory.select(f"SELECT eps, k, round(mean_k - k, 6) AS measured, round(0.9e0 * (({coarse('w2')} - n_pos) / 2e0 - theta), 6) AS predicted FROM th JOIN mk USING (eps_i) CROSS JOIN ccut"))
    register("exp_bounds", _bound_study, " UNION ALL ".join(f"SELECT * FROM ({_bounds_sql(w, m)}) x" for w in ("w1", "w2", "w3", "w4") for m in METHODS[1:]))
    register("exp_sampled_w4", _sampled_study, _sampled_sql())


def _with_truth(s: SparkSession, d: str, w: str, lines: DataFrame, measure, metric: str) -> DataFrame:
    counts, compact = kept_points(s, d, w)
    with ThreadPoolExecutor(1) as aside:  # the techniques do not wait for the true clusters, only their measures do
        t = aside.submit(lambda: materialise(mt.cluster_counts_matrix(counts, WORKLOADS[w].spec, WORKLOADS[w].p).cells.select("wcell", "cluster", "w"), "truth"))

        def written(m: mt.PrivateClustering) -> DataFrame:
            m.cells = materialise(m.cells, "released")  # a measure reads them more than once
            return measure(t.result(), m, lines)

        return report(each_method(s, d, w, lines, written, counts=counts, compact=compact), metric, lines)


def _classifier(s: SparkSession, d: str, w: str, lines: DataFrame) -> DataFrame:
    split = split_workload(s, d, w)

    def one(m: str) -> DataFrame:
        tested = materialise(classifier_predictions(s, d, w, lines, m, split).groupBy(*RUN, "pred_t", "pred_p").agg(F.sum("n").alias("c")), "predictions")
        return me.class_matching_dissimilarity(tested, weight="c").select(*RUN, "cmd").join(me.pair_disagreement(tested, weight="c"), list(RUN)).withColumn("method", F.lit(SHORT[m]))

    made = together(one, METHODS)
    named = made.join(F.broadcast(lines.select("eps_i", "eps").distinct()), "eps_i")
    return named.groupBy("method", "eps").agg(r6(F.avg("cmd"), "cmd"), r6(F.avg("ppd"), "ppd"), F.count("cmd").alias("runs"))


def _nonprivate(s: SparkSession, d: str) -> DataFrame:
    made = None
    for w in ("w1", "w2", "w3", "w4"):
        c = mt.cluster_grid(pts(w)(s, d), WORKLOADS[w].cols, WORKLOADS[w].spec, WORKLOADS[w].p)
        line = c.cut.crossJoin(c.cells.agg(F.count_distinct("cluster").alias("clusters"))).select(F.lit(w).alias("workload"), "n_pos", (F.lit(coarse(w)) - F.col("n_pos")).alias("n_nonpos"), "k", "clusters")
        made = line if made is None else made.unionByName(line)
    return made


def _alphas(s: SparkSession, d: str, w: str, fn, alphas) -> DataFrame:
    wl, t, counts, lines = WORKLOADS[w], truth(s, d, w), kept_counts(s, d, w), runs_frame(s, [0.5, 1.0], SWEEP_REPS)
    made = None
    for a in alphas:
        part = me.grid_cluster_dissimilarity(t, fn(counts, wl.spec, wl.p, lines, KEY, a).cells, lines).withColumn("alpha", F.lit(a))
        made = part if made is None else made.unionByName(part)
    return made.join(F.broadcast(lines.select("eps_i", "eps").distinct()), "eps_i").groupBy("alpha", "eps").agg(r6(F.avg("gcd"), "gcd"), F.count("gcd").alias("runs"))


def _study(compact: DataFrame, cols, spec, p: float, lines: DataFrame, o: mt.Options = mt.Options()) -> DataFrame:
    """Mean dissimilarity of all techniques on one matrix of compact points: ``method, gcd``."""
    counts = pu.compact_counts(compact, cols, spec)
    t = materialise(mt.cluster_counts_matrix(counts, spec, p, (), o).cells, "truth")

    def one(m: str) -> DataFrame:
        if m == "synthetic":
            released = mt.release_synthetic(compact, cols, spec, p, lines, KEY, o=o, compact=True)
        else:
            released = {"noisy_counts": mt.release_noisy_counts, "trimmed": mt.release_trimmed, "sampled_cut": mt.release_sampled_cut}[m](counts, spec, p, lines, KEY, o=o)
        cells = materialise(released.cells, "released")
        return me.grid_cluster_dissimilarity(t, cells, lines).agg(r6(F.avg("gcd"), "gcd")).select(F.lit(SHORT[m]).alias("method"), "gcd")

    return together(one, METHODS)


def _grid_sizes(s: SparkSession, d: str) -> DataFrame:
    wl = WORKLOADS["w2"]
    compact = pu.compact_points(wl.points(s, d), wl.cols, wl.spec)
    made = together(lambda g: _study(compact, wl.cols, unit(g), wl.p, runs_frame(s, [1.0], SWEEP_REPS)).withColumn("g", F.lit(g)), (16, 24, 32, 40, 64, 96))
    return made.select("g", "method", "gcd")


def _wavelet_study(s: SparkSession, d: str) -> DataFrame:
    wl = WORKLOADS["w2"]
    compact = pu.compact_points(wl.points(s, d), wl.cols, wl.spec)
    made = together(lambda wave: _study(compact, wl.cols, wl.spec, wl.p, runs_frame(s, [1.0], SWEEP_REPS), mt.Options(wavelet=wave)).withColumn("wavelet", F.lit(wave)), ("haar", "bior2.2", "db2"))
    return made.select("wavelet", "method", "gcd")


#: Share of the check-ins that the sampled experiment keeps.
SAMPLED = 1 / 6.4


def _sampled_study(s: SparkSession, d: str) -> DataFrame:
    """All techniques on the check-ins and on a fixed share of them: clusters, rank error and F-measure."""
    wl, lines, made = WORKLOADS["w4"], runs_frame(s, [0.5, 1.0], SWEEP_REPS), None
    for name in ("full", "sampled"):
        points = wl.points(s, d).select("point_id", *wl.cols)
        points = materialise((points if name == "full" else me.sample_share(points, KEY, SAMPLED)).select(*wl.cols), "points")
        counts = mt._counts(points, wl.cols, wl.spec)
        true = mt.cluster_counts_matrix(counts, wl.spec, wl.p)
        t = materialise(true.cells, "truth")
        for m in METHODS:
            if m == "synthetic":
                released = mt.release_synthetic(points, wl.cols, wl.spec, wl.p, lines, KEY)
            else:
                released = {"noisy_counts": mt.release_noisy_counts, "trimmed": mt.release_trimmed, "sampled_cut": mt.release_sampled_cut}[m](counts, wl.spec, wl.p, lines, KEY)
            cells = materialise(released.cells, "released")
            each = me.rank_error(true.cut, released.cut).select(*RUN, "rank_error").join(me.f_measure(t, cells, lines), list(RUN)).join(me.cluster_counts(t, cells, lines), list(RUN))
            part = each.select(F.lit(name).alias("data"), F.lit(SHORT[m]).alias("method"), "eps_i", "rank_error", "f", "clusters_true", "clusters_private")
            made = part if made is None else made.unionByName(part)
    return made.groupBy("data", "method", "eps_i").agg(F.max("clusters_true").alias("clusters_true"), r6(F.avg("clusters_private"), "clusters"), r6(F.avg("rank_error"), "rank_error"), r6(F.avg("f"), "f"))


def _sampled_sql() -> str:
    made, share = [], f"WHERE {duck.uniform(KEY, 'share', 'point_id')} < {num(SAMPLED)}"
    for name in ("full", "sampled"):
        for m in METHODS:
            q = _both_labels("w4", m, (0.5, 1.0), SWEEP_REPS).cut(WORKLOADS["w4"].p, "band", "rcut")
            if name == "sampled":
                q.parts = [(n, f"SELECT * FROM ({b}) z {share}" if n == "pts" else b) for n, b in q.parts]
            q.add("o", "SELECT p.eps_i, p.rep, t.cluster AS a, p.cluster AS b, count(*) AS o FROM plab p JOIN tlab t USING (wcell) GROUP BY ALL").add("na", "SELECT cluster AS a, count(*) AS n_a FROM tlab GROUP BY 1").add("nb", "SELECT eps_i, rep, cluster AS b, count(*) AS n_b FROM plab GROUP BY ALL")
            q.add("be", "SELECT eps_i, rep, a, max(2e0 * o / (n_a + n_b)) AS best FROM o JOIN na USING (a) JOIN nb USING (eps_i, rep, b) GROUP BY ALL")
            q.add("ff", "SELECT eps_i, rep, sum(n_a * coalesce(best, 0e0)) / sum(n_a) AS f FROM runs CROSS JOIN na LEFT JOIN be USING (eps_i, rep, a) GROUP BY ALL")
            q.add("cc", "SELECT eps_i, rep, count(DISTINCT cluster) AS c FROM plab GROUP BY ALL")
            made.append(q.select(f"SELECT '{name}' AS data, '{SHORT[m]}' AS method, eps_i, (SELECT count(DISTINCT cluster) FROM tlab) AS clusters_true, round(avg(coalesce(c, 0)), 6) AS clusters, round(avg(abs(k_priv - k) * 1e0 / k), 6) AS rank_error, round(avg(f), 6) AS f FROM pcut JOIN ff USING (eps_i, rep) LEFT JOIN cc USING (eps_i, rep) CROSS JOIN (SELECT k FROM rcut) r GROUP BY eps_i"))
    return " UNION ALL ".join(f"SELECT * FROM ({q}) x{i}" for i, q in enumerate(made))


#: Grid of the bridge study: two blocks of four coarse cells and a lone cell beside the second; a coarse cell is free between the blocks.
BRIDGE, BRIDGE_P = GridSpec((0.0, 0.0), (12.0, 4.0), (12, 4)), 0.05


def bridge_points(s: SparkSession, d: str, bridged: bool) -> DataFrame:
    """Orders dealt by key to the 36 cells of the blocks; that of least key lies between the blocks, or is left out."""
    orders = s.read.parquet(f"{d}/orders.parquet").select(F.col("o_orderkey").alias("key"))
    rows = orders.crossJoin(F.broadcast(orders.agg(F.min("key").alias("least")))).where("key IS NOT NULL" if bridged else "key > least")
    block, quarter, first = F.floor(F.col("key") % 36 / 4), F.col("key") % 4, F.col("key") == F.col("least")
    x0 = 2 * (F.floor(block / 2) + F.when(block >= 4, 1).otherwise(0)) + F.floor(quarter / 2) + 0.5
    x1 = 2 * (block % 2) + quarter % 2 + 0.5
    return rows.select(F.when(first, 4.5).otherwise(x0).alias("x0"), F.when(first, 0.5).otherwise(x1).alias("x1"))


def bridge_record(s: SparkSession, d: str) -> DataFrame:
    """One record turns two clusters into one."""
    made = None
    for name, with_ in (("without", False), ("with", True)):
        c = mt.cluster_grid(bridge_points(s, d, with_), ["x0", "x1"], BRIDGE, BRIDGE_P)
        line = c.cut.crossJoin(c.cells.agg(F.count_distinct("cluster").alias("clusters"))).select(F.lit(name).alias("data"), "k", "clusters")
        made = line if made is None else made.unionByName(line)
    return made


def _bridge_sql() -> str:
    made = []
    for name, test in (("without", "key > least"), ("with", "key IS NOT NULL")):
        q = Query().add("rows", f"SELECT key, least, key % 36 // 4 AS b, key % 4 AS q FROM (SELECT o_orderkey AS key FROM orders) o CROSS JOIN (SELECT min(o_orderkey) AS least FROM orders) l WHERE {test}")
        q.add("pts", "SELECT CASE WHEN key = least THEN 4.5e0 ELSE 2 * (b // 2 + CASE WHEN b >= 4 THEN 1 ELSE 0 END) + q // 2 + 0.5e0 END AS x0, CASE WHEN key = least THEN 0.5e0 ELSE 2 * (b % 2) + q % 2 + 0.5e0 END AS x1 FROM rows")
        q.add("m", f"SELECT cell, count(*) AS cnt FROM (SELECT {duck.cell_sql(['x0', 'x1'], BRIDGE)} AS cell FROM pts) z GROUP BY cell").haar(BRIDGE).cut(BRIDGE_P).keep("band", "cut").components(BRIDGE.coarse(1))
        made.append(q.select(f"SELECT '{name}' AS data, c.k, (SELECT count(DISTINCT cluster) FROM lab) AS clusters FROM cut c"))
    return " UNION ALL ".join(f"SELECT * FROM ({q}) x{i}" for i, q in enumerate(made))


def _theory(s: SparkSession, d: str) -> DataFrame:
    lines = sweep(s)
    st = bo.statistics(band(s, d, "w2"), lines, 0.10, coarse("w2"))
    shift = technique(s, d, "w2", "noisy_counts", lines).cut.groupBy("eps_i").agg(F.avg("k_priv").alias("mean_k"))
    return st.join(shift, "eps_i").select("eps", "k", r6(F.col("mean_k") - F.col("k"), "measured"), r6(bo.expected_rank_shift(0.10, F.col("n_nonpos"), F.col("theta")), "predicted"))


def _bound_study(s: SparkSession, d: str) -> DataFrame:
    made, lines = None, runs_frame(s, [0.5, 1.0, 2.0], SWEEP_REPS)
    for w in ("w1", "w2", "w3", "w4"):
        clean_band = materialise(band(s, d, w), "band")
        st = bo.statistics(clean_band, lines, WORKLOADS[w].p, coarse(w))
        for m, fn in (("noisy_counts", bo.bounds_noisy_counts), ("trimmed", bo.bounds_trimmed), ("sampled_cut", bo.bounds_sampled_cut)):
            held = bo.verify_bounds(clean_band, fn(st, WORKLOADS[w].p, OMEGA), technique(s, d, w, m, lines).cells, lines)
            part = held.agg(r6(F.avg(F.col("holds").cast("double")), "coverage"), F.sum("must").alias("must"), F.sum("must_not").alias("must_not")).select(F.lit(w).alias("workload"), F.lit(SHORT[m]).alias("method"), "coverage", "must", "must_not")
            made = part if made is None else made.unionByName(part)
    return made


def _relational() -> None:
    register("star_join_points", lambda s, d: pts("w4")(s, d).groupBy("truth").agg(F.count(F.lit(1)).alias("n"), r6(F.avg("x0"), "mx"), r6(F.max("x1"), "hy")), "SELECT truth, count(*) AS n, round(avg(x0), 6) AS mx, round(max(x1), 6) AS hy FROM (" + WORKLOADS["w4"].sql("duckdb") + ") q GROUP BY truth")
    register("sample_points_w4", lambda s, d: me.sample_points(pts("w4")(s, d).select("point_id"), KEY, 1000).select("point_id"), f"SELECT point_id FROM ({WORKLOADS['w4'].sql('duckdb')}) q ORDER BY {duck.uniform(KEY, 'sample', 'point_id')}, point_id LIMIT 1000")
    register("split_points_w2", lambda s, d: me.split_points(pts("w2")(s, d), KEY).groupBy("train").agg(F.count(F.lit(1)).alias("n"), F.min("point_id").alias("least")), f"SELECT {duck.uniform(KEY, 'split', 'point_id')} < 0.9e0 AS train, count(*) AS n, min(point_id) AS least FROM ({WORKLOADS['w2'].sql('duckdb')}) q GROUP BY 1")
    two = lambda: clean("w2").cut(0.10).keep("band", "cut").cut(0.30, "band", "cut3").keep("band", "cut3", "kept3")
    register("setops_cells", _setops, two().select("SELECT 'both' AS kind, wcell FROM (SELECT wcell FROM kept INTERSECT SELECT wcell FROM kept3) x UNION ALL SELECT 'only_wide', wcell FROM (SELECT wcell FROM kept EXCEPT SELECT wcell FROM kept3) y"))
    spec = WORKLOADS["w2"].spec
    i, j = duck.unrolled("cell", spec.g)
    register("rollup_levels", _rollup, clean("w2").select(f"SELECT i0, i1, sum(cnt) AS cnt, CAST(grouping_id(i0, i1) AS INT) AS level FROM (SELECT ({i}) // 8 AS i0, ({j}) // 8 AS i1, cnt FROM m) q GROUP BY ROLLUP (i0, i1)").replace("sum(cnt) AS cnt,", "CAST(sum(cnt) AS BIGINT) AS cnt,"))
    register("window_frames_w", _frames, clean("w2").select("SELECT wcell, round(w, 6) AS w, row_number() OVER o AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd, CAST(ntile(4) OVER o AS INT) AS q4, round(lag(w) OVER o, 6) AS before, round(avg(w) OVER (o ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS smooth, count(*) OVER (ORDER BY w RANGE BETWEEN 5 PRECEDING AND CURRENT ROW) AS near FROM band WHERE w > 0 WINDOW o AS (ORDER BY w, wcell), v AS (ORDER BY w)").replace("row_number() OVER o AS rn", "CAST(row_number() OVER o AS INT) AS rn").replace("rank() OVER v AS rk, dense_rank() OVER v AS dr", "CAST(rank() OVER v AS INT) AS rk, CAST(dense_rank() OVER v AS INT) AS dr"))
    boxes = "(VALUES (1, 0.1e0, 0.5e0, 0.2e0, 0.9e0), (2, 0.45e0, 0.55e0, 0.45e0, 0.55e0), (3, 0e0, 1e0, 0e0, 1e0)) b(box, qlo0, qhi0, qlo1, qhi1)"
    from dpgrid.catalog import _uniform_sql

    register("range_query_boxes", _range_boxes, _uniform_sql("w2").select(f"SELECT eps_i, rep, box, round(sum(cnt * (least(hi0, qhi0) - greatest(lo0, qlo0)) / (hi0 - lo0) * (least(hi1, qhi1) - greatest(lo1, qlo1)) / (hi1 - lo1)), 4) AS estimate FROM leaves JOIN {boxes} ON lo0 < qhi0 AND hi0 > qlo0 AND lo1 < qhi1 AND hi1 > qlo1 GROUP BY ALL"))
    register("asof_rank", _asof, clean("w2").rank_intervals().select("SELECT probe, coalesce((SELECT max(rank) FROM ivals WHERE hi >= probe), 0) AS rank FROM (VALUES (0.25e0), (5e0), (40e0), (100e0), (1e9)) p(probe)"))
    register("json_dim_events", lambda s, d: _json_cells(s, d), f"SELECT cell, count(*) AS cnt FROM (SELECT {duck.cell_sql(['x0', 'x1', 'x2'], _json_spec())} AS cell FROM ({WORKLOADS['w6'].sql('duckdb')}) q WHERE x2 IS NOT NULL) z GROUP BY cell")


def _json_spec():
    return unit(16, 3)


def _json_cells(s: SparkSession, d: str) -> DataFrame:
    return quantize(pts("w6")(s, d), ["x0", "x1", "x2"], _json_spec())


def _setops(s: SparkSession, d: str) -> DataFrame:
    b = band(s, d, "w2")
    a, c = (significant_cells(b, p=p)[0].select("wcell") for p in (0.10, 0.30))
    return a.intersect(c).select(F.lit("both").alias("kind"), "wcell").unionByName(a.exceptAll(c).select(F.lit("only_wide").alias("kind"), "wcell"))


def _rollup(s: SparkSession, d: str) -> DataFrame:
    spec = WORKLOADS["w2"].spec
    m = quantize(pts("w2")(s, d), ["x0", "x1"], spec)
    at = m.select("cnt", *[F.floor(c / 8).cast("long").alias(f"i{a}") for a, c in enumerate(coordinates(F.col("cell"), spec.g))])
    return at.rollup("i0", "i1").agg(F.sum("cnt").alias("cnt"), F.grouping_id().cast("int").alias("level")).select("i0", "i1", "cnt", "level")


def _frames(s: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    o, v = Window.orderBy("w", "wcell"), Window.orderBy("w")
    return band(s, d, "w2").where("w > 0").select(
        "wcell", r6("w"), F.row_number().over(o).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), r6(F.percent_rank().over(v), "pr"), r6(F.cume_dist().over(v), "cd"), F.ntile(4).over(o).alias("q4"),
        r6(F.lag("w").over(o), "before"), r6(F.avg("w").over(o.rowsBetween(-2, 0)), "smooth"), F.count(F.lit(1)).over(v.rangeBetween(-5, 0)).alias("near"),
    )


def _range_boxes(s: SparkSession, d: str) -> DataFrame:
    boxes = s.createDataFrame([(1, 0.1, 0.5, 0.2, 0.9), (2, 0.45, 0.55, 0.45, 0.55), (3, 0.0, 1.0, 0.0, 1.0)], "box int, qlo0 double, qhi0 double, qlo1 double, qhi1 double")
    leaves = pu.publish_uniform(pts("w2")(s, d), ["x0", "x1"], WORKLOADS["w2"].spec, runs(s), KEY)
    return pu.range_count(leaves, boxes).select(*RUN, "box", F.round("estimate", 4).alias("estimate"))


def _asof(s: SparkSession, d: str) -> DataFrame:
    """Rank of any value among the clean ones: probes and values in one sorted stream, each probe taking the last rank before it."""
    from pyspark.sql import Window

    from dpgrid.operators.threshold import rank_intervals

    known = rank_intervals(band(s, d, "w2")).select(F.col("hi").alias("at"), "rank", F.lit(None).cast("double").alias("probe"))
    probes = s.createDataFrame([(p,) for p in (0.25, 5.0, 40.0, 100.0, 1e9)], "probe double").select(F.col("probe").alias("at"), F.lit(None).cast("long").alias("rank"), "probe")
    down = Window.orderBy(F.col("at").desc(), F.col("probe").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    return known.unionByName(probes).withColumn("r", F.last("rank", ignorenulls=True).over(down)).where("probe is not null").select("probe", F.coalesce("r", F.lit(0).cast("long")).alias("rank"))


def _streams() -> None:
    spec = unit(8)
    cell = duck.cell_sql(["x0", "x1"], spec)
    pt = f"(SELECT ts, {cell} AS cell FROM (SELECT ts, (hour(ts) * 60 + minute(ts)) / 1440e0 AS x0, ln(value + 1e0) / ln(501e0) AS x1 FROM events) z)"
    closed = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"
    text = lambda c: f"strftime({c}, '%Y-%m-%d %H:%M:%S')"
    register("tumbling_events", lambda s, d: win.run_available(win.windowed_counts(win.clock_points(win.event_stream(s, d)), ["x0", "x1"], spec), "tumbling").select(win.start_text(), "cell", "cnt"), f"SELECT {text('start')} AS start, cell, count(*) AS cnt FROM (SELECT date_trunc('hour', ts) AS start, cell FROM {pt} p) q WHERE start + INTERVAL 1 HOUR <= {closed} GROUP BY ALL")
    register("sliding_events", lambda s, d: win.run_available(win.windowed_counts(win.clock_points(win.event_stream(s, d)), ["x0", "x1"], spec, "2 hours", "1 hour"), "sliding").select(win.start_text(), "cell", "cnt"), f"SELECT {text('start')} AS start, cell, count(*) AS cnt FROM (SELECT date_trunc('hour', ts) - INTERVAL (unnest([0, 1])) HOUR AS start, cell FROM {pt} p) q WHERE start + INTERVAL 2 HOUR <= {closed} GROUP BY ALL")
    register("session_events", lambda s, d: win.run_available(win.session_counts(win.clock_points(win.event_stream(s, d))), "session").select("user_id", win.start_text(), "n"), f"SELECT user_id, {text('min(ts)')} AS start, count(*) AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events) a) b GROUP BY user_id, g HAVING max(ts) + INTERVAL 30 MINUTE <= {closed}")
    spans = "SELECT event_id % 500 AS span, min(ts) AS begin, min(ts) + INTERVAL 90 MINUTE AS finish FROM events GROUP BY 1"
    register("interval_join_events", _interval_join, f"SELECT span, count(*) AS n, sum(CAST(round(value * 100) AS BIGINT)) AS cents FROM events e JOIN ({spans}) s ON e.ts >= s.begin AND e.ts < s.finish GROUP BY span")
    register("occupied_w4", lambda s, d: occupied_cells(pts("w4")(s, d), ["x0", "x1"], WORKLOADS["w4"].spec), clean("w4").select("SELECT count(*) AS occupied FROM m"))
    register("running_counts_events", lambda s, d: _running(s, d), f"SELECT cell, count(*) AS cnt FROM {pt} p GROUP BY cell")
    register("stream_release_events", _stream_release, _stream_release_sql())
    register("stream_cap_events", lambda s, d: win.run_available(win.cap_stream(win.clock_points(win.event_stream(s, d)), 3), "cap").groupBy("user_id").agg(F.count(F.lit(1)).alias("n")), "SELECT user_id, least(count(*), 3) AS n FROM events GROUP BY user_id")
    spec6 = WORKLOADS["w6"].spec
    at = f"SELECT point_id AS event_id, {duck.block_sql('cell', spec6)} AS wcell FROM (SELECT point_id, {duck.cell_sql(WORKLOADS['w6'].cols, spec6)} AS cell FROM pts) q"
    register("stream_labels_events", _stream_labels, private_sql("w6", "trimmed", [1.0], 1).components(spec6.coarse(1), by=RUN).select(f"SELECT event_id, coalesce(cluster, -1) AS cluster FROM ({at}) e LEFT JOIN lab USING (wcell)"))


def _stream_release_sql() -> str:
    """The batch reading: weeks that the watermark has closed, each a run with draws keyed by its start."""
    week = 7 * 86400
    draw = lambda cell: duck.laplace(duck.uniform(KEY, "{s}", "'count'", "0", "0", cell).replace("'{s}'", "start"), "1e0 / 0.9e0")
    inner = " + ".join(draw(f"((wcell // 4 * 2 + {a}) * 8 + wcell % 4 * 2 + {b})") for a in (0, 1) for b in (0, 1))
    cell = duck.cell_sql(["x0", "x1"], unit(8))
    z = duck.laplace(duck.uniform(KEY, "{s}", "'z'", "0", "0").replace("'{s}'", "start"), f"1e0 / {num(1 - 0.9)}")
    q = Query().add("ev", f"SELECT CAST(floor(epoch(ts) / {week}) AS BIGINT) * {week} AS start, {cell} AS cell FROM (SELECT ts, (hour(ts) * 60 + minute(ts)) / 1440e0 AS x0, ln(value + 1e0) / ln(501e0) AS x1 FROM events) z")
    q.add("st", f"SELECT DISTINCT start FROM ev WHERE start + {week} <= (SELECT epoch(max(ts)) - 86400 FROM events)")
    q.add("band", "SELECT start, cell // 8 // 2 * 4 + cell % 8 // 2 AS wcell, count(*) / 2e0 AS w FROM ev JOIN st USING (start) GROUP BY ALL")
    q.add("nband", f"SELECT start, wcell, (coalesce(w, 0e0) * 2e0 + {inner}) / 2e0 AS w FROM (SELECT start, unnest(range(16)) AS wcell FROM st) d LEFT JOIN band USING (start, wcell)")
    q.add("dr", f"SELECT start, CAST(floor((16 - n + {z}) / 2e0) AS BIGINT) AS r FROM (SELECT start, count(*) AS n FROM band WHERE w > 0 GROUP BY start) c")
    return q.cut(0.25, "nband", "ncut", ("start",), "dr").keep("nband", "ncut", "kept", ("start",)).components((4, 4), by=("start",)).select("SELECT start, wcell, cluster FROM lab")


def _interval_join(s: SparkSession, d: str) -> DataFrame:
    events = s.read.parquet(f"{d}/events.parquet").select("event_id", "value", F.col("ts").cast("timestamp").alias("ts"))
    begin = events.groupBy((F.col("event_id") % 500).alias("span")).agg(F.min("ts").alias("begin"))
    spans = begin.withColumn("finish", F.col("begin") + F.expr("INTERVAL 90 MINUTES"))
    held = win.events_in_windows(events.select("ts", "value"), spans)
    return held.groupBy("span").agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))


def _running(s: SparkSession, d: str) -> DataFrame:
    """Totals after each batch, kept by overwriting one small table."""
    path = new_path(s, "running")
    stream = win.running_counts(win.clock_points(win.event_stream(s, d)), ["x0", "x1"], unit(8))
    win.run_available(stream, "running", lambda batch, _: batch.write.mode("overwrite").parquet(path), "complete")
    return s.read.schema("cell long, cnt long").parquet(path)


def _stream_release(s: SparkSession, d: str) -> DataFrame:
    path = new_path(s, "stream_release")
    counts = win.windowed_counts(win.clock_points(win.event_stream(s, d)), ["x0", "x1"], unit(8), "7 days", late="1 day")
    win.run_available(counts, "release", win.releaser(unit(8), 0.25, 1.0, KEY, "trimmed", path))
    return s.read.schema("start long, wcell long, cluster long, batch int").parquet(path).drop("batch")


def _stream_labels(s: SparkSession, d: str) -> DataFrame:
    wl = WORKLOADS["w6"]
    grid = mt.release_trimmed(kept_counts(s, d, "w6"), wl.spec, wl.p, runs_frame(s, [1.0]), KEY).cells.drop(*RUN)
    labelled = win.label_stream(win.unique_events(win.clock_points(win.event_stream(s, d))), materialise(grid, "grid"), wl.cols, wl.spec)
    return win.run_available(labelled.select("event_id", "cluster"), "labels")


def _surface() -> None:
    """SQL functions, table functions, pandas functions, percentiles, pivots, audits and costs."""
    from dpgrid.operators.components import edges
    from dpgrid.plans import sqlapi

    wl = WORKLOADS["w2"]
    g = wl.spec.coarse(1)

    def by_sql(s: SparkSession, d: str) -> DataFrame:
        sqlapi.register_sql(s)
        return s.sql("SELECT haar_block(cell_id(cell_index(x0, 0e0, 1e0, 40), cell_index(x1, 0e0, 1e0, 40), 40), 40) AS wcell, count(*) / 2e0 AS w FROM {p} GROUP BY 1", p=wl.points(s, d))

    register("sql_functions_w2", by_sql, clean("w2").select("SELECT wcell, w FROM band"))

    def around(s: SparkSession, d: str) -> DataFrame:
        sqlapi.register_sql(s)
        kept = significant_cells(band(s, d, "w2"), p=0.10)[0]
        return s.sql(f"SELECT wcell, count(*) AS n FROM {{k}}, LATERAL grid_neighbors(wcell, {g[0]}, {g[1]}, true) GROUP BY wcell", k=kept.select("wcell"))

    i, j = "wcell // 20", "wcell % 20"
    register("udtf_neighbors_w2", around, clean("w2").cut(0.10).keep("band", "cut").select(f"SELECT wcell, (3 - CASE WHEN {i} IN (0, 19) THEN 1 ELSE 0 END) * (3 - CASE WHEN {j} IN (0, 19) THEN 1 ELSE 0 END) - 1 AS n FROM kept").replace("- 1 AS n", "- CAST(1 AS BIGINT) AS n"))
    register("pandas_udf_cells_w7", lambda s, d: s.read.parquet(f"{d}/embeddings.parquet").select(sqlapi.cell_udf(WORKLOADS["w7_3d"].spec)("embedding").alias("cell")).groupBy("cell").agg(F.count(F.lit(1)).alias("cnt")), ORACLES["quantize_w7_3d"])
    register("udaf_entropy_w1", lambda s, d: pts("w1")(s, d).groupBy("truth").agg(F.count(F.lit(1)).alias("n")).groupBy((F.col("truth") % 3).alias("status")).agg(sqlapi.weighted_entropy()(F.col("n").cast("double")).alias("bits"), sqlapi.log_sum_exp()(F.log("n")).alias("lse")).select("status", r6("bits"), r6("lse")), f"SELECT status, round(-sum(n / t * log2(n / t)), 6) AS bits, round(ln(max(t)), 6) AS lse FROM (SELECT truth % 3 AS status, n, sum(n) OVER (PARTITION BY truth % 3) AS t FROM (SELECT truth, count(*) AS n FROM ({WORKLOADS['w1'].sql('duckdb')}) q GROUP BY 1) a) b GROUP BY status")
    register("percentiles_w2", lambda s, d: band(s, d, "w2").where("w > 0").agg(r6(F.expr("percentile(w, 0.25)"), "p25"), r6(F.expr("percentile_cont(0.5) WITHIN GROUP (ORDER BY w)"), "p50"), r6(F.expr("percentile_disc(0.9) WITHIN GROUP (ORDER BY w)"), "p90"), F.count_distinct("w").alias("different"), F.bool_and(F.col("w") > 0).alias("positive")), clean("w2").select("SELECT round(quantile_cont(w, 0.25), 6) AS p25, round(quantile_cont(w, 0.5), 6) AS p50, round(quantile_disc(w, 0.9), 6) AS p90, count(DISTINCT w) AS different, bool_and(w > 0) AS positive FROM band WHERE w > 0"))
    register("adjacency_edges_w2", lambda s, d: edges(significant_cells(band(s, d, "w2"), p=0.10)[0], g).select("a", "b"), clean("w2").cut(0.10).keep("band", "cut").select("SELECT a.wcell AS a, b.wcell AS b FROM kept a JOIN kept b ON b.wcell = a.wcell + 20 OR (b.wcell = a.wcell + 1 AND a.wcell % 20 < 19)"))
    register("components_periodic_w2", lambda s, d: connected_components(significant_cells(band(s, d, "w2"), p=0.10)[0], g, periodic=True).select("wcell", "cluster"), clean("w2").cut(0.10).keep("band", "cut").components(g, periodic=True).select("SELECT wcell, cluster FROM lab"))
    register("components_periodic_tiled_w2", lambda s, d: connected_components(significant_cells(band(s, d, "w2"), p=0.10)[0], g, strategy="tiled", tile=8, periodic=True).select("wcell", "cluster"), ORACLES["components_periodic_w2"])

    def boxes(s: SparkSession, d: str) -> DataFrame:
        """Boxes of an 8 x 8 grid over the orders, each with its share of a thousand points less two: some counts are negative."""
        sqlapi.register_sql(s)
        return s.sql("""SELECT box, round(x0, 6) AS x0, round(x1, 6) AS x1 FROM (SELECT box, box div 8 * 0.125D AS lo0, (box div 8 + 1) * 0.125D AS hi0, box % 8 * 0.125D AS lo1, (box % 8 + 1) * 0.125D AS hi1, n * 1000D / sum(n) OVER () - 2D AS cnt
            FROM (SELECT cell div 512 * 8 + cell % 64 div 8 AS box, sum(cnt) AS n FROM {m} GROUP BY 1) q) AS b, LATERAL boxes_to_points(lo0, hi0, lo1, hi1, cnt)""", m=counts(s, d, "w1"))

    shares = Query().points("w1").counts("w1").add("b", "SELECT box, box // 8 * 0.125e0 AS lo0, (box // 8 + 1) * 0.125e0 AS hi0, box % 8 * 0.125e0 AS lo1, (box % 8 + 1) * 0.125e0 AS hi1, n * 1000e0 / sum(n) OVER () - 2e0 AS cnt FROM (SELECT cell // 512 * 8 + cell % 64 // 8 AS box, CAST(sum(cnt) AS BIGINT) AS n FROM m GROUP BY 1) q")
    register("udtf_boxes", boxes, shares.select("SELECT box, round(lo0 + (hi0 - lo0) * ((k + 0.5e0) / n), 6) AS x0, round(lo1 + (hi1 - lo1) * ((k * 0.6180339887498949e0 + 0.5e0) % 1e0), 6) AS x1 FROM (SELECT *, unnest(range(n)) AS k FROM (SELECT *, CAST(floor(greatest(cnt, 0e0) + 0.5e0) AS BIGINT) AS n FROM b) c) e"))
    from dpgrid.catalog import _drawn_sql

    spec = wl.spec
    cells = f"SELECT eps_i, rep, q.cell AS leaf, q.cell // 40 * 0.025e0 AS lo0, (q.cell // 40 + 1) * 0.025e0 AS hi0, q.cell % 40 * 0.025e0 AS lo1, (q.cell % 40 + 1) * 0.025e0 AS hi1, coalesce(cnt, 0) + {duck.laplace(duck.uniform(KEY, 'count', 'eps_i', 'rep', 'q.cell'), '1e0 / eps')} AS cnt FROM (SELECT unnest(range({spec.cells})) AS cell) q LEFT JOIN m ON m.cell = q.cell CROSS JOIN runs"
    register("syn_contingency_w2", lambda s, d: technique(s, d, "w2", "synthetic", publisher="contingency").cells, _drawn_sql(Query().points("w2").counts("w2").runs(list(EPS), REPS).add("leaves", cells), "w2"))
    register("report_rank_error", lambda s, d: QUERIES["rank_error_sweep_w2"](s, d).groupBy("eps").pivot("method", ["NQ", "TRIM", "CUT"]).agg(F.first("mean_error")), "SELECT eps, max(mean_error) FILTER (WHERE method = 'NQ') AS NQ, max(mean_error) FILTER (WHERE method = 'TRIM') AS TRIM, max(mean_error) FILTER (WHERE method = 'CUT') AS CUT FROM (" + ORACLES["rank_error_sweep_w2"] + ") q GROUP BY eps")
    register("neighbours_w2", _neighbours, clean("w2").add("one", "SELECT cell FROM m ORDER BY cell LIMIT 1").select("SELECT CAST(1 AS BIGINT) AS count_change, CAST(1 AS BIGINT) AS changed, CASE WHEN (SELECT sum(cnt) FROM m JOIN (SELECT cell AS c FROM one) o ON cell // 40 // 2 = c // 40 // 2 AND cell % 40 // 2 = c % 40 // 2) = 1 THEN 1 ELSE 0 END AS nonpositive_change").replace("THEN 1 ELSE 0 END AS nonp", "THEN CAST(1 AS BIGINT) ELSE 0 END AS nonp"))
    register("audit_ratio_w2", _audit)
    register("run_cost_w2", _cost)


def _neighbours(s: SparkSession, d: str) -> DataFrame:
    """Counts with and without one record of the first occupied cell."""
    wl = WORKLOADS["w2"]
    counts = kept_counts(s, d, "w2")
    first = counts.agg(F.min("cell").alias("c"))
    other = counts.crossJoin(F.broadcast(first)).select("cell", (F.col("cnt") - (F.col("cell") == F.col("c")).cast("long")).alias("cnt")).where("cnt > 0")
    return me.neighbour_audit(counts, other, wl.spec)


def _audit(s: SparkSession, d: str) -> DataFrame:
    """Released ranks of the drawn cut on neighbouring matrices, over many keyed runs."""
    from dpgrid.operators import audit
    from dpgrid.operators.privacy import exponential_cut
    from dpgrid.operators.threshold import rank_intervals

    wl, lines = WORKLOADS["w2"], runs_frame(s, [1.0], 2000)
    counts = kept_counts(s, d, "w2")
    first = counts.agg(F.min("cell").alias("c"))
    other = counts.crossJoin(F.broadcast(first)).select("cell", (F.col("cnt") - (F.col("cell") == F.col("c")).cast("long")).alias("cnt")).where("cnt > 0")
    made = []
    for i, c in enumerate((counts, other)):  # each with draws of its own
        b = materialise(wavelet_transform(c, wl.spec), "band")
        made.append(audit.released_rank(exponential_cut(rank_intervals(b), percentile_cut(b, wl.p), lines, f"{KEY}{i}", 1.0)))
    return audit.frequency_ratio(*made, 1.0).select("outcome", "n", "m", r6("log_ratio"), "within")


def _cost(s: SparkSession, d: str) -> DataFrame:
    from dpgrid.operators import audit

    names = ("quantize_w2", "nq_w2", "trim_w2", "cut_release_w2")
    made = None
    for n in names:
        part = audit.run_cost(s, n, lambda n=n: QUERIES[n](s, d))
        made = part if made is None else made.unionByName(part)
    return made


for _part in (_measures, _experiments, _relational, _streams, _surface):
    _part()
