"""Registered queries of the library, with their DuckDB SQL where SQL can express them.

Doubles are rounded to six places on both sides, as engines differ in the last bit of logarithms and sines.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dpgrid.functions.keyed import keyed_uniform, laplace
from dpgrid.operators import bounds as bo
from dpgrid.operators import measures as me
from dpgrid.operators import methods as mt
from dpgrid.operators import publish as pu
from dpgrid.operators.components import connected_components
from dpgrid.operators.grid import unit
from dpgrid.operators.privacy import RUN, exponential_cut, noisy_nonpositive, private_quantize, runs_frame
from dpgrid.operators.quantize import bound_contribution, densify, quantize, quantize_vec
from dpgrid.operators.threshold import bracket_cut, count_signs, percentile_cut, rank_intervals, significant_cells, value_histogram
from dpgrid.operators.wavelet import REGISTRY, wavelet_transform
from dpgrid.plans import duck
from dpgrid.plans.duck import Query, num, uniform
from dpgrid.sources.workloads import WORKLOADS

KEY = "evaluation"
EPS = (0.5, 1.0)
REPS = 2
#: Budgets and repetitions of sweeps.
SWEEP, SWEEP_REPS = (0.1, 0.25, 0.5, 0.75, 1.0, 1.5, 2.0), 10
Fn = Callable[[SparkSession, str], DataFrame]

QUERIES: dict[str, Fn] = {}
ORACLES: dict[str, str] = {}


def register(name: str, fn: Fn, sql: str | None = None) -> None:
    QUERIES[name] = fn
    if sql is not None:
        ORACLES[name] = sql


def r6(c: str | Column, name: str | None = None) -> Column:
    col = F.col(c) if isinstance(c, str) else c
    return F.round(col, 6).alias(name or str(c))


def pts(w: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: WORKLOADS[w].points(spark, d)


def counts(spark: SparkSession, d: str, w: str) -> DataFrame:
    wl = WORKLOADS[w]
    return quantize(wl.points(spark, d), wl.cols, wl.spec)


def kept_counts(spark: SparkSession, d: str, w: str) -> DataFrame:
    wl = WORKLOADS[w]
    return mt._counts(wl.points(spark, d), wl.cols, wl.spec)


def band(spark: SparkSession, d: str, w: str) -> DataFrame:
    return wavelet_transform(counts(spark, d, w), WORKLOADS[w].spec)


def coarse(w: str) -> int:
    made = 1
    for k in WORKLOADS[w].spec.coarse(1):
        made *= k
    return made


def clean(w: str) -> Query:
    return Query().points(w).counts(w).haar(WORKLOADS[w].spec)


def _quantize() -> None:
    for w in WORKLOADS:
        register(f"quantize_{w}", lambda s, d, w=w: counts(s, d, w), Query().points(w).counts(w).select("SELECT cell, cnt FROM m"))
    spec = WORKLOADS["w2"].spec
    register("quantize_dense_w2", lambda s, d: densify(counts(s, d, "w2"), spec).select("cell", "cnt"), Query().points("w2").counts("w2").select(f"SELECT r.cell, coalesce(cnt, 0) AS cnt FROM (SELECT unnest(range({spec.cells})) AS cell) r LEFT JOIN m USING (cell)"))
    register("quantize_vec_w7", lambda s, d: quantize_vec(s.read.parquet(f"{d}/embeddings.parquet"), "embedding", WORKLOADS["w7"].spec), ORACLES["quantize_w7"])
    small = WORKLOADS["w5"].spec.__class__((2000.0, 5.0), (90000.0, 40.0), (40, 40))
    for policy, where in (("clamp", ""), ("drop", "WHERE x0 >= 2000e0 AND x0 <= 90000e0 AND x1 >= 5e0 AND x1 <= 40e0")):
        register(f"quantize_{policy}_w5", lambda s, d, policy=policy: quantize(pts("w5")(s, d), ["x0", "x1"], small, (), policy), Query().points("w5").select(f"SELECT {duck.cell_sql(['x0', 'x1'], small)} AS cell, count(*) AS cnt FROM pts {where} GROUP BY ALL"))
    register("semi_anti_noise_points", _noise_points, clean("w2").cut(0.10).keep("band", "cut").select(f"SELECT p.point_id, CASE WHEN k.wcell IS NULL THEN 1 ELSE 0 END AS noise FROM (SELECT point_id, {duck.block_sql('cell', spec)} AS wcell FROM (SELECT point_id, {duck.cell_sql(['x0', 'x1'], spec)} AS cell FROM pts) q) p LEFT JOIN kept k USING (wcell)"))


def _noise_points(s: SparkSession, d: str) -> DataFrame:
    from dpgrid.operators.grid import block_of, cell_of

    wl = WORKLOADS["w2"]
    placed = wl.points(s, d).select("point_id", block_of(cell_of(wl.cols, wl.spec), wl.spec).alias("wcell"))
    cells, _ = significant_cells(band(s, d, "w2"), p=wl.p)
    cells = cells.select("wcell")
    inside = placed.join(F.broadcast(cells), "wcell", "left_semi").select("point_id", F.lit(0).alias("noise"))
    return inside.unionByName(placed.join(F.broadcast(cells), "wcell", "left_anti").select("point_id", F.lit(1).alias("noise")))


def _wavelets() -> None:
    for w in ("w1", "w2", "w3", "w4", "w7_3d"):
        register(f"haar_{w}", lambda s, d, w=w: band(s, d, w).select("wcell", r6("w")), clean(w).select("SELECT wcell, round(w, 6) AS w FROM band"))
    spec = WORKLOADS["w2"].spec
    register("haar_mean_w2", lambda s, d: wavelet_transform(counts(s, d, "w2"), spec, scale="mean").select("wcell", r6("w")), clean("w2").select("SELECT wcell, round(w / 2, 6) AS w FROM band"))
    register("haar_level2_w2", lambda s, d: wavelet_transform(counts(s, d, "w2"), spec, level=2).select("wcell", r6("w")), Query().points("w2").counts("w2").haar(spec, 2).select("SELECT wcell, round(w, 6) AS w FROM band"))
    i, j = duck.unrolled("cell", spec.g)
    rows = " UNION ALL ".join(f"SELECT '{b}' AS band, {duck.block_sql('cell', spec)} AS wcell, sum(cnt * {f0} * {f1}) / 2e0 AS w FROM m GROUP BY ALL" for b, f0, f1 in (("LL", "1", "1"), ("LH", "1", f"(1 - 2 * ({j} % 2))"), ("HL", f"(1 - 2 * ({i} % 2))", "1"), ("HH", f"(1 - 2 * ({i} % 2))", f"(1 - 2 * ({j} % 2))")))
    register("haar_bands_w2", lambda s, d: wavelet_transform(counts(s, d, "w2"), spec, bands="all").select("band", "wcell", r6(F.col("w") + 0.0, "w")), Query().points("w2").counts("w2").select(f"SELECT band, wcell, round(w, 6) AS w FROM ({rows}) q"))
    for name, wave in (("bior_w2", "bior2.2"), ("db2_w2", "db2")):
        register(name, lambda s, d, wave=wave: wavelet_transform(counts(s, d, "w2"), spec, wave).select("wcell", r6("w")), Query().points("w2").counts("w2").filter_axis(wave, spec, "m", "f").select("SELECT wcell, round(w, 6) AS w FROM f"))
    register("sensitivity_wavelets", _sensitivities, _sensitivity_sql())


def _sensitivities(s: SparkSession, d: str) -> DataFrame:
    """Most coefficients of one sign, and of any, that a record of the events can move: the transform of a lone record in every cell that holds one."""
    wl, made = WORKLOADS["w6"], None
    for n in (1, 2, 3):
        spec, cols = unit(16, n), ["x0", "x1", "x2"][:n]
        lone = mt._counts(wl.points(s, d), cols, spec).select(F.col("cell").alias("record"), "cell", F.lit(1).alias("cnt"))
        for name in ("haar", "db2", "bior2.2"):
            moved = wavelet_transform(lone, spec, name, by=["record"]).groupBy("record").agg(*[F.count(F.when(test, 1)).cast("int").alias(c) for c, test in (("pos", F.col("w") > 1e-12), ("neg", F.col("w") < -1e-12))])
            part = moved.agg(F.max(F.greatest("pos", "neg")).alias("s_z"), F.max(F.col("pos") + F.col("neg")).alias("s_rank")).select(F.lit(name).alias("wavelet"), F.lit(n).alias("n"), "s_z", "s_rank")
            made = part if made is None else made.unionByName(part)
    return made


def _sensitivity_sql() -> str:
    """Signs of the taps by phase, multiplied over the axes, worked out in SQL."""
    taps = ", ".join(f"('{n}', {t + REGISTRY[n].offset}, {num(c)})" for n in ("haar", "db2", "bior2.2") for t, c in enumerate(REGISTRY[n].low))
    return f"""WITH t AS (SELECT * FROM (VALUES {taps}) v(wavelet, s, c)),
    p AS (SELECT wavelet, (s % 2 + 2) % 2 AS phase, count(*) FILTER (WHERE c > 0) AS pos, count(*) FILTER (WHERE c < 0) AS neg FROM t GROUP BY ALL),
    a1 AS (SELECT wavelet, 1 AS n, pos, neg FROM p),
    a2 AS (SELECT a.wavelet, 2 AS n, a.pos * p.pos + a.neg * p.neg AS pos, a.pos * p.neg + a.neg * p.pos AS neg FROM a1 a JOIN p USING (wavelet)),
    a3 AS (SELECT a.wavelet, 3 AS n, a.pos * p.pos + a.neg * p.neg AS pos, a.pos * p.neg + a.neg * p.pos AS neg FROM a2 a JOIN p USING (wavelet)),
    u AS (SELECT * FROM a1 UNION ALL SELECT * FROM a2 UNION ALL SELECT * FROM a3)
    SELECT wavelet, n, CAST(max(greatest(pos, neg)) AS INT) AS s_z, CAST(CASE WHEN wavelet = 'haar' THEN 1 ELSE max(pos + neg) END AS INT) AS s_rank FROM u GROUP BY wavelet, n"""


def _thresholds() -> None:
    for w in ("w1", "w2", "w3", "w4"):
        register(f"cut_{w}", lambda s, d, w=w: significant_cells(band(s, d, w), p=WORKLOADS[w].p)[0].select("wcell", r6("w")), clean(w).cut(WORKLOADS[w].p).keep("band", "cut").select("SELECT wcell, round(w, 6) AS w FROM kept"))
    register("cut_strict_w2", lambda s, d: significant_cells(band(s, d, "w2"), p=0.10, ties="strict")[0].select("wcell", r6("w")), clean("w2").cut(0.10).keep("band", "cut", test=">").select("SELECT wcell, round(w, 6) AS w FROM kept"))
    register("cut_topk_w2", lambda s, d: significant_cells(band(s, d, "w2"), k=50)[0].select("wcell", r6("w")), clean("w2").select("SELECT wcell, round(w, 6) AS w FROM band WHERE w > 0 AND w >= (SELECT w FROM band ORDER BY w DESC LIMIT 1 OFFSET 49)"))
    register("cut_value_w2", lambda s, d: significant_cells(band(s, d, "w2"), d=25.0)[0].select("wcell", r6("w")), clean("w2").select("SELECT wcell, round(w, 6) AS w FROM band WHERE w >= 25"))
    register("percentile_check_w2", lambda s, d: percentile_cut(band(s, d, "w2"), 0.10).select("n_pos", "k", r6("d")), clean("w2").cut(0.10).select("SELECT n_pos, k, round(d, 6) AS d FROM cut"))
    register("bracket_cut_w4", lambda s, d: bracket_cut(band(s, d, "w4"), WORKLOADS["w4"].p).select("n_pos", "k", r6("d")), clean("w4").cut(WORKLOADS["w4"].p).select("SELECT n_pos, k, round(d, 6) AS d FROM cut"))
    register("bracket_cut_noisy_w2", lambda s, d: bracket_cut(technique(s, d, "w2", "noisy_counts").band, 0.10, RUN).select(*RUN, "n_pos", "k", r6("d")), clean("w2").runs(list(EPS), REPS).noisy_band(WORKLOADS["w2"].spec, KEY).cut(0.10, "nband", "ncut", RUN).select("SELECT eps_i, rep, n_pos, k, round(d, 6) AS d FROM ncut"))
    register("rank_intervals_w2", lambda s, d: rank_intervals(band(s, d, "w2")).select("rank", r6("lo"), r6("hi")), clean("w2").rank_intervals().select("SELECT rank, round(lo, 6) AS lo, round(hi, 6) AS hi FROM ivals"))
    register("value_histogram_w2", lambda s, d: value_histogram(band(s, d, "w2")).select(r6("w"), "mult", "rank_ge"), clean("w2").rank_intervals().select("SELECT round(w, 6) AS w, mult, rank AS rank_ge FROM ivals_h JOIN ivals ON hi = w"))


def _clustered(w: str, adjacency: str = "face") -> Query:
    wl = WORKLOADS[w]
    return clean(w).cut(wl.p).keep("band", "cut").components(wl.spec.coarse(1), adjacency=adjacency)


def np_cells(s: SparkSession, d: str, w: str, **o) -> DataFrame:
    wl = WORKLOADS[w]
    return mt.cluster_grid(wl.points(s, d), wl.cols, wl.spec, wl.p, (), mt.Options(**o)).cells


def _components() -> None:
    for w in ("w1", "w2", "w3", "w4", "w5", "w6", "w7", "w7_proj", "w8", "w9"):
        register(f"components_{w}", lambda s, d, w=w: np_cells(s, d, w).select("wcell", "cluster"), _clustered(w).select("SELECT wcell, cluster FROM lab"))
    register("components_full_w2", lambda s, d: np_cells(s, d, "w2", adjacency="full").select("wcell", "cluster"), _clustered("w2", "full").select("SELECT wcell, cluster FROM lab"))
    for strategy in ("iterate", "tiled"):
        register(f"components_{strategy}_w3", lambda s, d, strategy=strategy: connected_components(significant_cells(band(s, d, "w3"), p=0.23)[0], WORKLOADS["w3"].spec.coarse(1), strategy=strategy, tile=8).select("wcell", "cluster"), ORACLES["components_w3"])
    g = WORKLOADS["w2"].spec.coarse(1)
    i, j = duck.unrolled("wcell", g)
    register("profile_w2", _profile, _clustered("w2").select(f"SELECT cluster, count(*) AS cells, round(sum(w), 6) AS mass, min({i}) AS min0, max({i}) AS max0, round(sum(({i}) * w) / sum(w), 6) AS centre0, min({j}) AS min1, max({j}) AS max1, round(sum(({j}) * w) / sum(w), 6) AS centre1 FROM lab JOIN kept USING (wcell) GROUP BY cluster"))
    spec = WORKLOADS["w2"].spec
    register("assign_w2", _assign, _clustered("w2").select(f"SELECT point_id, coalesce(cluster, -1) AS cluster FROM (SELECT point_id, {duck.block_sql('cell', spec)} AS wcell FROM (SELECT point_id, {duck.cell_sql(['x0', 'x1'], spec)} AS cell FROM pts) q) p LEFT JOIN lab USING (wcell)"))
    n = WORKLOADS["w3"].spec.coarse(1)
    register("ascii_map_w3", lambda s, d: mt.ascii_map(np_cells(s, d, "w3"), WORKLOADS["w3"].spec), _clustered("w3").select(f"SELECT wcell // {n[1]} AS line, string_agg(coalesce(chr(CAST(65 + r % 26 AS INT)), '.'), '' ORDER BY wcell) AS picture FROM (SELECT unnest(range({n[0] * n[1]})) AS wcell) q LEFT JOIN (SELECT wcell, dense_rank() OVER (ORDER BY cluster) - 1 AS r FROM lab) l USING (wcell) GROUP BY line"))


def _profile(s: SparkSession, d: str) -> DataFrame:
    p = mt.cluster_profile(np_cells(s, d, "w2"), WORKLOADS["w2"].spec)
    return p.select("cluster", "cells", *[r6(c) if c[:4] in ("mass", "cent") else F.col(c) for c in p.columns[2:]])


def _assign(s: SparkSession, d: str) -> DataFrame:
    wl = WORKLOADS["w2"]
    p = wl.points(s, d)
    return mt.assign_points(p, mt.cluster_grid(p, wl.cols, wl.spec, wl.p).cells, wl.cols, wl.spec).select("point_id", "cluster")


def runs(s: SparkSession) -> DataFrame:
    return runs_frame(s, EPS, REPS)


def sweep(s: SparkSession, reps: int = SWEEP_REPS) -> DataFrame:
    return runs_frame(s, SWEEP, reps)


def _mechanisms() -> None:
    spec = WORKLOADS["w2"].spec
    base = lambda: clean("w2").runs(list(EPS), REPS)
    cell = f"(SELECT r.cell, coalesce(cnt, 0) AS cnt FROM (SELECT unnest(range({spec.cells})) AS cell) r LEFT JOIN m USING (cell))"
    register("laplace_cells_w2", lambda s, d: private_quantize(counts(s, d, "w2"), spec, runs(s), KEY).select(*RUN, "cell", r6("cnt_noisy")), base().select(f"SELECT eps_i, rep, cell, round(cnt + {duck.laplace(uniform(KEY, 'count', 'eps_i', 'rep', 'cell'), '1e0 / (eps * 1e0)')}, 6) AS cnt_noisy FROM {cell} q CROSS JOIN runs"))
    geo = f"floor(ln({uniform(KEY, 'count', 'eps_i', 'rep', 'cell')}) * -(1e0 / eps)) - floor(ln({uniform(KEY, 'count2', 'eps_i', 'rep', 'cell')}) * -(1e0 / eps))"
    register("geometric_cells_w2", lambda s, d: private_quantize(counts(s, d, "w2"), spec, runs(s), KEY, noise="geometric").select(*RUN, "cell", F.col("cnt_noisy").cast("long").alias("cnt_noisy")), base().select(f"SELECT eps_i, rep, cell, CAST(cnt + {geo} AS BIGINT) AS cnt_noisy FROM {cell} q CROSS JOIN runs"))
    register("noisy_band_w2", lambda s, d: mt._noisy_band(counts(s, d, "w2"), spec, runs(s), KEY, 1.0, mt.Options()).select(*RUN, "wcell", r6("w")), base().noisy_band(spec, KEY).select("SELECT eps_i, rep, wcell, round(w, 6) AS w FROM nband"))
    register("noisy_z_w2", lambda s, d: noisy_nonpositive(count_signs(band(s, d, "w2"), coarse("w2")), runs(s), KEY, 0.1).select(*RUN, r6("z_noisy")), base().nonpositive(coarse("w2")).noisy_z(KEY, 0.1).select("SELECT eps_i, rep, round(z_noisy, 6) AS z_noisy FROM zn"))
    register("exp_mech_w2", lambda s, d: exponential_cut(rank_intervals(band(s, d, "w2")), percentile_cut(band(s, d, "w2"), 0.10), runs(s), KEY, 0.3).select(*RUN, "k_priv", r6("d")), base().cut(0.10).rank_intervals().sampled_cut(KEY, 0.3).select("SELECT eps_i, rep, k_priv, round(d, 6) AS d FROM drawn"))
    register("exp_mech_cumulative_w2", lambda s, d: exponential_cut(rank_intervals(band(s, d, "w2")), percentile_cut(band(s, d, "w2"), 0.10), runs(s), KEY, 0.3, sampler="cumulative").select(*RUN, "k_priv", r6("d")), base().cut(0.10).rank_intervals().add("cv", f"SELECT eps_i, rep, rank, lo, hi, ln(hi - lo) + eps * 0.3e0 * -abs(rank - k) / 2e0 AS v FROM ivals CROSS JOIN (SELECT k FROM cut) c CROSS JOIN runs WHERE hi > lo").add("ce", "SELECT *, exp(v - max(v) OVER (PARTITION BY eps_i, rep)) AS e FROM cv").add("ct", "SELECT *, sum(e) OVER (PARTITION BY eps_i, rep ORDER BY rank) / sum(e) OVER (PARTITION BY eps_i, rep) AS t FROM ce").select(f"SELECT eps_i, rep, rank AS k_priv, round(lo + (hi - lo) * {uniform(KEY, 'within', 'eps_i', 'rep')}, 6) AS d FROM ct WHERE t >= {uniform(KEY, 'pick', 'eps_i', 'rep')} QUALIFY row_number() OVER (PARTITION BY eps_i, rep ORDER BY t) = 1"))
    register("ledger_all", _ledgers, "SELECT * FROM (VALUES ('noisy_counts', 1e0), ('trimmed', 0.9e0 + 0.1e0), ('sampled_cut', 0.7e0 + 0.3e0), ('synthetic', 1e0)) t(method, spent)")
    cap = f"SELECT event_id, user_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY {uniform(KEY, 'cap', 'event_id')}, event_id) <= 3"
    register("contribution_cap_events", lambda s, d: bound_contribution(s.read.parquet(f"{d}/events.parquet").select("event_id", "user_id"), "user_id", 3, KEY, "event_id"), cap)


def _ledgers(s: SparkSession, d: str) -> DataFrame:
    """What each technique's release of the events has spent."""
    lines, own = runs_frame(s, [1.0], 1), kept_counts(s, d, "w6")
    rows = [(m, round(technique(s, d, "w6", m, lines, own).ledger.spent(), 9)) for m in ("noisy_counts", "trimmed", "sampled_cut", "synthetic")]
    return s.createDataFrame(rows, "method string, spent double")


def technique(s: SparkSession, d: str, w: str, method: str, lines: DataFrame | None = None, counts: DataFrame | None = None, compact: DataFrame | None = None, **how):
    """A technique's release; ``counts``, and ``compact`` points for the publisher, are the workload's own where several techniques share them."""
    wl, lines = WORKLOADS[w], runs(s) if lines is None else lines
    if method == "synthetic" and compact is not None:
        return mt.release_synthetic(compact, wl.cols, wl.spec, wl.p, lines, KEY, compact=True, **how)
    if method == "synthetic":
        return mt.release_synthetic(wl.points(s, d).select(*wl.cols), wl.cols, wl.spec, wl.p, lines, KEY, **how)
    fn = {"noisy_counts": mt.release_noisy_counts, "trimmed": mt.release_trimmed, "sampled_cut": mt.release_sampled_cut}[method]
    return fn(kept_counts(s, d, w) if counts is None else counts, wl.spec, wl.p, lines, KEY, **how)


def private_sql(w: str, method: str, eps: list[float] | None = None, reps: int = REPS, alpha: float | None = None, base: Query | None = None) -> Query:
    """Up to relation ``kept(eps_i, rep, wcell, w)`` and ``pcut(eps_i, rep, k_priv, d)``, with the clean ``band`` beside them."""
    wl = WORKLOADS[w]
    if method == "synthetic":
        q = _drawn(_adaptive_sql(w, eps or EPS, reps), w).add("pcut", "SELECT eps_i, rep, k AS k_priv, d FROM scut")
        return q.counts(w).haar(wl.spec)
    q = (base or clean(w)).runs(list(eps or EPS), reps)
    if method == "noisy_counts":
        q.noisy_band(wl.spec, KEY).cut(wl.p, "nband", "ncut", RUN).add("pcut", "SELECT eps_i, rep, k AS k_priv, d FROM ncut")
        return q.keep("nband", "pcut", "kept", RUN)
    if method == "trimmed":
        a = alpha or 0.9
        q.noisy_band(wl.spec, KEY, a).nonpositive(coarse(w)).noisy_z(KEY, 1 - a).add("drop_r", "SELECT eps_i, rep, CAST(floor(z_noisy / 2e0) AS BIGINT) AS r FROM zn")
        q.cut(wl.p, "nband", "ncut", RUN, "drop_r").add("pcut", "SELECT eps_i, rep, k AS k_priv, d FROM ncut")
        return q.keep("nband", "pcut", "kept", RUN)
    a = alpha or 0.7
    q.noisy_band(wl.spec, KEY, a).cut(wl.p, "band", "ccut").rank_intervals().sampled_cut(KEY, 1 - a, "ccut", "pcut")
    return q.keep("nband", "pcut", "kept", RUN, ">")


def _techniques() -> None:
    for w in ("w1", "w2", "w3", "w4"):
        for name, method in (("nq", "noisy_counts"), ("trim", "trimmed"), ("cut_release", "sampled_cut")):
            sql = private_sql(w, method).components(WORKLOADS[w].spec.coarse(1), by=RUN).select("SELECT eps_i, rep, wcell, cluster FROM lab")
            register(f"{name}_{w}", lambda s, d, w=w, method=method: technique(s, d, w, method).cells.select(*RUN, "wcell", "cluster"), sql)
        register(f"syn_adaptive_{w}", lambda s, d, w=w: technique(s, d, w, "synthetic").cells, _drawn_sql(_adaptive_sql(w), w))
    for publisher in ("quadtree", "kd", "wavelet"):
        leaves = {"quadtree": _quadtree_sql, "kd": _kd_sql, "wavelet": _wavelet_sql}[publisher]("w2")
        register(f"publish_{publisher}_w2", lambda s, d, publisher=publisher: pu.PUBLISHERS[publisher](pts("w2")(s, d), ["x0", "x1"], WORKLOADS["w2"].spec, runs(s), KEY).select(*RUN, "leaf", r6("lo0"), r6("hi0"), r6("lo1"), r6("hi1"), r6("cnt")), leaves.select("SELECT eps_i, rep, leaf, round(lo0, 6) AS lo0, round(hi0, 6) AS hi0, round(lo1, 6) AS lo1, round(hi1, 6) AS hi1, round(cnt, 6) AS cnt FROM leaves"))
        register(f"syn_{publisher}_w2", lambda s, d, publisher=publisher: technique(s, d, "w2", "synthetic", publisher=publisher).cells, _drawn_sql(leaves, "w2"))
    uniform_leaves = _uniform_sql("w2")
    register("publish_uniform_w2", lambda s, d: pu.publish_uniform(pts("w2")(s, d), ["x0", "x1"], WORKLOADS["w2"].spec, runs(s), KEY).select(*RUN, "leaf", r6("lo0"), r6("hi0"), r6("lo1"), r6("hi1"), r6("cnt")), uniform_leaves.select("SELECT eps_i, rep, leaf, round(lo0, 6) AS lo0, round(hi0, 6) AS hi0, round(lo1, 6) AS lo1, round(hi1, 6) AS hi1, round(cnt, 6) AS cnt FROM leaves"))
    register("syn_uniform_w2", lambda s, d: technique(s, d, "w2", "synthetic", publisher="uniform").cells, _drawn_sql(_uniform_sql("w2"), "w2"))
    register("syn_areal_w2", lambda s, d: technique(s, d, "w2", "synthetic", synth="areal").cells, _areal_sql(_adaptive_sql("w2"), "w2"))
    register("publish_adaptive_w2", lambda s, d: pu.publish_adaptive(pts("w2")(s, d), ["x0", "x1"], WORKLOADS["w2"].spec, runs(s), KEY).select(*RUN, "leaf", r6("cnt")), _adaptive_sql("w2").select("SELECT eps_i, rep, leaf, round(cnt, 6) AS cnt FROM leaves"))
    cube = f"SELECT eps_i, rep, CAST(marginal AS INT) AS marginal, i0, i1, round(c + {duck.laplace(uniform(KEY, 'cube', 'eps_i', 'rep', 'place'), '4e0 / eps')}, 6) AS cnt FROM cu CROSS JOIN runs"
    spec = WORKLOADS["w2"].spec
    i, j = duck.unrolled("r.cell", spec.g)
    register("cube_marginals", lambda s, d: pu.publish_marginals(pts("w2")(s, d), ["x0", "x1"], spec, runs(s), KEY).select(*RUN, "marginal", "i0", "i1", r6("cnt")), Query().points("w2").counts("w2").runs(list(EPS), REPS).add("de", f"SELECT {i} AS i0, {j} AS i1, coalesce(cnt, 0) AS cnt FROM (SELECT unnest(range({spec.cells})) AS cell) r LEFT JOIN m USING (cell)").add("cu", "SELECT i0, i1, sum(cnt) AS c, grouping_id(i0, i1) AS marginal, coalesce(CAST(i0 AS VARCHAR), '*') || ',' || coalesce(CAST(i1 AS VARCHAR), '*') AS place FROM de GROUP BY CUBE (i0, i1)").select(cube))
    ab = clean("w2").runs(list(EPS), REPS)
    register("ablation_clean_counts_w2", lambda s, d: mt.release_ablation(kept_counts(s, d, "w2"), spec, 0.10, runs(s), KEY, "clean_counts").cells, ab.cut(0.10, "band", "ccut").rank_intervals().sampled_cut(KEY, 0.3, "ccut", "pcut").add("bb", "SELECT eps_i, rep, wcell, w FROM band CROSS JOIN runs").keep("bb", "pcut", "kept", RUN, ">").components(spec.coarse(1), by=RUN).select("SELECT eps_i, rep, wcell, cluster FROM lab"))
    ac = clean("w2").runs(list(EPS), REPS)
    register("ablation_clean_cut_w2", lambda s, d: mt.release_ablation(kept_counts(s, d, "w2"), spec, 0.10, runs(s), KEY, "clean_cut").cells, ac.noisy_band(spec, KEY, 0.7).cut(0.10, "band", "ccut").add("pcut", "SELECT eps_i, rep, d FROM runs CROSS JOIN ccut").keep("nband", "pcut", "kept", RUN).components(spec.coarse(1), by=RUN).select("SELECT eps_i, rep, wcell, cluster FROM lab"))


def _uniform_sql(w: str) -> Query:
    q = Query().points(w).runs(list(EPS), REPS)
    q.add("sides", "SELECT DISTINCT eps_i, eps, CAST(greatest(1, floor(sqrt((SELECT count(*) FROM pts) * eps / 10e0) + 0.5e0)) AS BIGINT) AS m FROM runs")
    q.add("lc", "SELECT eps_i, CAST(greatest(least(floor((x0 - 0e0) * m / 1e0), m - 1), 0) AS BIGINT) * m + CAST(greatest(least(floor((x1 - 0e0) * m / 1e0), m - 1), 0) AS BIGINT) AS leaf, count(*) AS c FROM pts CROSS JOIN sides GROUP BY ALL")
    noise = duck.laplace(uniform(KEY, "ugrid", "eps_i", "rep", "leaf"), "1e0 / eps")
    return q.add("leaves", f"SELECT eps_i, rep, leaf, 0e0 + leaf // m * (1e0 / m) AS lo0, 0e0 + (leaf // m + 1) * (1e0 / m) AS hi0, 0e0 + leaf % m * (1e0 / m) AS lo1, 0e0 + (leaf % m + 1) * (1e0 / m) AS hi1, coalesce(c, 0) + {noise} AS cnt FROM (SELECT eps_i, eps, m, unnest(range(m * m)) AS leaf FROM sides) d LEFT JOIN lc USING (eps_i, leaf) JOIN (SELECT eps_i, rep FROM runs) r USING (eps_i)")


def _adaptive_sql(w: str, eps=EPS, reps: int = REPS) -> Query:
    q = Query().points(w).runs(list(eps), reps)
    q.add("sides", "SELECT DISTINCT eps_i, eps, CAST(greatest(10, ceil(0.25e0 * sqrt((SELECT count(*) FROM pts) * eps / 10e0))) AS BIGINT) AS m FROM runs")
    q.add("placed", "SELECT eps_i, m, x0, x1, CAST(greatest(least(floor((x0 - 0e0) * m / 1e0), m - 1), 0) AS BIGINT) AS a, CAST(greatest(least(floor((x1 - 0e0) * m / 1e0), m - 1), 0) AS BIGINT) AS b FROM pts CROSS JOIN sides")
    q.add("tc", "SELECT eps_i, a * m + b AS top, count(*) AS c FROM placed GROUP BY ALL")
    v = f"coalesce(c, 0) + {duck.laplace(uniform(KEY, 'agrid1', 'eps_i', 'rep', 'top'), '1e0 / (eps * 0.5e0)')}"
    q.add("tops0", f"SELECT eps_i, rep, eps, m, top, {v} AS v FROM (SELECT eps_i, eps, m, unnest(range(m * m)) AS top FROM sides) d LEFT JOIN tc USING (eps_i, top) JOIN (SELECT eps_i, rep FROM runs) r USING (eps_i)")
    q.add("tops", "SELECT *, CAST(greatest(1, ceil(sqrt(greatest(v, 0e0) * (eps * 0.5e0) / 5e0))) AS BIGINT) AS m2 FROM tops0")
    inner = "CAST(greatest(least(floor((x0 - (0e0 + a * (1e0 / p.m))) / (1e0 / p.m) * m2), m2 - 1), 0) AS BIGINT) * m2 + CAST(greatest(least(floor((x1 - (0e0 + b * (1e0 / p.m))) / (1e0 / p.m) * m2), m2 - 1), 0) AS BIGINT)"
    q.add("lc", f"SELECT p.eps_i, t.rep, t.top, {inner} AS inr, count(*) AS c FROM placed p JOIN tops t ON t.eps_i = p.eps_i AND t.top = p.a * p.m + p.b GROUP BY ALL")
    u = f"coalesce(c, 0) + {duck.laplace(uniform(KEY, 'agrid2', 'eps_i', 'rep', 'top', 'inr'), '1e0 / (eps * 0.5e0)')}"
    q.add("us", f"SELECT eps_i, rep, m, top, inr, m2, v, {u} AS u FROM (SELECT *, unnest(range(m2 * m2)) AS inr FROM tops) d LEFT JOIN lc USING (eps_i, rep, top, inr)")
    return q.add("leaves", "SELECT eps_i, rep, CAST(top AS VARCHAR) || '.' || CAST(inr AS VARCHAR) AS leaf, (top // m * m2 + inr // m2) * (1e0 / (m * m2)) AS lo0, (top // m * m2 + inr // m2 + 1) * (1e0 / (m * m2)) AS hi0, (top % m * m2 + inr % m2) * (1e0 / (m * m2)) AS lo1, (top % m * m2 + inr % m2 + 1) * (1e0 / (m * m2)) AS hi1, u + ((0.25e0 * m2 * m2 * v + 0.25e0 * s) / (0.25e0 + 0.25e0 * m2 * m2) - s) / (m2 * m2) AS cnt FROM (SELECT *, sum(u) OVER (PARTITION BY eps_i, rep, top) AS s FROM us) q")


def _areal_sql(q: Query, w: str) -> str:
    """Rounded counts of ``leaves`` shared out by overlap, then the plain algorithm on them."""
    spec = WORKLOADS[w].spec
    g = spec.g[0]
    q.add("whole", "SELECT eps_i, rep, lo0, hi0, lo1, hi1, floor(greatest(cnt, 0e0) + 0.5e0) AS n FROM leaves WHERE floor(greatest(cnt, 0e0) + 0.5e0) > 0")
    for a in range(2):
        source = "whole" if a == 0 else "axis0"
        edge = lambda x, a=a: f"CAST(greatest(least(floor(({x}{a} {'+' if x == 'lo' else '-'} 1e-12) * {g}), {g - 1}), 0) AS BIGINT)"
        over = f"greatest(least(hi{a}, (i{a} + 1) / {num(g)}) - greatest(lo{a}, i{a} / {num(g)}), 0e0) / (hi{a} - lo{a})"
        q.add(f"axis{a}", f"SELECT *, {over} AS f{a} FROM (SELECT *, unnest(range({edge('lo')}, {edge('hi')} + 1)) AS i{a} FROM {source}) z")
    q.add("sm", f"SELECT eps_i, rep, i0 * {g} + i1 AS cell, round(sum(n * f0 * f1) * 1048576e0) / 1048576e0 AS cnt FROM axis1 GROUP BY ALL").haar(spec, 1, "sm", "sband", "eps_i, rep,")
    return q.cut(WORKLOADS[w].p, "sband", "scut", RUN).keep("sband", "scut", "kept", RUN).components(spec.coarse(1), by=RUN).select("SELECT eps_i, rep, wcell, cluster FROM lab")


def _drawn(q: Query, w: str) -> Query:
    """Synthetic points of ``leaves``, up to the cells that the plain algorithm keeps of them."""
    spec = WORKLOADS[w].spec
    q.add("drawn", "SELECT eps_i, rep, leaf, lo0, hi0, lo1, hi1, unnest(range(1, CAST(floor(greatest(cnt, 0e0) + 0.5e0) AS BIGINT) + 1)) AS j FROM leaves")
    xs = [f"lo{a} + (hi{a} - lo{a}) * {uniform(KEY, f'synth_x{a}', 'eps_i', 'rep', 'leaf', 'j')} AS x{a}" for a in range(2)]
    q.add("syn", f"SELECT eps_i, rep, {', '.join(xs)} FROM drawn").counts(w, "syn", "sm", "eps_i, rep,").haar(spec, 1, "sm", "sband", "eps_i, rep,")
    return q.cut(WORKLOADS[w].p, "sband", "scut", RUN).keep("sband", "scut", "kept", RUN)


def _drawn_sql(q: Query, w: str) -> str:
    """The plain algorithm on synthetic points of ``leaves``."""
    return _drawn(q, w).components(WORKLOADS[w].spec.coarse(1), by=RUN).select("SELECT eps_i, rep, wcell, cluster FROM lab")


def _dense_sql(w: str) -> Query:
    """``dense(cell, i, j, cnt)`` of a square grid beside the runs."""
    spec = WORKLOADS[w].spec
    i, j = duck.unrolled("r.cell", spec.g)
    return Query().points(w).counts(w).runs(list(EPS), REPS).add("dense", f"SELECT r.cell, {i} AS i, {j} AS j, coalesce(cnt, 0) AS cnt FROM (SELECT unnest(range({spec.cells})) AS cell) r LEFT JOIN m USING (cell)")


def _quadtree_sql(w: str) -> Query:
    """Level after level: counts and noise, estimates from the leaves up, agreement from the root down."""
    spec = WORKLOADS[w].spec
    h = (max(spec.g) - 1).bit_length()
    shares = [2 ** (i / 3) for i in range(h + 1)]
    shares = [x / sum(shares) for x in shares]
    q = Query().points(w).runs(list(EPS), REPS)
    part = lambda x, k: f"CAST(greatest(least(floor(({x} - 0e0) * {num(2**k)} / 1e0), {2**k - 1}), 0) AS BIGINT)"
    parent = lambda k: f"(node // {2**k} // 2 * {2 ** (k - 1)} + node % {2**k} // 2)"
    for k, share in enumerate(shares):
        draw = duck.laplace(uniform(KEY, "quad", "eps_i", "rep", str(k), "d.node"), f"1e0 / (eps * {num(share)})")
        q.add(f"v{k}", f"SELECT eps_i, rep, d.node, coalesce(c, 0) + {draw} AS v FROM (SELECT unnest(range({4**k})) AS node) d LEFT JOIN (SELECT {part('x0', k)} * {2**k} + {part('x1', k)} AS node, count(*) AS c FROM pts GROUP BY 1) n ON n.node = d.node CROSS JOIN runs")
    q.add(f"z{h}", f"SELECT eps_i, rep, node, v AS z FROM v{h}")
    var = 1 / shares[h] ** 2
    for k in range(h - 1, -1, -1):
        below, own = 4 * var, 1 / shares[k] ** 2
        q.add(f"p{k}", f"SELECT eps_i, rep, {parent(k + 1)} AS node, sum(z) AS s FROM z{k + 1} GROUP BY ALL")
        q.add(f"z{k}", f"SELECT eps_i, rep, node, (v * {num(below)} + s * {num(own)}) / {num(below + own)} AS z FROM v{k} JOIN p{k} USING (eps_i, rep, node)")
        var = below * own / (below + own)
    q.add("t0", "SELECT eps_i, rep, node, z AS t FROM z0")
    for k in range(1, h + 1):
        q.add(f"t{k}", f"SELECT c.eps_i, c.rep, c.node, c.z + (t.t - p.s) / 4e0 AS t FROM (SELECT *, {parent(k)} AS up FROM z{k}) c JOIN t{k - 1} t ON t.eps_i = c.eps_i AND t.rep = c.rep AND t.node = c.up JOIN p{k - 1} p ON p.eps_i = c.eps_i AND p.rep = c.rep AND p.node = c.up")
    side = 2**h
    return q.add("leaves", f"SELECT eps_i, rep, node AS leaf, 0e0 + node // {side} * (1e0 / {side}) AS lo0, 0e0 + (node // {side} + 1) * (1e0 / {side}) AS hi0, 0e0 + node % {side} * (1e0 / {side}) AS lo1, 0e0 + (node % {side} + 1) * (1e0 / {side}) AS hi1, t AS cnt FROM t{h}")


def _kd_sql(w: str, height: int = 6) -> Query:
    """Boxes of cells split in turn at drawn medians."""
    g = WORKLOADS[w].spec.g
    q = _dense_sql(w).add("b0", f"SELECT eps_i, rep, eps, i, j, cnt, 0 AS box, 0 AS f0, {g[0]} AS t0, 0 AS f1, {g[1]} AS t1 FROM dense CROSS JOIN runs")
    for k in range(height):
        a, c = k % 2, "ij"[k % 2]
        q.add(f"l{k}", f"SELECT *, sum(s) OVER (PARTITION BY eps_i, rep, box ORDER BY {c}) AS below, sum(s) OVER (PARTITION BY eps_i, rep, box) AS total FROM (SELECT eps_i, rep, eps, box, t{a} AS t, {c}, sum(cnt) AS s FROM b{k} GROUP BY ALL) z")
        u = uniform(KEY, "kd", "eps_i", "rep", str(k), "box", f"({c} + 1)")
        q.add(f"c{k}", f"SELECT eps_i, rep, box, arg_max({c} + 1, eps * {num(0.3 / height / 2)} * -abs(below - total / 2e0) - ln(-ln({u}))) AS cut FROM l{k} WHERE {c} + 1 < t GROUP BY ALL")
        q.add(f"b{k + 1}", f"SELECT eps_i, rep, eps, i, j, cnt, box * 2 + CASE WHEN {c} >= cut THEN 1 ELSE 0 END AS box, {', '.join(x for y in (0, 1) for x in ((f'CASE WHEN {c} >= cut THEN cut ELSE f{y} END AS f{y}', f'CASE WHEN {c} < cut THEN cut ELSE t{y} END AS t{y}') if y == a else (f'f{y}', f't{y}')))} FROM b{k} LEFT JOIN c{k} USING (eps_i, rep, box)")
    draw = duck.laplace(uniform(KEY, "kdleaf", "eps_i", "rep", "box"), f"1e0 / (eps * {num(1 - 0.3)})")
    return q.add("leaves", f"SELECT eps_i, rep, CAST(box AS BIGINT) AS leaf, f0 / {num(g[0])} AS lo0, t0 / {num(g[0])} AS hi0, f1 / {num(g[1])} AS lo1, t1 / {num(g[1])} AS hi1, c + {draw} AS cnt FROM (SELECT eps_i, rep, eps, box, f0, t0, f1, t1, sum(cnt) AS c FROM b{height} GROUP BY ALL) z")


def _wavelet_sql(w: str) -> Query:
    """Every cell with the noise of all coefficients above it."""
    g = WORKLOADS[w].spec.g
    wide = [1 << (k - 1).bit_length() for k in g]
    rho = (wide[0].bit_length()) * (wide[1].bit_length())
    scales = [", ".join(f"({s})" for s in [0, *[1 << x for x in range(k.bit_length() - 1)]]) for k in wide]
    coef = lambda c, s, k: f"({s} + {c} * {s} // {k})"
    sign = lambda c, s, k: f"(CASE WHEN {s} > 0 AND {c} * {s} * 2 // {k} % 2 = 1 THEN -1e0 ELSE 1e0 END)"
    weight = " * ".join(f"({num(k)} / greatest(s{a}, 1))" for a, k in enumerate(wide))
    draw = duck.laplace(uniform(KEY, "wave", "eps_i", "rep", coef("i", "s0", wide[0]), coef("j", "s1", wide[1])), f"({num(2 * rho)} / eps / ({weight}))")
    q = _dense_sql(w).add("noise", f"SELECT eps_i, rep, cell, i, j, cnt, sum({sign('i', 's0', wide[0])} * {sign('j', 's1', wide[1])} * {draw}) AS x FROM dense CROSS JOIN runs CROSS JOIN (VALUES {scales[0]}) a(s0) CROSS JOIN (VALUES {scales[1]}) b(s1) GROUP BY ALL")
    return q.add("leaves", f"SELECT eps_i, rep, cell AS leaf, 0e0 + i * (1e0 / {g[0]}) AS lo0, 0e0 + (i + 1) * (1e0 / {g[0]}) AS hi0, 0e0 + j * (1e0 / {g[1]}) AS lo1, 0e0 + (j + 1) * (1e0 / {g[1]}) AS hi1, cnt + x AS cnt FROM noise")


for _part in (_quantize, _wavelets, _thresholds, _components, _mechanisms, _techniques):
    _part()
