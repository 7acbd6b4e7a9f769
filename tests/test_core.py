"""The algorithm's steps by hand, on fixtures, and against theory."""

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from dpgrid.experiments import bridge_record
from dpgrid.functions.keyed import keyed_uniform, laplace
from dpgrid.operators import bounds, measures, methods, publish, tree
from dpgrid.operators.assignment import assign, matching_cost
from dpgrid.operators.components import connected_components, label_array
from dpgrid.operators.grid import GridSpec, coordinates, linear, unit
from dpgrid.operators.privacy import Ledger, exponential_cut, private_haar, private_quantize, runs_frame
from dpgrid.operators.quantize import bounds_from_data, densify, quantize, quantize_vec
from dpgrid.operators.threshold import bracket_cut, count_signs, percentile_cut, rank_intervals, significant_cells, top_count
from dpgrid.operators.wavelet import REGISTRY, Wavelet, influence, register_wavelet, sensitivity_rank, sensitivity_z, wavelet_transform
from tests.conftest import SF_SMALL


def points(spark, rows, names="x0 double, x1 double"):
    return spark.createDataFrame(rows, names)


def band_of(spark, values):
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(values)], "wcell long, w double")


def labels(spark, sets, run=None):
    rows = [((*run,) if run else ()) + (c, min(s)) for s in sets for c in s]
    return spark.createDataFrame(rows, ("eps_i int, rep int, " if run else "") + "wcell long, cluster long")


def test_cells_at_edges_and_bad_coordinates(spark):
    spec = GridSpec((0.0, 0.0), (1.0, 2.0), (4, 5))
    rows = [(0.0, 0.0), (1.0, 2.0), (0.25, 0.4), (-3.0, 9.0), (None, 1.0), (float("nan"), 1.0), (0.2499, 0.3999)]
    got = {r["cell"]: r["cnt"] for r in quantize(points(spark, rows), ["x0", "x1"], spec).collect()}
    assert got == {0: 2, 19: 1, 6: 1, 4: 1}
    assert sum(r["cnt"] for r in quantize(points(spark, rows), ["x0", "x1"], spec, (), "drop").collect()) == 4
    with pytest.raises(Exception, match="outside"):
        quantize(points(spark, rows), ["x0", "x1"], spec, (), "error").collect()
    assert densify(quantize(points(spark, rows), ["x0", "x1"], spec), spec).count() == 20


def test_empty_and_vector_points(spark):
    spec = unit(4)
    empty = points(spark, [])
    assert quantize(empty, ["x0", "x1"], spec).count() == 0
    assert methods.cluster_grid(empty, ["x0", "x1"], spec, 0.1).cells.count() == 0
    v = spark.createDataFrame([([0.1, 0.9],), ([0.6],), (None,), ([0.6, None],), ([0.6, 0.6, 5.0],)], "v array<double>")
    assert {r["cell"] for r in quantize_vec(v, "v", spec).collect()} == {3, 10}
    b = bounds_from_data(points(spark, [(1.0, 2.0), (3.0, 7.0)]), ["x0", "x1"], (2, 2))
    assert (b.lo, b.hi) == ((1.0, 2.0), (3.0, 7.0))


def test_linear_and_coordinates_invert(spark):
    g = (3, 4, 5)
    df = spark.range(60).select("id", linear(coordinates(F.col("id"), g), g).alias("back"))
    assert all(r["id"] == r["back"] for r in df.collect())


def matrix(spark, m):
    g = m.shape
    return spark.createDataFrame([(int(np.ravel_multi_index(i, g)), int(m[i])) for i in np.ndindex(*g)], "cell long, cnt long")


def test_haar_by_hand_and_energy(spark):
    m = np.arange(16).reshape(4, 4) ** 2 % 7
    spec = GridSpec((0.0, 0.0), (1.0, 1.0), (4, 4))
    w = {r["wcell"]: r["w"] for r in wavelet_transform(matrix(spark, m), spec).collect()}
    want = m.reshape(2, 2, 2, 2).sum((1, 3)).ravel() / 2
    assert [w.get(i, 0.0) for i in range(4)] == pytest.approx(list(want))
    every = wavelet_transform(matrix(spark, m), spec, bands="all").collect()
    assert sum(r["w"] ** 2 for r in every) == pytest.approx(float((m**2).sum()))
    mean = wavelet_transform(matrix(spark, m), spec, scale="mean").collect()
    assert sorted(r["w"] for r in mean) == pytest.approx(sorted(want / 2))
    assert {r["band"] for r in every} == {"LL", "LH", "HL", "HH"}


@pytest.mark.parametrize("name", ["haar", "db2", "db3", "bior2.2"])
def test_wavelets_keep_constants_and_shift(spark, name):
    spec = GridSpec((0.0, 0.0), (1.0, 1.0), (12, 12))
    flat = {r["wcell"]: r["w"] for r in wavelet_transform(matrix(spark, np.ones((12, 12))), spec, name).collect()}
    assert len(flat) == 36 and all(v == pytest.approx(2.0) for v in flat.values())
    m = np.zeros((12, 12))
    m[3, 5], m[8, 2] = 4, 7
    a = {r["wcell"]: r["w"] for r in wavelet_transform(matrix(spark, m), spec, name).collect()}
    b = {r["wcell"]: r["w"] for r in wavelet_transform(matrix(spark, np.roll(m, (2, 4), (0, 1))), spec, name).collect()}
    for cell, v in a.items():
        i, j = divmod(cell, 6)
        assert b.get((i + 1) % 6 * 6 + (j + 2) % 6, 0.0) == pytest.approx(v)


def test_orthogonal_filter_keeps_energy_and_levels(spark):
    m = np.random.default_rng(0).integers(0, 9, (16, 16))
    spec = GridSpec((0.0, 0.0), (1.0, 1.0), (16, 16))
    every = wavelet_transform(matrix(spark, m), spec, "db2", bands="all").collect()
    assert sum(r["w"] ** 2 for r in every) == pytest.approx(float((m**2).sum()))
    two = {r["wcell"]: r["w"] for r in wavelet_transform(matrix(spark, m), spec, level=2).collect()}
    assert [two[i] for i in range(16)] == pytest.approx(list(m.reshape(4, 4, 4, 4).sum((1, 3)).ravel() / 4))
    odd = wavelet_transform(matrix(spark, np.ones((5, 3))), GridSpec((0.0, 0.0), (1.0, 1.0), (5, 3)))
    assert sorted(r["w"] for r in odd.collect()) == [0.5, 1.0, 1.0, 1.0, 2.0, 2.0]
    line = GridSpec((0.0,), (1.0,), (8,))
    one = wavelet_transform(spark.createDataFrame([(i, i) for i in range(8)], "cell long, cnt long"), line)
    assert sorted(r["w"] for r in one.collect()) == pytest.approx([x / math.sqrt(2) for x in (1, 5, 9, 13)])


def test_own_wavelet_and_sensitivities():
    assert [(sensitivity_z(n), sensitivity_rank(n)) for n in ("haar", "db2", "bior2.2")] == [(1, 1), (4, 4), (5, 9)]
    assert influence("bior2.2", 2) == [(5, 4), (4, 0), (2, 4)]
    assert sensitivity_rank("haar", 2, "replace") == 2 and sensitivity_z("haar", 2, "replace") == 1
    register_wavelet(Wavelet("mine", (0.5, 0.5), (0.5, -0.5)))
    assert sensitivity_z("mine", 3) == 1 and "mine" in REGISTRY


def test_rank_rule(spark):
    row = spark.range(1).select(top_count(F.lit(159), 0.10).alias("k"), top_count(F.lit(10), 0.5).alias("h")).first()
    assert (row["k"], row["h"]) == (144, 5)
    cut = percentile_cut(band_of(spark, [5, 3, 3, 2, 0.5, 0, -4]), 0.5).first()
    assert (cut["n_pos"], cut["k"], cut["d"]) == (5, 3, 3.0)
    cells, _ = significant_cells(band_of(spark, [5, 3, 3, 2, 0.5, 0, -4]), p=0.6)
    assert {r["wcell"] for r in cells.collect()} == {0, 1, 2}  # a tie at the cut stays
    strict, _ = significant_cells(band_of(spark, [5, 3, 3, 2, 0.5]), p=0.6, ties="strict")
    assert {r["wcell"] for r in strict.collect()} == {0}
    assert significant_cells(band_of(spark, [0, -1]), p=0.1)[0].count() == 0
    b = band_of(spark, np.random.default_rng(1).exponential(5, 500).round(3))
    assert bracket_cut(b, 0.3).first()["d"] == percentile_cut(b, 0.3).first()["d"]


def test_rank_intervals(spark):
    got = [(r["lo"], r["hi"], r["rank"]) for r in rank_intervals(band_of(spark, [5, 3, 3, 2, 0.5])).orderBy("rank").collect()]
    assert got == [(3.0, 5.0, 1), (2.0, 3.0, 3), (0.5, 2.0, 4), (0.0, 0.5, 5)]
    top = rank_intervals(band_of(spark, [5, 3]), upper=9.0).where("rank = 0").first()
    assert (top["lo"], top["hi"]) == (5.0, 9.0)


def test_components_agree(spark):
    rng = np.random.default_rng(3)
    for g, full in (((20, 20), False), ((9, 7), True), ((6, 5, 4), False)):
        cells = np.sort(rng.choice(int(np.prod(g)), int(np.prod(g) * 0.45), replace=False))
        adjacency = "full" if full else "face"
        want = dict(zip(cells.tolist(), brute_components(cells.tolist(), g, full), strict=True))
        assert dict(zip(cells.tolist(), label_array(cells, g, adjacency).tolist(), strict=True)) == want
        df = spark.createDataFrame([(int(c), 1.0) for c in cells], "wcell long, w double")
        for strategy in ("local", "iterate", "tiled"):
            got = {r["wcell"]: r["cluster"] for r in connected_components(df, g, (), adjacency, strategy, tile=4).collect()}
            assert got == want, (g, strategy)


def brute_components(cells, g, full):
    at = {c: np.unravel_index(c, g) for c in cells}
    label = {c: c for c in cells}
    moved = True
    while moved:
        moved = False
        for a, b in itertools.combinations(cells, 2):
            d = [abs(int(x) - int(y)) for x, y in zip(at[a], at[b], strict=True)]
            if (max(d) == 1 if full else sum(d) == 1) and label[a] != label[b]:
                label[a] = label[b] = min(label[a], label[b])
                moved = True
    return [label[c] for c in cells]


def test_one_record_bridges_clusters(spark):
    got = {r["data"]: (r["k"], r["clusters"]) for r in bridge_record(spark, SF_SMALL).collect()}
    assert got == {"without": (9, 2), "with": (10, 1)}


def test_noise_law_and_keying(spark):
    u = keyed_uniform("k", "count", F.col("id"))
    df = spark.range(100_000).select("id", laplace(u, 1.0).alias("x"), u.alias("u"))
    x = np.sort(np.array([r["x"] for r in df.collect()]))
    cdf = np.where(x < 0, 0.5 * np.exp(x), 1 - 0.5 * np.exp(-x))
    assert np.abs(cdf - np.arange(len(x)) / len(x)).max() < 0.006
    assert abs(x.mean()) < 0.02 and abs(x.var() - 2) < 0.06
    again = {r["id"]: r["x"] for r in df.repartition(7).where("id < 50").collect()}
    assert again == {r["id"]: r["x"] for r in df.where("id < 50").collect()}
    secret = spark.range(10).select(keyed_uniform("k", "count", F.col("id"), source="secret").alias("u")).collect()
    assert all(0 < r["u"] < 1 for r in secret)


def test_fused_noise_equals_unfused(spark):
    spec, runs = GridSpec((0.0, 0.0), (1.0, 1.0), (6, 7)), runs_frame(spark, [0.5, 2.0], 2)
    m = matrix(spark, np.random.default_rng(0).integers(0, 5, (6, 7)))
    a = {(r["eps_i"], r["rep"], r["wcell"]): r["w"] for r in private_haar(m, spec, runs, "k").collect()}
    b = {(r["eps_i"], r["rep"], r["wcell"]): r["w"] for r in wavelet_transform(private_quantize(m, spec, runs, "k"), spec, value="cnt_noisy", by=("eps_i", "rep")).collect()}
    assert a.keys() == b.keys() and all(a[k] == pytest.approx(b[k]) for k in a)
    single = private_haar(m, spec, runs.where("eps_i = 1 and rep = 1"), "k").collect()
    assert all(a[(1, 1, r["wcell"])] == r["w"] for r in single)


def test_sum_of_four_tail(spark):
    row = spark.range(1).select(bounds.tail(F.lit(0.5)).alias("a"), bounds.tail(F.lit(1.0)).alias("b")).first()
    s = np.random.default_rng(0).laplace(0, 1, (400_000, 4)).sum(1)
    assert row["a"] == pytest.approx((s <= -0.5).mean(), abs=0.004) and row["b"] == pytest.approx((s <= -1).mean(), abs=0.004)


@pytest.mark.parametrize("sampler", ["gumbel", "cumulative"])
def test_exponential_mechanism_law(spark, sampler):
    values, k, eps = [5, 3, 3, 2, 0.5], 3, 1.5
    runs = runs_frame(spark, [eps], 4000)
    b = band_of(spark, values)
    drawn = exponential_cut(rank_intervals(b), percentile_cut(b, 0.4).select(F.lit(k).alias("k")), runs, "law", 1.0, 1, sampler).groupBy("k_priv").count().collect()
    got = {r["k_priv"]: r["count"] / 4000 for r in drawn}
    weight = {r: w * math.exp(-eps * abs(r - k) / 2) for r, w in ((1, 2.0), (3, 1.0), (4, 1.5), (5, 0.5))}
    for r, w in weight.items():
        assert got.get(r, 0) == pytest.approx(w / sum(weight.values()), abs=0.03)


def test_ledger():
    ledger = Ledger(1.0)
    ledger.parallel([0.9, 0.4], "counts")
    ledger.spend(0.1, "z")
    assert ledger.spent() == pytest.approx(1.0)
    with pytest.raises(ValueError):
        ledger.spend(0.01, "more")
    with pytest.raises(ValueError):
        Ledger(1.0).spend(0, "none")


@pytest.mark.parametrize("alpha", [0.0, 1.0])
def test_split_bounds(spark, alpha):
    m = matrix(spark, np.ones((4, 4)))
    for fn in (methods.release_trimmed, methods.release_sampled_cut):
        with pytest.raises(ValueError):
            fn(m, unit(4), 0.1, runs_frame(spark, [1.0]), "k", alpha)


def test_releases_hide_clean_values_and_survive_nothing(spark):
    runs = runs_frame(spark, [0.1], 2)
    empty = spark.createDataFrame([], "cell long, cnt long")
    for fn in (methods.release_noisy_counts, methods.release_trimmed, methods.release_sampled_cut):
        for counts in (empty, matrix(spark, np.eye(4) * 30)):
            made = fn(counts, unit(4), 0.1, runs, "k")
            assert set(made.cells.columns) == {"eps_i", "rep", "wcell", "cluster"}
            assert set(made.cut.columns) == {"eps_i", "rep", "k_priv", "d_priv"}
            made.cells.count()


def test_cluster_distance_and_matching(spark):
    d = measures.cluster_distance(labels(spark, [{1, 3, 5}]), labels(spark, [{1, 5, 7, 9}], (0, 0))).first()
    assert d["distance"] == 2
    runs = runs_frame(spark, [1.0])
    g = measures.grid_cluster_dissimilarity(labels(spark, [{1, 2}, {3}]), labels(spark, [{1}, {2, 3}], (0, 0)), runs).first()
    assert (g["cost"], g["gcd"]) == (2.0, pytest.approx(2 / 3))
    none = measures.grid_cluster_dissimilarity(labels(spark, [{1, 2}, {3}]), labels(spark, [{1}], (0, 1)), runs).where("rep = 0").first()
    assert none["gcd"] == 1.0


def test_assignment_is_least():
    rng = np.random.default_rng(5)
    for _ in range(60):
        n = int(rng.integers(1, 7))
        c = rng.integers(0, 9, (n, n)).astype(float)
        want = min(sum(c[i, p[i]] for i in range(n)) for p in itertools.permutations(range(n)))
        assert matching_cost(c) == want and sorted(assign(c)) == list(range(n)) and matching_cost(c.T) == want


def test_f_measure_of_split_and_equal(spark):
    runs = runs_frame(spark, [1.0])
    t = labels(spark, [{1, 2, 3, 4}, {10, 11}])
    assert measures.f_measure(t, labels(spark, [{1, 2, 3, 4}, {10, 11}], (0, 0)), runs).first()["f"] == pytest.approx(1.0)
    split = measures.f_measure(t, labels(spark, [{1, 2, 3}, {4}, {10, 11}], (0, 0)), runs).first()["f"]
    assert split == pytest.approx((4 * (6 / 7) + 2) / 6)
    weights = spark.createDataFrame([(c, 1.0) for c in (1, 2, 3, 4, 10, 11)], "wcell long, weight double")
    assert measures.f_measure(t, labels(spark, [{1, 2, 3}, {4}, {10, 11}], (0, 0)), runs, weights=weights).first()["f"] == pytest.approx(split)


def test_pair_measures(spark):
    rows = [(0, 0, i, a, b) for i, (a, b) in enumerate([(1, 7), (1, 7), (2, 7), (2, 8)])]
    df = spark.createDataFrame(rows, "eps_i int, rep int, point_id long, pred_t long, pred_p long")
    assert measures.class_matching_dissimilarity(df).first()["cmd"] == pytest.approx(0.25)
    assert measures.pair_disagreement(df).first()["ppd"] == pytest.approx(0.5)
    rng = np.random.default_rng(2)
    rows = [(0, r, i, int(rng.integers(4)), int(rng.integers(3))) for r in range(2) for i in range(120)]
    df = spark.createDataFrame(rows, df.schema)
    fast = {r["rep"]: r["ppd"] for r in measures.pair_disagreement(df).collect()}
    slow = {r["rep"]: r["ppd"] for r in measures.pair_disagreement_exact(df).collect()}
    assert fast == pytest.approx(slow)
    one = df.where("point_id = 0")
    assert measures.pair_disagreement(one).first()["ppd"] is None
    flipped = [(0, 0, i, int(i % 3), int(i % 3) if i > 4 else 9) for i in range(50)]
    assert measures.pair_disagreement(spark.createDataFrame(flipped, df.schema)).first()["ppd"] <= measures.pair_flip_bound(5, 50)


def test_negative_counts_cancel_in_ranges_but_not_in_points(spark):
    leaves = spark.createDataFrame([(0, 0, 1, 0.0, 1.0, 0.0, 1.0, -2.0), (0, 0, 2, 1.0, 2.0, 0.0, 1.0, 14.0)], "eps_i int, rep int, leaf long, lo0 double, hi0 double, lo1 double, hi1 double, cnt double")
    boxes = spark.createDataFrame([(1, 0.0, 2.0, 0.0, 1.0)], "box int, qlo0 double, qhi0 double, qlo1 double, qhi1 double")
    assert publish.range_count(leaves, boxes).first()["estimate"] == pytest.approx(12.0)
    assert publish.sample_boxes(leaves, "k").count() == 14
    areal = publish.areal_counts(leaves, GridSpec((0.0, 0.0), (2.0, 1.0), (4, 2)))
    assert areal.agg(F.sum("cnt")).first()[0] == pytest.approx(14.0)


@pytest.mark.parametrize("publisher", ["contingency", "uniform", "adaptive_grid", "quadtree", "kd", "wavelet"])
def test_publishers_with_large_budget_find_the_points(spark, publisher):
    rng = np.random.default_rng(0)
    rows = [tuple(map(float, x)) for x in np.clip(rng.normal((0.3, 0.6), 0.05, (400, 2)), 0, 1)]
    spec, runs = unit(8), runs_frame(spark, [200.0])
    how = {"height": 4} if publisher == "quadtree" else {}
    leaves = publish.PUBLISHERS[publisher](points(spark, rows), ["x0", "x1"], spec, runs, "k", **how)
    total = leaves.agg(F.sum("cnt")).first()[0]
    assert total == pytest.approx(400, rel=0.05)
    box = spark.createDataFrame([(1, 0.1, 0.5, 0.4, 0.8)], "box int, qlo0 double, qhi0 double, qlo1 double, qhi1 double")
    assert publish.range_count(leaves, box).first()["estimate"] == pytest.approx(400, rel=0.3)


@pytest.mark.parametrize("publisher", ["contingency", "uniform", "adaptive_grid", "quadtree", "kd", "wavelet"])
def test_publishers_follow_secret_and_neighbour_rule(spark, publisher):
    """A secret source draws anew; a replaced record doubles the noise of the same draws."""
    spec, runs, rows = unit(4), runs_frame(spark, [0.5]), [(0.1, 0.1), (0.9, 0.4), (0.6, 0.7)]
    leaves = lambda **how: {r["leaf"]: r["cnt"] for r in publish.PUBLISHERS[publisher](points(spark, rows), ["x0", "x1"], spec, runs, "k", **how).collect()}
    plain, again, secret, double = leaves(), leaves(), leaves(source="secret"), leaves(sensitivity=2)
    assert plain == pytest.approx(again)
    assert all(abs(plain[x] - secret.get(x, 1e9)) > 1e-9 for x in plain)
    if publisher in ("contingency", "wavelet"):
        clean = {r["leaf"]: r["cnt"] for r in publish.publish_contingency(points(spark, rows), ["x0", "x1"], spec, runs_frame(spark, [1e12]), "k").collect()}
        assert all(double[x] - clean[x] == pytest.approx(2 * (plain[x] - clean[x]), abs=1e-6) for x in plain)
    else:
        assert any(abs(plain.get(x, 1e9) - double[x]) > 1e-9 for x in double)


def test_synthetic_release_takes_its_options(spark):
    spec, runs, rows = unit(8), runs_frame(spark, [0.5]), [(x / 40, (x * 7 % 40) / 40) for x in range(40)] * 5
    band = lambda **o: {r["wcell"]: r["w"] for r in methods.release_synthetic(points(spark, rows), ["x0", "x1"], spec, 0.1, runs, "k", o=methods.Options(**o)).band.collect()}
    plain = band()
    assert band(source="secret") != plain and band(neighbor="replace") != plain
    with pytest.raises(ValueError):
        band(noise="geometric")


def test_quadtree_is_as_fine_as_the_grid(spark):
    leaves = publish.publish_quadtree(points(spark, [(0.5, 0.5)]), ["x0", "x1"], GridSpec((0.0, 0.0), (1.0, 1.0), (300, 2)), runs_frame(spark, [1e9]), "k")
    assert leaves.count() == 512**2 and leaves.where("cnt > 0.5").count() == 1


def test_adaptive_leaves_have_names_of_their_own(spark):
    """More than a thousand parts a side in one first-level cell."""
    leaves = publish.publish_adaptive(points(spark, [(0.05, 0.05)]), ["x0", "x1"], unit(4), runs_frame(spark, [1e8]), "k", n_hint=1.0)
    assert leaves.count() == leaves.select("leaf").distinct().count() > 1000**2


def test_trim_keeps_a_value_and_rounds_as_told(spark):
    band = band_of(spark, [5, 4, 3, 2, 1, -1])
    drop = lambda r: spark.createDataFrame([(r,)], "r long")
    assert percentile_cut(band, 0.0, drop=drop(100)).first()["k"] == 1 and percentile_cut(band, 0.0, drop=drop(-5)).first()["k"] == 5
    for cut in (percentile_cut, bracket_cut):
        assert tuple(cut(band, 0.25, drop=drop(2)).select("n_pos", "k", "d").first()) == (5, 3, 3.0)
    counts = spark.createDataFrame([(i, 100) for i in range(48)], "cell long, cnt long")  # twelve positive blocks of sixteen
    k = [methods.release_trimmed(counts, unit(8), 0.0, runs_frame(spark, [50.0]), "k", trim_rounding=x).cut.first()["k_priv"] for x in ("floor", "round", "ceil")]
    assert k[0] >= k[1] >= k[2] and k[0] == k[2] + 1


def test_cuts_in_a_bracket_equal_those_of_the_whole(spark, monkeypatch):
    """Many runs, ties, a bracket at either end; and a release that goes that way."""
    band = spark.range(60_000).select((F.col("id") % 3).cast("int").alias("run"), F.col("id").alias("wcell"), (F.hash("id") % 5000 / F.when(F.col("id") % 3 == 0, 1.0).otherwise(1e6)).alias("w"))
    for p in (0.0, 0.001, 0.37, 0.999):
        whole = {r["run"]: (r["n_pos"], r["k"], r["d"]) for r in percentile_cut(band, p, ["run"]).collect()}
        assert {r["run"]: (r["n_pos"], r["k"], r["d"]) for r in bracket_cut(band, p, ["run"]).collect()} == whole and len(whole) == 3
    counts = spark.createDataFrame([(i, 10 * i % 37) for i in range(64)], "cell long, cnt long")
    cut = lambda: methods.release_trimmed(counts, unit(8), 0.3, runs_frame(spark, [0.7], 3), "k").cut.orderBy("rep").collect()
    plain = cut()
    monkeypatch.setattr(methods, "LARGE_BAND", 1)
    assert cut() == plain


def test_large_grids_are_labelled_by_tiles(spark, monkeypatch):
    from dpgrid.operators import components

    cells = spark.createDataFrame([(c,) for c in (0, 19, 200, 201, 380, 399)], "wcell long")
    got = lambda **how: {r["wcell"]: r["cluster"] for r in connected_components(cells, (20, 20), **how).collect()}
    for periodic in (False, True):
        for adjacency in ("face", "full"):
            want = got(strategy="local", periodic=periodic, adjacency=adjacency)
            assert got(strategy="tiled", tile=8, periodic=periodic, adjacency=adjacency) == want == got(strategy="tiled", periodic=periodic, adjacency=adjacency)
    assert want[0] == want[19] == want[399] == want[380] == 0
    monkeypatch.setattr(components, "LOCAL_CELLS", 10)
    assert got(strategy="auto", periodic=True, adjacency="full") == want


def test_counted_samples_equal_listed_ones(spark):
    rows = [(0, 0, a, b) for a, b in [(1, 1)] * 5 + [(1, 2)] * 3 + [(2, 2)] * 4]
    listed = spark.createDataFrame(rows, "eps_i int, rep int, pred_t long, pred_p long")
    counted = listed.groupBy("eps_i", "rep", "pred_t", "pred_p").agg(F.count(F.lit(1)).alias("n"))
    for fn in (measures.pair_disagreement, measures.class_matching_dissimilarity):
        assert fn(listed).collect() == fn(counted, weight="n").collect()


def test_tree_learns_separable_cells(spark):
    g = (10, 10)
    cells = [(i * 10 + j, 0 if i < 4 else (1 if j < 5 else 2)) for i in range(10) for j in range(10) if i not in (4, 5)]
    df = spark.createDataFrame(cells, "wcell long, cluster long")
    leaves = tree.fit_tree(df, g, ())
    assert leaves.count() == 3
    pred = {r["wcell"]: r["pred"] for r in tree.predict_cells(leaves, GridSpec((0.0, 0.0), (1.0, 1.0), (20, 20)), 1, ()).collect()}
    assert len(pred) == 100 and all(pred[c] == lab for c, lab in cells)
    assert tree.best_split(np.array([[0.0], [1.0], [2.0], [3.0]]), np.array([0, 0, 1, 1]), 2) == (0, 1.5)
    one = tree.grow(np.array([[0.0], [1.0]]), np.array([7, 7]))
    assert len(one) == 1 and one[0][2] == 7


def test_tree_close_to_spark_ml(spark):
    from pyspark.ml.classification import DecisionTreeClassifier
    from pyspark.ml.feature import VectorAssembler

    rng = np.random.default_rng(1)
    cells = [(i * 16 + j, int((i - 8) ** 2 + (j - 8) ** 2 < 30)) for i in range(16) for j in range(16) if rng.random() < 0.8]
    df = spark.createDataFrame(cells, "wcell long, cluster long")
    ours = tree.predict_cells(tree.fit_tree(df, (16, 16), ()), GridSpec((0.0, 0.0), (1.0, 1.0), (32, 32)), 1, ())
    rows = VectorAssembler(inputCols=["w0", "w1"], outputCol="features").transform(tree.training_rows(df, (16, 16)).withColumn("label", F.col("cluster").cast("double")))
    model = DecisionTreeClassifier(impurity="entropy", maxDepth=10, maxBins=64).fit(rows)
    both = model.transform(rows).select("wcell", "prediction").join(ours, "wcell")
    assert both.agg(F.avg((F.col("prediction") == F.col("pred")).cast("double"))).first()[0] >= 0.95


def test_neighbours_differ_as_the_sensitivities_say(spark):
    m = np.random.default_rng(4).integers(0, 3, (8, 8))
    other = m.copy()
    other[3, 3] += 1
    spec = GridSpec((0.0, 0.0), (1.0, 1.0), (8, 8))
    for name in ("haar", "db2", "bior2.2"):
        row = measures.neighbour_audit(matrix(spark, m), matrix(spark, other), spec, name).first()
        assert row["count_change"] == 1 and row["changed"] <= max(sum(p) for p in influence(name, 2)) and row["nonpositive_change"] <= sensitivity_z(name)


def test_assignment_of_points_and_summaries(spark):
    rows = [(0.1, 0.1)] * 5 + [(0.9, 0.9)] * 4 + [(0.5, 0.1)]
    spec = unit(8)
    made = methods.cluster_grid(points(spark, rows), ["x0", "x1"], spec, 0.4)
    got = methods.assign_points(points(spark, rows), made.cells, ["x0", "x1"], spec).groupBy("cluster").count().collect()
    assert sorted(r["count"] for r in got) == [1, 4, 5] and -1 in {r["cluster"] for r in got}
    assert methods.cluster_profile(made.cells, spec).count() == 2
    picture = [r["picture"] for r in methods.ascii_map(made.cells, spec).orderBy("line").collect()]
    assert picture == ["A...", "....", "....", "...B"]


def test_sign_counts_include_absent_cells(spark):
    row = count_signs(band_of(spark, [3, 0, -1]), 10).first()
    assert (row["n_pos"], row["n_nonpos"]) == (1, 9)


def test_shape_source_and_sql_helper(spark):
    from dpgrid.plans import sqlapi
    from dpgrid.sources.shapes import ShapeSource

    spark.dataSource.register(ShapeSource)
    two = spark.read.format("dpgrid_shapes").option("shape", "two").option("rows", 2000).load()
    assert two.count() == 2000 and two.select("point_id").distinct().count() == 2000
    two.createOrReplaceTempView("two_discs")
    cells = sqlapi.sql_cluster(spark, "two_discs", "two_cells", ["x0", "x1"], unit(24), 0.1)
    assert spark.sql("SELECT count(DISTINCT cluster) FROM two_cells").first()[0] == 2 == cells.select("cluster").distinct().count()
    private = sqlapi.sql_cluster(spark, "two_discs", "two_private", ["x0", "x1"], unit(24), 0.1, "trimmed", 5.0, "secret")
    assert set(private.columns) == {"eps_i", "rep", "wcell", "cluster"}
    sqlapi.register_sql(spark)
    assert spark.sql("SELECT count(*) FROM boxes_to_points(0e0, 1e0, 0e0, 1e0, 3.4e0)").first()[0] == 3
    assert sorted(r[0] for r in spark.sql("SELECT * FROM grid_neighbors(0, 3, 3, false)").collect()) == [1, 3]


def test_periodic_components_join_opposite_edges(spark):
    df = spark.createDataFrame([(0, 1.0), (3, 1.0), (9, 1.0)], "wcell long, w double")
    labels_ = {r["wcell"]: r["cluster"] for r in connected_components(df, (3, 4), periodic=True).collect()}
    assert labels_ == {0: 0, 3: 0, 9: 9}
    assert labels_ == {r["wcell"]: r["cluster"] for r in connected_components(df, (3, 4), strategy="iterate", periodic=True).collect()}


def test_graph_components_on_long_paths_and_stars(spark):
    from dpgrid.plans.graph import connected_components as graph

    rows = [(i, i + 1) for i in range(60)] + [(100, 100 + i) for i in range(1, 40)] + [(7, 7), (None, 3), (5, 4)]
    got = {r["vertex"]: r["component"] for r in graph(spark.createDataFrame(rows, "src long, dst long")).collect()}
    assert all(got[i] == 0 for i in range(61)) and all(got[100 + i] == 100 for i in range(40)) and len(got) == 101
    assert graph(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_audit_accepts_equal_and_rejects_far_distributions(spark):
    from dpgrid.operators import audit

    a = spark.range(2000).select((F.col("id") % 2).alias("outcome"))
    b = spark.range(2000).select((F.col("id") % 10 == 0).cast("long").alias("outcome"))
    assert all(r["within"] for r in audit.frequency_ratio(a, a, 0.1).collect())
    assert not all(r["within"] for r in audit.frequency_ratio(a, b, 0.1).collect())
    cost = audit.run_cost(spark, "range", lambda: spark.range(50)).first()
    assert cost["rows"] == 50 and cost["jobs"] >= 1


def test_run_cost_outlives_the_status_store(tmp_path):
    """Run apart, as the store's size is fixed when a session starts: it drops skipped stages first, then old ones."""
    import os
    import subprocess
    import sys

    code = """
from pyspark.sql import SparkSession
from dpgrid.operators.audit import run_cost
import sys
kept, src = sys.argv[1:]
s = SparkSession.builder.master("local[2]").config("spark.ui.enabled", "false").config("spark.ui.retainedStages", kept).config("spark.sql.shuffle.partitions", "2").config("spark.sql.autoBroadcastJoinThreshold", "-1").getOrCreate()
s.range(100).write.parquet(src)
t = s.read.parquet(src)
for i in range(12):
    t.groupBy("id").count().groupBy("count").count().collect()
made = run_cost(s, "q", lambda: t.groupBy("id").count().join(t, "id").groupBy("count").count()).first()
print("COST", made["rows"], made["scanned"], made["jobs"] > 1, made["stages"] > made["jobs"])
"""
    said = {}
    for kept in ("10", "2"):
        run = subprocess.run([sys.executable, "-c", code, kept, str(tmp_path / kept)], capture_output=True, text=True, timeout=180, cwd=os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
        assert "COST" in run.stdout, run.stderr[-2000:]
        said[kept] = run.stdout.split("COST")[1].split()
    assert said["10"] == ["1", "200", "True", "True"]
    assert said["2"][:2] == ["1", "None"]


def test_audit_judges_outcomes_that_one_side_lacks(spark):
    from dpgrid.operators import audit

    always = spark.range(2000).select(F.lit(1).cast("long").alias("outcome"))
    for rare in (0, 49):  # seen in all runs on one input, in hardly any on the other
        seldom = spark.range(2000).select((F.col("id") < rare).cast("long").alias("outcome"))
        for pair in ((always, seldom), (seldom, always)):
            got = {r["outcome"]: r for r in audit.frequency_ratio(*pair, 1.0).collect()}
            assert set(got) == {0, 1} and not got[0]["within"] and not got[1]["within"]
    one = spark.range(2000).select(F.when(F.col("id") < 1990, F.lit(-1)).when(F.col("id") < 1998, F.col("id")).alias("outcome"))
    two = spark.range(2000).select(F.when(F.col("id") < 1995, F.lit(-1)).when(F.col("id") < 1998, F.col("id") + 3000).alias("outcome"))
    rows = audit.frequency_ratio(one, two, 1.0).collect()
    assert all(r["within"] for r in rows) and len(rows) == 13 and sum(r["n"] for r in rows) == sum(r["m"] for r in rows) == 2000
    assert {(r["n"], r["m"]) for r in rows if r["outcome"] is None} == {(2, 2)}


@pytest.mark.parametrize("name", [*(f"exp_classifier_w{i}" for i in range(1, 5)), "exp_grid_size", "exp_wavelets", "exp_synthetic_merge"])
def test_experiments_average_over_all_repetitions(spark, monkeypatch, name):
    from dpgrid import catalog, experiments
    from tests.conftest import SF_SMALL

    class Drawn(Exception):
        pass

    def drawn(s, budgets, reps=1):
        raise Drawn(reps)

    monkeypatch.setattr(experiments, "runs_frame", drawn)
    with pytest.raises(Drawn) as seen:
        catalog.QUERIES[name](spark, SF_SMALL)
    assert seen.value.args == (catalog.SWEEP_REPS,)


def test_batch_draws_equal_column_draws(spark):
    import pyarrow as pa

    from dpgrid.functions.batch import uniforms

    places, numbers = ["0|1|7", "é" * 30, ""], [0, 9, 10, 123456, 10**12]
    rows = [(i, p, n) for i, p in enumerate(places) for n in numbers]
    df = spark.createDataFrame(rows, "i int, place string, n long")
    for source in ("keyed", "secret"):
        want = {(r["i"], r["n"]): r["u"] for r in df.select("i", "n", keyed_uniform("k", "p", "place", "n", source=source).alias("u")).collect()}
        for some in (places, places[:1]):  # the second lies within one block
            mine = [(i, n) for i, _, n in rows if i < len(some)]
            got = uniforms("k", "p", pa.array(some), np.array([i for i, _ in mine]), np.array([n for _, n in mine]), source)
            assert got.tolist() == [want[x] for x in mine]


def test_counts_of_synthetic_points_draw_only_across_borders(spark, monkeypatch):
    spec = GridSpec((0.0, 0.0), (1.0, 1.0), (10, 10))
    boxes = [(0.0, 0.1, 0.0, 0.1, 40.0), (0.1, 0.3, 0.1, 0.2, 50.2), (0.05, 0.25, 0.45, 0.65, 60.0), (0.9, 1.0, 0.9, 1.0, 7.0), (0.2, 0.3, 0.2, 0.3, -4.0), (-0.5, 0.0, 1.0, 1.5, 3.0), (0.3, 0.30000000000000004, 0.6, 0.7, 9.0)]
    leaves = spark.createDataFrame([(0, r, f"{i}.0", *b) for i, b in enumerate(boxes) for r in (0, 1)], "eps_i int, rep int, leaf string, lo0 double, hi0 double, lo1 double, hi1 double, cnt double")
    rows = lambda df: sorted(map(tuple, df.select("eps_i", "rep", "cell", "cnt").collect()))
    want = rows(quantize(publish.sample_boxes(leaves, "k"), ["x0", "x1"], spec, ["eps_i", "rep"]))
    for most in (publish.DRAWS, 7):  # large boxes are cut into shares
        monkeypatch.setattr(publish, "DRAWS", most)
        assert rows(publish.drawn_counts(leaves, "k", spec)) == want
    huge = spark.createDataFrame([(0, 0, "0.0", 0.2, 0.21, 0.2, 0.21, 1e12)], leaves.schema)  # would be 10^12 points
    assert rows(publish.drawn_counts(huge, "k", spec))[0][3] == 10**12


def test_equal_points_are_published_as_one_row(spark):
    spec = GridSpec((0.0, 0.0), (1.0, 1.0), (10, 10))
    pts = spark.createDataFrame([(0.31, 0.31)] * 500 + [(0.77, 0.5), (None, 0.5), (float("nan"), 0.2)], "x0 double, x1 double")
    made = publish.compact_points(pts, ["x0", "x1"], spec)
    assert sorted(map(tuple, made.collect())) == [(0.31, 0.31, 500), (0.77, 0.5, 1)]
    runs = runs_frame(spark, [1.0], 2)
    one = publish.publish_adaptive(pts, ["x0", "x1"], spec, runs, "k")
    two = publish.publish_adaptive(made, ["x0", "x1"], spec, runs, "k", compact=True)
    assert sorted(map(tuple, one.collect())) == sorted(map(tuple, two.collect()))
    assert publish.publish_adaptive(pts.limit(0), ["x0", "x1"], spec, runs, "k").where("cnt is null").count() == 0


@pytest.mark.parametrize("name, table", [("exp_bridge_record", "orders"), ("ledger_all", "events"), ("sensitivity_wavelets", "events"), ("udtf_boxes", "orders")])
def test_small_studies_read_their_table(spark, tmp_path, monkeypatch, name, table):
    from dpgrid import registry
    from tests.oracle import same

    assert same(spark, registry.queries()[name], registry.oracle_sql()[name], SF_SMALL)
    with pytest.raises(Exception, match=f"{table}.parquet"):  # there is no such table
        registry.queries()[name](spark, str(tmp_path)).collect()


def test_sensitivities_of_records_are_those_of_the_taps(spark):
    from dpgrid import registry

    for r in registry.queries()["sensitivity_wavelets"](spark, SF_SMALL).collect():
        assert (r["s_z"], r["s_rank"]) == (sensitivity_z(r["wavelet"], r["n"]), sensitivity_rank(r["wavelet"], r["n"]))


def test_fused_adaptive_counts_equal_drawn_leaves(spark, monkeypatch):
    """Cells counted where the leaves' noise is drawn are those of the published leaves: in two and three dimensions, with large leaves, dense and sparse tallies."""
    from dpgrid.operators import publish

    def same(pts, cols, spec, runs):
        want = publish.drawn_counts(publish.publish_adaptive(pts, cols, spec, runs, "k"), "k", spec)
        assert sorted(map(tuple, publish.adaptive_counts(pts, cols, spec, runs, "k").collect())) == sorted(map(tuple, want.collect()))

    runs = runs_frame(spark, [0.5, 2.0], 2)
    pts = spark.range(4000).select((F.col("id") * 0.618 % 1).alias("x0"), F.pow(F.col("id") * 0.377 % 1, 2).alias("x1"), (F.col("id") * 0.211 % 1).alias("x2"))
    same(pts, ["x0", "x1"], unit(7), runs)
    same(pts, ["x0", "x1", "x2"], unit(5, 3), runs_frame(spark, [1.0]))
    same(pts.limit(0), ["x0", "x1"], unit(7), runs)
    monkeypatch.setattr(publish, "DRAWS", 3)  # leaves across a border are dealt in shares
    monkeypatch.setattr(publish, "TALLIED", 60)  # and the tally lets go of what it holds
    monkeypatch.setattr(publish, "HELD", 50)
    same(pts, ["x0", "x1"], unit(7), runs)


def test_batch_draws_of_long_texts_and_numbers():
    """Digests by array equal hashlib's for every length of text up to and beyond a block, and for numbers beyond the table of digits."""
    import hashlib

    import numpy as np
    import pyarrow as pa

    from dpgrid.functions import batch

    places, rng = ["x" * n for n in range(70)], np.random.default_rng(1)
    for some in (places[:20], places[20:36], places, ["é|1", "2"]):
        for top in (9, 10_001, 10**9):
            rows, k = rng.integers(0, len(some), 300), rng.integers(0, top, 300)
            want = [(int(hashlib.md5(f"key|p|{some[r]}|{n}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52 for r, n in zip(rows, k, strict=True)]
            assert batch.uniforms("key", "p", pa.array(some), rows, k).tolist() == want


def test_points_are_read_once_for_all_methods(spark, tmp_path):
    """Counts from compact points equal those of the points, null and NaN coordinates left out, with or without a column beside them."""
    from dpgrid.operators import publish
    from dpgrid.operators.quantize import quantize

    pts = points(spark, [(0.1, 0.1), (0.1, 0.1), (0.9, 0.2), (float("nan"), 0.5), (None, 0.5)]).withColumn("train", F.lit(True))
    want = sorted(map(tuple, quantize(pts, ["x0", "x1"], unit(6)).collect()))
    for by in ([], ["train"]):
        assert sorted(map(tuple, publish.compact_counts(publish.compact_points(pts, ["x0", "x1"], unit(4), by), ["x0", "x1"], unit(6)).collect())) == want


def test_formulas_of_points_are_worked_out_once(spark, monkeypatch):
    """A compact table's plan holds the sines and cosines of the view as often as the view itself, however often later steps name the coordinates."""
    from dpgrid.sources.workloads import WORKLOADS

    monkeypatch.setattr(publish, "materialise", lambda df, label: df)
    wl = WORKLOADS["w3"]
    pts = wl.points(spark, SF_SMALL)
    waves = lambda df: sum(df._jdf.queryExecution().optimizedPlan().toString().count(f) for f in ("SIN(", "COS("))
    assert waves(publish.compact_points(pts, wl.cols, wl.spec)) == waves(pts.select(*wl.cols)) > 0


def test_noisy_tops_equal_column_draws(spark):
    """Top cells' noise by batch, for budgets of different repetitions, cells without points and numbers of any length."""
    lines = {0: [0, 3], 2: [1]}
    rows = [(e, eps, 500, t, c) for e, eps in ((0, 0.25), (2, 2.0)) for t, c in ((0, None), (7, 900), (9_999, 0), (10_000, 41), (249_999, 7_000_000))]
    df = spark.createDataFrame(rows, "eps_i int, eps double, m int, top long, c long")
    runs = spark.createDataFrame([(e, x) for e, some in lines.items() for x in some], "eps_i int, rep int")
    for source in ("keyed", "secret"):
        v = F.coalesce("c", F.lit(0)) + laplace(keyed_uniform("k", "agrid1", "eps_i", "rep", "top", source=source), 2 / (F.col("eps") * 0.5))
        want = {(r["eps_i"], r["top"], r["rep"]): r["v"] for r in df.join(runs, "eps_i").select("eps_i", "top", "rep", v.alias("v")).collect()}
        made = df.mapInArrow(publish._noisy_tops("k", source, 2, lines), "eps_i int, eps double, m int, top long, m2 int, reps binary").collect()
        assert len({(r["eps_i"], r["top"], r["m2"]) for r in made}) == len(made)
        got = {(r["eps_i"], r["top"], int(x["rep"])): (float(x["v"]), r["m2"], r["eps"]) for r in made for x in np.frombuffer(bytes(r["reps"]), publish.REPS_OF)}
        assert got.keys() == want.keys()
        for at, (v, m2, eps) in got.items():
            assert v == pytest.approx(want[at], rel=1e-12) and m2 == max(1, math.ceil(math.sqrt(max(v, 0) * eps * 0.5 / 5)))


def test_draws_below_a_share_by_their_digits(spark):
    from dpgrid.functions.keyed import keyed_below

    ids = spark.range(500)
    for source in ("keyed", "secret"):
        for share in (0.0, 2.0**-53, 1e-3, 1 / 6.4, 0.5, 0.9, 1.0 - 2.0**-53, 1.0, 1.5):
            assert ids.where(keyed_below(share, "k", "p", "id", source=source) != (keyed_uniform("k", "p", "id", source=source) < share)).count() == 0
    u = ids.select(keyed_uniform("k", "p", "id").alias("u")).first()["u"]  # the draw of id 0 itself, and what follows it
    assert ids.where("id = 0").select(keyed_below(u, "k", "p", "id"), keyed_below(math.nextafter(u, 1), "k", "p", "id")).first()[:] == (False, True)


def test_top_cells_are_dealt_by_tile(spark, monkeypatch):
    """Leaves are the same however top cells are dealt, for points on every border of tiles and top cells; neither top cells nor leaf counts are written."""
    written, write = [], publish.materialise
    monkeypatch.setattr(publish, "materialise", lambda df, label: (written.append(label), write(df, label))[1])
    runs, spec = runs_frame(spark, [0.5, 4.0], 2), GridSpec((0.0, -1.0), (1.0, 1.0), (7, 5))
    places = [(i / 40, j / 20 - 1.1) for i in range(41) for j in range(45)] + [(0.5, 0.0)] * 300
    pts = spark.createDataFrame(places, "x0 double, x1 double").coalesce(1)
    rows = lambda: sorted(map(tuple, publish.publish_adaptive(pts, ["x0", "x1"], spec, runs, "k").collect()))
    want = rows()
    monkeypatch.setattr(publish, "TILE_DRAWS", 60)
    monkeypatch.setattr(publish, "HELD", 100)
    assert rows() == want
    assert written == ["agrid_points"] * 2


def test_compact_points_are_dealt_from_whole_files(spark, monkeypatch):
    """Files stand for a table only where they hold just its rows, and the leaves are the same as those of the rows."""
    pts = spark.range(3000).select((F.col("id") * 0.618 % 1).alias("x0"), F.pow(F.col("id") * 0.377 % 1, 2).alias("x1"), (F.col("id") % 3 == 0).alias("train"))
    cols, spec, runs = ["x0", "x1"], unit(7), runs_frame(spark, [0.5, 2.0], 2)
    table = publish.compact_points(pts, cols, spec, ["train"])
    some = table.where("train").select(*cols, "weight")
    assert publish._whole_files(table, cols) is not None
    assert publish._whole_files(some, cols) is None and publish._whole_files(pts, cols) is None and publish._whole_files(table.limit(5), cols) is None
    rows = lambda df: sorted(map(tuple, publish.adaptive_counts(df, cols, spec, runs, "k", compact=True).collect()))
    whole = publish.materialise(some, "train_points")
    assert publish._whole_files(whole, cols) is not None and rows(whole) == rows(some)
    monkeypatch.setattr(publish, "MOST_BYTES", 10)
    assert publish._whole_files(whole, cols) is None
