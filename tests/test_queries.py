"""Registered queries against their DuckDB SQL, and the trends of repeated private runs."""

import pytest

from dpgrid import catalog, experiments, registry
from dpgrid.operators.privacy import runs_frame
from dpgrid.sources.workloads import WORKLOADS
from tests.conftest import SF, SF_SMALL
from tests.oracle import same

FAST = ["quantize_w1", "quantize_w3", "quantize_w4", "quantize_w6", "quantize_w9", "haar_bands_w2", "bior_w2", "db2_w2", "cut_w3", "components_w1", "components_w7_proj", "components_tiled_w3", "ascii_map_w3", "geometric_cells_w2", "exp_mech_cumulative_w2", "nq_w2", "trim_w2", "trim_w4", "cut_release_w2", "syn_uniform_w2", "publish_adaptive_w2", "cube_marginals", "fmeasure_w2", "ppd_w2", "bounds_cut_w2", "range_query_boxes", "tumbling_events", "sliding_events", "session_events", "stream_cap_events"]


@pytest.mark.parametrize("name", FAST)
def test_matches_sql(spark, name):
    assert same(spark, registry.queries()[name], registry.oracle_sql()[name], SF_SMALL)


def test_expected_facts(spark):
    """Positive and non-positive cells, cut rank and clusters of the views at two scales."""
    got = {r["workload"]: (r["n_pos"], r["n_nonpos"], r["k"], r["clusters"]) for r in catalog.QUERIES["exp_nonprivate"](spark, SF).collect()}
    assert got["w1"] == (677, 347, 285, 15) and got["w2"] == (129, 271, 117, 3) and got["w3"] == (149, 175, 115, 5)
    assert got["w4"][:3] == (744, 856, 514)


def test_point_ids_are_unique(spark):
    for w in ("w2", "w4"):
        p = WORKLOADS[w].points(spark, SF).select("point_id")
        assert p.count() == p.distinct().count()


@pytest.fixture(scope="module")
def spiral(spark):
    lines = runs_frame(spark, [0.1, 0.5, 1.0, 2.0], 5)
    truth = experiments.truth(spark, SF, "w2")
    gcd = experiments.each_method(spark, SF, "w2", lines, lambda m: experiments.me.grid_cluster_dissimilarity(truth, m.cells, lines)).collect()
    ranks = experiments.each_method(spark, SF, "w2", lines, lambda m: experiments.me.rank_error(experiments.percentile_cut(experiments.band(spark, SF, "w2"), 0.10), m.cut)).collect()
    mean = lambda rows, m, e, c: sum(r[c] for r in rows if r["method"] == m and r["eps_i"] == e) / 5
    return lambda kind, m, e: mean(gcd if kind == "gcd" else ranks, m, e, "gcd" if kind == "gcd" else kind)


def test_threshold_techniques_beat_the_others(spiral):
    for e in (1, 2, 3):
        for better in ("TRIM", "CUT"):
            for worse in ("SYN", "NQ"):
                assert spiral("gcd", better, e) < spiral("gcd", worse, e)
                assert spiral("rank_error", better, e) < spiral("rank_error", worse, e)


def test_noisy_counts_hardly_improve_with_budget(spiral):
    nq = [spiral("gcd", "NQ", e) for e in range(4)]
    assert max(nq) - min(nq) < 0.5 * min(nq)
    assert spiral("gcd", "TRIM", 3) < 0.5 * spiral("gcd", "TRIM", 0)


def test_noisy_counts_inflate_the_rank_as_predicted(spark):
    for r in catalog.QUERIES["exp_theory_nq"](spark, SF).collect():
        assert r["measured"] == pytest.approx(r["predicted"], rel=0.15)


def test_sampled_cut_suffers_more_from_small_budgets(spiral):
    assert spiral("rank_error", "CUT", 0) > spiral("rank_error", "TRIM", 0)


def test_bounds_hold(spark):
    for r in catalog.QUERIES["exp_bounds"](spark, SF).collect():
        assert r["coverage"] >= (1 - experiments.OMEGA) ** 3


def test_release_sink_refuses_clean_columns(spark, tmp_path):
    from dpgrid.sources.workloads import points_from, write_release

    with pytest.raises(ValueError):
        write_release(spark.createDataFrame([(1, 2)], "wcell long, cnt long"), str(tmp_path / "x"))
    write_release(spark.createDataFrame([(1, 0.5, 0.25)], "point_id long, x0 double, x1 double"), str(tmp_path / "p"), "json")
    assert points_from(spark, str(tmp_path / "p"), "json", "point_id long, x0 double, x1 double").first()["x1"] == 0.25


def test_every_oracle_has_a_query():
    assert set(registry.oracle_sql()) <= set(registry.queries())


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
