"""Chi-square machinery, seeding, clustering, fits and baselines: hand-checked values and invariants."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from driftlab.functions import chisq
from driftlab.operators import baselines, fitting, measures
from driftlab.operators.histogram import fixed_histogram, from_json, nearest, to_json
from driftlab.plans import harness, workloads


def gauss(n, seed=0, m=2):
    return np.random.default_rng(seed).normal(size=(n, m))


# ---------------------------------------------------------------- chi-square


def test_known_tails():
    assert abs(chisq.chi2_sf(2, 2) - math.exp(-1)) < 1e-15
    assert abs(chisq.chi2_sf(3.841458820694124, 1) - 0.05) < 1e-12
    assert abs(chisq.chi2_ppf(0.95, 10) - 18.307038053275146) < 1e-9
    assert chisq.chi2_sf(5, 0) == 1.0 and chisq.chi2_sf(0, 3) == 1.0
    assert 0 <= chisq.chi2_sf(1e5, 7) < 1e-300 or chisq.chi2_sf(1e5, 7) == 0


def test_column_tail_is_numpy_tail(spark):
    rows = [(x, k) for k in (1, 2, 3, 5, 8, 39, 60) for x in (1e-6, 0.3, 2.0, 4.4, 4.6, 30.0, 200.0)]
    got = spark.createDataFrame(rows, "x double, k int").select("x", "k", chisq.chi2_sf_col(F.col("x"), F.col("k")).alias("p")).collect()
    for r in got:
        assert abs(r.p - chisq.chi2_sf(r.x, r.k)) < 1e-12


def test_hand_tables():
    s, d = chisq.table_stat([60, 60, 60], [[20, 20, 20]])
    assert s[0] == 0 and d[0] == 2
    s, d = chisq.table_stat([100, 100], [[30, 10]])
    e = [130 / 6 * 5, 110 / 6 * 5, 130 / 6, 110 / 6]
    assert abs(s[0] - sum((o - x) ** 2 / x for o, x in zip([100, 100, 30, 10], e, strict=True))) < 1e-9 and chisq.chi2_sf(s[0], d[0]) < 0.05
    s, d = chisq.table_stat([50, 0, 50], [[10, 0, 10]])
    assert (s[0], d[0]) == (0, 1)
    assert chisq.table_stat([70], [[9]])[1][0] == 0
    assert abs(baselines.peel_stats(np.array([5, 5]), [[7, 3]], "tv")[0] - 0.2) < 1e-12


# ---------------------------------------------------------------- fit


def test_block_sizes():
    assert fitting.block_sizes(10, 3) == [4, 3, 3]
    with pytest.raises(ValueError):
        fitting.block_sizes(2, 3)


def test_seeding_by_hand():
    x = np.array([[0.0], [1], [2], [10], [11], [20]])
    seeds, block = fitting.greedy_seed(x, 3)
    assert seeds.ravel().tolist() == [15.5, 6.0, 0.5] and block.tolist() == [2, 2, 1, 1, 0, 0]


@pytest.mark.parametrize("nn", ["brute", "grid", "incremental"])
def test_neighbour_engines_agree(nn):
    x = np.round(gauss(300, 3), 2)
    a, b = fitting.greedy_seed(x, 7, nn="brute")
    c, d = fitting.greedy_seed(x, 7, nn=nn)
    assert np.array_equal(b, d) and np.allclose(a, c)
    assert np.bincount(b).tolist() == fitting.block_sizes(300, 7)


def test_explicit_sizes():
    _, block = fitting.greedy_seed(gauss(20), 2, sizes=[15, 5])
    assert np.bincount(block).tolist() == [15, 5]


def test_weights_and_labels():
    assert np.allclose(fitting.bin_weights([0.5, 1, 2], 1), np.exp([-0.5, 0, 1]))
    x, mu = gauss(200), gauss(5, 1)
    d = np.linalg.norm(x[:, None] - mu[None], axis=2)
    w = np.array([1, 0.5, 2, 1, 1.5])
    assert np.array_equal(nearest(x, mu, w), (d * w).argmin(1))
    assert np.array_equal(nearest(x, mu, fitting.bin_weights(np.arange(5), 0)), d.argmin(1))


@pytest.mark.parametrize("stop", ["best", "first"])
def test_fit_holds_its_promise(stop):
    x = np.concatenate([gauss(600), gauss(300, 1) * 0.3 + 4, gauss(100, 2) + 9])
    h = fitting.fit_array(x, ("a", "b"), fitting.FitOptions(stop=stop))
    assert h.kind == "balanced" and h.counts.min() >= 50 and h.counts.sum() == 1000
    assert np.array_equal(np.bincount(h.label(x), minlength=h.n_bins), h.counts)
    assert 2 <= h.n_bins <= 20 and h.trail[-1] == (h.n_bins, True)


def test_fit_edges():
    assert fitting.fit_array(gauss(60), ("a", "b")).n_bins == 1
    assert fitting.fit_array(np.ones((200, 2)), ("a", "b")).counts.sum() == 200
    assert fitting.fit_array(gauss(500)[:, :1], ("a",)).counts.min() >= 50
    for bad in (np.zeros((0, 2)), np.array([[np.nan, 1.0]])):
        with pytest.raises(ValueError):
            fitting.fit_array(bad, ("a", "b"))
    with pytest.raises(ValueError):
        fixed_histogram(("a", "b"), [[0, 0]]).label(gauss(3, m=3))


def test_waves_and_serial_agree(spark):
    x = gauss(700, 5)
    df = spark.createDataFrame(x.tolist(), "a double, b double")
    one = fitting.fit_balanced(df, ("a", "b"), sample_cap=700)
    two = fitting.fit_balanced(df, ("a", "b"), sample_cap=700, search="waves")
    assert one.n_bins == two.n_bins and np.array_equal(one.counts, two.counts) and one.theta == two.theta


def test_scales_and_store():
    x = gauss(400) * [1, 1000] + [5, 9]
    for how in ("none", "zscore", "minmax", "robust"):
        h = fitting.fit_array(x, ("a", "b"), fitting.FitOptions(scale=how))
        again = from_json(to_json(h))
        assert np.array_equal(again.label(x), h.label(x)) and again.trail == h.trail


# ---------------------------------------------------------------- baselines


def test_partitions_cover():
    x = gauss(1000, 4)
    for h in (baselines.plain_kmeans_array(x, ("a", "b")), baselines.midpoint_kd_array(x, ("a", "b")), baselines.quantile_peel_array(x, ("a", "b")), baselines.grid_array(x, ("a", "b"))):
        label = h.label(x)
        assert np.array_equal(np.bincount(label, minlength=h.n_bins), h.counts) and h.counts.sum() == 1000
    peel = baselines.quantile_peel_array(x, ("a", "b"), k=10)
    assert set(peel.counts.tolist()) == {100}


def test_expressions_are_kernels(spark):
    x = gauss(500, 8)
    df = spark.createDataFrame(x.tolist(), "a double, b double")
    hists = [baselines.plain_kmeans_array(x, ("a", "b")), baselines.midpoint_kd_array(x, ("a", "b")), baselines.quantile_peel_array(x, ("a", "b")), baselines.grid_array(x, ("a", "b"), 3), fitting.fit_array(x, ("a", "b"), fitting.FitOptions(scale="zscore"))]
    for h in hists:
        for how in ("expression", "arrow"):
            got = np.array([r.bin for r in h.assign(df, how=how).collect()])
            assert np.array_equal(got, h.label(x)), (h.kind, how)


def test_runs_by_hand():
    r = baselines.runs_test(np.array([[0.0], [1]]), np.array([[10.0], [11]]))
    assert r["runs"] == 2 and abs(r["mean"] - 3) < 1e-12
    same = baselines.runs_test(gauss(150), gauss(150, 1))
    far = baselines.runs_test(gauss(150), gauss(150, 1) + 3)
    assert far["p_value"] < 1e-6 < same["p_value"]
    with pytest.raises(ValueError):
        baselines.spanning_tree(np.zeros((baselines.QUADRATIC_CAP + 1, 1)))


def test_shared_training_tree():
    rng = np.random.default_rng(3)
    for n, q, m in ((1, 1, 2), (1, 6, 2), (9, 1, 3), (120, 40, 2), (60, 90, 7)):
        a, b = rng.normal(size=(n, m)), rng.normal(size=(q, m)) + 0.3
        assert baselines.RunsSample(a).test(b) == baselines.runs_test(a, b)
    a, b = rng.integers(0, 5, (80, 2)).astype(float), rng.integers(0, 5, (30, 2)).astype(float)  # ties: a tree of the same length
    x = np.concatenate([a, b])
    length = lambda e: ((x[e[:, 0]] - x[e[:, 1]]) ** 2).sum()
    got = baselines.RunsSample(a).joined(b)
    assert len(got) == 109 and length(got) == length(baselines.spanning_tree(x))


def test_boruvka_is_prim(spark):
    x = gauss(40, 6)
    df = spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate(x)], "id long, a double, b double")
    got = {(r.a, r.b) for r in baselines.boruvka(df, ("a", "b")).collect()}
    assert got == {tuple(e) for e in baselines.spanning_tree(x).tolist()}


def test_thresholds(spark):
    c = (100,) * 10
    t = [baselines.peel_threshold("chi2", c, 200, a) for a in (0.01, 0.05, 0.1)]
    assert t == sorted(t, reverse=True) and baselines.peel_threshold("chi2", c, 200, 0.05) == t[1]
    rows = baselines.threshold_table(spark, [("chi2", c, 200, 0.05)]).collect()
    assert abs(rows[0].threshold - t[1]) < 1.5


def test_kernel_density():
    a, b = gauss(80), gauss(80, 1)
    assert baselines.kde_test(a, b + 2, 60)["reject"] and not baselines.kde_test(a, b, 60)["p_value"] < 0.01
    h = baselines.scott_bandwidth(a)
    one = baselines.log_density(np.zeros((1, 2)), np.zeros((1, 2)), h)
    assert abs(math.exp(one[0]) - 1 / (2 * math.pi * h.prod())) < 1e-9


# ---------------------------------------------------------------- measures and workloads


def test_measures_by_hand(spark):
    rows = [("w", "m", r, t, t >= 1, None, r < 31 if t else False) for r in range(50) for t in range(2)]
    got = measures.error_table(spark.createDataFrame(rows, measures.TRIAL)).first()
    assert abs(100 - got.type2 - 62.0) < 1e-9 and abs(got.type2_sd - 49.03) < 0.01 and got.type1 == 0


def test_offsets_closed_form():
    rows = workloads.offset_toy(1.0, (-1.0, 0.0, 1.0, 2.0))
    assert [r["is_offset"] for r in rows] == [False, False, True, False, False]
    fine = workloads.offset_toy(1.0, (-1.0, 0.0, 0.5, 1.0, 2.0))
    assert not any(r["is_offset"] for r in fine)
    assert abs(sum(r["av"] for r in rows) - sum(r["av"] for r in fine)) < 1e-12 and sum(r["margin"] for r in fine) < sum(r["margin"] for r in rows)


def test_stationary_sets_are_accepted():
    rng = np.random.default_rng(1)
    train, tests = rng.normal(size=(2000, 2)), [rng.normal(size=(200, 2)) for _ in range(60)]
    moved = [t + [1.0, 0] for t in tests]
    for name in ("balanced", "plain_kmeans", "midpoint_kd", "peel_chi2", "peel_tv"):
        model = harness.fit_method(name, train, ("a", "b"))
        still = np.mean([r for _, r in harness.test_method(name, model, tests)])
        power = np.mean([r for _, r in harness.test_method(name, model, moved)])
        assert still <= 0.2 and power >= 0.8, (name, still, power)


def test_experiment_one(spark):
    sd = {(r.shape, r.method): r.intensity_sd for r in workloads.partition_experiment(spark).collect()}
    for shape in ("one", "even", "uneven"):
        assert sd[shape, "balanced"] < sd[shape, "plain_kmeans"]


def test_experiment_two_direction(spark):
    trials = workloads.two_dimensional(spark, runs=2, tests=25, kinds=("2d-1G-mean", "2d-2G-mean", "2d-4G-mean"), methods=("balanced", "plain_kmeans", "peel_tv"))
    got = {r.method: r for r in measures.error_rank(trials).collect()}
    assert got["balanced"].type2 < got["plain_kmeans"].type2 < got["peel_tv"].type2
    assert all(r.type1 <= 12 for r in got.values())
