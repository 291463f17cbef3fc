"""Tests on tables: detection, policies, plans, streams, sources, the query catalogue against DuckDB."""

import glob
import math
import os
import uuid

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from driftlab.operators import baselines, detect, fitting
from driftlab.operators.histogram import fixed_histogram
from driftlab.operators.ml import BalancedBins, BalancedBinsModel
from driftlab.plans.explain import fit_report, plan_report
from driftlab.queries import load
from driftlab.sources import tables
from driftlab.streaming import monitor

NAMES = tables.TABLES
HIST = fixed_histogram(("a", "b"), [[0.0, 0.0], [2.0, 2.0], [4.0, 0.0]], (1.0, 0.8, 1.2), counts=[100, 60, 40])


def points(spark, n=300, seed=0, shift=0.0):
    x = np.random.default_rng(seed).normal(size=(n, 2)) * 2 + 1 + shift
    return spark.createDataFrame([(i, float(a), float(b), i % 3) for i, (a, b) in enumerate(x)], "id long, a double, b double, g long")


def test_same_sample_has_no_drift(spark):
    p = points(spark)
    r = detect.detect(HIST, p, train=p).first()
    assert r.stat == 0 and r.p_value == 1 and not r.reject and r.n_train == r.n_test == 300


def test_stored_counts_and_many(spark):
    p = points(spark)
    one = detect.detect(HIST, p, by=["g"]).orderBy("g").collect()
    for r in one:
        alone = detect.detect(HIST, p.where(F.col("g") == r.g)).first()
        assert abs(alone.stat - r.stat) < 1e-9 and r.n_test == 100 and alone.dof == 2
    assert detect.detect(HIST, points(spark, shift=4.0)).first().reject
    fixed = detect.benjamini_hochberg(detect.detect(HIST, p, by=["g"])).collect()
    assert len(fixed) == 3


def test_empty_and_invalid(spark):
    p = points(spark, 6)
    bad = p.union(spark.createDataFrame([(9, None, 1.0, 0), (10, float("nan"), 1.0, 0), (11, float("inf"), 0.0, 0)], p.schema))
    assert HIST.assign(bad, on_invalid="drop").count() == 6
    assert HIST.assign(bad, on_invalid="bin").where("bin = -1").count() == 3
    with pytest.raises(Exception, match="NaN"):
        HIST.assign(bad).collect()
    assert detect.detect(HIST, p.limit(0)).first().p_value == 1.0
    with pytest.raises(ValueError):
        HIST.assign(p.drop("a"))
    with pytest.raises(ValueError):
        detect.judge(p, alpha=1.5)
    with pytest.raises(ValueError):
        fitting.fit_balanced(p.limit(0), ("a", "b"))


def test_categories_and_combination(spark):
    p = points(spark).withColumn("c", F.when(F.col("g") == 0, "x").otherwise("y"))
    hist = baselines.categories(p, "c")
    got = detect.detect(hist, p.union(p.withColumn("c", F.lit("new")))).first()
    assert got.dof == 2 and got.reject
    both = detect.detect_by_label({0: HIST, 1: HIST}, p.withColumn("label", F.col("g")), "label")
    assert both.count() == 2
    for how in ("bonferroni", "fisher"):
        assert 0 <= detect.detect_by_label({0: HIST, 1: HIST}, p.withColumn("label", F.col("g")), "label", combine=how).first().p_value <= 1


def test_offset_invariants(spark):
    a, b = points(spark, 2000), points(spark, 2000, 1, 0.7)
    rows = detect.offset_report(HIST, a, b, F.floor(F.col("a") * 2)).collect()
    assert all(r.av >= r.pv - 1e-12 >= -1e-12 and abs(r.margin - (r.av - r.pv)) < 1e-12 for r in rows)


def test_plans(spark, sf):
    li = tables.table(spark, sf, "lineitem")
    hist = fixed_histogram(("l_quantity", "l_tax"), [[10, 0.01], [40, 0.05]], counts=[10, 10])
    report = plan_report(detect.detect(hist, li.where(F.col("l_discount") > 0.02)))
    assert report["cartesian"] == 0 and report["python"] == 0 and report["exchanges"] <= 2
    assert any("l_quantity" in c and "l_comment" not in c and "l_shipdate" not in c for c in report["columns"])
    assert any("l_discount" in p for p in report["pushed"])
    assert "generated code" in fit_report(hist)


def test_compare(spark):
    from driftlab.plans.harness import METHODS, compare

    train = points(spark, 600)
    tests = points(spark, 450, 5).withColumn("a", F.when(F.col("g") == 2, F.col("a") + 3).otherwise(F.col("a")))
    got = {(r.method, r.g): r.reject for r in compare(METHODS, train, tests, ("a", "b"), "g", alpha=0.01).collect()}
    assert len(got) == 3 * len(METHODS) and all(got[m, 2] for m in METHODS)
    assert sum(got[m, g] for m in METHODS for g in (0, 1)) <= 3


def test_fit_counts_the_whole_table(spark, duck, sf):
    """Counts of a fit to a sample are those of all rows, by DuckDB, given the centroids and weights."""
    from driftlab.queries import drift

    p = drift.rows_of(spark, sf)
    fits = [fitting.fit_balanced(p, drift.XY, keys=drift.KEYS, sample_cap=1350, k_init=9), baselines.fit_table("plain_kmeans", p.where("yr < 1998"), drift.XY, 2000, keys=drift.KEYS)]
    for hist, cond, got in ((fits[0], "true", fits[0].counts), (fits[1], "yr < 1998", fitting.recounted(fits[1], p.where("yr < 1998")).counts)):
        rows = ", ".join(f"({k}, {float(m[0])!r}::DOUBLE, {float(m[1])!r}::DOUBLE, {float(w)!r}::DOUBLE)" for k, (m, w) in enumerate(zip(hist.centroids, hist.weights, strict=True)))
        found = duck.execute(f"""WITH c(k, a, b, w) AS (VALUES {rows}), p AS (SELECT row_number() OVER () AS i, x, y FROM {drift.P} WHERE {cond})
            SELECT k, count(*) FROM (SELECT i, arg_min(k, ((x - a) * (x - a) + (y - b) * (y - b)) * w * w) AS k FROM p, c GROUP BY i) GROUP BY k""").fetchall()
        want = dict(found)
        assert sum(got) == sum(want.values()) and sum(abs(int(n) - want.get(k, 0)) for k, n in enumerate(got)) <= 2
    # the fit itself: 50 rows of its sample in each bin, and the first strength that gives them
    x = fitting.take_sample(p, drift.XY, 1350, 0, drift.KEYS)
    again = fitting.fit_array(x, drift.XY, fitting.FitOptions(k_init=9))
    assert np.allclose(again.centroids, fits[0].centroids) and again.counts.min() >= 50 and again.counts.sum() == 1350
    for theta in fitting.theta_grid():
        if theta >= again.theta:
            break
        ratio = fitting.intensity(np.bincount(fitting.lloyd(x, fitting.greedy_seed(x, again.n_bins)[0])[1], minlength=again.n_bins))
        w = fitting.bin_weights(ratio, theta)
        d = ((x[:, None, :] - again.centroids[None]) ** 2).sum(axis=2) * w**2
        assert np.bincount(d.argmin(axis=1), minlength=again.n_bins).min() < 50


def test_samples_draw_repeated_rows_one_by_one(spark):
    p = spark.range(3000).select((F.col("id") % 3 == 0).cast("double").alias("a"), F.lit(1.0).alias("b"))
    got = fitting.take_sample(p, ("a", "b"), 600)[:, 0]
    assert len(got) == 600 and 140 <= got.sum() <= 260


def test_false_alarm_control(spark):
    rng = np.random.default_rng(4)
    for n, real in ((50, 8), (200, 0), (7, 7)):
        ps = np.concatenate([rng.random(n - real), rng.random(real) * 1e-4])
        order = np.sort(ps)
        k = max([i + 1 for i in range(n) if order[i] <= 0.05 * (i + 1) / n], default=0)
        df = spark.createDataFrame([(float(x),) for x in ps], "p_value double")
        got = detect.benjamini_hochberg(df).collect()
        assert sum(r.reject for r in got) == k and all(r.reject == (k > 0 and r.p_value <= order[k - 1]) for r in got)
    assert detect.benjamini_hochberg(df.limit(0)).count() == 0


def test_midpoint_tree_of_a_table(spark):
    p = points(spark, 700)
    x = np.array([(r.a, r.b) for r in p.collect()])
    low, high, most, depth = x.min(axis=0), x.max(axis=0), 40, 9
    got = {r.node: r.n for r in baselines.kd_table(p, ("a", "b"), low.tolist(), high.tolist(), depth, most).collect()}
    want = {}

    def build(rows, lo, hi, node, level):
        if len(rows) <= most or level == depth:
            if len(rows):
                want[node] = len(rows)
            return
        j = level % 2
        cut = (lo[j] + hi[j]) / 2
        right = x[rows, j] > cut
        build(rows[~right], lo, np.where(np.arange(2) == j, cut, hi), 2 * node, level + 1)
        build(rows[right], np.where(np.arange(2) == j, cut, lo), hi, 2 * node + 1, level + 1)

    build(np.arange(len(x)), low, high, 1, 0)
    assert got == want


def test_experiments_run_in_small(spark, sf):
    """Sizes, dimensions and documents by the least protocol: one row per workload, method and set."""
    from driftlab.plans import workloads

    got = workloads.training_sizes(spark, (2000, 3000), 1, 2, ("2d-1G-mean",)).groupBy("workload").count().collect()
    assert {r.workload: r["count"] for r in got} == {"2d-1G-mean/2000": 4, "2d-1G-mean/3000": 4}
    rows = workloads.dimensions(spark, (4,), 1, 2, ("balanced", "balanced_split", "mst_runs")).collect()
    assert len(rows) == 2 * 3 * 4
    for which in workloads.SIZES:
        rows = workloads.document_experiment(spark, sf, which, 1, 2, ("balanced", "plain_kmeans")).collect()
        assert len(rows) == 8 and {r.method for r in rows} == {"balanced", "plain_kmeans"}


def test_ml_stage(spark, tmp_path):
    p = points(spark, 500).withColumn("features", F.array("a", "b"))
    model = BalancedBins(beta=40).fit(p)
    counts = [r["count"] for r in model.transform(p).groupBy("bin").count().collect()]
    assert min(counts) >= 40 and sum(counts) == 500
    model.save_to(spark, str(tmp_path / "m"))
    again = BalancedBinsModel.load_from(spark, str(tmp_path / "m"))
    assert again.transform(p).select("bin").collect() == model.transform(p).select("bin").collect()


def test_sampling(spark):
    p = points(spark)
    assert tables.hash_top(p, 10, ["id"]).count() == 10
    assert tables.stratified(p, "g", {0: 5, 2: 7}, ["id"]).count() == 12
    assert tables.most_frequent(p.where("g < 2 OR id < 60"), "g", 2).select("g").distinct().count() == 2
    with pytest.raises(ValueError):
        tables.read(spark, "/nowhere", "csv")


def test_stream_equals_batch(spark, sf, tmp_path):
    e = tables.table(spark, sf, "events").select("event_id", "ts", (F.col("value") / 20).alias("a"), F.hour("ts").cast("double").alias("b"))
    src = str(tmp_path / "in")
    for k in range(4):
        e.where(F.col("event_id") % 4 == k).coalesce(1).write.mode("append").parquet(src)
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(src)
    got = monitor.run_to_memory(spark, monitor.window_counts(stream, HIST, "ts", ("1 day",), "40 days"), f"t_{uuid.uuid4().hex}", str(tmp_path / "c"), "complete")
    want = monitor.window_counts(e, HIST, "ts", ("1 day",))
    key = lambda r: (r.start, r.bin)
    assert sorted(((r.start, r.bin, r.n) for r in got.collect())) == sorted(((r.start, r.bin, r.n) for r in want.collect()))
    del key


def test_late_rows_are_dropped(spark, sf):
    assert load()[0]["stream_late"](spark, sf).first().dropped > 0


def test_adaptation_recovers(spark):
    rows = load()[0]["adapt_accuracy"](spark, "/root/testdata/sf0.01").collect()
    last = {r.policy: r.accuracy for r in rows if r.batch == 5}
    assert last["retrain"] >= last["none"] and any(r.drift for r in rows if r.batch == 3)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in NAMES:
        path = f"/root/testdata/sf0.001/{t}.parquet"
        files = f"{path}/*.parquet" if os.path.isdir(path) else path
        assert glob.glob(files)
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{files}')")
    return con


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else repr(round(v, 5) + 0.0)
    if isinstance(v, (list, tuple)):
        return [plain(x) for x in v]
    return str(v)


SLOW = ("exp2", "exp3", "exp4")


@pytest.mark.parametrize("name", sorted(load()[0]))
def test_catalogue(spark, sf, duck, name):
    if name.startswith(SLOW):
        pytest.skip("minutes long; test_experiments_run_in_small and the kernels' tests run their workloads")
    queries, oracle = load()
    df = queries[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted(str([plain(r[c]) for c in cols]) for r in df.collect())
    if name not in oracle:
        assert got
        return
    duck.execute(oracle[name])
    names = [c[0] for c in duck.description]
    assert sorted(names) == cols
    want = sorted(str([plain(r[names.index(c)]) for c in cols]) for r in duck.fetchall())
    assert got == want


def test_kde_table_takes_all_rows(spark):
    """A sample beyond the cap of the quadratic kernels counts in full."""
    n = baselines.QUADRATIC_CAP + 10_000
    sample = spark.range(n).select((F.col("id") / n).alias("x"))
    at = spark.createDataFrame([(0, 0.1), (1, 0.9)], "id long, x double")
    got = {r.id: r.density for r in baselines.kde_table(at, sample, ["x"], [0.2]).collect()}
    x = np.arange(n) / n
    for i, p in ((0, 0.1), (1, 0.9)):
        want = np.exp(-0.5 * ((p - x) / 0.2) ** 2).mean() / (0.2 * np.sqrt(2 * np.pi))
        assert abs(got[i] - want) < 1e-9
