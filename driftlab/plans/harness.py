"""Trials: fit every method on a training set, test it on stationary and drifted sets, keep the decisions.

One task works on one (workload, run) group: it fits all methods and judges all test sets, so a
protocol of many runs is one shuffle by (workload, run) and no loop on the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.chisq import chi2_sf, table_stat
from ..operators import baselines
from ..operators.detect import contingency_wide, detect
from ..operators.fitting import FitOptions, fit_array, recounted, take_sample
from ..operators.measures import TRIAL
from ..session import ship
from ..sources import gen

METHODS = ("balanced", "plain_kmeans", "midpoint_kd", "peel_chi2", "peel_tv", "mst_runs")


def fit_method(name: str, x: np.ndarray, features: Sequence[str], beta: int = 50, seed: int = 0, **options):
    """A fitted model of a method; the runs test keeps the sample and its tree, the density test the sample."""
    if name == "balanced":
        return fit_array(x, features, FitOptions(beta=beta, seed=seed, **options))
    if name == "balanced_split":
        return fit_array(x, features, FitOptions(**{"beta": beta, "seed": seed, "count_share": 0.5, **options}))
    if name == "plain_kmeans":
        return baselines.plain_kmeans_array(x, features, beta=beta, seed=seed)
    if name == "midpoint_kd":
        return baselines.midpoint_kd_array(x, features, max_points=2 * beta)
    if name in ("peel_chi2", "peel_tv"):
        return baselines.quantile_peel_array(x, features, beta=beta, seed=seed)
    if name == "grid":
        return baselines.grid_array(x, features)
    if name == "mst_runs":
        return baselines.RunsSample(x)
    if name == "kde":
        return np.asarray(x, float)
    raise ValueError(f"no such method: {name}")


def test_method(name: str, model, tests: Sequence[np.ndarray], alpha: float = 0.05) -> list[tuple[float | None, bool]]:
    """(p-value or None, reject) of each test set."""
    if name == "mst_runs":
        found = [model.test(t)["p_value"] for t in tests]
        return [(p, p < alpha) for p in found]
    if name == "kde":
        return [(r["p_value"], r["reject"]) for r in (baselines.kde_test(model, t, alpha=alpha) for t in tests)]
    counts = np.stack([np.bincount(model.label(t), minlength=model.n_bins) for t in tests])
    if name in ("peel_chi2", "peel_tv"):
        stat = name.removeprefix("peel_")
        values = baselines.peel_stats(model.counts, counts, stat)
        # a test set's threshold goes by its own size
        limits = [baselines.peel_threshold(stat, tuple(model.counts.tolist()), len(t), alpha) for t in tests]
        return [(None, bool(v > c)) for v, c in zip(values, limits, strict=True)]
    stat, dof = table_stat(model.counts, counts)
    found = [chi2_sf(float(s), int(d)) for s, d in zip(stat, dof, strict=True)]
    return [(p, p < alpha) for p in found]


def run_trials(sets: DataFrame, features: Sequence[str], methods: Sequence[str] = METHODS, beta: int = 50, alpha: float = 0.05, fit: dict | None = None) -> DataFrame:
    """Trials of rows (workload, run, test_no, drifted, features...); test_no -1 is the training set of its run."""

    ship(sets.sparkSession)

    def one(key, f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values(["test_no", "row"])
        train = f[f.test_no < 0][list(features)].to_numpy(float)
        tests = [(no, bool(g.drifted.iloc[0]), g[list(features)].to_numpy(float)) for no, g in f[f.test_no >= 0].groupby("test_no")]
        rows = []
        for name in methods:
            model = fit_method(name, train, features, beta=beta, seed=int(key[1]), **((fit or {}) if name.startswith("balanced") else {}))
            for (no, drifted, _), (p, reject) in zip(tests, test_method(name, model, [t for _, _, t in tests], alpha), strict=True):
                rows.append((key[0], name, int(key[1]), int(no), drifted, p, bool(reject)))
        return pd.DataFrame(rows, columns=["workload", "method", "run", "test_no", "drifted", "p_value", "reject"]).astype({"run": "int32", "test_no": "int32"})

    # a fixed number of tasks: the sets are small, the work on them is not, so adaptive coalescing would put all groups into one task
    tasks = 4 * sets.sparkSession.sparkContext.defaultParallelism
    rows = sets.select("workload", "run", "test_no", "drifted", "row", *features).repartition(tasks, "workload", "run")
    return rows.groupBy("workload", "run").applyInPandas(one, TRIAL)


def synthetic_sets(spark: SparkSession, kinds: Sequence[str] | None = None, runs: int = 5, n_train: int = 2000, n_test: int = 200, tests: int = 20, dims: int = 2, drift: float | None = None, source: Callable[[int], DataFrame] | None = None, **options) -> DataFrame:
    """Training and test rows of the generated workloads: `tests` stationary and as many drifted sets in each run.

    source: gives n rows of a table (sources.tables.standard_rows), whose values take the place of random ones; the drift is put on them.
    """
    out = None
    rows_per_run = n_train + 2 * tests * n_test
    place = F.col("id") % rows_per_run
    test_no = F.when(place < n_train, F.lit(-1)).otherwise(F.floor((place - n_train) / n_test)).cast("int")
    given = source(runs * rows_per_run) if source else None
    if given is not None:
        options["given"] = tuple([F.col(f"{k}{j + 1}") for j in range(dims)] for k in "gu")
    for kind in kinds or gen.MARGINS:
        margin = gen.MARGINS[kind] if drift is None else drift
        ids = spark.range(0, runs * rows_per_run, 1, max(1, runs)) if given is None else given
        base = ids.select("*", F.floor(F.col("id") / rows_per_run).cast("int").alias("run"), test_no.alias("test_no"))
        base = base.withColumn("drifted", F.col("test_no") >= tests)
        still = gen.point(kind, F.col("id"), 0.0, kind[:5], dims=dims, **options)
        moved = gen.point(kind, F.col("id"), margin, kind[:5], dims=dims, **options)
        cols = [F.when(F.col("drifted"), b).otherwise(a).alias(f"x{j + 1}") for j, (a, b) in enumerate(zip(still, moved, strict=True))]
        name = kind if dims == 2 else f"{dims}d-{kind[3:]}"
        part = base.select(F.lit(name).alias("workload"), "run", "test_no", "drifted", F.col("id").alias("row"), *cols)
        out = part if out is None else out.unionByName(part)
    return out


def sampled_sets(same: DataFrame, other: DataFrame, workload: str, features: Sequence[str], runs: int, n_train: int, n_test: int, tests: int, groups: tuple[dict, dict] | None = None, group: str | None = None) -> DataFrame:
    """Sets drawn from tables: training and stationary test rows from `same`, drifted ones from `other`.

    groups: shares of each group in the two populations; without, plain draws. Training rows are drawn without
    replacement; each test set without replacement from the rows that training left (with, where these are too few). Whole runs are drawn in one task each.
    """
    spark = same.sparkSession
    cols = list(features) + ([group] if group else [])
    keep = lambda df: df.select(*cols)
    a = keep(same).withColumn("side", F.lit(0))
    b = keep(other).withColumn("side", F.lit(1))
    both = a.unionByName(b)
    spread = both.crossJoin(F.broadcast(spark.range(runs).select(F.col("id").cast("int").alias("run"))))

    def draw(key, f: pd.DataFrame) -> pd.DataFrame:
        rng = np.random.default_rng([int(key[0]), len(workload)])
        f = f.sort_values(["side", *cols]).reset_index(drop=True)
        pools = [f[f.side == s] for s in (0, 1)]

        def parts(pool: pd.DataFrame, n: int, shares: dict | None, replace: bool) -> pd.DataFrame:
            if shares is None:
                return pool.iloc[rng.choice(len(pool), min(n, len(pool)) if not replace else n, replace=replace and len(pool) < n)]
            took = []
            for g, share in shares.items():
                rows = pool[pool[group] == g]
                want = int(round(share * n))
                if want and len(rows):
                    took.append(rows.iloc[rng.choice(len(rows), want if replace else min(want, len(rows)), replace=replace and len(rows) < want)])
            return pd.concat(took)

        train = parts(pools[0], n_train, groups and groups[0], False)
        left = pools[0].drop(index=train.index)
        if len(left) < n_test:
            left = pools[0]
        out = [train.assign(test_no=-1, drifted=False)]
        for k in range(2 * tests):
            moved = k >= tests
            rows = parts(pools[1] if moved else left, n_test, groups and groups[int(moved)], True)
            out.append(rows.assign(test_no=k, drifted=moved))
        res = pd.concat(out)
        res["row"] = np.arange(len(res))
        return pd.DataFrame({"workload": workload, "run": int(key[0]), "test_no": res.test_no, "drifted": res.drifted, "row": res.row, **{c: res[c].astype(float) for c in features}})

    kinds = ", ".join(f"{c} double" for c in features)
    # as in run_trials: adaptive coalescing would draw all runs in one task
    spread = spread.repartition(4 * spark.sparkContext.defaultParallelism, "run")
    return spread.groupBy("run").applyInPandas(draw, f"workload string, run int, test_no int, drifted boolean, row long, {kinds}")


def compare(methods: Sequence[str], train: DataFrame, tests: DataFrame, features: Sequence[str], by: str, alpha: float = 0.05, beta: int = 50, sample_cap: int = 20_000, seed: int = 0, keys: Sequence[str] = ()) -> DataFrame:
    """(method, by, stat, p_value, reject): every batch of `tests` judged by every method fitted on one bounded sample of `train`.

    Histogram methods count the whole training table and whole batches in one distributed pass; peeling methods take thresholds simulated for each
    batch's size; the runs test takes the whole sample, works on one batch per task and refuses samples and batches beyond the quadratic cap.
    keys: columns that tell the rows of `train` apart.
    """
    spark = train.sparkSession
    x = take_sample(train, features, sample_cap, seed, keys)
    out = None
    for name in methods:
        if name == "mst_runs":
            got = baselines.runs_table(tests, x, features, by, alpha).select(F.lit(name).alias("method"), by, F.col("z").alias("stat"), "p_value", "reject")
        elif name in ("peel_chi2", "peel_tv"):
            hist = recounted(fit_method(name, x, features, beta, seed), train)
            wide = contingency_wide(hist, tests, [by]).withColumn("q", F.aggregate("t", F.lit(0).cast("long"), lambda s, v: s + v))
            sizes = [r.q for r in wide.select("q").distinct().collect()]
            kind = name.removeprefix("peel_")
            limits = spark.createDataFrame([(int(q), baselines.peel_threshold(kind, tuple(hist.counts.tolist()), int(q), alpha)) for q in sizes], "q long, limit double")
            n = float(hist.counts.sum())
            term = (lambda o, t: F.abs(t / F.col("q") - o / n) / 2) if kind == "tv" else (lambda o, t: F.when(o > 0, (t - F.col("q") * o / n) * (t - F.col("q") * o / n) / (F.col("q") * o / n)).otherwise(0.0))
            stat = F.aggregate(F.zip_with("o", "t", term), F.lit(0.0), lambda s, v: s + v)
            got = wide.join(F.broadcast(limits), "q").select(F.lit(name).alias("method"), by, stat.alias("stat"), F.lit(None).cast("double").alias("p_value"), (stat > F.col("limit")).alias("reject"))
        else:
            got = detect(fit_method(name, x, features, beta, seed), tests, [by], alpha, train=train).select(F.lit(name).alias("method"), by, "stat", "p_value", "reject")
        out = got if out is None else out.unionByName(got)
    return out
