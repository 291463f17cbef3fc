"""Error measures over trials, and the cost model.

A trial is a row (workload, method, run, test_no, drifted, p_value, reject).
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

TRIAL = "workload string, method string, run int, test_no int, drifted boolean, p_value double, reject boolean"


def run_errors(trials: DataFrame) -> DataFrame:
    """(workload, method, run, type1, type2) in percent."""
    hit = F.col("reject").cast("int")
    return trials.groupBy("workload", "method", "run").agg(
        (100 * F.avg(F.when(~F.col("drifted"), hit))).alias("type1"), (100 * F.avg(F.when(F.col("drifted"), 1 - hit))).alias("type2")
    )


def error_table(trials: DataFrame) -> DataFrame:
    """(workload, method, type1, type1_sd, type2, type2_sd): mean and sample sd over runs."""
    return run_errors(trials).groupBy("workload", "method").agg(
        F.avg("type1").alias("type1"), F.stddev_samp("type1").alias("type1_sd"), F.avg("type2").alias("type2"), F.stddev_samp("type2").alias("type2_sd")
    )


def error_rank(trials: DataFrame) -> DataFrame:
    """(method, type1, type2, rank): averages over workloads, ranked by type2."""
    out = error_table(trials).groupBy("method").agg(F.avg("type1").alias("type1"), F.avg("type2").alias("type2"))
    return out.withColumn("rank", F.rank().over(Window.orderBy("type2")))


def error_flags(trials: DataFrame, alpha: float = 0.05) -> DataFrame:
    """error_table with markers: type1 above alpha, lowest type2 of the workload."""
    low = F.min("type2").over(Window.partitionBy("workload"))
    return error_table(trials).select("workload", "method", "type1", "type2", (F.col("type1") > 100 * alpha).alias("over_alpha"), (F.col("type2") == low).alias("best"))


def error_cube(trials: DataFrame) -> DataFrame:
    """Rejection rates over every subset of (workload, method, drifted)."""
    return trials.cube("workload", "method", "drifted").agg(F.avg(F.col("reject").cast("int")).alias("rate"), F.count("*").alias("n"), F.grouping_id().alias("level"))


def cost_model(n: int, k: int, m: int, thetas: int = 31, tried: int = 1) -> dict[str, float]:
    """Operations of the parts of a fit and of a test on n rows, with all constants 1."""
    log = math.log2(max(2, n))
    return {
        "seed_round": n * log, "seeding": n * k * log, "clustering_pass": float(k * n * m), "theta_sweep": float(thetas * k * n),
        "fit_worst": k * k * n * log, "fit": tried * (n * k * log + k * n * m + thetas * k * n), "test": float(k), "detection": float(n * k),
    }
