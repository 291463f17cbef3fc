"""Drift tests on count tables.

Rows are labelled and counted in one pass; the shuffle carries at most partitions x batches x bins
rows. Training counts are part of the histogram and are not recounted.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.chisq import chi2_sf_col, table_dof_col, table_stat_col
from .histogram import Histogram

RESULT = ("stat", "dof", "p_value", "reject", "n_bins", "min_train", "min_expected", "n_train", "n_test", "cramers_v", "valid_train", "valid_expected")


def contingency_long(hist: Histogram, test: DataFrame, by: Sequence[str] = (), how: str = "auto", on_invalid: str = "error") -> DataFrame:
    """(by..., bin, n) of the rows of test."""
    return hist.assign(test, how=how, on_invalid=on_invalid).groupBy(*by, "bin").agg(F.count("*").alias("n"))


def contingency_wide(hist: Histogram, test: DataFrame, by: Sequence[str] = (), train: DataFrame | None = None, how: str = "auto", on_invalid: str = "error") -> DataFrame:
    """(by..., o, t): arrays of training and test counts, zeros where a bin is empty. train: counted instead of the stored counts."""
    bins = list(range(hist.n_bins)) + ([hist.n_bins] if hist.kind == "category" else []) + ([-1] if on_invalid == "bin" else [])

    def arrays(df: DataFrame, keys: Sequence[str], name: str) -> DataFrame:
        cells = [F.coalesce(F.sum(F.when(F.col("bin") == b, F.col("n"))), F.lit(0)).cast("long") for b in bins]
        return contingency_long(hist, df, keys, how, on_invalid).groupBy(*keys).agg(F.array(*cells).alias(name))

    got = arrays(test, by, "t")
    if train is not None:
        return got.crossJoin(F.broadcast(arrays(train, (), "o"))).select(*by, "o", "t")
    counts = [int(hist.counts[b]) if 0 <= b < hist.n_bins else 0 for b in bins]
    return got.select(*by, F.array(*(F.lit(c).cast("long") for c in counts)).alias("o"), "t")


def judge(tables: DataFrame, alpha: float = 0.05, form: str = "table", yates: bool = False, keep: Sequence[str] = ()) -> DataFrame:
    """Test results of rows with count arrays o and t."""
    if not 0 < alpha < 1:
        raise ValueError("alpha must be in (0, 1)")
    total = lambda a: F.aggregate(a, F.lit(0).cast("long"), lambda s, v: s + v)
    n, q = total(F.col("o")), total(F.col("t"))
    o, t = F.col("o"), F.col("t")
    if form == "table":
        stat, dof = table_stat_col(o, t), table_dof_col(o, t)
        if yates:
            gap = lambda a, b: F.greatest(F.abs(q * a - n * b) - (n + q) / 2.0, F.lit(0.0))
            cells = F.zip_with(o, t, lambda a, b: F.when(a + b > 0, gap(a, b) * gap(a, b) / (a + b)).otherwise(0.0))
            stat = F.aggregate(cells, F.lit(0.0), lambda s, v: s + v) / (n.cast("double") * q)
    elif form == "gof":
        cells = F.zip_with(o, t, lambda a, b: F.when(a > 0, (b - q * a / n) * (b - q * a / n) / (q * a / n)).otherwise(0.0))
        stat, dof = F.aggregate(cells, F.lit(0.0), lambda s, v: s + v), F.size(F.filter(o, lambda a: a > 0)) - 1
    else:
        raise ValueError("form is 'table' or 'gof'")
    out = tables.withColumn("n_train", n).withColumn("n_test", q)
    ready = (F.col("n_train") > 0) & (F.col("n_test") > 0)
    out = out.withColumn("stat", F.when(ready, stat).otherwise(0.0)).withColumn("dof", F.when(ready, dof).otherwise(0).cast("int"))
    out = out.withColumn("p_value", chi2_sf_col(F.col("stat"), F.col("dof")))
    expected = F.col("n_test") * F.array_min("o") / F.col("n_train")
    return out.select(
        *keep, "stat", "dof", "p_value", (F.col("p_value") < alpha).alias("reject"), F.size("o").alias("n_bins"), F.array_min("o").alias("min_train"),
        F.when(F.col("n_train") > 0, expected).alias("min_expected"), "n_train", "n_test",
        F.when(ready, F.sqrt(F.col("stat") / (F.col("n_train") + F.col("n_test")))).otherwise(0.0).alias("cramers_v"),
        (F.array_min("o") >= 50).alias("valid_train"), F.coalesce(expected >= 5, F.lit(False)).alias("valid_expected"),
    )


def detect(hist: Histogram, test: DataFrame, by: Sequence[str] = (), alpha: float = 0.05, form: str = "table", yates: bool = False, train: DataFrame | None = None, how: str = "auto", on_invalid: str = "error") -> DataFrame:
    """One test result for each value of `by` (one in all without)."""
    return judge(contingency_wide(hist, test, by, train, how, on_invalid), alpha, form, yates, by)


def benjamini_hochberg(results: DataFrame, alpha: float = 0.05) -> DataFrame:
    """results with `reject` at a controlled rate of false alarms over all their rows (one row per window or batch).

    The number of rejections is the largest k with k p-values at or below alpha k / n; from k = n on, counting those and taking the count as
    the next k falls to it, so each step is one distributed count and no row is ranked.
    """
    held = results.persist()
    n = held.count()
    k = n
    while k:
        fewer = held.where(F.col("p_value") <= alpha * k / n).count()
        if fewer == k:
            break
        k = fewer
    return held.withColumn("reject", F.col("p_value") <= alpha * k / n if k else F.lit(False))


def as_feature(df: DataFrame, label: str, features: Sequence[str], scale: float = 1.0) -> tuple[DataFrame, tuple[str, ...]]:
    """Supervised option 1: the label joins the features as a number, scaled."""
    return df.withColumn("label_feature", F.col(label).cast("double") * scale), (*features, "label_feature")


def detect_by_label(hists: dict, test: DataFrame, label: str, alpha: float = 0.05, combine: str | None = None) -> DataFrame:
    """Supervised option 2: a histogram and a test per label; combine: 'bonferroni' or 'fisher' adds one result over the labels."""
    out = None
    for value, hist in sorted(hists.items(), key=lambda kv: str(kv[0])):
        got = detect(hist, test.where(F.col(label) == value), alpha=alpha).withColumn("label", F.lit(str(value)))
        out = got if out is None else out.unionByName(got)
    if combine is None:
        return out
    if combine == "bonferroni":
        return out.agg(F.least(F.lit(1.0), F.min("p_value") * F.count("*")).alias("p_value"), F.count("*").alias("n_labels")).withColumn("reject", F.col("p_value") < alpha)
    if combine == "fisher":
        both = out.agg((-2 * F.sum(F.log(F.greatest("p_value", F.lit(1e-300))))).alias("stat"), (2 * F.count("*")).cast("int").alias("dof"))
        return both.withColumn("p_value", chi2_sf_col(F.col("stat"), F.col("dof"))).withColumn("reject", F.col("p_value") < alpha)
    raise ValueError("combine is 'bonferroni' or 'fisher'")


def offset_report(hist: Histogram, a: DataFrame, b: DataFrame, cell: Column, eps: float = 0.0) -> DataFrame:
    """(bin, av, pv, is_offset, margin): absolute and probability variation of each bin between samples a and b.

    cell: an expression that cuts rows into fine cells; av sums the cells' differences of share, pv is the difference of the sums.
    """
    na, nb = a.count(), b.count()
    if not na or not nb:
        raise ValueError("both samples need rows")
    side = lambda df, n, sign: hist.assign(df).withColumn("cell", cell).groupBy("bin", "cell").agg((F.count("*") * sign / n).alias("s"))
    cells = side(a, na, 1.0).unionByName(side(b, nb, -1.0)).groupBy("bin", "cell").agg(F.sum("s").alias("gap"))
    out = cells.groupBy("bin").agg(F.sum(F.abs("gap")).alias("av"), F.abs(F.sum("gap")).alias("pv"))
    return out.select("bin", "av", "pv", (F.col("av") - F.col("pv") > eps).alias("is_offset"), (F.col("av") - F.col("pv")).alias("margin"))


def bin_table(hist: Histogram, df: DataFrame) -> DataFrame:
    """(bin, n, share, extent): counts, shares and mean distance to the bin's mean."""
    cols = hist.columns()
    placed = hist.assign(df).select("bin", *(c.alias(f"f{i}") for i, c in enumerate(cols)))
    means = placed.groupBy("bin").agg(*(F.avg(f"f{i}").alias(f"m{i}") for i in range(len(cols))))
    gap = sum(((F.col(f"f{i}") - F.col(f"m{i}")) * (F.col(f"f{i}") - F.col(f"m{i}")) for i in range(len(cols))), F.lit(0.0))
    out = placed.join(F.broadcast(means), "bin").groupBy("bin").agg(F.count("*").alias("n"), F.avg(F.sqrt(gap)).alias("extent"))
    total = out.agg(F.sum("n").alias("total"))
    return out.crossJoin(F.broadcast(total)).select("bin", "n", (F.col("n") / F.col("total")).alias("share"), "extent")


def partition_quality(hist: Histogram, df: DataFrame) -> DataFrame:
    """One row: mean bin extent, sd of shares (population), least count, bins possible at 50 rows each."""
    return bin_table(hist, df).agg(F.avg("extent").alias("mean_extent"), F.stddev_pop("share").alias("intensity_sd"), F.min("n").alias("min_count"), F.floor(F.sum("n") / 50).alias("bins_possible"))
