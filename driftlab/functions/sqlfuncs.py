"""SQL functions: labels, weights, tails, reports."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..session import ship
from .chisq import chi2_sf, table_stat


def chi2_sf_series(x: pd.Series, dof: pd.Series) -> pd.Series:
    return pd.Series([chi2_sf(float(a), int(b)) for a, b in zip(x, dof, strict=True)])


def bin_weight_series(ratio: pd.Series, theta: pd.Series) -> pd.Series:
    return np.exp(theta * (ratio - 1.0))


def vec_mean_series(v: pd.Series) -> list[float]:
    """Mean vector of a group."""
    return np.stack(v.to_numpy()).mean(axis=0).astype(float).tolist()


class Chi2Report:
    """chi2_report(TABLE(bin, o, t)): the test of a long count table."""

    def __init__(self):
        self.o, self.t = [], []

    def eval(self, row):
        self.o.append(row["o"])
        self.t.append(row["t"])

    def terminate(self) -> Iterator[tuple]:
        if self.o:
            stat, dof = table_stat(self.o, [self.t])
            yield float(stat[0]), int(dof[0]), chi2_sf(float(stat[0]), int(dof[0]))


class ThetaSweep:
    """theta_sweep(TABLE(features), centroids as flat array, bins, top, step): counts of every bin at every strength."""

    def __init__(self):
        self.rows = []

    def eval(self, row, centroids, bins, top, step):
        self.rows.append(list(row["features"]))
        self.args = (centroids, bins, top, step)

    def terminate(self) -> Iterator[tuple]:
        from ..operators.fitting import bin_weights, intensity, theta_grid
        from ..operators.histogram import nearest

        if not self.rows:
            return
        centroids, bins, top, step = self.args
        x, mu = np.array(self.rows, float), np.array(centroids, float).reshape(int(bins), -1)
        ratio = intensity(np.bincount(nearest(x, mu), minlength=len(mu)))
        for theta in theta_grid(float(top), float(step)):
            for b, n in enumerate(np.bincount(nearest(x, mu, bin_weights(ratio, theta)), minlength=len(mu)).tolist()):
                yield float(theta), b, int(n)


def register_tables(spark: SparkSession) -> None:
    """Registers the table functions chi2_report and theta_sweep."""
    ship(spark)
    spark.udtf.register("chi2_report", udtf(Chi2Report, returnType="stat double, dof int, p_value double"))
    spark.udtf.register("theta_sweep", udtf(ThetaSweep, returnType="theta double, bin int, n long"))


def register_all(spark: SparkSession, models: dict | None = None) -> None:
    """Registers chi2_sf, bin_weight, vec_mean, chi2_report, theta_sweep, and assign_bin(features, model name) over the given histograms."""
    ship(spark)
    held = dict(models or {})

    @F.pandas_udf("int")
    def assign_bin(features: pd.Series, model: pd.Series) -> pd.Series:
        out = np.full(len(features), -1, np.int32)
        for name in model.unique():
            rows = np.flatnonzero((model == name).to_numpy())
            out[rows] = held[name].label(np.stack(features.iloc[rows].to_numpy()).astype(float))
        return pd.Series(out)

    spark.udf.register("chi2_sf", F.pandas_udf(chi2_sf_series, "double"))
    spark.udf.register("bin_weight", F.pandas_udf(bin_weight_series, "double"))
    spark.udf.register("vec_mean", F.pandas_udf(vec_mean_series, "array<double>"))
    spark.udf.register("assign_bin", assign_bin)
    register_tables(spark)
