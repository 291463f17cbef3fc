"""The balanced histogram as a stage of a machine-learning pipeline."""

from __future__ import annotations

from dataclasses import replace

from pyspark.ml import Estimator, Model
from pyspark.ml.functions import vector_to_array
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import histogram
from .fitting import SAMPLE_CAP, FitOptions, fit_array


class _Shared(Params):
    featuresCol = Param(Params._dummy(), "featuresCol", "vector or array column", TypeConverters.toString)
    binCol = Param(Params._dummy(), "binCol", "column of bins", TypeConverters.toString)

    def _plain(self, df: DataFrame) -> DataFrame:
        name = self.getOrDefault("featuresCol")
        kind = df.schema[name].dataType.simpleString()
        return df.withColumn("__x", vector_to_array(name) if kind == "vector" else F.col(name).cast("array<double>"))


class BalancedBins(Estimator, _Shared):
    """Fits the balanced histogram to a features column."""

    beta = Param(Params._dummy(), "beta", "least count of a bin", TypeConverters.toInt)
    kInit = Param(Params._dummy(), "kInit", "first number of bins, 0 for rows / beta", TypeConverters.toInt)
    ratio = Param(Params._dummy(), "ratio", "'relative' or 'share'", TypeConverters.toString)
    stop = Param(Params._dummy(), "stop", "'first', 'last' or 'best'", TypeConverters.toString)
    search = Param(Params._dummy(), "search", "'linear' or 'bisect'", TypeConverters.toString)
    seed = Param(Params._dummy(), "seed", "seed", TypeConverters.toInt)

    def __init__(self, **params):
        super().__init__()
        self._setDefault(featuresCol="features", binCol="bin", beta=50, kInit=0, ratio="relative", stop="first", search="linear", seed=0)
        self._set(**params)

    def _fit(self, df: DataFrame) -> BalancedBinsModel:
        get = self.getOrDefault
        rows = self._plain(df).select("__x").withColumn("__draw", F.xxhash64(F.lit(get("seed")), F.monotonically_increasing_id())).orderBy("__draw", "__x").limit(SAMPLE_CAP).collect()
        if not rows:
            raise ValueError("the training sample is empty")
        import numpy as np

        x = np.array([r[0] for r in rows], float)
        o = FitOptions(beta=get("beta"), k_init=get("kInit") or None, ratio=get("ratio"), stop=get("stop"), search=get("search"), seed=get("seed"))
        hist = replace(fit_array(x, ("__x",), o), width=x.shape[1])
        return BalancedBinsModel(hist, featuresCol=get("featuresCol"), binCol=get("binCol"))


class BalancedBinsModel(Model, _Shared):
    """Adds the bin column; `hist` is the fitted histogram."""

    def __init__(self, hist: histogram.Histogram, **params):
        super().__init__()
        self.hist = hist
        self._setDefault(featuresCol="features", binCol="bin")
        self._set(**params)

    def _transform(self, df: DataFrame) -> DataFrame:
        return self.hist.assign(self._plain(df), bin_col=self.getOrDefault("binCol")).drop("__x")

    def save_to(self, spark, path: str, version: int = 1) -> None:
        histogram.save(spark, self.hist, path, version)

    @classmethod
    def load_from(cls, spark, path: str, version: int | None = None, **params) -> BalancedBinsModel:
        return cls(histogram.load(spark, path, version), **params)
