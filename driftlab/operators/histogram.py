"""Fitted partitions of feature space and the assignment of rows to their bins.

A histogram is small (bins x features numbers), travels inside the plan as literals or inside
Arrow functions, and labels rows without a shuffle. Assignment of weighted centroids is
argmin over bins of w^2 |x - mu|^2, ties to the lower bin.
"""

from __future__ import annotations

import json
from collections.abc import Sequence
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship

#: Up to so many terms (bins x features) the labels are generated code; beyond, an Arrow function.
EXPRESSION_TERMS = 256


@dataclass(frozen=True)
class Histogram:
    """features: column names, or one name of an array column with the number of its elements in `width`."""

    features: tuple[str, ...]
    counts: np.ndarray
    kind: str = "balanced"
    shift: np.ndarray | None = None
    scale: np.ndarray | None = None
    theta: float = 0.0
    width: int | None = None
    params: dict = field(default_factory=dict)
    trail: tuple = ()

    @property
    def n_bins(self) -> int:
        return len(self.counts)

    @property
    def n_features(self) -> int:
        return self.width or len(self.features)

    def columns(self) -> list[Column]:
        """Scaled feature columns."""
        raw = [F.col(self.features[0])[i] for i in range(self.width)] if self.width else [F.col(f) for f in self.features]
        out = []
        for i, c in enumerate(raw):
            c = c.cast("double")
            if self.shift is not None:
                c = (c - float(self.shift[i])) / float(self.scale[i])
            out.append(c)
        return out

    def scaled(self, x: np.ndarray) -> np.ndarray:
        x = np.asarray(x, float)
        if x.ndim != 2 or x.shape[1] != self.n_features:
            raise ValueError(f"schema mismatch: the histogram has {self.n_features} features, the rows {x.shape[-1] if x.ndim else 0}")
        return x if self.shift is None else (x - self.shift) / self.scale

    def label(self, x: np.ndarray) -> np.ndarray:
        return self.label_scaled(self.scaled(x))

    def label_scaled(self, x: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def expression(self, cols: list[Column]) -> Column:
        raise NotImplementedError

    def check(self, df: DataFrame) -> None:
        missing = [f for f in self.features if f not in df.columns]
        if missing:
            raise ValueError(f"schema mismatch: the rows lack {missing}")

    def assign(self, df: DataFrame, how: str = "auto", on_invalid: str = "error", bin_col: str = "bin") -> DataFrame:
        """df with the bin of each row. Null, NaN or infinite features: an error, dropped, or bin -1."""
        self.check(df)
        cols = self.columns()
        bad = F.lit(False)
        for c in cols:
            bad = bad | c.isNull() | F.isnan(c) | (F.abs(c) == float("inf"))
        if how == "auto":
            how = "expression" if self.n_bins * self.n_features <= EXPRESSION_TERMS else "arrow"
        if how == "expression":
            got = self.expression(cols)
        else:
            ship(df.sparkSession)
            shipped = replace(self, shift=None, scale=None)

            @F.pandas_udf("int")
            def labels(*parts: pd.Series) -> pd.Series:
                x = np.stack([p.to_numpy(float) for p in parts], axis=1)
                fine = np.isfinite(x).all(axis=1)
                out = np.full(len(x), -1, np.int32)
                if fine.any():
                    out[fine] = shipped.label_scaled(x[fine])
                return pd.Series(out)

            got = labels(*cols)
        if on_invalid == "drop":
            return df.where(~bad).withColumn(bin_col, got)
        if on_invalid == "bin":
            return df.withColumn(bin_col, F.when(bad, F.lit(-1)).otherwise(got))
        if on_invalid != "error":
            raise ValueError("on_invalid is 'error', 'drop' or 'bin'")
        return df.withColumn(bin_col, F.when(bad, F.raise_error(F.lit("a feature is null, NaN or infinite")).cast("int")).otherwise(got))

    def describe(self) -> dict:
        raise NotImplementedError


@dataclass(frozen=True)
class CentroidHistogram(Histogram):
    """Weighted centroids: the proposed partition, and plain k-means with unit weights."""

    centroids: np.ndarray = None
    weights: np.ndarray = None

    def label_scaled(self, x: np.ndarray) -> np.ndarray:
        return nearest(x, self.centroids, self.weights)

    def expression(self, cols: list[Column]) -> Column:
        cells = []
        for k, (mu, w) in enumerate(zip(self.centroids, self.weights, strict=True)):
            d = F.lit(0.0)
            for c, m in zip(cols, mu, strict=True):
                d = d + (c - float(m)) * (c - float(m))
            cells.append(F.struct((d * float(w * w)).alias("d"), F.lit(k).alias("bin")))
        return (F.array_min(F.array(*cells)) if len(cells) > 1 else cells[0])["bin"]

    def describe(self) -> dict:
        return {"centroids": self.centroids.tolist(), "weights": self.weights.tolist()}


@dataclass(frozen=True)
class RuleHistogram(Histogram):
    """Half-space rules in order: (feature, bound, below); the first that holds names the bin, else the last bin."""

    rules: tuple[tuple[int, float, bool], ...] = ()

    def label_scaled(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), len(self.rules), np.int64)
        open_ = np.ones(len(x), bool)
        for k, (j, bound, below) in enumerate(self.rules):
            hit = open_ & ((x[:, j] <= bound) if below else (x[:, j] >= bound))
            out[hit] = k
            open_ &= ~hit
        return out

    def expression(self, cols: list[Column]) -> Column:
        cases = [F.when((cols[j] <= bound) if below else (cols[j] >= bound), F.lit(k)) for k, (j, bound, below) in enumerate(self.rules)]
        return F.coalesce(*cases, F.lit(len(self.rules)))

    def describe(self) -> dict:
        return {"rules": [list(r) for r in self.rules]}


@dataclass(frozen=True)
class BoxTree(Histogram):
    """A binary tree of midpoint cuts. nodes: (feature, cut, left, right); a child below zero is bin -1 - child."""

    nodes: tuple[tuple[int, float, int, int], ...] = ()

    def label_scaled(self, x: np.ndarray) -> np.ndarray:
        if not self.nodes:
            return np.zeros(len(x), np.int64)
        table = np.array([(j, a, b) for j, _, a, b in self.nodes], np.int64)
        cut = np.array([c for _, c, _, _ in self.nodes])
        at = np.zeros(len(x), np.int64)
        live = np.arange(len(x))
        while len(live):
            node = at[live]
            right = x[live, table[node, 0]] > cut[node]
            at[live] = np.where(right, table[node, 2], table[node, 1])
            live = live[at[live] >= 0]
        return -1 - at

    def expression(self, cols: list[Column]) -> Column:
        def build(at: int) -> Column:
            if at < 0:
                return F.lit(-1 - at)
            j, cut, left, right = self.nodes[at]
            return F.when(cols[j] > cut, build(right)).otherwise(build(left))

        return build(0) if self.nodes else F.lit(0)

    def describe(self) -> dict:
        return {"nodes": [list(n) for n in self.nodes]}


@dataclass(frozen=True)
class GridHistogram(Histogram):
    """Equal-width bins per feature; the bin number counts them in mixed radix, rows beyond the edges go to the edge bins."""

    low: np.ndarray = None
    high: np.ndarray = None
    per_feature: int = 4

    def label_scaled(self, x: np.ndarray) -> np.ndarray:
        span = np.where(self.high > self.low, self.high - self.low, 1.0)
        cell = np.clip(np.floor((x - self.low) / span * self.per_feature), 0, self.per_feature - 1).astype(np.int64)
        return cell @ (self.per_feature ** np.arange(x.shape[1]))

    def expression(self, cols: list[Column]) -> Column:
        out = F.lit(0)
        for i, c in enumerate(cols):
            span = float(self.high[i] - self.low[i]) or 1.0
            cell = F.greatest(F.lit(0), F.least(F.lit(self.per_feature - 1), F.floor((c - float(self.low[i])) / span * self.per_feature).cast("int")))
            out = out + cell * self.per_feature**i
        return out.cast("int")

    def describe(self) -> dict:
        return {"low": self.low.tolist(), "high": self.high.tolist(), "per_feature": self.per_feature}


@dataclass(frozen=True)
class CategoryHistogram(Histogram):
    """A categorical column: its values are the bins; values unseen in training share the last bin."""

    values: tuple[str, ...] = ()

    def check(self, df: DataFrame) -> None:
        super().check(df)

    def assign(self, df: DataFrame, how: str = "auto", on_invalid: str = "bin", bin_col: str = "bin") -> DataFrame:
        at = F.array_position(F.array(*(F.lit(v) for v in self.values)), F.col(self.features[0]).cast("string")).cast("int")
        return df.withColumn(bin_col, F.when(at > 0, at - 1).otherwise(F.lit(len(self.values))))

    def describe(self) -> dict:
        return {"values": list(self.values)}


def nearest(x: np.ndarray, centroids: np.ndarray, weights: np.ndarray | None = None) -> np.ndarray:
    """argmin of w |x - mu|, in blocks; ties to the lower bin."""
    w2 = np.ones(len(centroids)) if weights is None else np.asarray(weights, float) ** 2
    out = np.empty(len(x), np.int64)
    step = max(1, (1 << 22) // max(1, centroids.size))
    for i in range(0, len(x), step):
        part = x[i : i + step]
        d = ((part[:, None, :] - centroids[None, :, :]) ** 2).sum(axis=2) * w2
        out[i : i + step] = d.argmin(axis=1)
    return out


def bins_frame(spark: SparkSession, hist: Histogram) -> DataFrame:
    """One row per bin: bin, n_train, share, and centroid and weight where the kind has them."""
    rows = []
    total = max(1, int(hist.counts.sum()))
    for k, n in enumerate(hist.counts.tolist()):
        mu = hist.centroids[k].tolist() if isinstance(hist, CentroidHistogram) else None
        w = float(hist.weights[k]) if isinstance(hist, CentroidHistogram) else None
        rows.append((k, int(n), n / total, mu, w))
    return spark.createDataFrame(rows, "bin int, n_train long, share double, centroid array<double>, weight double")


_KINDS = {c.__name__: c for c in (CentroidHistogram, RuleHistogram, BoxTree, GridHistogram, CategoryHistogram)}


def to_json(hist: Histogram) -> str:
    out = {}
    for name, v in hist.__dict__.items():
        out[name] = v.tolist() if isinstance(v, np.ndarray) else list(v) if isinstance(v, tuple) else v
    return json.dumps({"class": type(hist).__name__, **out})


def from_json(text: str) -> Histogram:
    raw = json.loads(text)
    kind = _KINDS[raw.pop("class")]
    for name in ("counts", "shift", "scale", "centroids", "weights", "low", "high"):
        if raw.get(name) is not None and name in kind.__dataclass_fields__:
            raw[name] = np.array(raw[name])
    raw["features"], raw["trail"] = tuple(raw["features"]), tuple(tuple(t) for t in raw["trail"])
    for name in ("rules", "nodes", "values"):
        if name in raw:
            raw[name] = tuple(tuple(x) if isinstance(x, list) else x for x in raw[name])
    return kind(**raw)


def save(spark: SparkSession, hist: Histogram, path: str, version: int = 1) -> None:
    """Writes one version of a histogram; other versions at the path stay."""
    frame = spark.createDataFrame([(version, to_json(hist))], "version int, model string")
    frame.coalesce(1).write.mode("append").parquet(path)


def load(spark: SparkSession, path: str, version: int | None = None) -> Histogram:
    """A version of a stored histogram, the latest by default."""
    table = spark.read.parquet(path)
    if version is not None:
        table = table.where(F.col("version") == version)
    row = table.orderBy(F.desc("version")).select("model").first()
    if row is None:
        raise ValueError("no such histogram")
    return from_json(row.model)


def fixed_histogram(features: Sequence[str], centroids, weights=None, counts=None, shift=None, scale=None) -> CentroidHistogram:
    """A centroid histogram of given numbers."""
    mu = np.array(centroids, float)
    as_array = lambda v: None if v is None else np.array(v, float)
    return CentroidHistogram(
        features=tuple(features), counts=np.zeros(len(mu), np.int64) if counts is None else np.array(counts, np.int64), kind="fixed",
        shift=as_array(shift), scale=as_array(scale), centroids=mu, weights=np.ones(len(mu)) if weights is None else np.array(weights, float),
    )
