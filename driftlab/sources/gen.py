"""Synthetic samples with known drift, from hash streams that SQL can reproduce.

Kinds: uniform squares, one, two and four Gaussians, with drift of a margin in mean, variance or
covariance, and any number of further dimensions without drift. Batch form: columns on any table
with an id. A Python data source gives the same rows in batch and streaming reads.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

from ..functions.hashing import normal, uniform

# Drift margins of the six two-dimensional workloads.
MARGINS = {"2d-U-mean": 0.06, "2d-1G-mean": 0.3, "2d-1G-var": 0.2, "2d-1G-cov": 0.2, "2d-2G-mean": 0.4, "2d-4G-mean": 0.8}
# Component centres (the last one moves; centres that the source leaves open are ours).
TWO = ((4.0, 0.0), (0.0, 0.0))
FOUR = ((0.0, 0.0), (5.0, 0.0), (0.0, 5.0), (5.0, 5.0))


def point(kind: str, row: Column, drift: float = 0.0, seed: int | str = 0, run: int | str = 0, dims: int = 2, mean_shift: bool = False, mixture: str = "fixed", slide: bool = False, given: tuple[Sequence[Column], Sequence[Column]] | None = None) -> list[Column]:
    """The coordinates of one row.

    mean_shift: the variance and covariance workloads also move the mean, as their printed table has it.
    slide: the uniform workload's first coordinate moves as a whole instead of growing its range.
    given: the row's own values in place of random streams, standardised (for Gaussians) and scaled to [0, 1] (for the uniform workload).
    """
    if given is not None and min(map(len, given)) < dims:
        raise ValueError(f"{dims} dimensions need as many columns")
    extra = list(given[0][2:dims]) if given else [normal(seed, row, j, run) for j in range(10, 10 + dims - 2)]
    if kind == "2d-U-mean":
        u, *more = given[1][:dims] if given else (uniform(seed, row, j, run) for j in (0, 1, *range(10, 10 + dims - 2)))
        return [u + drift if slide else u * (1 + drift), *more]
    g0, g1 = given[0][:2] if given else (normal(seed, row, 1, run), normal(seed, row, 2, run))
    if kind == "2d-1G-mean":
        return [g0 + drift, g1, *extra]
    if kind == "2d-1G-var":
        s, m = (1 + drift) ** 0.5, drift if mean_shift else 0.0
        return [g0 * s + m, g1 * s, *extra]
    if kind == "2d-1G-cov":
        m = drift if mean_shift else 0.0
        return [g0 + m, g0 * drift + g1 * (1 - drift * drift) ** 0.5, *extra]
    if kind not in ("2d-2G-mean", "2d-4G-mean"):
        raise ValueError(f"no such kind: {kind}")
    centres = TWO if kind == "2d-2G-mean" else FOUR
    n = len(centres)
    part = F.pmod(row.cast("long"), F.lit(n)) if mixture == "fixed" else F.floor(uniform(seed, row, 9, run) * n)
    x, y = F.lit(centres[-1][0] - (drift if kind == "2d-4G-mean" else -drift)), F.lit(centres[-1][1])
    for k in range(n - 1):
        x, y = F.when(part == k, F.lit(centres[k][0])).otherwise(x), F.when(part == k, F.lit(centres[k][1])).otherwise(y)
    return [g0 + x, g1 + y, *extra]


def points(df: DataFrame, id_col: str, kind: str, drift: float = 0.0, seed: int | str = 0, dims: int = 2, **options) -> DataFrame:
    """(id, x1, x2, ...) for every row of df."""
    cols = point(kind, F.col(id_col), drift, seed, dims=dims, **options)
    return df.select(F.col(id_col).alias("id"), *(c.alias(f"x{j + 1}") for j, c in enumerate(cols)))


def partition_points(spark: SparkSession, shape: str, n: int = 1350, given: DataFrame | None = None) -> DataFrame:
    """(id, cluster, x1, x2) of the partition-shape experiment: 'one', 'even' (three equal) or 'uneven' (1 : 3 : 5) Gaussians.

    given: n rows (id, g1, g2) of a table whose standardised values stand in the place of Gaussians.
    """
    bounds = {"one": (0, 0), "even": (n // 3, 2 * n // 3), "uneven": (n // 9, 4 * n // 9)}[shape]
    ids = spark.range(n) if given is None else given
    own = (normal(shape, F.col("id"), 1), normal(shape, F.col("id"), 2)) if given is None else (F.col("g1"), F.col("g2"))
    cluster = F.lit(1) if shape == "one" else F.when(F.col("id") < bounds[0], 0).when(F.col("id") < bounds[1], 1).otherwise(2)
    x = F.when(cluster == 0, F.lit(-5.0)).when(cluster == 1, F.lit(0.0)).otherwise(5.0)
    return ids.select("id", cluster.alias("cluster"), (own[0] + x).alias("x1"), own[1].alias("x2"))


# ------------------------------------------------------------------ data source


def _uniform(seed, run, row, j) -> float:
    import hashlib

    return int(hashlib.md5(f"{seed}:{run}:{row}:{j}".encode()).hexdigest()[:8], 16) / float(1 << 32)


def _rows(start: int, stop: int, seed: str, drift: float, after: int) -> Iterator[tuple]:
    import math

    for i in range(start, stop):
        g = [math.sqrt(-2 * math.log(1 - _uniform(seed, 0, i, 2 * j))) * math.cos(2 * math.pi * _uniform(seed, 0, i, 2 * j + 1)) for j in (1, 2)]
        d = drift if i >= after else 0.0
        yield i, g[0] + d, g[1] + d


class _Part(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class DriftSource(DataSource):
    """format('drift_points'): one Gaussian whose mean moves by `drift` from row `after` on. Options: rows, seed, drift, after, parts, step."""

    @classmethod
    def name(cls) -> str:
        return "drift_points"

    def schema(self) -> str:
        return "id long, x1 double, x2 double"

    def _option(self, name: str, default: float) -> float:
        return type(default)(self.options.get(name, default))

    def reader(self, schema) -> DataSourceReader:
        return _Batch(self)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _Stream(self)


class _Batch(DataSourceReader):
    def __init__(self, source: DriftSource):
        self.n, self.parts = source._option("rows", 1000), source._option("parts", 4)
        self.args = (source.options.get("seed", "0"), source._option("drift", 0.0), source._option("after", 0))

    def partitions(self) -> list[InputPartition]:
        edge = [self.n * k // self.parts for k in range(self.parts + 1)]
        return [_Part(a, b) for a, b in zip(edge, edge[1:], strict=False)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        return _rows(partition.start, partition.stop, *self.args)


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, source: DriftSource):
        self.n, self.step = source._option("rows", 1000), source._option("step", 250)
        self.args = (source.options.get("seed", "0"), source._option("drift", 0.0), source._option("after", 0))

    def initialOffset(self) -> dict:
        return {"row": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        stop = min(self.n, start["row"] + self.step)
        return iter(list(_rows(start["row"], stop, *self.args))), {"row": stop}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return _rows(start["row"], end["row"], *self.args)
