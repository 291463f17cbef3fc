"""Fitting the balanced partition: equal-count seeding, seeded clustering, rescaling, choice of K.

The kernels work on a bounded sample inside one task; `fit_balanced` brings the sample to the
driver once (its size is a checked parameter), broadcasts it and tries numbers of bins in parallel tasks.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import shared_folder, ship
from .histogram import CentroidHistogram, nearest

#: Rows a fit may bring to one task.
SAMPLE_CAP = 20_000


@dataclass(frozen=True)
class FitOptions:
    """Options of a fit.

    beta: least count of a bin. k_init: first number of bins, rows / beta by default. ratio: 'relative' (count
    over expected count) or 'share' (count over rows). stop: 'first' feasible strength, 'last' of
    the grid only, or 'best' (most even counts). search: 'linear', 'waves' (parallel tasks) or
    'bisect' (approximate: feasibility is not monotone). fallback: k-means with unit weights from 'random' rows or
    from the 'first' ones, which are a random choice of a sample drawn by keys. init: 'greedy', 'random' or 'first'. expect_test_size: also ask for 5 expected test rows in each bin.
    scale: 'none', 'zscore', 'minmax' or 'robust'. nn: neighbour engine 'incremental', 'brute' or 'grid'.
    sample_cap: rows of the table that a fit sees, drawn by a hash of the columns `keys` (of the row's place without). recount: the histogram of
    a table carries the counts of the whole table, not of the rows it was fitted to. count_share: share of a sample that is kept from the fit
    and counted in its place, since bins made even on the rows they are fitted to are too even on them.
    """

    beta: int = 50
    k_init: int | None = None
    grid: tuple[float, ...] | None = None
    ratio: str = "relative"
    stop: str = "first"
    search: str = "linear"
    fallback: str = "random"
    init: str = "greedy"
    expect_test_size: int | None = None
    scale: str = "none"
    nn: str = "incremental"
    sample_cap: int | None = SAMPLE_CAP
    max_iter: int = 100
    tol: float = 1e-6
    k_max: int | None = None
    seed: int = 0
    keys: tuple[str, ...] = ()
    recount: bool = True
    count_share: float = 0.0


def theta_grid(top: float = 1.5, step: float = 0.05) -> tuple[float, ...]:
    return tuple(round(i * step, 10) for i in range(int(round(top / step)) + 1))


def block_sizes(n: int, k: int) -> list[int]:
    """n split into k sizes that differ by one at most, the larger ones first."""
    if not 0 < k <= n:
        raise ValueError("need 0 < K <= n")
    return [n // k + (i < n % k) for i in range(k)]


# ------------------------------------------------------------------ seeding


def _distances(x: np.ndarray, rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
    a, b = x[rows], x[cols]
    if x.shape[1] < 8:  # by differences: equal distances are equal to the last bit, so ties go to the lower row
        d = np.zeros((len(a), len(b)))
        for j in range(x.shape[1]):
            gap = a[:, j, None] - b[None, :, j]
            gap *= gap
            d += gap
        return d
    d = (a**2).sum(1)[:, None] + (b**2).sum(1)[None, :] - 2 * a @ b.T
    return np.maximum(d, 0.0)


class Neighbours:
    """Squared distance to the nearest remaining row, for each remaining row."""

    def __init__(self, x: np.ndarray, how: str = "incremental"):
        self.x, self.how = x - x.mean(axis=0) if x.shape[1] >= 8 else x, how
        self.left = np.ones(len(x), bool)
        self.near = np.full(len(x), -1)
        self.dist = np.full(len(x), np.inf)
        self.update(np.arange(len(x)))

    def update(self, rows: np.ndarray) -> None:
        cols = np.flatnonzero(self.left)
        if self.how == "grid" and self.x.shape[1] <= 3 and len(cols) > 64:
            self._by_grid(rows, cols)
            return
        for i in range(0, len(rows), 1024):
            part = rows[i : i + 1024]
            d = _distances(self.x, part, cols)
            d[np.arange(len(part)), np.searchsorted(cols, part)] = np.inf
            if d.shape[1] > 1:
                at = d.argmin(axis=1)
                self.near[part], self.dist[part] = cols[at], d[np.arange(len(part)), at]
            else:
                self.near[part], self.dist[part] = -1, np.inf

    def _by_grid(self, rows: np.ndarray, cols: np.ndarray) -> None:
        """Rows of the neighbouring grid cells first; a row whose find is not nearer than the cell's reach is searched in full."""
        m = self.x.shape[1]
        low, high = self.x[cols].min(axis=0), self.x[cols].max(axis=0)
        cells = max(1, int(round((len(cols) / 8) ** (1 / m))))
        width = np.where(high > low, (high - low) / cells, 1.0)
        cell = np.clip(((self.x - low) / width).astype(int), 0, cells - 1)
        of: dict[tuple, list[int]] = {}
        for r in cols.tolist():
            of.setdefault(tuple(cell[r]), []).append(r)
        far = []
        for r in rows.tolist():
            around = [()]
            for j in range(m):
                around = [(*a, c) for a in around for c in (cell[r][j] - 1, cell[r][j], cell[r][j] + 1)]
            cand = np.array([c for a in around for c in of.get(a, []) if c != r], int)
            if len(cand):
                d = ((self.x[cand] - self.x[r]) ** 2).sum(axis=1)
                best = d.argmin()
                if d[best] <= width.min() ** 2:
                    self.near[r], self.dist[r] = cand[best], d[best]
                    continue
            far.append(r)
        how, self.how = self.how, "brute"
        if far:
            self.update(np.array(far))
        self.how = how

    def drop(self, rows: np.ndarray) -> None:
        self.left[rows] = False
        self.dist[rows] = -np.inf
        keep = np.flatnonzero(self.left)
        if not len(keep):
            return
        if self.how == "brute":
            self.update(keep)
        else:
            self.update(keep[~self.left[self.near[keep]] | (self.near[keep] < 0)])


def greedy_seed(x: np.ndarray, k: int, sizes: Sequence[int] | None = None, nn: str = "incremental") -> tuple[np.ndarray, np.ndarray]:
    """(seeds, block of each row): each round takes the most isolated remaining row and its closest remaining rows as a block.

    Ties go to the lower row. A single remaining row is taken as it is.
    """
    x = np.asarray(x, float)
    sizes = block_sizes(len(x), k) if sizes is None else list(sizes)
    if len(sizes) != k or sum(sizes) != len(x) or min(sizes) < 1:
        raise ValueError("block sizes must be positive and sum to the rows")
    state = Neighbours(x, nn)
    block = np.full(len(x), -1)
    seeds = np.empty((k, x.shape[1]))
    for b, size in enumerate(sizes):
        left = np.flatnonzero(state.left)
        first = left[state.dist[left].argmax()] if len(left) > 1 else left[0]
        d = ((x[left] - x[first]) ** 2).sum(axis=1)
        d[left == first] = -1.0
        take = left[np.argsort(d, kind="stable")[:size]]
        block[take] = b
        seeds[b] = x[take].mean(axis=0)
        state.drop(take)
    return seeds, block


# ------------------------------------------------------------------ clustering


def lloyd(x: np.ndarray, init: np.ndarray, max_iter: int = 100, tol: float = 1e-6) -> tuple[np.ndarray, np.ndarray, int]:
    """(centroids, labels, passes); an empty cluster keeps its centre."""
    mu = np.array(init, float)
    label = nearest(x, mu)
    for step in range(1, max_iter + 1):
        n = np.bincount(label, minlength=len(mu))
        new = mu.copy()
        for j in range(x.shape[1]):
            s = np.bincount(label, weights=x[:, j], minlength=len(mu))
            new[n > 0, j] = s[n > 0] / n[n > 0]
        moved = float(((new - mu) ** 2).sum())
        mu = new
        after = nearest(x, mu)
        if moved <= tol or np.array_equal(after, label):
            return mu, after, step
        label = after
    return mu, label, max_iter


def lloyd_table(df: DataFrame, features: Sequence[str], init: np.ndarray, max_iter: int = 20, tol: float = 1e-6) -> tuple[np.ndarray, int]:
    """The same on a table of any size: each pass is one aggregation to K rows, which alone come to the driver."""
    from .histogram import fixed_histogram

    mu = np.array(init, float)
    for step in range(1, max_iter + 1):
        rows = fixed_histogram(features, mu).assign(df.select(*features)).groupBy("bin").agg(*(F.avg(F.col(f).cast("double")).alias(f"m{i}") for i, f in enumerate(features))).collect()
        new = mu.copy()
        for r in rows:
            new[r.bin] = [r[f"m{i}"] for i in range(len(features))]
        moved = float(((new - mu) ** 2).sum())
        mu = new
        if moved <= tol:
            return mu, step
    return mu, max_iter


# ------------------------------------------------------------------ intensity, weights, strength


def intensity(counts: np.ndarray, mode: str = "relative") -> np.ndarray:
    counts = np.asarray(counts, float)
    n = counts.sum()
    if mode == "share":
        return counts / n
    if mode == "relative":
        return counts / np.array(block_sizes(int(n), len(counts)), float)
    raise ValueError("ratio is 'share' or 'relative'")


def bin_weights(ratio: np.ndarray, theta: float) -> np.ndarray:
    return np.exp(theta * (np.asarray(ratio, float) - 1.0))


def _feasible(counts: np.ndarray, o: FitOptions) -> bool:
    if counts.min() < o.beta:
        return False
    return o.expect_test_size is None or o.expect_test_size * counts.min() / counts.sum() >= 5


def theta_search(x: np.ndarray, mu: np.ndarray, ratio: np.ndarray, o: FitOptions) -> tuple[float, np.ndarray, np.ndarray, int] | None:
    """(strength, weights, counts, tried) of the strength chosen by o.stop, or None."""
    grid = theta_grid() if o.grid is None else o.grid
    d = ((x[:, None, :] - mu[None, :, :]) ** 2).sum(axis=2)
    best, tried = None, 0
    for theta in grid[-1:] if o.stop == "last" else grid:
        w = bin_weights(ratio, theta)
        counts = np.bincount((d * w**2).argmin(axis=1), minlength=len(mu))
        tried += 1
        if _feasible(counts, o):
            if o.stop != "best":
                return theta, w, counts, tried
            if best is None or counts.std() < best[2].std() - 1e-12:
                best = (theta, w, counts, tried)
    return best


def theta_table(df: DataFrame, features: Sequence[str], centroids: np.ndarray, ratio: np.ndarray, grid: Sequence[float] | None = None) -> DataFrame:
    """(theta, bin, n): bin counts of a table of any size at every strength.

    Distances are computed once per Arrow batch and reused for the whole grid; a batch puts out its counts, strengths x bins
    rows, and those are summed in one small shuffle.
    """
    ship(df.sparkSession)
    mu = np.asarray(centroids, float)
    steps = tuple(theta_grid() if grid is None else grid)
    squares = [bin_weights(ratio, t) ** 2 for t in steps]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = np.zeros((len(steps), len(mu)), np.int64)
        for f in frames:
            x = f.to_numpy(float)
            d = np.zeros((len(x), len(mu)))
            for j in range(x.shape[1]):
                d += (x[:, [j]] - mu[:, j]) ** 2
            for k, w2 in enumerate(squares):
                total[k] += np.bincount((d * w2).argmin(axis=1), minlength=len(mu))
        at, b = np.nonzero(total)
        yield pd.DataFrame({"theta": np.array(steps, float)[at], "bin": b.astype(np.int32), "n": total[at, b]})

    rows = df.select(*(F.col(f).cast("double").alias(f"x{i}") for i, f in enumerate(features)))
    return rows.mapInPandas(run, "theta double, bin int, n long").groupBy("theta", "bin").agg(F.sum("n").alias("n"))


# ------------------------------------------------------------------ the whole fit


def start_rows(x: np.ndarray, k: int, how: str, seed) -> np.ndarray:
    """k rows to start from: 'random' ones, or the 'first' ones of a sample that is in random order already."""
    if how not in ("random", "first"):
        raise ValueError("rows to start from are 'random' or 'first'")
    return x[:k] if how == "first" else x[np.random.default_rng(seed).choice(len(x), k, replace=False)]


def try_k(x: np.ndarray, k: int, o: FitOptions) -> tuple[float, np.ndarray, np.ndarray, np.ndarray, int, int] | None:
    """(theta, centroids, weights, counts, passes, thetas tried) if k bins are feasible."""
    if o.init == "greedy":
        seeds, _ = greedy_seed(x, k, nn=o.nn)
    else:
        seeds = start_rows(x, k, o.init, [o.seed, k])
    mu, label, passes = lloyd(x, seeds, o.max_iter, o.tol)
    found = theta_search(x, mu, intensity(np.bincount(label, minlength=k), o.ratio), o)
    return None if found is None else (found[0], mu, found[1], found[2], passes, found[3])


def first_k(n: int, o: FitOptions) -> int:
    k = o.k_init or n // o.beta
    return max(1, min(k, n, o.k_max or n))


def _one_bin(x: np.ndarray, features: Sequence[str], o: FitOptions, trail: tuple) -> CentroidHistogram:
    """Nothing was feasible: k-means from random (or the first) rows with unit weights, on the first K."""
    k = first_k(len(x), o)
    init = start_rows(x, k, o.fallback, o.seed)
    mu, label, _ = lloyd(x, init, o.max_iter, o.tol)
    return CentroidHistogram(features=tuple(features), counts=np.bincount(label, minlength=k), kind="fallback", centroids=mu, weights=np.ones(k), trail=trail)


def scaler(x: np.ndarray, how: str) -> tuple[np.ndarray | None, np.ndarray | None]:
    if how == "none":
        return None, None
    if how == "zscore":
        shift, scale = x.mean(axis=0), x.std(axis=0)
    elif how == "minmax":
        shift, scale = x.min(axis=0), np.ptp(x, axis=0)
    elif how == "robust":
        low, shift, high = np.percentile(x, [25, 50, 75], axis=0)
        scale = high - low
    else:
        raise ValueError("scale is 'none', 'zscore', 'minmax' or 'robust'")
    return shift, np.where(scale > 0, scale, 1.0)


def fit_array(x: np.ndarray, features: Sequence[str], o: FitOptions | None = None, attempt: Callable | None = None) -> CentroidHistogram:
    """Fits a sample: K from its first value down to 2 until a strength is feasible."""
    o = o or FitOptions()
    x = np.asarray(x, float)
    if len(x) == 0:
        raise ValueError("the training sample is empty")
    if not np.isfinite(x).all():
        raise ValueError("a training feature is null, NaN or infinite")
    if o.count_share:
        order = np.random.default_rng([o.seed, 1]).permutation(len(x))
        kept = max(1, round(len(x) * (1 - o.count_share)))
        hist = fit_array(x[order[:kept]], features, replace(o, count_share=0.0), attempt)
        return replace(hist, counts=np.bincount(hist.label(x[order[kept:]]), minlength=hist.n_bins))
    shift, scale = scaler(x, o.scale)
    z = x if shift is None else (x - shift) / scale
    attempt = attempt or (lambda k: try_k(z, k, o))
    trail: list = []
    hit = None
    if o.search == "bisect":
        lo, hi = 2, first_k(len(z), o)
        while lo <= hi:
            mid = (lo + hi) // 2
            got = attempt(mid)
            trail.append((mid, got is not None))
            if got is not None:
                hit, lo = (mid, got), mid + 1
            else:
                hi = mid - 1
    else:
        for k in range(first_k(len(z), o), 1, -1):
            got = attempt(k)
            trail.append((k, got is not None))
            if got is not None:
                hit = (k, got)
                break
    if hit is None:
        out = _one_bin(z, features, o, tuple(trail))
    else:
        theta, mu, w, counts, passes, tried = hit[1]
        out = CentroidHistogram(features=tuple(features), counts=counts, kind="balanced", theta=theta, centroids=mu, weights=w, trail=tuple(trail), params={"passes": passes, "thetas": tried})
    return replace(out, shift=shift, scale=scale, params={**out.params, "beta": o.beta, "ratio": o.ratio, "stop": o.stop})


def take_sample(df: DataFrame, features: Sequence[str], cap: int | None, seed: int = 0, keys: Sequence[str] = ()) -> np.ndarray:
    """At most cap rows of smallest hash, as an array; all rows where cap is None, which must then be few.

    The hash is the MD5 of seed and key columns, or, without keys, a hash of the row's place in the table, so rows of equal features are drawn each by
    itself. With keys the sample and its order do not depend on how the table is split, and other engines can draw it too.
    """
    drawn = F.md5(F.concat_ws(":", F.lit(str(seed)), *(F.col(k).cast("string") for k in keys))) if keys else F.xxhash64(F.lit(seed), F.monotonically_increasing_id())
    rows = df.select(*(F.col(f).cast("double").alias(f) for f in features), drawn.alias("__draw"))
    if cap is not None:
        rows = rows.orderBy("__draw", *features).limit(cap)
    return rows.drop("__draw").toPandas().to_numpy(float)


def recounted(hist: CentroidHistogram, train: DataFrame):
    """hist with the counts of the whole table, by one distributed pass."""
    got = {r.bin: r.n for r in hist.assign(train).groupBy("bin").agg(F.count("*").alias("n")).collect()}
    return replace(hist, counts=np.array([got.get(b, 0) for b in range(hist.n_bins)], np.int64))


def fit_balanced(train: DataFrame, features: Sequence[str], options: FitOptions | None = None, **changes) -> CentroidHistogram:
    """The balanced histogram of a table: a bounded sample is fitted, by search='waves' with one task per number of bins; the counts are the whole table's."""
    o = replace(options or FitOptions(), **changes)
    hist = _fit_sample(train, features, o)
    return recounted(hist, train) if o.recount else hist


def _fit_sample(train: DataFrame, features: Sequence[str], o: FitOptions) -> CentroidHistogram:
    x = take_sample(train, features, o.sample_cap, o.seed, o.keys)
    if o.search != "waves" or o.count_share or not len(x):
        return fit_array(x, features, o)
    spark = train.sparkSession
    ship(spark)
    shift, scale = scaler(x, o.scale)
    z = x if shift is None else (x - shift) / scale
    held = spark.sparkContext.broadcast((z, o))
    width = max(2, spark.sparkContext.defaultParallelism)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        points, opts = held.value
        for f in frames:
            for k in f["id"]:
                got = try_k(points, int(k), opts)
                if got is not None:
                    theta, mu, w, counts, passes, tried = got
                    yield pd.DataFrame({"k": [int(k)], "theta": [theta], "mu": [mu.ravel().tolist()], "w": [w.tolist()], "counts": [counts.tolist()], "passes": [passes], "tried": [tried]})

    top = first_k(len(x), o)
    trail: list = []
    while top > 1:
        low = max(1, top - width)
        found = spark.range(low + 1, top + 1, 1, top - low).mapInPandas(run, "k int, theta double, mu array<double>, w array<double>, counts array<long>, passes int, tried int").orderBy(F.desc("k")).collect()
        best = found[0] if found else None
        trail += [(k, best is not None and k == best.k) for k in range(top, (best.k if best else low + 1) - 1, -1)]
        if best is not None:
            mu = np.array(best.mu).reshape(best.k, -1)
            return CentroidHistogram(features=tuple(features), counts=np.array(best.counts), kind="balanced", theta=best.theta, centroids=mu, weights=np.array(best.w), shift=shift, scale=scale, trail=tuple(trail), params={"passes": best.passes, "thetas": best.tried, "beta": o.beta, "ratio": o.ratio, "stop": o.stop})
        top = low
    out = _one_bin(z, features, o, tuple(trail))
    return replace(out, shift=shift, scale=scale)


def principal_axes(x: np.ndarray, d: int) -> np.ndarray:
    """Columns of the first d principal axes (signs fixed by their largest element)."""
    _, _, vt = np.linalg.svd(x - x.mean(axis=0), full_matrices=False)
    axes = vt[:d].T
    return axes * np.sign(axes[np.abs(axes).argmax(axis=0), np.arange(axes.shape[1])])


def pca_columns(df: DataFrame, features: Sequence[str], d: int, sample_cap: int = SAMPLE_CAP, seed: int = 0) -> tuple[DataFrame, tuple[str, ...], np.ndarray]:
    """df with d projected columns pc1, ..., their names, and the axes: dimension reduction before a fit, as generated code."""
    x = take_sample(df, features, sample_cap, seed)
    axes, centre = principal_axes(x, d), x.mean(axis=0)
    names = tuple(f"pc{k + 1}" for k in range(d))
    cols = {}
    for k, name in enumerate(names):
        c = F.lit(0.0)
        for j, f in enumerate(features):
            c = c + (F.col(f).cast("double") - float(centre[j])) * float(axes[j, k])
        cols[name] = c
    return df.withColumns(cols), names, axes


# ------------------------------------------------------------------ relational twin


def _sum_squares(features: Sequence[str], other: str):
    """Squared distance between the row and the fields of the struct `other`."""
    return sum(((F.col(f) - F.col(f"{other}.{f}")) * (F.col(f) - F.col(f"{other}.{f}")) for f in features), F.lit(0))


#: Grid levels of a search for the most isolated row; each halves the cells.
LEVELS = 26


def most_isolated(left: DataFrame, features: Sequence[str], id_col: str = "id") -> dict:
    """The row that is farthest from its nearest neighbour, ties to the lower id.

    Rows with equal features have distance 0 and need no search. A single row shares a grid cell with another row at some finest level, which bounds its distance;
    rows whose bound is below a distance already found are out, the others meet the rows of the cells around theirs. At most 2^m of them are in one cell
    of their level (m features), so the pairs grow with the rows and not with their square, but for the levels beyond the finest one. Cells go by the first three features.
    """
    m = min(3, len(features))
    copies = left.groupBy(*features).agg(F.min(id_col).alias(id_col), F.count("*").alias("copies")).persist()
    whole = left.agg(F.min_by(F.struct(id_col, *features), id_col).alias("s"))
    low = copies.agg(F.count("*").alias("n"), F.count_if(F.col("copies") == 1).alias("single"), *(F.min(f).cast("double").alias(f"l{j}") for j, f in enumerate(features)), *(F.max(f).cast("double").alias(f"h{j}") for j, f in enumerate(features))).first()
    if low.n < 2 or not low.single:
        copies.unpersist()
        return whole.first().s.asDict()
    width = max(low[f"h{j}"] - low[f"l{j}"] for j in range(len(features))) * (1 + 1e-9)
    cell = lambda level, j, f: F.floor((F.col(f).cast("double") - F.lit(low[f"l{j}"])) / F.lit(width) * F.pow(F.lit(2.0), level)).cast("long")
    levels = copies.select(id_col, "copies", F.explode(F.sequence(F.lit(0), F.lit(LEVELS))).alias("level"), *features)
    shared = levels.groupBy("level", *(cell(F.col("level"), j, f).alias(f"c{j}") for j, f in enumerate(features))).agg(F.count("*").alias("k"), F.min(F.struct("copies", id_col, *features)).alias("row"))
    # a row is alone in its cell from some level on; the level before bounds its distance
    alone = shared.where("k = 1 AND row.copies = 1").groupBy(F.col("row").alias("row")).agg((F.min("level") - 1).alias("level"))
    deep = levels.where((F.col("level") == LEVELS) & (F.col("copies") == 1)).select(F.struct("copies", id_col, *features).alias("row"))
    found = deep.join(alone, "row", "left").select("row", F.coalesce("level", F.lit(LEVELS)).alias("level")).persist()
    near = lambda some, rows: some.join(rows, F.col(f"row.{id_col}") != F.col(id_col)).groupBy("row").agg(F.min(_sum_squares(features, "row")).alias("d"))
    # the distances of a few rows of the widest bounds, by a scan
    first = near(F.broadcast(found.orderBy("level", f"row.{id_col}").limit(64)), copies.select(id_col, *features)).agg(F.max("d").alias("d")).first().d
    # bound of a level: the diagonal of its cell, a little more for rounding
    reach = F.pow(F.lit(0.5), F.col("level")) * F.lit(width * (1 + 1e-6))
    rest = found.where(reach * reach * len(features) * (1 + 1e-6) >= F.lit(float(first or 0))).persist()
    used = [r.level for r in rest.select("level").distinct().collect()]
    steps = int(np.sqrt(len(features))) + 1
    around = F.array(*(F.array(*(F.lit(c).cast("long") for c in at)) for at in np.ndindex(*(2 * steps + 1,) * m)))
    places = [cell(F.col("level"), j, f) for j, f in enumerate(features[:m])]
    rows = copies.select(id_col, *features, F.explode(F.array(*(F.lit(v) for v in used))).alias("level")).select(id_col, *features, "level", F.array(*places).alias("place"))
    seekers = rest.select("row", F.col("level"), F.struct("row.*").alias("r")).select("row", "level", *(F.col(f"r.{f}").alias(f) for f in features))
    seekers = seekers.select("row", "level", F.array(*places).alias("own")).select("row", "level", F.explode(around).alias("step"), "own")
    seekers = seekers.select("row", "level", F.zip_with("own", "step", lambda a, b: a + b - steps).alias("place"))
    pairs = seekers.join(rows, ["level", "place"]).where(F.col(f"row.{id_col}") != F.col(id_col))
    gaps = pairs.groupBy("row").agg(F.min(_sum_squares(features, "row")).alias("d"))
    best = gaps.where("d IS NOT NULL").agg(F.max_by(F.struct(F.col(f"row.{id_col}").alias(id_col), *(F.col(f"row.{f}").alias(f) for f in features)), F.struct("d", -F.col(f"row.{id_col}"))).alias("s"))
    s = best.first().s or whole.first().s
    for x in (rest, found, copies):
        x.unpersist()
    return s.asDict()


def first_rows(dealt: DataFrame, size: int, order: Sequence[str]) -> DataFrame:
    """The first `size` rows by `order`, of rows that are dealt to tasks by ranges of it, the number of the range in __part; only the range at the cut is sorted."""
    taken, cut = 0, None
    for r in sorted(dealt.groupBy("__part").agg(F.count("*").alias("n")).collect(), key=lambda r: r["__part"]):
        cut = r["__part"]
        if taken + r.n >= size:
            break
        taken += r.n
    at = dealt.where(F.col("__part") == F.lit(cut)).orderBy(*order).limit(size - taken)
    return dealt.where(F.col("__part") < F.lit(cut)).unionByName(at)


def seed_table(points: DataFrame, k: int, features: Sequence[str], id_col: str = "id", rounds: int | None = None) -> DataFrame:
    """Block of each row by DataFrame operators, for tables of any size: (round, id, features). Each round is the row farthest from its nearest neighbour, and its closest rows.

    The ids are unique. What the rounds leave and take is written to the shared folder, so no plan grows with the rounds.
    """
    spark = points.sparkSession
    folder = f"{shared_folder(spark)}/driftlab-seed-{uuid.uuid4().hex}"
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    sizes = block_sizes(points.count(), k)
    left = points.select(id_col, *features)
    for b in range(rounds or k):
        s = most_isolated(left, features, id_col)
        to_first = sum(((F.col(f) - F.lit(s[f])) * (F.col(f) - F.lit(s[f])) for f in features), F.lit(0))
        ranked = left.withColumn("__d", F.when(F.col(id_col) == F.lit(s[id_col]), -1).otherwise(to_first))
        dealt = ranked.repartitionByRange(tasks, "__d", id_col).withColumn("__part", F.spark_partition_id()).persist()
        first_rows(dealt, sizes[b], ("__d", id_col)).select(F.lit(b).alias("round"), id_col, *features).write.parquet(f"{folder}/blocks/b{b}")
        dealt.unpersist()
        block = spark.read.parquet(f"{folder}/blocks/b{b}")
        left.join(block.select(id_col), id_col, "left_anti").write.parquet(f"{folder}/left{b}")
        left = spark.read.parquet(f"{folder}/left{b}")
    return spark.read.parquet(*(f"{folder}/blocks/b{b}" for b in range(rounds or k))).select("round", id_col, *features)
