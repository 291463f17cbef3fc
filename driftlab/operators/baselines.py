"""The detectors compared with the balanced histogram."""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.chisq import normal_cdf
from ..session import ship
from .fitting import SAMPLE_CAP, lloyd, start_rows, take_sample
from .histogram import BoxTree, CategoryHistogram, CentroidHistogram, GridHistogram, RuleHistogram

#: The quadratic baselines refuse more rows than this.
QUADRATIC_CAP = 20_000


# ------------------------------------------------------------------ fits on arrays


def plain_kmeans_array(x: np.ndarray, features: Sequence[str], k: int | None = None, beta: int = 50, max_iter: int = 100, seed: int = 0, init: str = "random") -> CentroidHistogram:
    """Random-start k-means, unit weights, no control of counts."""
    k = k or max(1, len(x) // beta)
    mu, label, passes = lloyd(x, start_rows(x, k, init, seed), max_iter)
    return CentroidHistogram(features=tuple(features), counts=np.bincount(label, minlength=k), kind="plain_kmeans", centroids=mu, weights=np.ones(k), params={"passes": passes})


def midpoint_kd_array(x: np.ndarray, features: Sequence[str], max_points: int = 100, min_side: float | None = None, max_depth: int = 30) -> BoxTree:
    """Cells are halved at the middle of their box, features in turn, while they hold more than max_points rows."""
    m = x.shape[1]
    nodes: list = []
    counts: list[int] = []

    def build(rows: np.ndarray, low: np.ndarray, high: np.ndarray, depth: int) -> int:
        j = depth % m
        side = high[j] - low[j]
        if len(rows) <= max_points or depth >= max_depth or (min_side is not None and side < min_side) or side <= 0:
            counts.append(len(rows))
            return -len(counts)
        cut = (low[j] + high[j]) / 2
        at = len(nodes)
        nodes.append(None)
        right = x[rows, j] > cut
        left_high, right_low = high.copy(), low.copy()
        left_high[j] = right_low[j] = cut
        a = build(rows[~right], low, left_high, depth + 1)
        b = build(rows[right], right_low, high, depth + 1)
        nodes[at] = (j, float(cut), a, b)
        return at

    build(np.arange(len(x)), x.min(axis=0), x.max(axis=0), 0)
    return BoxTree(features=tuple(features), counts=np.array(counts), kind="midpoint_kd", nodes=tuple(nodes))


def quantile_peel_array(x: np.ndarray, features: Sequence[str], k: int | None = None, beta: int = 50, seed: int = 0, plan: Sequence[tuple[int, bool]] | None = None) -> RuleHistogram:
    """K - 1 rounds peel about n / K rows off a tail of a feature (both random, or by plan: (feature, below)); the rest is the last bin."""
    k = k or max(1, len(x) // beta)
    rng = np.random.default_rng(seed)
    left = np.arange(len(x))
    rules, counts = [], []
    for r in range(k, 1, -1):
        j, below = plan[k - r] if plan else (int(rng.integers(x.shape[1])), bool(rng.integers(2)))
        take = max(1, int(math.floor(len(left) / r + 0.5)))
        v = np.sort(x[left, j])
        bound = float(v[take - 1] if below else v[len(v) - take])
        hit = x[left, j] <= bound if below else x[left, j] >= bound
        rules.append((j, bound, below))
        counts.append(int(hit.sum()))
        left = left[~hit]
        if not len(left):
            break
    counts.append(len(left))
    return RuleHistogram(features=tuple(features), counts=np.array(counts), kind="quantile_peel", rules=tuple(rules))


def peel_stats(counts: np.ndarray, t: np.ndarray, stat: str) -> np.ndarray:
    """Pearson ('chi2') or total-variation ('tv') statistic of each row of test counts."""
    t = np.atleast_2d(np.asarray(t, float))
    share, q = counts / counts.sum(), t.sum(axis=1, keepdims=True)
    if stat == "tv":
        return 0.5 * np.abs(t / q - share).sum(axis=1)
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(share > 0, (t - q * share) ** 2 / (q * share), 0.0).sum(axis=1)


@functools.lru_cache(maxsize=256)
def peel_threshold(stat: str, counts: tuple[int, ...], q: int, alpha: float = 0.05, draws: int = 4000, seed: int = 0) -> float:
    """(1 - alpha) quantile of the statistic without drift: Dirichlet spacings, then multinomial counts; the same for every continuous distribution."""
    rng = np.random.default_rng(seed)
    shape = np.array(counts, float)
    shape[-1] += 1
    p = rng.dirichlet(np.maximum(shape, 1e-9), size=draws)
    return float(np.quantile(peel_stats(np.array(counts), rng.multinomial(q, p), stat), 1 - alpha, method="higher"))


def threshold_table(spark: SparkSession, rows: Sequence[tuple[str, Sequence[int], int, float]], draws: int = 4000, tasks: int = 8, seed: int = 0) -> DataFrame:
    """(stat, n, q, k, alpha, threshold): thresholds simulated in parallel tasks, for (stat, bin counts, test size, alpha)."""
    ship(spark)
    frame = spark.createDataFrame([(i, s, list(map(int, c)), int(q), float(a)) for i, (s, c, q, a) in enumerate(rows)], "id int, stat string, counts array<long>, q int, alpha double")
    parts = frame.crossJoin(spark.range(tasks).select(F.col("id").cast("int").alias("part")))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for r in f.itertuples():
                rng = np.random.default_rng([seed, r.id, r.part])
                c = np.array(r.counts, float)
                shape = c.copy()
                shape[-1] += 1
                p = rng.dirichlet(np.maximum(shape, 1e-9), size=-(-draws // tasks))
                yield pd.DataFrame({"id": r.id, "value": peel_stats(c, rng.multinomial(r.q, p), r.stat)})

    values = parts.repartition(tasks, "part").mapInPandas(run, "id int, value double")
    cut = values.groupBy("id").agg(F.sort_array(F.collect_list("value")).alias("v"))
    at = F.least(F.ceil((F.size("v") - 1) * (1 - F.col("alpha"))).cast("int") + 1, F.size("v"))
    total = F.aggregate("counts", F.lit(0).cast("long"), lambda s, v: s + v)
    return cut.join(frame, "id").select("stat", total.alias("n"), "q", F.size("counts").alias("k"), "alpha", F.element_at("v", at).alias("threshold"))


def grid_array(x: np.ndarray, features: Sequence[str], per_feature: int = 4) -> GridHistogram:
    out = GridHistogram(features=tuple(features), counts=np.zeros(per_feature ** x.shape[1], np.int64), kind="grid", low=x.min(axis=0), high=x.max(axis=0), per_feature=per_feature)
    counts = np.bincount(out.label_scaled(x), minlength=out.n_bins)
    return GridHistogram(features=tuple(features), counts=counts, kind="grid", low=out.low, high=out.high, per_feature=per_feature)


def categories(train: DataFrame, column: str, max_values: int = 10_000) -> CategoryHistogram:
    """A categorical column is multinomial as it stands: one bin per value."""
    rows = train.groupBy(F.col(column).cast("string").alias("v")).agg(F.count("*").alias("n")).where("v IS NOT NULL").orderBy("v").limit(max_values + 1).collect()
    if len(rows) > max_values:
        raise ValueError(f"more than {max_values} values")
    return CategoryHistogram(features=(column,), counts=np.array([r.n for r in rows]), kind="category", values=tuple(r.v for r in rows))


# ------------------------------------------------------------------ fits on tables


def fit_table(name: str, train: DataFrame, features: Sequence[str], sample_cap: int | None = SAMPLE_CAP, seed: int = 0, keys: Sequence[str] = (), **options):
    """A baseline fitted on a bounded sample of a table."""
    x = take_sample(train, features, sample_cap, seed, keys)
    if not len(x):
        raise ValueError("the training sample is empty")
    kinds = {"plain_kmeans": plain_kmeans_array, "midpoint_kd": midpoint_kd_array, "quantile_peel": quantile_peel_array, "grid": grid_array}
    if name in ("plain_kmeans", "quantile_peel"):
        options.setdefault("seed", seed)
    return kinds[name](x, features, **options)


def kd_table(df: DataFrame, features: Sequence[str], low: Sequence[float], high: Sequence[float], depth: int, max_points: int) -> DataFrame:
    """(node, n): the midpoint tree of a table of any size; heavy nodes are halved, nodes at most max_points rows stay leaves.

    The cuts are known beforehand, so one pass counts the cells of the full depth; the tree is read off sums of these counts, level by level.
    """
    if depth > 60:
        raise ValueError("a depth of 60 at most")
    m = len(features)

    def path(f: str, a: float, b: float, bits: int):
        """The feature's halves, one bit each, the first one highest."""
        begin = F.struct(F.lit(float(a)).alias("lo"), F.lit(float(b)).alias("hi"), F.lit(0).cast("long").alias("way"))

        def step(s, _):
            mid = (s["lo"] + s["hi"]) / 2
            right = F.col(f) > mid
            return F.struct(F.when(right, mid).otherwise(s["lo"]).alias("lo"), F.when(right, s["hi"]).otherwise(mid).alias("hi"), (s["way"] * 2 + right.cast("int")).alias("way"))

        return F.aggregate(F.sequence(F.lit(1), F.lit(bits)), begin, step)["way"] if bits else F.lit(0).cast("long")

    bits = [len(range(j, depth, m)) for j in range(m)]
    ways = df.select(*(path(f, a, b, n).alias(f"w{j}") for j, (f, a, b, n) in enumerate(zip(features, low, high, bits, strict=True))))
    node = F.lit(1).cast("long")
    for level in range(depth):
        j = level % m
        node = node * 2 + F.shiftright(F.col(f"w{j}"), bits[j] - 1 - level // m).bitwiseAND(F.lit(1).cast("long"))
    cells = ways.groupBy(node.alias("cell")).agg(F.count("*").alias("n")).persist()
    state = cells.withColumn("node", F.lit(None).cast("long"))
    for level in range(depth):
        above = F.shiftright("cell", depth - level)
        light = cells.groupBy(above.alias("up")).agg(F.sum("n").alias("m")).where(F.col("m") <= max_points).select("up")
        state = state.withColumn("at", above).join(light, F.col("at") == F.col("up"), "left").withColumn("node", F.coalesce("node", "up")).drop("at", "up")
    return state.groupBy(F.coalesce("node", "cell").alias("node")).agg(F.sum("n").alias("n"))


# ------------------------------------------------------------------ spanning-tree runs test


def spanning_tree(x: np.ndarray) -> np.ndarray:
    """Edges (i, j) of the Euclidean minimum spanning tree; ties by distance, then the lower rows."""
    n = len(x)
    if n > QUADRATIC_CAP:
        raise ValueError(f"the spanning tree is quadratic; at most {QUADRATIC_CAP} rows")
    out = np.empty((max(0, n - 1), 2), np.int64)
    best, from_ = np.full(n, np.inf), np.zeros(n, np.int64)
    open_ = np.ones(n, bool)
    at = 0
    for k in range(n - 1):
        open_[at] = False
        d = ((x - x[at]) ** 2).sum(axis=1)
        better = open_ & (d < best)
        best[better], from_[better] = d[better], at
        nxt = int(np.where(open_, best, np.inf).argmin())
        out[k] = min(nxt, from_[nxt]), max(nxt, from_[nxt])
        at = nxt
    return out


class RunsSample:
    """A training sample with its spanning tree, to be joined with many test sets.

    Edges between training rows that are not in the tree of the training rows alone are in no joint tree (with ties: need not be),
    so a joint tree is sought among that tree's edges and those that touch a test row: distances inside the sample are computed once.
    """

    def __init__(self, a: np.ndarray):
        self.x = np.asarray(a, float)
        edges = spanning_tree(self.x)
        size = ((self.x[edges[:, 0]] - self.x[edges[:, 1]]) ** 2).sum(axis=1)
        ends, other = edges.ravel(), edges[:, ::-1].ravel()
        order = np.argsort(ends, kind="stable")
        self.first = np.searchsorted(ends[order], np.arange(len(self.x) + 1))
        self.other, self.size = other[order], np.repeat(size, 2)[order]

    def joined(self, b: np.ndarray) -> np.ndarray:
        """Edges (i, j) of the spanning tree of the sample and b; rows of b follow the sample's."""
        n, q = len(self.x), len(b)
        total = n + q
        if total > QUADRATIC_CAP:
            raise ValueError(f"the spanning tree is quadratic; at most {QUADRATIC_CAP} rows")
        x = np.concatenate([self.x, np.asarray(b, float)]) if n else np.asarray(b, float)
        out = np.empty((max(0, total - 1), 2), np.int64)
        best, from_ = np.full(total, np.inf), np.zeros(total, np.int64)
        open_ = np.ones(total, bool)
        at = 0
        for k in range(total - 1):
            open_[at], best[at] = False, np.inf
            # a training row reaches test rows and its neighbours in the training tree, a test row reaches all
            low = n if at < n else 0
            d = ((x[low:] - x[at]) ** 2).sum(axis=1)
            better = np.flatnonzero(open_[low:] & (d < best[low:]))
            best[low + better], from_[low + better] = d[better], at
            if at < n:
                for e in range(self.first[at], self.first[at + 1]):
                    j = self.other[e]
                    if open_[j] and self.size[e] < best[j]:
                        best[j], from_[j] = self.size[e], at
            nxt = int(best.argmin())
            out[k] = min(nxt, from_[nxt]), max(nxt, from_[nxt])
            at = nxt
        return out

    def test(self, b: np.ndarray) -> dict:
        return _runs(self.joined(b), len(self.x), len(b))


def runs_test(a: np.ndarray, b: np.ndarray) -> dict:
    """Multivariate runs test: few edges of the joint tree between the samples speak for a difference."""
    return _runs(spanning_tree(np.concatenate([a, b])), len(a), len(b))


def _runs(edges: np.ndarray, n: int, q: int) -> dict:
    total = n + q
    runs = int(((edges < n).sum(axis=1) == 1).sum()) + 1
    degree = np.bincount(edges.ravel(), minlength=total)
    pairs = float((degree * (degree - 1)).sum()) / 2
    mean = 2 * n * q / total + 1
    inner = (2 * n * q - total) / total
    if total > 3:
        inner += (pairs - total + 2) / ((total - 2) * (total - 3)) * (total * (total - 1) - 4 * n * q + 2)
    var = 2 * n * q / (total * (total - 1)) * inner
    z = (runs - mean) / math.sqrt(var) if var > 0 else 0.0
    return {"runs": runs, "mean": mean, "var": var, "z": z, "p_value": normal_cdf(z)}


def runs_table(tests: DataFrame, train: np.ndarray, features: Sequence[str], by: str, alpha: float = 0.05) -> DataFrame:
    """(by, runs, z, p_value, reject) of each batch against a training sample, one batch per task."""
    if len(train) > QUADRATIC_CAP:
        raise ValueError(f"the spanning tree is quadratic; at most {QUADRATIC_CAP} rows")
    ship(tests.sparkSession)
    held = tests.sparkSession.sparkContext.broadcast(RunsSample(train))

    def one(key, f: pd.DataFrame) -> pd.DataFrame:
        r = held.value.test(f[list(features)].to_numpy(float))
        return pd.DataFrame({by: [key[0]], "runs": [r["runs"]], "z": [r["z"]], "p_value": [r["p_value"]], "reject": [r["p_value"] < alpha]})

    kind = tests.schema[by].dataType.simpleString()
    return tests.select(by, *features).groupBy(by).applyInPandas(one, f"{by} {kind}, runs long, z double, p_value double, reject boolean")


def boruvka(points: DataFrame, features: Sequence[str], id_col: str = "id", max_rounds: int = 30) -> DataFrame:
    """(a, b, d2): the spanning tree by rounds of joins, for tables up to the quadratic cap.

    Each round takes every component's lightest outgoing edge (ties by lower ids) and relabels the components with the smallest id they reach.
    """
    n = points.count()
    if n > QUADRATIC_CAP:
        raise ValueError(f"the spanning tree is quadratic; at most {QUADRATIC_CAP} rows")
    spark = points.sparkSession
    p = points.select(F.col(id_col).alias("a"), *(F.col(f).alias(f"x{i}") for i, f in enumerate(features)))
    q = points.select(F.col(id_col).alias("b"), *(F.col(f).alias(f"y{i}") for i, f in enumerate(features)))
    gap = sum(((F.col(f"x{i}") - F.col(f"y{i}")) * (F.col(f"x{i}") - F.col(f"y{i}")) for i in range(len(features))), F.lit(0))
    edges = p.join(q, F.col("a") < F.col("b")).select("a", "b", gap.alias("d2")).persist()
    comp = {r.a: r.a for r in p.select("a").collect()}
    tree: set = set()
    for _ in range(max_rounds):
        if len(set(comp.values())) <= 1:
            break
        label = spark.createDataFrame(list(comp.items()), "id long, c long")
        la, lb = label.select(F.col("id").alias("a"), F.col("c").alias("ca")), label.select(F.col("id").alias("b"), F.col("c").alias("cb"))
        cross = edges.join(F.broadcast(la), "a").join(F.broadcast(lb), "b").where("ca <> cb")
        ends = cross.select(F.explode(F.array("ca", "cb")).alias("c"), F.struct("d2", "a", "b").alias("e"))
        for r in ends.groupBy("c").agg(F.min("e").alias("e")).collect():
            tree.add((r.e.a, r.e.b, r.e.d2))
        low = dict(comp)
        changed = True
        while changed:
            changed = False
            for a, b, _d in tree:
                m = min(low[a], low[b])
                if low[a] != m or low[b] != m:
                    low[a] = low[b] = m
                    changed = True
        comp = low
    edges.unpersist()
    return spark.createDataFrame(sorted(tree), "a long, b long, d2 double")


# ------------------------------------------------------------------ kernel densities


def scott_bandwidth(x: np.ndarray) -> np.ndarray:
    sd = x.std(axis=0, ddof=1) if len(x) > 1 else np.ones(x.shape[1])
    return np.where(sd > 0, sd, 1.0) * len(x) ** (-1 / (x.shape[1] + 4))


def log_density(at: np.ndarray, x: np.ndarray, h: np.ndarray) -> np.ndarray:
    out = np.empty(len(at))
    const = math.log(len(x)) + float(np.log(h).sum()) + 0.5 * x.shape[1] * math.log(2 * math.pi)
    for i in range(0, len(at), 256):
        z = -0.5 * (((at[i : i + 256, None, :] - x[None, :, :]) / h) ** 2).sum(axis=2)
        top = z.max(axis=1, keepdims=True)
        out[i : i + 256] = top[:, 0] + np.log(np.exp(z - top).sum(axis=1)) - const
    return out


def kde_test(a: np.ndarray, b: np.ndarray, permutations: int = 200, seed: int = 0, alpha: float = 0.05) -> dict:
    """Mean gap of log densities under the two samples, judged by permutation."""
    if len(a) + len(b) > QUADRATIC_CAP:
        raise ValueError(f"kernel densities are quadratic; at most {QUADRATIC_CAP} rows")
    both = np.concatenate([a, b])
    h = scott_bandwidth(both)
    z = np.exp(-0.5 * (((both[:, None, :] - both[None, :, :]) / h) ** 2).sum(axis=2))
    n = len(a)

    def gap(order: np.ndarray) -> float:
        first, second = order[:n], order[n:]
        return float((np.log(z[:, first].mean(axis=1)) - np.log(z[:, second].mean(axis=1)))[first].mean() - (np.log(z[:, first].mean(axis=1)) - np.log(z[:, second].mean(axis=1)))[second].mean())

    rng = np.random.default_rng(seed)
    stat = gap(np.arange(len(both)))
    more = sum(gap(rng.permutation(len(both))) >= stat for _ in range(permutations))
    p = (1 + more) / (1 + permutations)
    return {"stat": stat, "p_value": p, "reject": p < alpha}


def kde_table(points: DataFrame, sample: DataFrame, features: Sequence[str], bandwidth: Sequence[float], id_col: str = "id") -> DataFrame:
    """(id, density) of points under all rows of a sample, by a nested-loop join and partial sums in each block of rows."""
    s = sample.select(*(F.col(f).cast("double").alias(f"s{i}") for i, f in enumerate(features)))
    z = sum((((F.col(f) - F.col(f"s{i}")) / h) * ((F.col(f) - F.col(f"s{i}")) / h) for i, (f, h) in enumerate(zip(features, bandwidth, strict=True))), F.lit(0.0))
    const = float(np.prod(bandwidth)) * (2 * math.pi) ** (len(features) / 2)
    return points.crossJoin(s).groupBy(id_col).agg((F.avg(F.exp(-0.5 * z)) / const).alias("density"))
