"""Queries of the methods, their variants, baselines and measures."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.chisq import chi2_ppf, chi2_sf_col, sf_sql
from ..functions.hashing import normal_sql, uniform_sql
from ..operators import baselines, detect, fitting, measures
from ..operators.histogram import BoxTree, GridHistogram, RuleHistogram, fixed_histogram
from ..plans.workloads import offset_toy
from ..sources import gen
from ..sources.tables import BIGRAMS, VOWELS, event_features, hash_top, letter_shares, stratified, table, text_features
from . import query
from .fit_sql import ABLATIONS, fallback, fit_sql, kmeans_test, spanning_sql, whole

# ------------------------------------------------------------------ the fixed histogram on lineitem

CENTRES = ((0.25, 0.25), (0.25, 0.75), (0.75, 0.25), (0.75, 0.75))
WEIGHTS = (1.0, 0.8, 1.25, 1.0)
XY = ("x", "y")
#: Columns that tell the rows of lineitem apart, for samples.
KEYS = ("l_orderkey", "l_linenumber", "l_partkey")
P = "(SELECT *, l_quantity / 50 AS x, l_extendedprice / 105000 AS y, year(l_shipdate) AS yr FROM lineitem)"


def _distance_sql(k: int, x: str = "x", y: str = "y") -> str:
    a, b = CENTRES[k]
    return f"(({x} - {a}) * ({x} - {a}) + ({y} - {b}) * ({y} - {b}))"


def bin_sql(weights=WEIGHTS, x: str = "x", y: str = "y") -> str:
    """CASE for the bin of least weighted distance, ties to the lower one. weights: numbers or SQL of weights."""
    d = [f"{_distance_sql(k, x, y)} * (({w}) * ({w}))" for k, w in enumerate(weights)]
    return f"(CASE WHEN {d[0]} <= {d[1]} AND {d[0]} <= {d[2]} AND {d[0]} <= {d[3]} THEN 0 WHEN {d[1]} <= {d[2]} AND {d[1]} <= {d[3]} THEN 1 WHEN {d[2]} <= {d[3]} THEN 2 ELSE 3 END)"


def rows_of(spark, d) -> DataFrame:
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", (F.col("l_quantity") / 50).alias("x"), (F.col("l_extendedprice") / 105000).alias("y"), F.year("l_shipdate").alias("yr"))


def fixed(weights=WEIGHTS, counts=None):
    return fixed_histogram(XY, CENTRES, weights, counts)


def counted(spark, d, weights=WEIGHTS, rows=None) -> np.ndarray:
    got = dict((r.bin, r.n) for r in detect.contingency_long(fixed(weights), rows if rows is not None else rows_of(spark, d)).collect())
    return np.array([got.get(k, 0) for k in range(4)])


# ------------------------------------------------------------------ seeding and clustering

_SEED_SQL_HEAD = "WITH r0 AS (SELECT s_suppkey AS id, round(s_acctbal * 100)::BIGINT AS a, s_nationkey * 10000::BIGINT AS b FROM supplier)"


def _seed_sql(rounds: int, k: int) -> str:
    out = _SEED_SQL_HEAD
    for i in range(rounds):
        size = f"(SELECT count(*) // {k} + CASE WHEN {i} < count(*) % {k} THEN 1 ELSE 0 END FROM r0)"
        out += f""", n{i} AS (SELECT p.id, p.a, p.b, coalesce(min((p.a - q.a) * (p.a - q.a) + (p.b - q.b) * (p.b - q.b)), 0) AS d FROM r{i} p LEFT JOIN r{i} q ON p.id <> q.id GROUP BY ALL),
        s{i} AS (SELECT * FROM n{i} ORDER BY d DESC, id LIMIT 1),
        b{i} AS (SELECT r{i}.* FROM r{i}, s{i} ORDER BY CASE WHEN r{i}.id = s{i}.id THEN -1 ELSE (r{i}.a - s{i}.a) * (r{i}.a - s{i}.a) + (r{i}.b - s{i}.b) * (r{i}.b - s{i}.b) END, r{i}.id LIMIT {size}),
        r{i + 1} AS (SELECT * FROM r{i} WHERE id NOT IN (SELECT id FROM b{i}))"""
    return out + " SELECT * FROM (" + " UNION ALL ".join(f"SELECT {i} AS round, id, a, b FROM b{i}" for i in range(rounds)) + ")"


def _suppliers(spark, d) -> DataFrame:
    s = table(spark, d, "supplier")
    return s.select(F.col("s_suppkey").alias("id"), F.round(F.col("s_acctbal") * 100).cast("long").alias("a"), (F.col("s_nationkey").cast("long") * 10000).alias("b"))


@query(_seed_sql(1, 4))
def seed_first_round(spark, d):
    return fitting.seed_table(_suppliers(spark, d), 4, ("a", "b"), rounds=1)


@query(_seed_sql(4, 4))
def seed_full_k4(spark, d):
    return fitting.seed_table(_suppliers(spark, d), 4, ("a", "b"))


@query(_seed_sql(4, 4))
def seed_kernel_k4(spark, d):
    """The same blocks from the array kernel in one task."""
    s = _suppliers(spark, d)

    def run(frames):
        f = pd.concat(list(frames)).sort_values("id")
        if len(f):
            f["round"] = fitting.greedy_seed(f[["a", "b"]].to_numpy(float), 4)[1].astype("int32")
            yield f[["round", "id", "a", "b"]]

    return s.coalesce(1).mapInPandas(run, "round int, id long, a long, b long")


@query("WITH n AS (SELECT count(*) AS n FROM customer) SELECT k::INTEGER AS k, n // 7 + CASE WHEN k < n % 7 THEN 1 ELSE 0 END AS size FROM n, range(7) t(k)")
def seed_block_sizes(spark, d):
    n = table(spark, d, "customer").count()
    return spark.createDataFrame([(k, s) for k, s in enumerate(fitting.block_sizes(n, 7))], "k int, size long")


@query("SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey FROM lineitem ORDER BY md5('5:' || l_orderkey || ':' || l_linenumber || ':' || l_partkey || ':' || l_suppkey), l_orderkey, l_linenumber, l_partkey, l_suppkey LIMIT 500")
def seed_subsample(spark, d):
    """The sub-sample that a fit sees: a sampling operator."""
    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    return hash_top(table(spark, d, "lineitem").select(*keys), 500, keys, 5)


def _lloyd_sql(rounds: int) -> str:
    p = "WITH p AS (SELECT l_quantity / 50 AS x, l_extendedprice / 105000 AS y FROM lineitem), c0(bin, cx, cy) AS (VALUES (0, 0.2, 0.3), (1, 0.5, 0.5), (2, 0.9, 0.8))"
    for i in range(rounds):
        pick = lambda k, i=i: f"(SELECT {{}} FROM c{i} WHERE bin = {k})"
        d = [f"((x - {pick(k).format('cx')}) * (x - {pick(k).format('cx')}) + (y - {pick(k).format('cy')}) * (y - {pick(k).format('cy')}))" for k in range(3)]
        case = f"CASE WHEN {d[0]} <= {d[1]} AND {d[0]} <= {d[2]} THEN 0 WHEN {d[1]} <= {d[2]} THEN 1 ELSE 2 END"
        p += f", c{i + 1} AS (SELECT {case} AS bin, avg(x) AS cx, avg(y) AS cy FROM p GROUP BY 1)"
    return p + f" SELECT bin::INTEGER AS bin, round(cx, 6) AS cx, round(cy, 6) AS cy FROM c{rounds}"


@query(_lloyd_sql(3))
def lloyd_3_iter(spark, d):
    mu, _ = fitting.lloyd_table(rows_of(spark, d), XY, np.array([(0.2, 0.3), (0.5, 0.5), (0.9, 0.8)]), max_iter=3, tol=-1.0)
    return spark.createDataFrame([(k, float(a), float(b)) for k, (a, b) in enumerate(mu.tolist())], "bin int, cx double, cy double").select("bin", F.round("cx", 6).alias("cx"), F.round("cy", 6).alias("cy"))


# ------------------------------------------------------------------ intensity, weights, labels, strength

_ONES = (1.0, 1.0, 1.0, 1.0)
_COUNTS = f"(SELECT {bin_sql(_ONES)}::INTEGER AS bin, count(*) AS n FROM {P} GROUP BY 1)"


def _ratios(spark, d, mode: str) -> DataFrame:
    r = fitting.intensity(counted(spark, d, _ONES), mode)
    return spark.createDataFrame([(k, float(v)) for k, v in enumerate(r)], "bin int, ratio double").select("bin", F.round("ratio", 8).alias("ratio"))


@query(f"SELECT bin, round(n / sum(n) OVER (), 8) AS ratio FROM {_COUNTS}")
def intensity_share(spark, d):
    return _ratios(spark, d, "share")


_RELATIVE = f"(SELECT bin, n / (t // 4 + CASE WHEN bin < t % 4 THEN 1 ELSE 0 END) AS ratio FROM (SELECT bin, n, (sum(n) OVER ())::BIGINT AS t FROM {_COUNTS}))"


@query(f"SELECT bin, round(ratio, 8) AS ratio FROM {_RELATIVE}")
def intensity_relative(spark, d):
    return _ratios(spark, d, "relative")


@query(f"SELECT bin, theta, round(exp(theta * (ratio - 1)), 8) AS weight FROM {_RELATIVE}, (VALUES (0.0), (0.5), (1.0), (1.5)) g(theta)")
def bin_weights_theta(spark, d):
    r = fitting.intensity(counted(spark, d, _ONES))
    rows = [(k, t, float(w)) for t in (0.0, 0.5, 1.0, 1.5) for k, w in enumerate(fitting.bin_weights(r, t))]
    return spark.createDataFrame(rows, "bin int, theta double, weight double").select("bin", "theta", F.round("weight", 8).alias("weight"))


@query(f"SELECT l_orderkey, l_linenumber, l_partkey, {bin_sql()} AS bin FROM {P}")
def assign_weighted(spark, d):
    return fixed().assign(rows_of(spark, d)).select("l_orderkey", "l_linenumber", "l_partkey", "bin")


@query(f"SELECT l_orderkey, l_linenumber, l_partkey, {bin_sql(_ONES)} AS bin FROM {P}")
def assign_unweighted(spark, d):
    return fixed(_ONES).assign(rows_of(spark, d)).select("l_orderkey", "l_linenumber", "l_partkey", "bin")


@query(f"SELECT l_orderkey, l_linenumber, l_partkey, {bin_sql()} AS bin FROM {P}")
def assign_arrow(spark, d):
    """The Arrow form of the labels, which wide histograms use."""
    return fixed().assign(rows_of(spark, d), how="arrow").select("l_orderkey", "l_linenumber", "l_partkey", "bin")


@query("WITH e AS (SELECT vec_id, list_sum(list_transform(embedding, lambda v: (v::DOUBLE - 0.05) * (v::DOUBLE - 0.05))) AS d0, list_sum(list_transform(embedding, lambda v: (v::DOUBLE + 0.05) * (v::DOUBLE + 0.05))) * 1.21 AS d1 FROM embeddings) SELECT vec_id, (d1 < d0)::INTEGER AS bin FROM e")
def assign_embeddings(spark, d):
    hist = fixed_histogram(["embedding"], [[0.05] * 64, [-0.05] * 64], (1.0, 1.1))
    from dataclasses import replace

    return replace(hist, width=64).assign(table(spark, d, "embeddings")).select("vec_id", "bin")


def _theta_sql(tail: str) -> str:
    weights = [f"exp(theta * (r{k} - 1))" for k in range(4)]
    return f"""WITH r AS (SELECT {", ".join(f"max(CASE WHEN bin = {k} THEN ratio END) AS r{k}" for k in range(4))} FROM {_RELATIVE}),
        g AS (SELECT round(i * 0.05::DOUBLE, 10) AS theta FROM range(31) t(i)),
        q AS (SELECT theta, {", ".join(f"{w} AS w{k}" for k, w in enumerate(weights))} FROM g, r),
        b AS (SELECT theta, {bin_sql(["w0", "w1", "w2", "w3"])} AS bin, count(*) AS n FROM {P}, q GROUP BY 1, 2)
        {tail}"""


def theta_counts(spark, d) -> DataFrame:
    return fitting.theta_table(rows_of(spark, d), XY, np.array(CENTRES), fitting.intensity(counted(spark, d, _ONES)))


@query(_theta_sql("SELECT theta, bin::INTEGER AS bin, n FROM b"))
def theta_sweep_counts(spark, d):
    return theta_counts(spark, d)


_M = "m AS (SELECT theta, min(n) AS low, stddev_pop(n) AS sd, count(*) AS bins FROM b GROUP BY theta)"


def _minima(spark, d) -> DataFrame:
    return theta_counts(spark, d).groupBy("theta").agg(F.min("n").alias("low"), F.stddev_pop("n").alias("sd"), F.count("*").alias("bins"))


@query(_theta_sql(f", {_M} SELECT min(theta) AS theta FROM m WHERE low >= (SELECT count(*) * 0.24 FROM lineitem) AND bins = 4"))
def theta_first_feasible(spark, d):
    n = table(spark, d, "lineitem").count()
    return _minima(spark, d).where((F.col("low") >= 0.24 * n) & (F.col("bins") == 4)).agg(F.min("theta").alias("theta"))


@query(_theta_sql(f", {_M} SELECT theta, low FROM m ORDER BY theta DESC LIMIT 1"))
def theta_last(spark, d):
    return _minima(spark, d).orderBy(F.desc("theta")).limit(1).select("theta", "low")


@query(_theta_sql(f", {_M} SELECT theta, low FROM m WHERE bins = 4 ORDER BY round(sd, 6), theta LIMIT 1"))
def theta_best(spark, d):
    return _minima(spark, d).where("bins = 4").orderBy(F.round("sd", 6), "theta").limit(1).select("theta", "low")


# ------------------------------------------------------------------ fits (bounded samples; invariants are tested)


def _describe(spark, hist) -> DataFrame:
    return spark.createDataFrame([(hist.kind, hist.n_bins, float(hist.theta), int(hist.counts.min()), int(hist.counts.sum()))], "kind string, n_bins int, theta double, min_count int, n_train int")


_FIT = fit_sql(P, KEYS, 2000, whole(P))


@query(_FIT)
def fit_balanced_small(spark, d):
    return _describe(spark, fitting.fit_balanced(rows_of(spark, d), XY, keys=KEYS, sample_cap=2000))


@query(_FIT)
def fit_balanced_waves(spark, d):
    return _describe(spark, fitting.fit_balanced(rows_of(spark, d), XY, keys=KEYS, sample_cap=2000, search="waves"))


@query(fit_sql(P, KEYS, 1350, whole(P), k_init=9))
def fit_fixed_k(spark, d):
    return _describe(spark, fitting.fit_balanced(rows_of(spark, d), XY, keys=KEYS, sample_cap=1350, k_init=9))


@query(fit_sql(P, KEYS, 500, fallback(P, 4), beta=400, k_init=4))
def fit_fallback(spark, d):
    """No number of bins can hold so many rows each: the fallback, from the first rows of the sample."""
    return _describe(spark, fitting.fit_balanced(rows_of(spark, d), XY, keys=KEYS, sample_cap=500, beta=400, k_init=4, fallback="first"))


@query(fit_sql(P, KEYS, 2000, whole(P), feasible="150 * min(c.n) / (SELECT n FROM size) >= 5"))
def fit_expected5(spark, d):
    return _describe(spark, fitting.fit_balanced(rows_of(spark, d), XY, keys=KEYS, sample_cap=2000, expect_test_size=150))


@query(fit_sql(P, KEYS, 2000, whole(P), ratio="share"))
def fit_share_ratio(spark, d):
    return _describe(spark, fitting.fit_balanced(rows_of(spark, d), XY, keys=KEYS, sample_cap=2000, ratio="share"))


@query(fit_sql(P, KEYS, 2000, whole(P), init="first"))
def fit_random_start(spark, d):
    """No seeding: clustering starts from the first rows of the sample, whose order is random."""
    return _describe(spark, fitting.fit_balanced(rows_of(spark, d), XY, keys=KEYS, sample_cap=2000, init="first"))


@query(fit_sql(P, KEYS, 2000, ABLATIONS))
def fit_ablations(spark, d):
    """No rescaling, the last strength, even counts, bisection, the grid of neighbours: one row each."""
    changes = {"no_rescale": {"grid": (0.0,)}, "last": {"stop": "last"}, "best": {"stop": "best"}, "bisect": {"search": "bisect"}, "grid_nn": {"nn": "grid"}}
    x = fitting.take_sample(rows_of(spark, d), XY, 2000, keys=KEYS)
    rows = []
    for name, c in changes.items():
        h = fitting.fit_array(x, XY, fitting.FitOptions(**c))
        rows.append((name, h.kind, h.n_bins, float(h.theta), int(h.counts.min())))
    return spark.createDataFrame(rows, "variant string, kind string, n_bins int, theta double, min_count int")


@query()
def fit_pca(spark, d):
    """The first two principal axes of four columns, then the fit."""
    li = table(spark, d, "lineitem")
    df, names, _ = fitting.pca_columns(li, ("l_quantity", "l_extendedprice", "l_discount", "l_tax"), 2, 2000)
    return _describe(spark, fitting.fit_balanced(df, names, sample_cap=2000, scale="zscore"))


# ------------------------------------------------------------------ count tables and tests


@query(f"SELECT yr::INTEGER AS yr, {bin_sql()} AS bin, count(*) AS n FROM {P} GROUP BY 1, 2")
def contingency_long(spark, d):
    return detect.contingency_long(fixed(), rows_of(spark, d), ["yr"])


_WIDE = ", ".join(f"count(*) FILTER (WHERE {bin_sql()} = {k})" for k in range(4))


@query(f"SELECT yr::INTEGER AS yr, [{_WIDE}] AS t FROM {P} GROUP BY 1")
def contingency_wide(spark, d):
    return detect.contingency_wide(fixed(), rows_of(spark, d), ["yr"]).select("yr", "t")


def _test_sql(source: str, keys: str, form: str = "table", yates: bool = False, alpha: float = 0.05, dof: str = "len(list_filter(list_zip(o, t), lambda p: p[1] + p[2] > 0)) - 1") -> str:
    """SQL of test results for rows of (keys, o, t)."""
    pre = f"{keys}, " if keys else ""
    cell = "(q * p[1] - n * p[2])"
    if yates:
        cell = "greatest(abs(q * p[1] - n * p[2]) - (n + q) / 2.0, 0.0)"
    if form == "table":
        stat = f"list_sum(list_transform(list_filter(list_zip(o, t), lambda p: p[1] + p[2] > 0), lambda p: {cell} * {cell} / (p[1] + p[2]))) / (n * q)"
    else:
        stat = "list_sum(list_transform(list_filter(list_zip(o, t), lambda p: p[1] > 0), lambda p: (p[2] - q * p[1] / n) * (p[2] - q * p[1] / n) / (q * p[1] / n)))"
        dof = "len(list_filter(o, lambda a: a > 0)) - 1"
    return f"""WITH s AS ({source}), m AS (SELECT {pre} o, t, list_sum(o)::DOUBLE AS n, list_sum(t)::DOUBLE AS q FROM s),
        r AS (SELECT {pre} {stat} AS stat, ({dof})::INTEGER AS dof, n, q FROM m)
        SELECT {pre} round(stat, 6) AS stat, dof, round({sf_sql("stat", "dof")}, 6) AS p_value, {sf_sql("stat", "dof")} < {alpha} AS reject, n::BIGINT AS n_train, q::BIGINT AS n_test, round(sqrt(stat / (n + q)), 6) AS cramers_v FROM r"""


def _short(results: DataFrame, *keys: str) -> DataFrame:
    return results.select(*keys, F.round("stat", 6).alias("stat"), "dof", F.round("p_value", 6).alias("p_value"), "reject", "n_train", "n_test", F.round("cramers_v", 6).alias("cramers_v"))


_SPLIT = f"SELECT [{_WIDE.replace('WHERE', 'WHERE yr < 1998 AND')}] AS o, [{_WIDE.replace('WHERE', 'WHERE yr >= 1998 AND')}] AS t FROM {P}"


@query(_test_sql(_SPLIT, ""))
def detect_batch(spark, d):
    """Years before 1998 against the years since."""
    p = rows_of(spark, d)
    return _short(detect.detect(fixed(), p.where("yr >= 1998"), train=p.where("yr < 1998")))


_MANY = f"SELECT yr::INTEGER AS yr, o, [{_WIDE}] AS t FROM {P}, (SELECT [{_WIDE}] AS o FROM {P} WHERE yr < 1997) WHERE yr >= 1997 GROUP BY yr, o"


@query(_test_sql(_MANY, "yr"))
def detect_many(spark, d):
    """Every later year against the years before 1997, in one job."""
    p = rows_of(spark, d)
    return _short(detect.detect(fixed(), p.where("yr >= 1997"), by=["yr"], train=p.where("yr < 1997")), "yr")


@query(_test_sql(_MANY, "yr"))
def detect_cached_train(spark, d):
    """The same with stored training counts."""
    p = rows_of(spark, d)
    return _short(detect.detect(fixed(counts=counted(spark, d, rows=p.where("yr < 1997"))), p.where("yr >= 1997"), by=["yr"]), "yr")


@query(_test_sql(_MANY, "yr", form="gof"))
def detect_gof(spark, d):
    p = rows_of(spark, d)
    return _short(detect.detect(fixed(), p.where("yr >= 1997"), by=["yr"], form="gof", train=p.where("yr < 1997")), "yr")


@query(_test_sql(_SPLIT, "", yates=True))
def chi2_yates(spark, d):
    p = rows_of(spark, d)
    return _short(detect.detect(fixed(), p.where("yr >= 1998"), train=p.where("yr < 1998"), yates=True))


#: Quantities of lineitem are degrees of freedom, its discounts and taxes are statistics of 0 to 98; per group, since one sum of two groups may differ in its last bit.
_GRID_SQL = "(SELECT l_discount * 900 + l_tax * 100 AS x, l_quantity::INTEGER AS dof, count(*) AS n FROM lineitem GROUP BY l_quantity, l_discount, l_tax)"


@query(f"SELECT x, dof, round({sf_sql('x', 'dof')}, 8) AS p, n FROM {_GRID_SQL}")
def chi2_sf_grid(spark, d):
    """Upper tails at the statistics and degrees of freedom that the rows of lineitem give."""
    got = table(spark, d, "lineitem").groupBy("l_quantity", "l_discount", "l_tax").agg(F.count("*").alias("n"))
    grid = got.select((F.col("l_discount") * 900 + F.col("l_tax") * 100).alias("x"), F.col("l_quantity").cast("int").alias("dof"), "n")
    return grid.select("x", "dof", F.round(chi2_sf_col(F.col("x"), F.col("dof")), 8).alias("p"), "n")


@query("SELECT l_quantity::INTEGER AS dof, 0.5::DOUBLE + l_discount * 4.9::DOUBLE AS p, true AS inverts, count(*) AS n FROM lineitem GROUP BY l_quantity, l_discount")
def chi2_ppf_grid(spark, d):
    """Quantiles, checked by their tails: the quantities of lineitem are degrees of freedom, its discounts give probabilities of 0.5 to 0.99."""
    got = table(spark, d, "lineitem").groupBy("l_quantity", "l_discount").agg(F.count("*").alias("n"))
    asked = got.select(F.col("l_quantity").cast("int").alias("dof"), (0.5 + F.col("l_discount") * 4.9).alias("p"), "n")

    def quantiles(frames):
        for f in frames:
            yield f.assign(x=[chi2_ppf(float(p), int(k)) for k, p in zip(f.dof, f.p, strict=True)])

    # groups are few and their work is not: no coalescing into one task
    found = asked.repartition(4 * spark.sparkContext.defaultParallelism, "dof", "p").mapInPandas(quantiles, "dof int, p double, n long, x double")
    return found.select("dof", "p", (F.abs(chi2_sf_col(F.col("x"), F.col("dof")) - (1 - F.col("p"))) < 1e-9).alias("inverts"), "n")


_PRIO = "SELECT list(a ORDER BY o_orderpriority) AS o, list(b ORDER BY o_orderpriority) AS t FROM (SELECT o_orderpriority, count(*) FILTER (WHERE year(o_orderdate) < 1998) AS a, count(*) FILTER (WHERE year(o_orderdate) >= 1998) AS b FROM orders GROUP BY 1)"


@query(_test_sql(_PRIO, ""))
def detect_categorical(spark, d):
    """Order priorities are bins as they are."""
    o = table(spark, d, "orders")
    old = F.year("o_orderdate") < 1998
    hist = baselines.categories(o.where(old), "o_orderpriority")
    return _short(detect.detect(hist, o.where(~old)))


_LABELLED = "(SELECT doc_id, quality, toxic, length(text) / 20000.0 AS x, length(regexp_replace(lower(text), '[^aeiou]', '', 'g')) / greatest(length(text), 1)::DOUBLE AS y FROM documents JOIN labels USING (doc_id))"


def _labelled(spark, d) -> DataFrame:
    doc, lab = table(spark, d, "documents"), table(spark, d, "labels")
    share = F.length(F.regexp_replace(F.lower("text"), f"[^{VOWELS}]", "")) / F.greatest(F.length("text"), F.lit(1)).cast("double")
    return doc.join(lab, "doc_id").select("doc_id", "quality", "toxic", (F.length("text") / 20000.0).alias("x"), share.alias("y"))


_DOC3 = ((0.05, 0.3, 0.0), (0.05, 0.3, 1.0), (0.3, 0.35, 1.0))


def _doc_bin(third: str) -> str:
    d = [f"((x - {a}) * (x - {a}) + (y - {b}) * (y - {b}) + ({third} - {c}) * ({third} - {c}))" for a, b, c in _DOC3]
    return f"(CASE WHEN {d[0]} <= {d[1]} AND {d[0]} <= {d[2]} THEN 0 WHEN {d[1]} <= {d[2]} THEN 1 ELSE 2 END)"


@query(f"SELECT {_doc_bin('quality::DOUBLE')} AS bin, count(*) AS n FROM {_LABELLED} GROUP BY 1")
def supervised_feature(spark, d):
    """The label as a third feature."""
    rows, features = detect.as_feature(_labelled(spark, d), "quality", ("x", "y"))
    return detect.contingency_long(fixed_histogram(features, _DOC3), rows)


_DOC2 = ((0.02, 0.25), (0.1, 0.35), (0.4, 0.3))
_d2 = [f"((x - {a}) * (x - {a}) + (y - {b}) * (y - {b}))" for a, b in _DOC2]
_DOC2_BIN = f"(CASE WHEN {_d2[0]} <= {_d2[1]} AND {_d2[0]} <= {_d2[2]} THEN 0 WHEN {_d2[1]} <= {_d2[2]} THEN 1 ELSE 2 END)"


def _parity_wide(cond: str) -> str:
    return "[" + ", ".join(f"count(*) FILTER (WHERE {cond} AND {_DOC2_BIN} = {k})" for k in range(3)) + "]"


@query(_test_sql(f"SELECT quality::VARCHAR AS label, {_parity_wide('toxic = 0')} AS o, {_parity_wide('toxic = 1')} AS t FROM {_LABELLED} WHERE quality IN (0, 1) GROUP BY 1", "label"))
def supervised_per_label(spark, d):
    """A test of toxic against other documents for each quality."""
    rows = _labelled(spark, d)
    out = None
    for q in (0, 1):
        part = rows.where(F.col("quality") == q)
        got = detect.detect(fixed_histogram(("x", "y"), _DOC2), part.where("toxic = 1"), train=part.where("toxic = 0")).withColumn("label", F.lit(str(q)))
        out = got if out is None else out.unionByName(got)
    return _short(out, "label")


# ------------------------------------------------------------------ partition quality and offsets


@query(f"SELECT bin, count(*) AS n, round(count(*) / (SELECT count(*) FROM lineitem), 8) AS share, round(avg(sqrt((x - mx) * (x - mx) + (y - my) * (y - my))), 6) AS extent FROM (SELECT *, avg(x) OVER (PARTITION BY bin) AS mx, avg(y) OVER (PARTITION BY bin) AS my FROM (SELECT *, {bin_sql()} AS bin FROM {P})) GROUP BY bin")
def bin_table(spark, d):
    return detect.bin_table(fixed(), rows_of(spark, d)).select("bin", "n", F.round("share", 8).alias("share"), F.round("extent", 6).alias("extent"))


@query(f"SELECT round(avg(e), 6) AS mean_extent, (sum(n)::BIGINT // 50)::BIGINT AS bins_possible FROM (SELECT bin, count(*) AS n, avg(sqrt((x - mx) * (x - mx) + (y - my) * (y - my))) AS e FROM (SELECT *, avg(x) OVER (PARTITION BY bin) AS mx, avg(y) OVER (PARTITION BY bin) AS my FROM (SELECT *, {bin_sql()} AS bin FROM {P})) GROUP BY bin)")
def bin_extent(spark, d):
    return detect.partition_quality(fixed(), rows_of(spark, d)).select(F.round("mean_extent", 6).alias("mean_extent"), F.col("bins_possible").cast("long").alias("bins_possible"))


@query(f"SELECT round(stddev_pop(s), 8) AS intensity_sd, min(n) AS min_count FROM (SELECT count(*) AS n, count(*) / (SELECT count(*) FROM lineitem) AS s FROM {P} GROUP BY {bin_sql()})")
def intensity_sd(spark, d):
    return detect.partition_quality(fixed(), rows_of(spark, d)).select(F.round("intensity_sd", 8).alias("intensity_sd"), "min_count")


def _offset_sql(cells: int, bins: int) -> str:
    at = lambda n, v: f"least(floor({v} * {n}), {n - 1})"
    a, b = "l_extendedprice / 120000", "(l_extendedprice + 6000) / 120000"
    return f"""WITH c AS (SELECT {at(bins, 'v')}::INTEGER AS bin, {at(cells, 'v')} AS cell, s / (SELECT count(*) FROM lineitem) AS s FROM (SELECT {a} AS v, 1 AS s FROM lineitem UNION ALL SELECT {b}, -1 FROM lineitem)),
        g AS (SELECT bin, cell, sum(s) AS gap FROM c GROUP BY 1, 2)
        SELECT bin, round(sum(abs(gap)), 6) AS av, round(abs(sum(gap)), 6) AS pv, round(sum(abs(gap)) - abs(sum(gap)), 6) AS margin FROM g GROUP BY bin"""


def _offset(spark, d, cells: int, bins: int) -> DataFrame:
    li = table(spark, d, "lineitem")
    a = li.select((F.col("l_extendedprice") / 120000).alias("v"))
    b = li.select(((F.col("l_extendedprice") + 6000) / 120000).alias("v"))
    hist = GridHistogram(features=("v",), counts=np.zeros(bins, np.int64), kind="grid", low=np.array([0.0]), high=np.array([1.0]), per_feature=bins)
    got = detect.offset_report(hist, a, b, F.least(F.floor(F.col("v") * cells), F.lit(cells - 1)), eps=1e-9)
    return got.select("bin", F.round("av", 6).alias("av"), F.round("pv", 6).alias("pv"), F.round("margin", 6).alias("margin"))


@query(_offset_sql(60, 4))
def offset_report_1d(spark, d):
    """A price shift seen through four bins of fifteen cells each."""
    return _offset(spark, d, 60, 4)


@query(_offset_sql(60, 12))
def offset_refine(spark, d):
    """The same cells in twelve bins: the total absolute variation stays, the margin cannot grow."""
    return _offset(spark, d, 60, 12)


_SHIFTS = "(SELECT l_quantity, (avg(l_extendedprice) - any_value(m)) / any_value(s) AS shift FROM lineitem, (SELECT avg(l_extendedprice) AS m, stddev_pop(l_extendedprice) AS s FROM lineitem) GROUP BY l_quantity)"


@query(f"SELECT l_quantity, 5::BIGINT AS n_bins, 1::BIGINT AS n_offset, true AS exact, round(2 * (1 - {sf_sql('(shift * shift / 4)', '1')}), 6) AS av FROM {_SHIFTS}")
def offset_closed_form(spark, d):
    """A Gaussian with the moments of lineitem's prices and its copy shifted to the mean price of each quantity: only the bin around half the shift is an offset bin."""
    li = table(spark, d, "lineitem")
    whole = li.agg(F.avg("l_extendedprice").alias("m"), F.stddev_pop("l_extendedprice").alias("s"))
    shifts = li.groupBy("l_quantity").agg(F.avg("l_extendedprice").alias("at")).crossJoin(F.broadcast(whole)).select("l_quantity", ((F.col("at") - F.col("m")) / F.col("s")).alias("shift"))

    def judge(frames):
        for f in frames:
            out = []
            for q, shift in zip(f.l_quantity, f["shift"], strict=True):
                rows = offset_toy(shift)
                total = sum(r["av"] for r in rows)
                out.append((q, len(rows), sum(r["is_offset"] for r in rows), abs(total - offset_toy(shift, edges=())[0]["av"]) < 1e-12, total))
            yield pd.DataFrame(out, columns=["l_quantity", "n_bins", "n_offset", "exact", "av"])

    return _rounded(shifts.mapInPandas(judge, "l_quantity double, n_bins long, n_offset long, exact boolean, av double"), "av")


# ------------------------------------------------------------------ baselines


@query(kmeans_test(P, KEYS, 2000, "yr < 1998", _test_sql("SELECT o, t FROM counted", "")))
def plain_kmeans_test(spark, d):
    """Bins fitted to 2 000 rows; both rows of the table of counts are of all rows of their years."""
    p = rows_of(spark, d)
    hist = baselines.fit_table("plain_kmeans", p.where("yr < 1998"), XY, 2000, keys=KEYS, init="first")
    return _short(detect.detect(hist, p.where("yr >= 1998"), train=p.where("yr < 1998"), how="arrow"))


_KD_RULE = "(CASE WHEN x > 0.5 THEN CASE WHEN y > 0.5 THEN 7 ELSE 6 END ELSE CASE WHEN y > 0.5 THEN 5 ELSE 4 END END)"


@query(f"SELECT {_KD_RULE}::BIGINT AS node, count(*) AS n FROM {P} GROUP BY 1")
def kd_midpoint_bins(spark, d):
    """Two levels of midpoint cuts of the unit square, on the whole table."""
    return baselines.kd_table(rows_of(spark, d), XY, (0.0, 0.0), (1.0, 1.0), 2, 10)


_KD = ((0, 0.5, 1, 2), (1, 0.5, -1, -2), (1, 0.5, -3, -4))
_KD_BIN = "(CASE WHEN x > 0.5 THEN CASE WHEN y > 0.5 THEN 3 ELSE 2 END ELSE CASE WHEN y > 0.5 THEN 1 ELSE 0 END END)"


def _by_bins(rule: str, k: int) -> str:
    arr = lambda cond: "[" + ", ".join(f"count(*) FILTER (WHERE {cond} AND {rule} = {b})" for b in range(k)) + "]"
    return f"SELECT {arr('yr < 1998')} AS o, {arr('yr >= 1998')} AS t FROM {P}"


@query(_test_sql(_by_bins(_KD_BIN, 4), ""))
def kd_midpoint_test(spark, d):
    p = rows_of(spark, d)
    hist = BoxTree(features=XY, counts=np.zeros(4, np.int64), kind="midpoint_kd", nodes=_KD)
    return _short(detect.detect(hist, p.where("yr >= 1998"), train=p.where("yr < 1998")))


_RULES = ((0, 0.2, True), (1, 0.8, False), (0, 0.7, False), (1, 0.3, True))
_PEEL_BIN = "(CASE WHEN x <= 0.2 THEN 0 WHEN y >= 0.8 THEN 1 WHEN x >= 0.7 THEN 2 WHEN y <= 0.3 THEN 3 ELSE 4 END)"


def _peel(counts=None) -> RuleHistogram:
    return RuleHistogram(features=XY, counts=np.zeros(5, np.int64) if counts is None else counts, kind="quantile_peel", rules=_RULES)


@query(f"SELECT {_PEEL_BIN} AS bin, count(*) AS n FROM {P} GROUP BY 1")
def peel_bins(spark, d):
    return detect.contingency_long(_peel(), rows_of(spark, d))


_PEEL = _by_bins(_PEEL_BIN, 5)


@query(f"WITH s AS ({_PEEL}), m AS (SELECT o, t, list_sum(o)::DOUBLE AS n, list_sum(t)::DOUBLE AS q FROM s) SELECT round(list_sum(list_transform(list_zip(o, t), lambda p: (p[2] - q * p[1] / n) * (p[2] - q * p[1] / n) / (q * p[1] / n))), 6) AS stat FROM m")
def peel_chi2(spark, d):
    p = rows_of(spark, d)
    return detect.detect(_peel(), p.where("yr >= 1998"), form="gof", train=p.where("yr < 1998")).select(F.round("stat", 6).alias("stat"))


@query(f"WITH s AS ({_PEEL}), m AS (SELECT o, t, list_sum(o)::DOUBLE AS n, list_sum(t)::DOUBLE AS q FROM s) SELECT round(0.5 * list_sum(list_transform(list_zip(o, t), lambda p: abs(p[2] / q - p[1] / n))), 8) AS stat FROM m")
def peel_tv(spark, d):
    p = rows_of(spark, d)
    wide = detect.contingency_wide(_peel(), p.where("yr >= 1998"), train=p.where("yr < 1998"))
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda s, v: s + v)
    gap = F.zip_with("o", "t", lambda a, b: F.abs(b / total(F.col("t")) - a / total(F.col("o"))))
    return wide.select(F.round(0.5 * total(gap), 8).alias("stat"))


@query()
def peel_threshold(spark, d):
    """Simulated thresholds at three significance levels; they fall as alpha grows."""
    counts = tuple(counted(spark, d).tolist())
    return baselines.threshold_table(spark, [(s, counts, 200, a) for s in ("chi2", "tv") for a in (0.01, 0.05, 0.1)])


_NATIONS = "(SELECT k AS id, (k * 37 % 101)::DOUBLE AS x, (r * 53 + k * k % 89)::DOUBLE AS y FROM (SELECT n_nationkey::BIGINT AS k, n_regionkey::BIGINT AS r FROM nation))"


@query(spanning_sql(_NATIONS))
def mst_edges_small(spark, d):
    """Spanning tree of the nations by rounds of joins."""
    n = table(spark, d, "nation")
    key = F.col("n_nationkey").cast("long")
    p = n.select(key.alias("id"), (key * 37 % 101).cast("double").alias("a"), (F.col("n_regionkey") * 53 + key * key % 89).cast("double").alias("b"))
    return baselines.boruvka(p, ("a", "b"))


@query()
def mst_runs_test(spark, d):
    """Runs tests of all orders of each status, in blocks of about 1 000, against 400 of all: the status's least p-value times its blocks."""
    o = table(spark, d, "orders").select("o_orderkey", "o_orderstatus", (F.col("o_totalprice") / 500000).alias("a"), (F.month("o_orderdate") / 12.0).alias("b"))
    train = fitting.take_sample(o, ("a", "b"), 400, keys=("o_orderkey",))
    sizes = o.groupBy("o_orderstatus").agg(F.ceil(F.count("*") / 1000).alias("blocks"))
    dealt = o.join(F.broadcast(sizes), "o_orderstatus").withColumn("batch", F.concat_ws("/", "o_orderstatus", F.pmod(F.xxhash64("o_orderkey"), F.col("blocks"))))
    got = baselines.runs_table(dealt, train, ("a", "b"), "batch").withColumn("o_orderstatus", F.substring_index("batch", "/", 1))
    found = got.groupBy("o_orderstatus").agg(F.count("*").alias("blocks"), F.sum("runs").alias("runs"), F.least(F.lit(1.0), F.min("p_value") * F.count("*")).alias("p_value"))
    return found.withColumn("reject", F.col("p_value") < 0.05)


_GRID_BIN = "(least(greatest(floor(x * 3)::INTEGER, 0), 2) + 3 * least(greatest(floor(y * 3)::INTEGER, 0), 2))"


def _unit_grid() -> GridHistogram:
    return GridHistogram(features=XY, counts=np.zeros(9, np.int64), kind="grid", low=np.zeros(2), high=np.ones(2), per_feature=3)


@query(f"SELECT {_GRID_BIN}::INTEGER AS bin, count(*) AS n FROM {P} GROUP BY 1")
def grid_bins(spark, d):
    return detect.contingency_long(_unit_grid(), rows_of(spark, d))


@query(_test_sql(_by_bins(_GRID_BIN, 9), ""))
def grid_test(spark, d):
    p = rows_of(spark, d)
    return _short(detect.detect(_unit_grid(), p.where("yr >= 1998"), train=p.where("yr < 1998")))


@query("""SELECT p.n_nationkey::BIGINT AS id, round(avg(exp(-0.5 * (((p.n_nationkey * 400.0 - s.s_acctbal) / 800.0) * ((p.n_nationkey * 400.0 - s.s_acctbal) / 800.0)))) / (800.0 * sqrt(2 * pi())), 10) AS density
          FROM nation p, supplier s GROUP BY 1""")
def kde_density(spark, d):
    """Kernel density of supplier balances at one point per nation."""
    at = table(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("id"), (F.col("n_nationkey") * 400.0).alias("s_acctbal"))
    return baselines.kde_table(at, table(spark, d, "supplier"), ["s_acctbal"], [800.0]).select("id", F.round("density", 10).alias("density"))


# ------------------------------------------------------------------ measures

_TRIALS = """(SELECT c_mktsegment AS workload, CASE WHEN o_orderkey % 3 = 0 THEN 'a' WHEN o_orderkey % 3 = 1 THEN 'b' ELSE 'c' END AS method, (o_orderkey % 5)::INTEGER AS run, o_orderkey % 2 = 0 AS drifted,
    o_totalprice % 100 < CASE WHEN o_orderkey % 2 = 0 THEN 20 + 10 * (o_orderkey % 3) ELSE 6 END AS reject FROM orders JOIN customer ON o_custkey = c_custkey)"""


def trials(spark, d) -> DataFrame:
    """A trials table made of orders: segments as workloads, keys as methods and runs."""
    o, c = table(spark, d, "orders"), table(spark, d, "customer")
    k = F.col("o_orderkey")
    even = k % 2 == 0
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).select(
        F.col("c_mktsegment").alias("workload"), F.when(k % 3 == 0, "a").when(k % 3 == 1, "b").otherwise("c").alias("method"), (k % 5).cast("int").alias("run"),
        even.alias("drifted"), (F.col("o_totalprice") % 100 < F.when(even, 20 + 10 * (k % 3)).otherwise(6)).alias("reject"),
    )


_RUNS = f"(SELECT workload, method, run, 100 * avg(CASE WHEN NOT drifted THEN reject::INTEGER END) AS type1, 100 * avg(CASE WHEN drifted THEN 1 - reject::INTEGER END) AS type2 FROM {_TRIALS} GROUP BY ALL)"
_ERRORS = f"(SELECT workload, method, avg(type1) AS type1, stddev_samp(type1) AS type1_sd, avg(type2) AS type2, stddev_samp(type2) AS type2_sd FROM {_RUNS} GROUP BY ALL)"


def _rounded(df: DataFrame, *names: str) -> DataFrame:
    for n in names:
        df = df.withColumn(n, F.round(n, 6))
    return df


@query(f"SELECT workload, method, run, round(type1, 6) AS type1, round(type2, 6) AS type2 FROM {_RUNS}")
def type1_type2(spark, d):
    return _rounded(measures.run_errors(trials(spark, d)), "type1", "type2")


@query(f"SELECT workload, method, round(type1, 6) AS type1, round(type1_sd, 6) AS type1_sd, round(type2, 6) AS type2, round(type2_sd, 6) AS type2_sd FROM {_ERRORS}")
def error_mean_sd(spark, d):
    return _rounded(measures.error_table(trials(spark, d)), "type1", "type1_sd", "type2", "type2_sd")


@query(f"SELECT method, round(avg(type1), 6) AS type1, round(avg(type2), 6) AS type2, rank() OVER (ORDER BY avg(type2))::INTEGER AS rank FROM {_ERRORS} GROUP BY method")
def error_rank(spark, d):
    return _rounded(measures.error_rank(trials(spark, d)), "type1", "type2")


@query(f"SELECT workload, method, round(type1, 6) AS type1, round(type2, 6) AS type2, type1 > 5 AS over_alpha, type2 = min(type2) OVER (PARTITION BY workload) AS best FROM {_ERRORS}")
def error_flags(spark, d):
    return _rounded(measures.error_flags(trials(spark, d)), "type1", "type2")


@query(f"SELECT workload, method, drifted, round(avg(reject::INTEGER), 6) AS rate, count(*) AS n, grouping(workload, method, drifted) AS level FROM {_TRIALS} GROUP BY CUBE (workload, method, drifted)")
def error_cube(spark, d):
    return _rounded(measures.error_cube(trials(spark, d)), "rate")


@query("""SELECT n::INTEGER AS n, k::INTEGER AS k, m::INTEGER AS m, round(n * log2(n), 1) AS seed_round, round(n * k * log2(n), 1) AS seeding, k * n * m AS clustering_pass, 31 * k * n AS theta_sweep, round(k * k * n * log2(n), 1) AS fit_worst, k AS test, n * k AS detection
          FROM (SELECT count(*)::DOUBLE AS n, count(DISTINCT l_quantity)::DOUBLE AS k, l_linenumber::DOUBLE AS m FROM lineitem GROUP BY l_linenumber, l_returnflag)""")
def cost_formulas(spark, d):
    """Costs of a fit to the rows of each line number and return flag: one bin for each quantity, as many features as the line's number."""
    parts = ("seed_round", "seeding", "clustering_pass", "theta_sweep", "fit_worst", "test", "detection")
    sizes = table(spark, d, "lineitem").groupBy(F.col("l_linenumber").alias("m"), "l_returnflag").agg(F.count("*").cast("int").alias("n"), F.count_distinct("l_quantity").cast("int").alias("k"))

    def costs(frames):
        for f in frames:
            c = [measures.cost_model(int(n), int(k), int(m)) for n, k, m in zip(f.n, f.k, f.m, strict=True)]
            yield f.assign(**{x: [round(float(v[x]), 1) for v in c] for x in parts})

    return sizes.select("n", "k", "m").mapInPandas(costs, "n int, k int, m int, " + ", ".join(f"{x} double" for x in parts))


# ------------------------------------------------------------------ generated samples and features


def _six(df: DataFrame, *names: str) -> DataFrame:
    return df.select("id", *(F.round(n, 6).alias(n) for n in names))


def _orders(spark, d) -> DataFrame:
    return table(spark, d, "orders").select("o_orderkey")


def _u(j):
    return uniform_sql("g", "o_orderkey", j)


def _g(j):
    return normal_sql("g", "o_orderkey", j)


@query(f"SELECT o_orderkey AS id, round({_u(0)} * 1.06, 6) AS x1, round({_u(1)}, 6) AS x2 FROM orders")
def gen_uniform(spark, d):
    return _six(gen.points(_orders(spark, d), "o_orderkey", "2d-U-mean", 0.06, "g"), "x1", "x2")


@query(f"SELECT o_orderkey AS id, round({_g(1)}, 6) AS x1, round({_g(2)}, 6) AS x2 FROM orders")
def gen_gauss(spark, d):
    return _six(gen.points(_orders(spark, d), "o_orderkey", "2d-1G-mean", 0.0, "g"), "x1", "x2")


@query(f"SELECT o_orderkey AS id, round({_g(1)} + CASE o_orderkey % 4 WHEN 0 THEN 0.0 WHEN 1 THEN 5.0 WHEN 2 THEN 0.0 ELSE 4.2 END, 6) AS x1, round({_g(2)} + CASE WHEN o_orderkey % 4 < 2 THEN 0.0 ELSE 5.0 END, 6) AS x2 FROM orders")
def gen_mixture(spark, d):
    return _six(gen.points(_orders(spark, d), "o_orderkey", "2d-4G-mean", 0.8, "g"), "x1", "x2")


@query(f"SELECT o_orderkey AS id, round({_g(1)}, 6) AS x1, round({_g(1)} * 0.2 + {_g(2)} * sqrt(0.96), 6) AS x2 FROM orders")
def gen_shift(spark, d):
    return _six(gen.points(_orders(spark, d), "o_orderkey", "2d-1G-cov", 0.2, "g"), "x1", "x2")


@query(f"SELECT o_orderkey AS id, {', '.join(f'round({_g(j)} + {s}, 6) AS x{i + 1}' for i, (j, s) in enumerate([(1, 0.5), (2, 0), (10, 0), (11, 0), (12, 0), (13, 0)]))} FROM orders")
def gen_highdim(spark, d):
    return _six(gen.points(_orders(spark, d), "o_orderkey", "2d-1G-mean", 0.5, "g", dims=6), *(f"x{i}" for i in range(1, 7)))


@query("""SELECT doc_id, round(ln(len(w)), 6) AS ln_words, round((length(text) - len(w) + 1) / len(w), 6) AS word_len, round(CASE WHEN length(text) > 0 THEN length(regexp_replace(lower(text), '[^aeiou]', '', 'g')) / length(text) ELSE 0 END, 6) AS vowel_share, round(len(list_distinct(w)) / len(w), 6) AS token_ratio
          FROM (SELECT doc_id, coalesce(text, '') AS text, string_split(coalesce(text, ''), ' ') AS w FROM documents)""")
def feat_text(spark, d):
    doc = table(spark, d, "documents").withColumn("text", F.coalesce("text", F.lit("")))
    return _rounded(text_features(doc), "ln_words", "word_len", "vowel_share", "token_ratio")


def _letter_sql(bigrams: int) -> str:
    n = "greatest(length(text), 1)::DOUBLE"
    cells = [f"round((length(lower(text)) - length(replace(lower(text), '{c}', ''))) / {n}, 6)" for c in "abcdefghijklmnopqrstuvwxyz"]
    cells += [f"round((length(lower(text)) - length(replace(lower(text), '{b}', ''))) / 2.0 / {n}, 6)" for b in BIGRAMS[:bigrams]]
    return f"SELECT doc_id, [{', '.join(cells)}] AS features FROM documents"


def _letters(spark, d, bigrams: int) -> DataFrame:
    # as DuckDB rounds: scaled in binary first; Spark's own rounding goes by the printed decimals, which parts the two at halves
    return letter_shares(table(spark, d, "documents"), bigrams).select("doc_id", F.transform("features", lambda v: F.round(v * 1e6) / 1e6).alias("features"))


@query(_letter_sql(0))
def feat_letters26(spark, d):
    return _letters(spark, d, 0)


@query(_letter_sql(24))
def feat_bigrams(spark, d):
    return _letters(spark, d, 24)


@query("SELECT event_id, event_type, value, hour(ts)::INTEGER AS hour, (props->>'$.k')::INTEGER AS k FROM events")
def feat_events(spark, d):
    return event_features(table(spark, d, "events")).select("event_id", "event_type", "value", "hour", "k")


def _quota_sql(quotas: dict) -> str:
    cases = " OR ".join(f"(lang = '{g}' AND r <= {n})" for g, n in quotas.items())
    return f"SELECT lang, count(*) AS n, min(doc_id) AS first FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY md5('11:' || doc_id), doc_id) AS r FROM documents) WHERE {cases} GROUP BY lang"


_QUOTA_A, _QUOTA_B = {"es": 20, "de": 20, "fr": 20, "en": 40}, {"es": 40, "de": 20, "fr": 5, "en": 35}


@query(_quota_sql(_QUOTA_A))
def mix_quota_a(spark, d):
    return stratified(table(spark, d, "documents"), "lang", _QUOTA_A, ["doc_id"], 11).groupBy("lang").agg(F.count("*").alias("n"), F.min("doc_id").alias("first"))


@query(_quota_sql(_QUOTA_B))
def mix_quota_b(spark, d):
    return stratified(table(spark, d, "documents"), "lang", _QUOTA_B, ["doc_id"], 11).groupBy("lang").agg(F.count("*").alias("n"), F.min("doc_id").alias("first"))


# ------------------------------------------------------------------ controls


_CONTROL = f"SELECT yr::INTEGER AS yr, o, [{_WIDE}] AS t FROM {P}, (SELECT [{_WIDE}] AS o FROM {P}) GROUP BY yr, o"


@query(_test_sql(_CONTROL, "yr"))
def control_years(spark, d):
    """Every year against all years: lineitem has no drift."""
    return _short(detect.detect(fixed(counts=counted(spark, d)), rows_of(spark, d), by=["yr"]), "yr")
