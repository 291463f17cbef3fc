"""The experiment workloads on the given tables and on generated samples."""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.baselines import plain_kmeans_array
from ..operators.fitting import FitOptions, fit_array
from ..sources import gen
from ..sources.tables import BIGRAMS, letter_shares, table, text_features
from .harness import METHODS, run_trials, sampled_sets, synthetic_sets

TEXT4 = ("ln_words", "word_len", "vowel_share", "token_ratio")
TEXT3 = ("word_len", "vowel_share", "token_ratio")
GROUPS = ("low", "es", "de", "fr", "en")
# Shares of the five groups in the two populations of the mixture workloads.
SHARES_VII = (dict(zip(GROUPS, (0.0, 0.2, 0.2, 0.2, 0.4), strict=True)), dict(zip(GROUPS, (0.4, 0.4, 0.2, 0.0, 0.0), strict=True)))
SHARES_VIII = (dict(zip(GROUPS, (0.2,) * 5, strict=True)), dict(zip(GROUPS, (0.14, 0.14, 0.2, 0.2, 0.32), strict=True)))


def partition_experiment(spark: SparkSession, n: int = 1350, k: int = 9, source: Callable[[int], DataFrame] | None = None) -> DataFrame:
    """(shape, method, intensity_sd, min_count, max_count): how even the bins of both methods are on three shapes, of generated rows or of n rows of a table."""
    rows, given = [], source(n) if source else None
    for shape in ("one", "even", "uneven"):
        x = gen.partition_points(spark, shape, n, given).orderBy("id").select("x1", "x2").toPandas().to_numpy()
        for name, hist in (("balanced", fit_array(x, ("x1", "x2"), FitOptions(k_init=k, stop="best", beta=50))), ("plain_kmeans", plain_kmeans_array(x, ("x1", "x2"), k=k))):
            share = hist.counts / hist.counts.sum()
            rows.append((shape, name, float(share.std()), int(hist.counts.min()), int(hist.counts.max())))
    return spark.createDataFrame(rows, "shape string, method string, intensity_sd double, min_count int, max_count int")


def two_dimensional(spark: SparkSession, runs: int = 3, tests: int = 20, n_train: int = 2000, methods: Sequence[str] = METHODS, kinds: Sequence[str] | None = None, fit: dict | None = None, source: Callable[[int], DataFrame] | None = None) -> DataFrame:
    """Trials of the six two-dimensional workloads; source: on rows of a table."""
    return run_trials(synthetic_sets(spark, kinds, runs, n_train, 200, tests, source=source), ("x1", "x2"), methods, fit=fit)


def training_sizes(spark: SparkSession, sizes: Sequence[int] = (2000, 3000, 4000, 5000), runs: int = 2, tests: int = 20, kinds: Sequence[str] | None = ("2d-1G-mean", "2d-2G-mean"), expected: bool = True, source: Callable[[int], DataFrame] | None = None) -> DataFrame:
    """Trials of the proposed method with growing training sets; the workload carries the size.

    expected: bins must also expect 5 test rows, which bounds their number; without, it grows with the training set and single bins expect ever fewer.
    """
    out = None
    for n in sizes:
        got = two_dimensional(spark, runs, tests, n, ("balanced",), kinds, {"expect_test_size": 200} if expected else None, source).withColumn("workload", F.concat("workload", F.lit(f"/{n}")))
        out = got if out is None else out.unionByName(got)
    return out


def dimensions(spark: SparkSession, dims: Sequence[int] = (4, 6, 8, 10, 20), runs: int = 1, tests: int = 10, methods: Sequence[str] = METHODS, source: Callable[[int], DataFrame] | None = None) -> DataFrame:
    """Trials with unrelated dimensions added: one Gaussian (margin 0.5) and four (margin 1), doubled training set."""
    out = None
    for d in dims:
        for kind, drift in (("2d-1G-mean", 0.5), ("2d-4G-mean", 1.0)):
            sets = synthetic_sets(spark, [kind], runs, 4000, 200, tests, dims=d, drift=drift, source=source)
            got = run_trials(sets, [f"x{j + 1}" for j in range(d)], methods)
            out = got if out is None else out.unionByName(got)
    return out


# ------------------------------------------------------------------ documents


def _labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return docs.join(labels.select("doc_id", "quality"), "doc_id", "left").where("length(text) > 0")


def document_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents with grp: 'low' for low quality, else the language."""
    return _labelled(spark, sf_dir).withColumn("grp", F.when(F.col("quality") == 0, "low").otherwise(F.col("lang")))


def _wide(docs: DataFrame, bigrams: int, carry: Sequence[str]) -> tuple[DataFrame, list[str]]:
    """Letter features as columns f0, f1, ..."""
    m = 26 + bigrams
    feats = letter_shares(docs, bigrams)
    rows = docs.select("doc_id", *carry).join(feats, "doc_id")
    return rows.select("doc_id", *carry, *(F.col("features")[j].alias(f"f{j}") for j in range(m))), [f"f{j}" for j in range(m)]


#: Rows of training and test sets, and beta, of each document workload at a full-size table; smaller tables shrink them in proportion.
SIZES = {"i": (2000, 500, 50), "ii": (400, 150, 20), "iii": (2000, 500, 50), "iv": (2000, 500, 50), "v": (2000, 500, 50), "vi": (2000, 500, 50), "vii": (3000, 600, 50), "viii": (2000, 500, 50)}


def document_experiment(spark: SparkSession, sf_dir: str, which: str, runs: int = 2, tests: int = 10, methods: Sequence[str] = METHODS) -> DataFrame:
    """Trials of one of the eight two-population workloads on documents ('i' to 'viii').

    i, ii: high against low quality, four text features, both directions. iii, iv: English against other
    languages, fifty letter features, both directions. v, vi: ten classes of which one changes its language group.
    vii, viii: five groups in changing shares.
    """
    n_train, n_test, beta = SIZES[which]
    docs = document_groups(spark, sf_dir)
    total = docs.count()
    if total < 8000:  # sizes of the protocol belong to 10 000 documents
        f = total / 10000
        n_train, n_test, beta = max(60, int(n_train * f)), max(30, int(n_test * f)), max(5, int(beta * f * 2))
    groups, group = None, None
    if which in ("i", "ii"):
        rows = docs.select("doc_id", "quality").join(text_features(docs), "doc_id")
        features = list(TEXT4)
        a, b = rows.where("quality = 1"), rows.where("quality = 0")
        same, other = (a, b) if which == "i" else (b, a)
    elif which in ("iii", "iv"):
        rows, features = _wide(docs, 24, ["lang"])
        a, b = rows.where("lang = 'en'"), rows.where("lang <> 'en'")
        same, other = (a, b) if which == "iii" else (b, a)
    elif which in ("v", "vi"):
        cls = F.regexp_extract("source", "([0-9]+)", 1).cast("int") % 10
        rows, features = _wide(docs.withColumn("cls", cls), 0, ["lang", "cls"])
        english, late = F.col("lang") == "en", F.col("cls") == 9
        base = ((F.col("cls") <= 3) & english) | (F.col("cls").between(4, 8) & ~english)
        a, b = rows.where(base | (late & ~english)), rows.where(base | (late & english))
        same, other = (a, b) if which == "v" else (b, a)
    else:
        shares = SHARES_VII if which == "vii" else SHARES_VIII
        if which == "vii":
            rows, features = docs.select("doc_id", "grp").join(text_features(docs), "doc_id"), list(TEXT3)
        else:
            rows, features = _wide(docs, 23, ["grp"])
        # the group goes along as a number
        rows = rows.withColumn("g", F.array_position(F.array(*(F.lit(g) for g in GROUPS)), F.col("grp")).cast("int"))
        groups = tuple({k + 1: s[g] for k, g in enumerate(GROUPS)} for s in shares)
        same = other = rows
        group = "g"
    sets = sampled_sets(same, other, f"docs-{which}", features, runs, n_train, n_test, tests, groups, group)
    return run_trials(sets, features, methods, beta=beta, fit={"scale": "zscore"})


def assert_bigrams(n: int) -> tuple[str, ...]:
    if n > len(BIGRAMS):
        raise ValueError("not so many letter pairs")
    return BIGRAMS[:n]


def offset_toy(shift: float = 1.0, edges: Sequence[float] = (-1.0, 0.0, 1.0, 2.0)) -> list[dict]:
    """Closed form in one dimension: a Gaussian and its shifted copy over the bins between edges (the outer ones unbounded)."""
    from ..functions.chisq import normal_cdf

    cuts = [-np.inf, *edges, np.inf]
    out = []
    for a, b in zip(cuts, cuts[1:], strict=False):
        mass = lambda lo, hi, s: normal_cdf(hi - s) - normal_cdf(lo - s)
        mid = min(max(shift / 2, a), b)
        left, right = mass(a, mid, 0) - mass(a, mid, shift), mass(mid, b, 0) - mass(mid, b, shift)
        av, pv = abs(left) + abs(right), abs(left + right)
        out.append({"low": a, "high": b, "av": av, "pv": pv, "margin": av - pv, "is_offset": bool(a < shift / 2 < b)})
    return out
