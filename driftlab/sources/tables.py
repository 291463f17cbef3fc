"""Readers, writers and deterministic sampling."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import ship

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names: Sequence[str] = TABLES) -> None:
    """Temporary views of the given tables, for SQL users."""
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A scan of Parquet, ORC, CSV, JSON or text. CSV and JSON need a schema: types are never inferred from text."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", mode: str = "overwrite", partition_by: Sequence[str] = (), **options) -> None:
    out = df.write.mode(mode).options(**options)
    (out.partitionBy(*partition_by) if partition_by else out).format(kind).save(path)


def hash_top(df: DataFrame, n: int, keys: Sequence[str], seed: int = 0) -> DataFrame:
    """Exactly n rows (all, if fewer): those of smallest MD5 of seed and keys; a top-k plan, no full sort."""
    return df.orderBy(F.md5(F.concat_ws(":", F.lit(str(seed)), *(F.col(k).cast("string") for k in keys))), *keys).limit(n)


def hash_fraction(df: DataFrame, fraction: float, keys: Sequence[str], seed: int = 0) -> DataFrame:
    """About a fraction of the rows, the same ones in every run."""
    text = F.concat_ws(":", F.lit(str(seed)), *(F.col(k).cast("string") for k in keys))
    return df.where(F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") < int(fraction * (1 << 32)))


def stratified(df: DataFrame, group: str, quotas: dict[str, int], keys: Sequence[str], seed: int = 0) -> DataFrame:
    """For each group, its quota of rows of smallest MD5."""
    draw = F.md5(F.concat_ws(":", F.lit(str(seed)), *(F.col(k).cast("string") for k in keys)))
    quota = F.create_map(*(x for g, n in quotas.items() for x in (F.lit(g), F.lit(n))))
    placed = df.where(F.col(group).isin(*quotas)).withColumn("__place", F.row_number().over(Window.partitionBy(group).orderBy(draw, *keys)))
    return placed.where(F.col("__place") <= F.element_at(quota, F.col(group))).drop("__place")


def standard_rows(df: DataFrame, features: Sequence[str], keys: Sequence[str], folder: str) -> Callable[[int], DataFrame]:
    """A function of n: n rows (id from 0, g1, g2, ..., u1, u2, ...) of smallest MD5 of all rows of df, over again where df has fewer.

    g: features less their mean over the whole table by their deviation; u: features scaled to [0, 1] by the whole table. The rows are kept below `folder`.
    """
    spark = df.sparkSession
    drawn: dict[int, tuple] = {}

    def rows(n: int) -> DataFrame:
        if n not in drawn:
            drawn[n] = draw_rows(n)
        placed, count = drawn[n]
        return spark.range(n).withColumn("place", F.col("id") % count).join(F.broadcast(placed), "place").drop("place")

    def draw_rows(n: int) -> tuple[DataFrame, int]:
        path = f"{folder}/rows-{n}"
        m = df.agg(F.count("*").alias("n"), *(f(c).cast("double").alias(f"{k}{j}") for j, c in enumerate(features) for k, f in (("a", F.avg), ("s", F.stddev_pop), ("l", F.min), ("h", F.max)))).first()
        if not m.n:
            raise ValueError("the table is empty")
        by = lambda v: F.lit(float(v) if v else 1.0)
        g = [((F.col(c) - F.lit(m[f"a{j}"])) / by(m[f"s{j}"])).alias(f"g{j + 1}") for j, c in enumerate(features)]
        u = [((F.col(c) - F.lit(m[f"l{j}"])) / by(m[f"h{j}"] - m[f"l{j}"])).alias(f"u{j + 1}") for j, c in enumerate(features)]
        top = hash_top(df.select(*{*keys, *features}), n, keys)
        draw = F.md5(F.concat_ws(":", F.lit("0"), *(F.col(k).cast("string") for k in keys)))
        top.select((F.row_number().over(Window.orderBy(draw, *keys)) - 1).alias("place"), *g, *u).write.parquet(path)
        return spark.read.parquet(path), min(n, m.n)

    return rows


def most_frequent(df: DataFrame, group: str, n: int) -> DataFrame:
    """The rows of the n largest groups (ties to the smaller name)."""
    top = df.groupBy(group).agg(F.count("*").alias("__n")).orderBy(F.desc("__n"), group).limit(n).select(group)
    return df.join(F.broadcast(top), group, "left_semi")


# ------------------------------------------------------------------ text features

VOWELS = "aeiou"
#: Fixed list of letter pairs for the wide text features.
BIGRAMS = ("th", "he", "in", "er", "an", "re", "on", "at", "en", "nd", "ti", "es", "or", "te", "of", "ed", "is", "it", "al", "ar", "st", "to", "nt", "ng")


def _letters(text: Column, keep: str) -> Column:
    return F.length(F.regexp_replace(F.lower(text), f"[^{keep}]", "")).cast("double")


def text_features(docs: DataFrame) -> DataFrame:
    """doc_id, ln_words, word_len, vowel_share, token_ratio."""
    words = F.split("text", " ")
    n = F.size(words).cast("double")
    chars = F.length("text").cast("double")
    return docs.select(
        "doc_id",
        F.log(n).alias("ln_words"),
        ((chars - n + 1) / n).alias("word_len"),
        F.when(chars > 0, _letters(F.col("text"), VOWELS) / chars).otherwise(0.0).alias("vowel_share"),
        (F.size(F.array_distinct(words)) / n).alias("token_ratio"),
    )


def letter_shares(docs: DataFrame, bigrams: int = 0) -> DataFrame:
    """doc_id, features: shares of a-z in the lower-cased text, then of the first `bigrams` letter pairs."""
    n = F.greatest(F.length("text"), F.lit(1)).cast("double")
    low = F.lower("text")
    cells = [(F.length(low) - F.length(F.replace(low, F.lit(c)))) / n for c in "abcdefghijklmnopqrstuvwxyz"]
    cells += [(F.length(low) - F.length(F.replace(low, F.lit(b)))) / F.lit(2.0) / n for b in BIGRAMS[:bigrams]]
    return docs.select("doc_id", F.array(*cells).alias("features"))


def event_features(events: DataFrame) -> DataFrame:
    """event_id, ts, event_type, value, hour, k (of the JSON props)."""
    return events.select("event_id", "ts", "event_type", "value", F.hour("ts").alias("hour"), F.get_json_object("props", "$.k").cast("int").alias("k"))
