"""Extra columns whose names clash with the operators' own, and empty tables, through every operator."""

import pytest
from pyspark.sql import functions as F

from driftlab.llm import chat, exact_dedup, mixing, pieces, quality, recompression, secrets, simhash, suffix_dedup, topk

NAMES = ("id", "key", "keys", "salt", "shared", "copy", "places", "spans", "digest", "rep", "n", "fp", "part", "parts", "node", "component", "size", "taken", "full", "first", "src", "shard", "label", "lines", "score", "samples", "bucket", "run", "start", "end", "owner", "content", "body", "stop", "draw")


@pytest.fixture(scope="module")
def table(spark):
    rows = [(1, "a b c d e f g", "s"), (2, "a b c d e f g", None), (3, None, "s"), (4, "", "t"), (5, "token = abcdefgh123", "t"), (6, "é " * 400, "t")]
    df = spark.createDataFrame([(i, t, "en", s, 0) for i, t, s in rows], "doc_id long, text string, lang string, source string, n_chars long")
    return df.select("*", *(F.lit("clash").alias(n) for n in NAMES))


OPERATORS = {
    "mix": lambda d: mixing.mix(d),
    "mixed": lambda d: mixing.mixed_documents(d),
    "secrets": lambda d: secrets.find_secrets(d),
    "near": lambda d: simhash.near_components(d),
    "similar": lambda d: simhash.similar_components(d),
    "drop_near": lambda d: simhash.drop_near_copies(d),
    "pieces": lambda d: pieces.sample_segmentations(d),
    "groups": lambda d: exact_dedup.exact_groups(d),
    "drop_copies": lambda d: exact_dedup.drop_copies(d),
    "quality": lambda d: quality.score_documents(d, quality.fit_line_field(d, d.select("doc_id", (F.col("doc_id") % 2).cast("int").alias("quality"), "label", "text"))),
    "words": lambda d: recompression.cut_repeats(d, window=5),
    "bytes": lambda d: suffix_dedup.cut_repeated_bytes(d, length=40),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_documents(table, name):
    out = OPERATORS[name](table)
    rows = out.collect()
    if name in ("drop_copies", "drop_near"):
        assert out.columns == table.columns and len(rows) == 4
    elif name == "mixed":
        assert out.columns == table.columns and rows
    else:
        assert {r.doc_id for r in rows} == {1, 2, 3, 4, 5, 6}
    assert OPERATORS[name](table.limit(0)).count() == 0


def test_other_tables(spark):
    v = spark.createDataFrame([(i, [float(i), 1.0]) for i in range(3)], "vec_id long, embedding array<float>").select("*", *(F.lit("x").alias(n) for n in (*NAMES, "dim", "asks", "query_id", "rank")))
    assert topk.top_k(v, F.col("vec_id") == 0).count() == 2
    c = spark.createDataFrame([(1, 1, "user", "q"), (1, 2, "assistant", "r")], "conv_id long, turn long, role string, text string").select("*", *(F.lit("x").alias(n) for n in (*NAMES, "turns", "whole", "example", "t", "m")))
    assert chat.chat_digest(chat.chat_examples(c)).count() == 1
