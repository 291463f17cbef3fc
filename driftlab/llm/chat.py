"""Chat formatting by prefix-target expansion, in DataFrame functions only.

A turn is written `<s>[INST]role[/INST]text</s>`; a conversation is its turns in order. Every
assistant turn becomes an example of its own: all preceding turns as context, then that reply,
whose text alone is under the loss mask. Turns after the last reply (or a conversation without
one) close with an example that has no loss, so that nothing of the input is left out.

Inside texts and roles each backslash is doubled and each control string gets a backslash after
its first character; taking the character after every backslash as it stands undoes both.

Defined cases: null text or role is empty; a null turn number comes first; equal turn numbers are
ordered by role, then text; repeated rows are repeated turns; an empty table gives no example.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The control strings of the template.
OPEN, ROLE_END, CLOSE = "<s>[INST]", "[/INST]", "</s>"


def escape(c: Column) -> Column:
    c = F.replace(c, F.lit("\\"), F.lit("\\\\"))
    c = F.regexp_replace(c, r"<(/?s>)", r"<\\$1")
    return F.regexp_replace(c, r"\[(/?INST\])", r"[\\$1")


def unescape(c: Column) -> Column:
    return F.regexp_replace(c, r"(?s)\\(.)", "$1")


def chat_examples(turns: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text", target_role: str = "assistant") -> DataFrame:
    """conv_id, example (from 0), n_turns, text, loss_start, loss_end (code points, end exclusive)."""
    rows = turns.select(
        F.col(conv_col).alias("conv_id"),
        F.struct(F.col(turn_col).cast("long").alias("turn"), F.coalesce(F.col(role_col).cast("string"), F.lit("")).alias("role"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).alias("t"),
    )
    conv = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("turns"))
    marked = conv.select(
        "conv_id",
        F.transform("turns", lambda t: F.struct((t["role"] == target_role).alias("target"), F.concat(F.lit(OPEN), escape(t["role"]), F.lit(ROLE_END)).alias("head"), escape(t["text"]).alias("body"))).alias("m"),
    )
    # running ends of the turns in the formatted conversation
    zero = F.array().cast("array<int>")
    ends = F.aggregate("m", zero, lambda acc, t: F.concat(acc, F.array((F.coalesce(F.try_element_at(acc, F.lit(-1)), F.lit(0)) + F.length(t["head"]) + F.length(t["body"]) + F.lit(len(CLOSE))).cast("int"))))
    whole = F.array_join(F.transform("m", lambda t: F.concat(t["head"], t["body"], F.lit(CLOSE))), "")
    sized = marked.select("conv_id", F.size("m").alias("n"), whole.alias("whole"), F.transform("m", lambda t: t["target"]).alias("target"), F.transform("m", lambda t: F.length(t["body"])).alias("chars"), ends.alias("ends"))
    last = F.col("n") - 1
    targets = F.filter(F.sequence(F.lit(0), last), lambda i: F.element_at("target", i + 1) | (i == last))
    one = sized.select("conv_id", "whole", "target", "chars", "ends", F.posexplode(targets).alias("example", "at"))
    stop, trains = F.element_at("ends", F.col("at") + 1), F.element_at("target", F.col("at") + 1)
    loss_end = F.when(trains, stop - len(CLOSE)).otherwise(stop)
    return one.select(
        "conv_id",
        "example",
        (F.col("at") + 1).cast("long").alias("n_turns"),
        F.substring(F.col("whole"), F.lit(1), stop).alias("text"),
        (loss_end - F.when(trains, F.element_at("chars", F.col("at") + 1)).otherwise(0)).cast("long").alias("loss_start"),
        loss_end.cast("long").alias("loss_end"),
    )


def read_back(text: Column) -> Column:
    """Array of struct(role, text): the turns of a formatted text."""
    parts = F.split(text, CLOSE)
    cells = F.slice(parts, 1, F.size(parts) - 1)

    def one(c: Column) -> Column:
        inner = F.substring(c, F.lit(len(OPEN) + 1), F.length(c))
        cut = F.instr(inner, ROLE_END)
        return F.struct(unescape(F.substring(inner, F.lit(1), cut - 1)).alias("role"), unescape(F.substring(inner, cut + len(ROLE_END), F.length(inner))).alias("text"))

    return F.transform(cells, one)


def chat_digest(examples: DataFrame) -> DataFrame:
    """One row per conversation with digests of turns and of the text under the loss mask, parsed from the examples."""
    masked = unescape(F.substring(F.col("text"), (F.col("loss_start") + 1).cast("int"), (F.col("loss_end") - F.col("loss_start")).cast("int")))
    got = examples.groupBy("conv_id").agg(
        F.max_by("text", "n_turns").alias("longest"),
        F.sort_array(F.collect_list(F.struct("example", masked.alias("piece")))).alias("pieces"),
        F.sum(F.length("text")).cast("long").alias("formatted_chars"),
    )
    parsed = got.select("conv_id", read_back(F.col("longest")).alias("turns"), F.array_join(F.transform("pieces", lambda p: p["piece"]), "").alias("loss"), "formatted_chars")
    all_turns = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return parsed.select("conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2(all_turns, 256).alias("turns_sha256"), F.length("loss").cast("long").alias("loss_chars"), F.sha2("loss", 256).alias("loss_sha256"), "formatted_chars")
