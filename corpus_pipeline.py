"""The corpus pipeline: quality, exact copies, near copies, mixing, tokens.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes each stage's result as
Parquet in the shared folder and reads it again as the next stage's documents, and deletes what the stage before
has written. All stages but the last return the columns of documents.

In every stage null texts are empty texts, texts are worked on whole, extra columns are left behind, and an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftlab.llm.common import clear_cuts, cut, cuts_made, read_table
from driftlab.llm.exact_dedup import drop_copies
from driftlab.llm.mixing import mixed_documents
from driftlab.llm.pieces import sample_segmentations
from driftlab.llm.quality import fit_line_field, score_documents
from driftlab.llm.simhash import drop_near_copies

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose lines score 0.7 or more.

    Rows without an id, empty texts and repeated rows are each judged by their text like all others; equal texts have equal scores.
    Without labels of both kinds every document gets the score of the one kind, or 1.
    """
    model = fit_line_field(docs, read_table(spark, sf_dir, "labels"))
    scored = score_documents(docs, model, with_rows=COLUMNS)
    return scored.where("score >= 0.7").select(*COLUMNS)


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each distinct text: the smallest id, a row without an id only where no row of the text has one; of rows that repeat id and text, one."""
    return drop_copies(docs, keep="min").select(*COLUMNS)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word shingles, similarity 0.8): the smallest id.

    Rows without an id count as larger than all others, so one stays only where its group has none with an id. A text of fewer than five words
    has its whole word sequence as its shingle; texts without words are alike. Rows that repeat an id stay or go together.
    """
    return drop_near_copies(docs, shingle=5, similarity=0.8).select(*COLUMNS)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them: whole passes as copies, and the words of the blocks taken once more as a shorter text of the same id.

    A document that the mix does not take is left out, as are texts without words; n_chars follows the text. A null source is a source of its own.
    Rows that share an id share its plan (the most any of them is taken), and so do rows without one.
    """
    return mixed_documents(docs).select(*COLUMNS).withColumn("n_chars", F.length("text").cast("long"))


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, two sampled segmentations of each text, their log probabilities and inclusion scores.

    An empty text has the one empty segmentation. Rows that repeat id and text get equal samples; rows without an id are seeded by their text.
    """
    return sample_segmentations(docs, k=2)


STAGES = [
    ("quality classifier", quality_stage),
    ("exact dedup", exact_stage),
    ("simhash near-dedup", near_stage),
    ("mixing to target weights", mixing_stage),
    ("sentencepiece encoding", token_stage),
]

#: The classifier, the mix and the sampled segmentations have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select(*COLUMNS)
    start = cuts_made()
    for _, stage in STAGES:
        docs = cut(stage(spark, docs, sf_dir))
        clear_cuts(spark, start, keep=[docs])
    return docs
