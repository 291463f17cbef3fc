"""The opN queries: each applies its operator to its whole table and shapes the result."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .chat import chat_digest, chat_examples
from .common import read_table
from .exact_dedup import exact_groups
from .mixing import mix
from .pieces import sample_segmentations
from .quality import crc_mod, fit_line_field, score_documents
from .recompression import cut_repeats
from .secrets import find_secrets
from .simhash import near_components
from .suffix_dedup import cut_repeated_bytes
from .topk import top_k


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(read_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op2_find_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_secrets(read_table(spark, sf_dir, "documents"))


def op3_simhash_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_components(read_table(spark, sf_dir, "documents"), shingle=3)


def op4_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(read_table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0, k=5)


def op5_sample_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two distinct segmentations of every text, as digests of their piece ids."""
    found = sample_segmentations(read_table(spark, sf_dir, "documents"), k=2)
    digest = F.transform("samples", lambda s: F.xxhash64(s))
    return found.select("doc_id", F.size("samples").alias("n_samples"), F.transform("samples", F.size).alias("n_pieces"), digest.alias("ids_xxh64"), "log_p", "perturbed", "inclusion")


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_groups(read_table(spark, sf_dir, "documents"), keep="max")


def op7_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    model = fit_line_field(docs, read_table(spark, sf_dir, "labels"), train_if=crc_mod("doc_id", 4) != 2)
    scored = score_documents(docs, model)
    return scored.select("doc_id", (crc_mod("doc_id", 4) == 2).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-1, 0, "user", probe), (-1, 1, "assistant", probe)], "conv_id long, turn long, role string, text string")
    return chat_digest(chat_examples(turns.unionByName(extra)))


def op9_cut_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cut_repeats(read_table(spark, sf_dir, "documents"), window=50).select("doc_id", "n_words", "n_removed", "kept_sha256")


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cut_repeated_bytes(read_table(spark, sf_dir, "documents"), length=400).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


QUERIES = {f.__name__: f for f in (op1_mix_sources, op2_find_secrets, op3_simhash_components, op4_exact_topk, op5_sample_pieces, op6_exact_dedup, op7_line_quality, op8_chat_format, op9_cut_repeats, op10_suffix_dedup)}

ORACLE = {
    # the bytes as hexadecimal digits, so that a window of 400 bytes is a substring of 800 digits
    "op10_suffix_dedup": """
        WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h, strlen(coalesce(text, ''))::BIGINT AS n FROM documents),
             w AS (SELECT doc_id, h, unnest(range(0, greatest(n - 399, 0))) AS p FROM d),
             k AS (SELECT doc_id, p, md5(substr(h, 2 * p + 1, 800)) AS k FROM w),
             c AS (SELECT k FROM k GROUP BY k HAVING count(*) > 1),
             x AS (SELECT doc_id, p FROM k SEMI JOIN c USING (k)),
             f AS (SELECT doc_id, p, CASE WHEN p <= lag(p) OVER (PARTITION BY doc_id ORDER BY p) + 400 THEN 0 ELSE 1 END AS fresh FROM x),
             i AS (SELECT doc_id, p, sum(fresh) OVER (PARTITION BY doc_id ORDER BY p ROWS UNBOUNDED PRECEDING) AS g FROM f),
             s AS (SELECT doc_id, min(p) AS a, max(p) + 400 AS b FROM i GROUP BY doc_id, g),
             j AS (SELECT doc_id, list(a ORDER BY a) AS la, list(b ORDER BY a) AS lb, sum(b - a)::BIGINT AS gone, count(*) AS spans FROM s GROUP BY doc_id)
        SELECT d.doc_id, n AS n_bytes, coalesce(gone, 0) AS n_removed, coalesce(spans, 0) AS n_spans,
               sha256(unhex(CASE WHEN la IS NULL THEN h ELSE array_to_string(list_transform(range(0, len(la) + 1),
                   lambda i: substr(h, 2 * coalesce(lb[i], 0) + 1, 2 * (coalesce(la[i + 1], n) - coalesce(lb[i], 0)))), '') END)) AS kept_sha256
        FROM d LEFT JOIN j ON d.doc_id = j.doc_id""",
    "op9_cut_repeats": """
        WITH w AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x09-\\x0D\\x20]+'), lambda x: x <> '') AS ws FROM documents),
             g AS (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 48, 1))) AS p FROM w),
             h AS (SELECT doc_id, p, md5(array_to_string(ws[p:p + 49], ' ')) AS k FROM g),
             f AS (SELECT k, min(doc_id) AS low FROM h GROUP BY k),
             c AS (SELECT doc_id, list_distinct(flatten(list(range(p, p + 50)))) AS gone FROM h JOIN f USING (k) WHERE doc_id > low GROUP BY doc_id)
        SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(len(gone), 0)::BIGINT AS n_removed,
               sha256(array_to_string(CASE WHEN gone IS NULL THEN ws ELSE list_filter(ws, lambda x, i: NOT list_contains(gone, i)) END, ' ')) AS kept_sha256
        FROM w LEFT JOIN c ON w.doc_id = c.doc_id""",
    "op4_exact_topk": """
        WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS e FROM embeddings
                   WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
             s AS (SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.e, c.e)::BIGINT AS score
                   FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id),
             r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score FROM s)
        SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5""",
    "op6_exact_dedup": """
        WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents)
        SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, sha256(t) AS text_sha256
        FROM d WINDOW w AS (PARTITION BY t)""",
    "op8_chat_format": r"""
        WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
                   UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
             e AS (SELECT *, 20 + length(role) + length(regexp_replace(regexp_replace(replace(text, '\', '\\'), '<(/?s>)', '<\\\1', 'g'), '\[(/?INST\])', '[\\\1', 'g')) AS n FROM c),
             r AS (SELECT *, sum(n) OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS upto,
                          row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC, role DESC, text DESC) AS back FROM e)
        SELECT conv_id, count(*) AS n_turns,
               sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
               sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END)::BIGINT AS loss_chars,
               sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
               sum(CASE WHEN role = 'assistant' OR back = 1 THEN upto ELSE 0 END)::BIGINT AS formatted_chars
        FROM r GROUP BY conv_id""",
}
