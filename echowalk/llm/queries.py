"""Queries opN_<name> over the whole tables, and SQL for those that it can express."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, exact_dedup, lm_scoring, packing, segmentation, simhash, substring_dedup, top_k, toxicity, url_filter


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Fixed value: the text of both turns of conversation -1.
PROBE = "</s>[INST] ok [/INST]"


def op1_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = _table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.createDataFrame([(-1, 0, "user", PROBE), (-1, 1, "assistant", PROBE)], "conv_id long, turn long, role string, text string")
    return chat.format_digests(turns.unionByName(probe))


def toxicity_weights(docs: DataFrame, spark: SparkSession, sf_dir: str) -> toxicity.Weights:
    return toxicity.fit(docs, _table(spark, sf_dir, "labels"), learn_from=~toxicity.held_out(F.col("_id")))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = toxicity.add_scores(docs, toxicity_weights(docs, spark, sf_dir))
    return scored.select("doc_id", toxicity.held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op3_segmentation_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    return segmentation.sample_segmentations(_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"), k=3, digest=True)


def op4_top_products(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = top_k.top_k(_table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0, k=5, scale=256.0)
    return found.withColumn("rank", F.col("rank").cast("int"))


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_duplicates(_table(spark, sf_dir, "documents"))


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.remove_repeats(_table(spark, sf_dir, "documents"), window=35, with_text=False)


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.filter_urls(_table(spark, sf_dir, "pages"))


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_components(_table(spark, sf_dir, "documents"), shingle=3, distance=3)
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), capacity=2048, separator=0)


def op10_lm_difference(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Target: documents labelled as of high quality; background: all."""
    good = _table(spark, sf_dir, "labels").filter("quality = 1").select("doc_id")
    return lm_scoring.score_documents(_table(spark, sf_dir, "documents"), good)


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_chat_format, op2_toxicity, op3_segmentation_samples, op4_top_products, op5_exact_dedup, op6_substring_dedup, op7_url_filter, op8_simhash, op9_best_fit_packing, op10_lm_difference, pipeline)
}

_SIGNS = "(length({0}) + length(regexp_replace({0}, '[^~<\\[\\]]', '', 'g')))"

ORACLE_SQL: dict[str, str] = {
    "op1_chat_format": f"""
        WITH turns AS (
            SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
            UNION ALL SELECT -1, 0, 'user', '{PROBE}' UNION ALL SELECT -1, 1, 'assistant', '{PROBE}')
        SELECT conv_id, count(*) AS n_turns,
            sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
            CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
            sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
            CAST(sum(CASE WHEN role = 'assistant' THEN 7 + {_SIGNS.format("text")} ELSE 14 + {_SIGNS.format("role")} + {_SIGNS.format("text")} END) AS BIGINT) AS formatted_chars,
            CAST(0 AS BIGINT) AS rewrites
        FROM turns GROUP BY conv_id""",
    "op4_top_products": """
        WITH v AS (
            SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS DOUBLE)) AS v FROM embeddings
            WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
        s AS (
            SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.v, c.v) AS BIGINT) AS score
            FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0)
        SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
        FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 5""",
    "op5_exact_dedup": """
        WITH d AS (
            SELECT doc_id, length(coalesce(text, '')) AS chars, regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]', '', 'g') AS body FROM documents),
        k AS (
            SELECT doc_id, first_value(doc_id) OVER (PARTITION BY body ORDER BY chars DESC, doc_id) AS keep_id, count(*) OVER (PARTITION BY body) AS group_size, sha256(body) AS text_sha256 FROM d)
        SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM k""",
    "op6_substring_dedup": """
        WITH d AS (
            SELECT row_number() OVER () AS r, doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w FROM documents),
        g AS (SELECT r, w, unnest(range(1, len(w) - 33)) AS i FROM d WHERE len(w) >= 35),
        h AS (SELECT r, i, count(*) OVER (PARTITION BY array_to_string(w[i:i + 34], ' ')) AS n FROM g),
        c AS (SELECT DISTINCT r, unnest(range(i, i + 35)) AS p FROM h WHERE n > 1),
        u AS (SELECT r, unnest(w) AS word, generate_subscripts(w, 1) AS p FROM d),
        s AS (
            SELECT u.r, count(*) AS n_words, count(c.p) AS n_removed, sha256(coalesce(string_agg(word, ' ' ORDER BY u.p) FILTER (c.p IS NULL), '')) AS kept_sha256
            FROM u LEFT JOIN c ON u.r = c.r AND u.p = c.p GROUP BY u.r)
        SELECT doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed, coalesce(kept_sha256, sha256('')) AS kept_sha256
        FROM d LEFT JOIN s USING (r)""",
}
