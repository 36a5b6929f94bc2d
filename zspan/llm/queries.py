"""One query per corpus operator, over its whole table, with SQL where SQL can express it."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zspan.llm import bpe, chat, crf, iblt, jaccard, knn, langid, linededup, packing, secret_scan
from zspan.llm.common import is_held_out


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = knn.quantise(_table(spark, sf_dir, "embeddings"))
    return knn.top_k(vectors, vectors.where(F.col("vec_id") % 20 == 0), k=20)


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op3_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    model = langid.learn(docs.where(~is_held_out(F.col("doc_id"))).select("doc_id", "text", "lang"))
    found = langid.predict(spark, docs, model)
    return found.select("doc_id", is_held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score", "mixture")


def op4_perspective_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.rotate(_table(spark, sf_dir, "conversations"))


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    vocabulary = public_tokenizers.path("byte_bpe_50k.json")
    return secret_scan.findings(_table(spark, sf_dir, "documents"), secret_scan.train(vocabulary), vocabulary)


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = linededup.clean(_table(spark, sf_dir, "documents"), passages=True)
    return found.select("doc_id", "n_chunks", "n_dropped", F.length("text").cast("long").alias("n_chars_left"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"))


def op7_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.classes(_table(spark, sf_dir, "documents"))


def op9_iblt_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return iblt.versions(_table(spark, sf_dir, "documents"))


def op10_quality_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, held_out = _table(spark, sf_dir, "documents"), is_held_out(F.col("doc_id"))
    chain = crf.learn(docs, _table(spark, sf_dir, "labels").where(~held_out).select("doc_id", "quality"))
    return crf.score(spark, docs, chain).select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


QUERIES = {
    "op1_topk_search": op1_topk_search,
    "op2_best_fit_packing": op2_best_fit_packing,
    "op3_language_mixture": op3_language_mixture,
    "op4_perspective_chat": op4_perspective_chat,
    "op5_secret_scan": op5_secret_scan,
    "op6_line_dedup": op6_line_dedup,
    "op7_bpe_round_trip": op7_bpe_round_trip,
    "op8_jaccard_join": op8_jaccard_join,
    "op9_iblt_fingerprint": op9_iblt_fingerprint,
    "op10_quality_crf": op10_quality_crf,
}

ORACLE_SQL = {
    "op1_topk_search": """
        WITH v AS (
            SELECT vec_id, list_transform(embedding, lambda x: floor(64 * CAST(x AS DOUBLE))) AS v
            FROM embeddings
            WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
        ), scored AS (
            SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.v, c.v) AS BIGINT) AS score
            FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.v) = len(c.v)
            WHERE q.vec_id % 20 = 0
        )
        SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score
        FROM scored QUALIFY rank <= 20
    """,
    "op4_perspective_chat": """
        WITH said AS (
            SELECT DISTINCT conv_id, coalesce(turn, 0) AS turn, coalesce(role, 'unknown') AS role, coalesce(text, '') AS text
            FROM conversations WHERE conv_id IS NOT NULL
        ), seats AS (
            SELECT DISTINCT conv_id, role AS perspective FROM said WHERE role <> 'system'
        ), lines AS (
            SELECT conv_id, perspective, turn // 32 AS part, turn, role, text, role = perspective AS own,
                CASE WHEN role = 'system' THEN '<|system|>' WHEN role = perspective THEN '<|assistant|>'
                     ELSE '<|user name=' || replace(role, '<|', '< |') || '|>' END || chr(10) AS head,
                replace(text, '<|', '< |') || '<|end|>' || chr(10) AS body
            FROM said JOIN seats USING (conv_id)
        ), placed AS (
            SELECT *, coalesce(sum(length(head) + length(body)) OVER (PARTITION BY conv_id, perspective, part ORDER BY turn, role, text
                ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS place
            FROM lines
        ), parts AS (
            SELECT conv_id, perspective, part, count(*) AS n_messages, string_agg(head || body, '' ORDER BY turn, role, text) AS text,
                coalesce(string_agg(CASE WHEN own THEN CAST(place + length(head) AS BIGINT) || '-' || CAST(place + length(head) + length(body) - 1 AS BIGINT) END, ','
                    ORDER BY turn, role, text), '') AS train_spans, sum(length(head) + length(body)) AS size
            FROM placed GROUP BY ALL
        )
        SELECT conv_id, perspective, part, n_messages, text, train_spans,
            CAST(coalesce(sum(size) OVER (PARTITION BY conv_id, perspective ORDER BY part ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS char_start
        FROM parts
    """,
}
