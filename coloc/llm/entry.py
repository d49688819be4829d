"""Queries of this subpackage over the given tables, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from coloc.llm import near_dedup, quality_rules


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as vocabularies

    from coloc.llm import packing

    return packing.packed(_read(spark, sf_dir, "documents"), vocabularies.path("word_bpe_49k.json"))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.verdicts(_read(spark, sf_dir, "documents"))


def quality_rule_ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.ablations(quality_rules.ledger(_read(spark, sf_dir, "documents")))


def op3_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.groups(_read(spark, sf_dir, "documents"), near_dedup.Likeness(words=2, percent=80))


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as vocabularies

    from coloc.llm import byte_bpe

    return byte_bpe.digests(_read(spark, sf_dir, "documents"), vocabularies.path("byte_bpe_multi_50k.tiktoken"), vocabularies.PATTERN)


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as vocabularies

    from coloc.llm import token_counts

    return token_counts.token_counts(_read(spark, sf_dir, "documents"), vocabularies.path("piece_bpe_32k.model"))


def op6_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    from coloc.llm import exact_topk

    return exact_topk.nearest(_read(spark, sf_dir, "embeddings"))


def op7_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    from coloc.llm import quality_model

    docs = _read(spark, sf_dir, "documents")
    return quality_model.scores(docs, quality_model.train(docs, _read(spark, sf_dir, "labels")))


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from coloc.llm import warc

    return warc.archived(_read(spark, sf_dir, "pages"))


def op9_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    from coloc.llm import url_filters

    return url_filters.verdicts(_read(spark, sf_dir, "pages"), _read(spark, sf_dir, "labels"))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from coloc.llm import language_id

    return language_id.languages(_read(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_packing": op1_packing,
    "op2_quality_rules": op2_quality_rules,
    "quality_rule_ablations": quality_rule_ablations,
    "op3_near_dedup": op3_near_dedup,
    "op4_byte_bpe": op4_byte_bpe,
    "op5_token_counts": op5_token_counts,
    "op6_exact_topk": op6_exact_topk,
    "op7_quality_model": op7_quality_model,
    "op8_warc": op8_warc,
    "op9_url_filters": op9_url_filters,
    "op10_language_id": op10_language_id,
}
ORACLE_SQL: dict[str, str] = {
    "op2_quality_rules": quality_rules.VERDICTS_SQL,
    "quality_rule_ablations": quality_rules.ABLATIONS_SQL,
    "op3_near_dedup": near_dedup.groups_sql(2, 80),
    "op6_exact_topk": """
        WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS c FROM embeddings
                   WHERE embedding IS NOT NULL AND list_bool_and(list_transform(embedding, lambda x: x IS NOT NULL AND isfinite(x)))),
        s AS (SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.c::DOUBLE[], c.c::DOUBLE[])::BIGINT AS score
              FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id),
        r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s)
        SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
    """,
    "op8_warc": """
        WITH p AS (SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
        f AS (SELECT payload_digest, min(page_id) AS first_id, count(*) AS n FROM p WHERE payload_bytes >= 100 GROUP BY payload_digest)
        SELECT p.page_id, p.payload_bytes, p.payload_digest,
               CASE WHEN f.n > 1 AND p.page_id IS DISTINCT FROM f.first_id AND f.first_id IS NOT NULL THEN 'revisit' ELSE 'response' END AS record_type,
               CASE WHEN f.n > 1 AND p.page_id IS DISTINCT FROM f.first_id THEN f.first_id END AS refers_to
        FROM p LEFT JOIN f ON f.payload_digest = p.payload_digest AND p.payload_bytes >= 100
    """,
}
