"""The ten registered queries, each on its whole table, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import op1_vectors, op2_quality, op3_mix, op4_lines, op5_language, op6_secrets, op7_warc, op8_toxicity, op9_near_dup, op10_bpe


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_embedding_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op1_vectors.near_vectors(table(spark, sf_dir, "embeddings"))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = op2_quality.score(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "quality")


def op3_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op3_mix.mix(table(spark, sf_dir, "documents"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op4_lines.report(table(spark, sf_dir, "documents"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op5_language.identify(table(spark, sf_dir, "documents"))


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op6_secrets.scan(table(spark, sf_dir, "documents"))


def op7_warc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op7_warc.round_trip(spark, table(spark, sf_dir, "pages"))


def op8_toxicity_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op8_toxicity.rate_texts(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op9_minhash_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op9_near_dup.near_duplicates(table(spark, sf_dir, "documents"))


def op10_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op10_bpe.encode(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        f.__name__: f
        for f in (
            op1_embedding_near_dup,
            op2_quality_rules,
            op3_source_mix,
            op4_line_dedup,
            op5_language_id,
            op6_secret_scan,
            op7_warc_round_trip,
            op8_toxicity_score,
            op9_minhash_near_dup,
            op10_bpe_round_trip,
        )
    }


#: Base 32 of a SHA-1 in hexadecimal: five hexadecimal digits make four characters.
_BASE32 = (
    "list_aggregate(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', "
    "(((('0x' || substr(hex, (5 * (i // 4) + 1)::INTEGER, 5))::BIGINT >> (15 - 5 * (i % 4))::BIGINT) & 31) + 1)::INTEGER, 1)), 'string_agg', '')"
)
_OP7 = f"""WITH p AS (SELECT page_id, coalesce(html, '') AS html, sha1(coalesce(html, '')) AS hex FROM pages),
 q AS (SELECT *, min(page_id) OVER (PARTITION BY html) AS first FROM p)
SELECT page_id, octet_length(encode(html))::BIGINT AS payload_bytes, {_BASE32} AS payload_digest,
 CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
 CASE WHEN page_id = first THEN NULL ELSE first END AS refers_to FROM q"""


def oracle_sql() -> dict[str, str]:
    return {"op3_source_mix": op3_mix.oracle(), "op7_warc_round_trip": _OP7}
