"""The queries opN_<name> and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from multiagg.llm.common import load


def op1_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from multiagg.llm.ngram_join import near_duplicates

    return near_duplicates(load(spark, sf_dir, "documents")).drop("body_key")


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from multiagg.llm.packing import pack

    pieces = pack(load(spark, sf_dir, "documents"))
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from multiagg.llm.pii import span_digests

    return span_digests(load(spark, sf_dir, "documents"))


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from multiagg.llm.suffix_dedup import removal_digests

    return removal_digests(load(spark, sf_dir, "documents"))


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from multiagg.llm.exact_dedup import exact_groups

    return exact_groups(load(spark, sf_dir, "documents")).drop("body_key")


def op6_warc_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from multiagg.llm.warc import damaged, fixity

    pages = load(spark, sf_dir, "pages")
    found = fixity(pages, damaged(pages))
    return found.select(F.col("record_id").alias("page_id"), "n_bytes", "record_sha256", (F.col("state") != "intact").alias("corrupt"))


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from multiagg.llm.byte_bpe import digests

    return digests(load(spark, sf_dir, "documents"))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from multiagg.llm.token_counts import document_counts

    return document_counts(load(spark, sf_dir, "documents"))


def op9_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from multiagg.llm.quality_rules import ledger, passes

    rows = ledger(load(spark, sf_dir, "documents").select("doc_id", "text"))
    failed = F.col("ledger.failed")
    return rows.select(
        "doc_id", *(F.col(f"ledger.{m}").alias(m) for m in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")),
        (~passes(failed, "v1")).alias("base_failed"), passes(failed, "v2").alias("kept"), failed.alias("failed_bits"),
    )


def op10_pitman_yor(spark: SparkSession, sf_dir: str) -> DataFrame:
    from multiagg.llm.pitman_yor import score_documents

    return score_documents(load(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_ngram_join, op2_packing, op3_pii, op4_suffix_dedup, op5_exact_dedup, op6_warc_fixity, op7_byte_bpe, op8_token_counts, op9_quality_rules, op10_pitman_yor, pipeline)}

ORACLE_SQL: dict[str, str] = {
    "op5_exact_dedup": """
        SELECT doc_id, max(doc_id) OVER (PARTITION BY coalesce(text, '')) AS keep_id,
               count(*) OVER (PARTITION BY coalesce(text, '')) AS group_size,
               doc_id = max(doc_id) OVER (PARTITION BY coalesce(text, '')) AS kept,
               sha256(coalesce(text, '')) AS text_sha256
        FROM documents""",
    "op6_warc_fixity": """
        SELECT page_id, CAST(octet_length(encode(record)) AS BIGINT) AS n_bytes, sha256(record) AS record_sha256,
               sha256(coalesce(url, ''))[1] = '0' AND length(html) > 0 AS corrupt
        FROM (SELECT *, 'WARC/1.1' || chr(13) || chr(10) || 'WARC-Type: resource' || chr(13) || chr(10) || 'WARC-Target-URI: ' || coalesce(url, '') || chr(13) || chr(10)
                     || 'Content-Type: text/html' || chr(13) || chr(10) || 'Content-Length: ' || CAST(octet_length(encode(coalesce(html, ''))) AS VARCHAR)
                     || chr(13) || chr(10) || chr(13) || chr(10) || coalesce(html, '') || chr(13) || chr(10) || chr(13) || chr(10) AS record
              FROM pages)""",
}
