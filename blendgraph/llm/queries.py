"""The operators as registered queries, and SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontamination, licenses, line_chunks, line_quality, mixing, sentence_spans, simhash, sql, suffix_blocks, surrogates, url_trust
from .common import table


def op4_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("hit_spans")


def op1_url_trust(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_trust.judge_urls(table(spark, sf_dir, "pages"))


def op2_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = surrogates.replace_entities(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", F.col("pi_found").alias("n_replaced"), "text")


def op3_sentence_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Runs of two sentences and twelve words: a passage of 50 words may have no third full sentence."""
    found = sentence_spans.drop_repeated_spans(table(spark, sf_dir, "documents").select("doc_id", "text"), 2, 12)
    return found.select("doc_id", F.col("ss_sentences").alias("n_sentences"), F.col("ss_removed").alias("n_removed"), "text")


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_blocks.remove_repeats(table(spark, sf_dir, "documents")).drop("kept")


def op6_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_quality.score_quality(table(spark, sf_dir, "documents")).drop("n_failed_lines", "n_kept_words")


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op8_line_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = line_chunks.drop_repeated_chunks(table(spark, sf_dir, "documents").select("doc_id", "text"), runs=True)
    return found.select("doc_id", F.col("lc_removed_chunks").alias("n_removed_chunks"), F.col("lc_removed_lines").alias("n_removed_lines"), "text")


def op9_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    planned = mixing.plan_mixture(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    return planned.select("doc_id", F.col("mx_size").alias("size"), F.col("mx_source_size").alias("source_size"), F.col("mx_target").alias("target"), (F.col("mx_copies") * F.col("mx_size")).alias("taken"))


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_licenses(table(spark, sf_dir, "documents")).drop("blocks")


def queries() -> dict:
    return {f.__name__: f for f in (op1_url_trust, op2_surrogates, op3_sentence_spans, op4_decontaminate, op5_suffix_dedup, op6_line_quality, op7_simhash, op8_line_chunks, op9_mixture, op10_license_scan)}


def oracle_sql() -> dict[str, str]:
    return sql.oracle_sql()
