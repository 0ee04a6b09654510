"""Queries of the training-data operators, each over whole tables, with their SQL where there is any."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from linkveil.llm import decontaminate, hmm, host_rules, html_text, language, near_duplicates, pieces, quality, secrets, spans, sql


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op6_sentence_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spans.remove(_table(spark, sf_dir, "documents"), keep=["doc_id", "text"])


def op8_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify(_table(spark, sf_dir, "documents"))


def op9_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.find(_table(spark, sf_dir, "documents"))


def op7_host_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return host_rules.verdicts(_table(spark, sf_dir, "documents")).select("doc_id", *host_rules.MEASURES, "base_failed", "kept")


def op1_hmm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hmm.score(_table(spark, sf_dir, "documents"))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.score(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op3_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(_table(spark, sf_dir, "pages"))


def op4_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    encoded = pieces.encode(_table(spark, sf_dir, "documents"), keep=["doc_id"])
    return encoded.select("doc_id", "n_tokens", "token_ids", "round_trip")


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op10_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates.find(_table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_hmm_scores": op1_hmm_scores,
    "op2_quality": op2_quality,
    "op3_html_text": op3_html_text,
    "op4_sentencepiece": op4_sentencepiece,
    "op5_decontaminate": op5_decontaminate,
    "op6_sentence_spans": op6_sentence_spans,
    "op7_host_rules": op7_host_rules,
    "op8_language": op8_language,
    "op9_secret_scans": op9_secret_scans,
    "op10_near_duplicates": op10_near_duplicates,
}

ORACLE_SQL: dict[str, str] = {
    "op7_host_rules": sql.HOST_RULES,
    "op10_near_duplicates": sql.NEAR_DUPLICATES,
}
