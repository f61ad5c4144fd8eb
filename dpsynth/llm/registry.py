"""Queries of the training-data operators and, where SQL can say it, their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from dpsynth.llm import backoff, bpe, chat, fmindex, langid, licences, linededup, pii, quality, simhash
from dpsynth.llm.common import table


def op1_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
    said = "</s>[INST] ok [/INST]"
    probe = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    return chat.chat_digests(turns.unionByName(probe))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.predict_languages(table(spark, sf_dir, "documents"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents")).drop("grp", "distance")


def op4_backoff_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return backoff.score_documents(table(spark, sf_dir, "documents"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fmindex.contamination_digests(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_simhash_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.component_digests(table(spark, sf_dir, "documents"))


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.line_digests(table(spark, sf_dir, "documents"))


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan(table(spark, sf_dir, "documents"))


def op9_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.find(table(spark, sf_dir, "documents"))


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digests(table(spark, sf_dir, "documents"))


#: Every operator query: its function and its DuckDB twin, if SQL can express it.
REGISTERED: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {
    "op1_chat_format": (op1_chat_format, chat.ORACLE),
    "op2_language_id": (op2_language_id, None),
    "op3_quality_rules": (op3_quality_rules, None),
    "op4_backoff_scores": (op4_backoff_scores, backoff.ORACLE),
    "op5_decontaminate": (op5_decontaminate, fmindex.ORACLE),
    "op6_simhash_components": (op6_simhash_components, None),
    "op7_line_dedup": (op7_line_dedup, linededup.ORACLE),
    "op8_license_scan": (op8_license_scan, None),
    "op9_personal_data": (op9_personal_data, None),
    "op10_byte_bpe": (op10_byte_bpe, None),
}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: run for name, (run, _) in REGISTERED.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in REGISTERED.items() if sql}
