"""The queries of this subpackage and their oracle SQL, as ``__spark_entry__`` lists them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import line_dedup, lm_scoring, pii_spans, shard_table
from .best_fit_packing import pack
from .decontaminate import decontamination_report
from .jaccard_join import jaccard_classes
from .language_id import language_id
from .quality_rules import quality_report
from .toxicity import toxicity


def _read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_classes(_read(spark, sf_dir, "documents"))


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(_read(spark, sf_dir, "documents"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id(_read(spark, sf_dir, "documents"))


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_table.assign(_read(spark, sf_dir, "documents").select("doc_id"))


def op5_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.score(_read(spark, sf_dir, "documents"))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.drop_boilerplate(_read(spark, sf_dir, "documents")).select("doc_id", "text", "n_lines", "n_dropped")


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_report(_read(spark, sf_dir, "documents"))


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    report = decontamination_report(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "benchmark"), slop=2)
    return report.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "n_near_items")


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels"))


def op10_pii_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii_spans.find(_read(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_jaccard_join": op1_jaccard_join,
    "op2_best_fit_packing": op2_best_fit_packing,
    "op3_language_id": op3_language_id,
    "op4_sharding": op4_sharding,
    "op5_lm_scoring": op5_lm_scoring,
    "op6_line_dedup": op6_line_dedup,
    "op7_quality_rules": op7_quality_rules,
    "op8_decontamination": op8_decontamination,
    "op9_toxicity": op9_toxicity,
    "op10_pii_spans": op10_pii_spans,
}

ORACLES: dict[str, str] = {
    "op4_sharding": shard_table.ORACLE,
    "op6_line_dedup": line_dedup.ORACLE,
}
