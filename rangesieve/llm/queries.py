"""The registered queries of the corpus operators, on whole tables with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from rangesieve.llm import exact_dedup, jaccard_join, language_id, license_scan, line_dedup, merkle, packing, rule_quality, source_mix, toxicity
from rangesieve.llm.common import read_table


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify_languages(read_table(spark, sf_dir, "documents"))


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.near_groups(read_table(spark, sf_dir, "documents")).select("doc_id", "class_id", "links")


def op3_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return source_mix.mix_sources(read_table(spark, sf_dir, "documents"))


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.find_copies(read_table(spark, sf_dir, "documents")).drop("in_history")


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score_toxicity(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(read_table(spark, sf_dir, "documents"))


def op7_rule_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rule_quality.score_quality(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op8_merkle_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return merkle.fingerprint_documents(read_table(spark, sf_dir, "documents"))


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(read_table(spark, sf_dir, "documents"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.dedup_lines(read_table(spark, sf_dir, "pages"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_language_id, op2_ngram_jaccard_join, op3_source_mix, op4_exact_dedup, op5_toxicity, op6_packing, op7_rule_quality, op8_merkle_fingerprints, op9_license_scan, op10_line_dedup)
}

ORACLES: dict[str, str] = {
    "op2_ngram_jaccard_join": jaccard_join.ORACLE,
    "op3_source_mix": source_mix.ORACLE,
    "op4_exact_dedup": exact_dedup.ORACLE,
    "op9_license_scan": license_scan.oracle(),
    "op10_line_dedup": line_dedup.ORACLE,
}
