"""The queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import decontamination, mixing, near_dup, paragraph_dedup, quality_rules, rule_classifier, secret_scan, sharding, suffix_dedup, url_filter
from .common import load


def op1_shard_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_by_bytes(load(spark, sf_dir, "documents", "doc_id", "text"))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(load(spark, sf_dir, "documents", "doc_id", "text", "lang", "source"))


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.contained_items(load(spark, sf_dir, "documents", "doc_id", "text"), load(spark, sf_dir, "benchmark", "item_id", "text"))


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.removal_digests(load(spark, sf_dir, "documents", "doc_id", "text"))


def op5_rule_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rule_classifier.classify(load(spark, sf_dir, "documents", "doc_id", "text"), load(spark, sf_dir, "labels", "doc_id", "quality"))


def op6_paragraph_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return paragraph_dedup.repeated_passages(load(spark, sf_dir, "documents", "doc_id", "text"))


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(load(spark, sf_dir, "documents", "doc_id", "text"))


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages", "page_id", "url")
    return url_filter.judge(pages, url_filter.standing_list(pages))


def op9_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(load(spark, sf_dir, "documents", "doc_id", "text"), size=2)


def op10_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixed(load(spark, sf_dir, "documents", "doc_id", "text", "source"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_shard_best_fit, op2_quality_rules, op3_decontaminate, op4_suffix_dedup, op5_rule_classifier, op6_paragraph_dedup, op7_secret_scan, op8_url_filter, op9_near_duplicates, op10_mix_sources)}


def oracle_sql() -> dict[str, str]:
    return {"op3_decontaminate": decontamination.ORACLE, "op8_url_filter": url_filter.ORACLE, "op9_near_duplicates": near_dup.ORACLE, "op10_mix_sources": mixing.ORACLE}
