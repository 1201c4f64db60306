"""Queries opN_<name> of the training-data operators over whole tables, and SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .common import table
from .decontamination import CONTAMINATION_SQL, contamination
from .fuzzy_lines import dedup_report
from .html_extract import extract_pages
from .jaccard_join import jaccard_components
from .license_scan import scan_licenses
from .packing import pack_documents
from .pii import scan_pii
from .quality_rules import QUALITY_SQL, quality_report
from .secret_scan import scan_secrets
from .suffix_dedup import repeated_report


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents"))


def op2_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_report(table(spark, sf_dir, "documents"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_report(table(spark, sf_dir, "documents"))


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_secrets(table(spark, sf_dir, "documents"))


def op6_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(table(spark, sf_dir, "documents"))


def op7_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(table(spark, sf_dir, "pages"))


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_fuzzy_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_report(table(spark, sf_dir, "documents"))


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_pii(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_license_scan, op2_suffix_array_dedup, op3_quality_rules, op4_best_fit_packing, op5_secret_scan, op6_ngram_jaccard_join, op7_html_extraction, op8_decontamination, op9_fuzzy_lines, op10_pii)}
ORACLES: dict[str, str] = {"op3_quality_rules": QUALITY_SQL, "op8_decontamination": CONTAMINATION_SQL}
