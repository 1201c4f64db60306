"""All registered queries with their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from corpusmill.workloads import catalog, curation, filtering, flows, measures, mixtures, published, recalling, relational, synthesis  # noqa: F401  each workload module enters its queries


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return catalog.QUERIES["dedup_level_report"](spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(catalog.QUERIES)


def oracles() -> dict[str, str]:
    return dict(catalog.ORACLES)
