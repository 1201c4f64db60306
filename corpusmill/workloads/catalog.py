"""Where the workload modules enter their queries and SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from corpusmill.schema import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def add(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    assert name not in QUERIES, name
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


def both(name: str, sql: str, **used: str) -> None:
    """One statement that either engine runs; {t} stands for each table t."""
    import re

    tables = sorted(set(re.findall(r"\{(\w+)\}", sql)))
    add(name, lambda spark, sf_dir: spark.sql(sql, **{t: table(spark, sf_dir, t) for t in tables}), re.sub(r"\{(\w+)\}", r"\1", sql))
