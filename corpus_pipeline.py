"""The corpus pipeline over documents: quality rules, line dedup, near-duplicate removal, decontamination, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows of docs; what it returns is written as Parquet and read again as the next
one's docs. All stages but the last return the columns of docs.
Defined results: see the operators; a null or empty text fails the quality rules; where rows of one near-duplicate group tie, the least doc_id
(then the least text, of rows that repeat one doc_id a single row) stays.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmill.llm.common import settled, table
from corpusmill.llm.decontamination import drop_contaminated
from corpusmill.llm.fuzzy_lines import dedup_lines
from corpusmill.llm.jaccard_join import keep_one
from corpusmill.llm.packing import pack_documents
from corpusmill.llm.quality_rules import keep_quality

#: SQL cannot express stages 2, 3 and 5; tests/llm/test_pipeline.py holds each stage against a plain reading of its own input.
ORACLE_SQL = None


def _recounted(docs: DataFrame) -> DataFrame:
    """n_chars follows the text where documents have it."""
    kinds = dict(docs.dtypes)
    return docs.withColumn("n_chars", F.length("text").cast(kinds["n_chars"])) if "n_chars" in kinds else docs


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _recounted(keep_quality(docs))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _recounted(dedup_lines(docs))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_one(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs)


STAGES = [("quality rules", quality_stage), ("line dedup", line_stage), ("near duplicates", near_duplicate_stage), ("decontamination", decontamination_stage), ("packing", packing_stage)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result but the last is written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = settled(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
