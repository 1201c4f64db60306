"""Sinks with a manifest of counts, and their readers: Parquet partitioned by a column, JSON lines, and Parquet bucketed by a digest."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_partitioned(df: DataFrame, path: str, by: str, rows_per_file: int = 1_000_000) -> DataFrame:
    """Write df by a column's values and return the manifest (value, n). Rows of a value are dealt to salts, so a frequent value makes many files."""
    salted = df.withColumn("__salt", F.pmod(F.xxhash64(*df.columns), F.lit(64)).cast("int"))
    salted.repartition(by, "__salt").drop("__salt").write.mode("overwrite").option("maxRecordsPerFile", rows_per_file).partitionBy(by).parquet(path)
    manifest = df.sparkSession.read.schema(df.schema).parquet(path).groupBy(by).agg(F.count(F.lit(1)).alias("n"))
    manifest.write.mode("overwrite").parquet(f"{path}.manifest")
    return df.sparkSession.read.schema(manifest.schema).parquet(f"{path}.manifest")


def write_json_lines(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").option("compression", "gzip").option("ignoreNullFields", "false").json(path)


def read_json_lines(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.read.schema(schema).option("mode", "FAILFAST").json(path)


def write_digest_buckets(df: DataFrame, path: str, text_col: str = "text", buckets: int = 16) -> None:
    """Rows with their text's digest, in folders by its first bits, so that a later batch need read only the folders of its own digests."""
    keyed = df.withColumn("digest", F.sha2(F.coalesce(F.col(text_col), F.lit("")), 256)).withColumn("bucket", F.pmod(F.xxhash64("digest"), F.lit(buckets)).cast("int"))
    keyed.repartition("bucket", "digest").write.mode("overwrite").partitionBy("bucket").parquet(path)
