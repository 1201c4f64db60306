"""Structured Streaming jobs that run over what a source holds and leave a table: windows, joins, late rows, deduplication and near duplicates.

Aggregates end in complete mode, so windows that are still open at the end are in the table; appended results are files of the sink's own commit log.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmill.operators import minhash
from corpusmill.plans.durable import shared_folder


def folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark).rstrip('/')}/corpusmill-stream-{uuid.uuid4().hex}"


def as_stream(rows: DataFrame, at: str, name: str = "in", files_per_batch: int = 1000) -> DataFrame:
    """rows as files, read as a stream."""
    rows.write.parquet(f"{at}/{name}")
    return rows.sparkSession.readStream.schema(rows.schema).option("maxFilesPerTrigger", files_per_batch).parquet(f"{at}/{name}")


def appended(stream: DataFrame, at: str) -> DataFrame:
    """What a stream appends until its source is used up."""
    spark = stream.sparkSession
    stream.writeStream.format("parquet").option("checkpointLocation", f"{at}/state").option("path", f"{at}/out").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


def completed(stream: DataFrame, at: str) -> DataFrame:
    """The whole result table of an aggregate once its source is used up; each batch replaces the table, so a repeated batch changes nothing."""
    spark = stream.sparkSession

    def replace(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out")

    stream.writeStream.foreachBatch(replace).option("checkpointLocation", f"{at}/state").outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


def timed(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def windows(events: DataFrame, window) -> DataFrame:
    """Rows and users by window and kind, of all windows."""
    at = folder(events.sparkSession)
    counted = as_stream(timed(events), at).groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return completed(counted.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n"), at)


def late_counts(events: DataFrame, late: DataFrame, delay: str) -> DataFrame:
    """(kind, n) of daily counts after late rows have come in a last batch: those behind the watermark are dropped.

    The first batches hold events and close the days that they can; the last one holds the late rows.
    """
    spark = events.sparkSession
    at = folder(spark)
    timed(events).coalesce(1).write.parquet(f"{at}/in")
    source = spark.readStream.schema(timed(events).schema).option("maxFilesPerTrigger", 1).parquet(f"{at}/in")
    counted = source.withWatermark("ts", delay).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    out = counted.select(F.col("w.start").alias("start"), "event_type", "n")

    def run() -> None:
        out.writeStream.format("parquet").option("checkpointLocation", f"{at}/state").option("path", f"{at}/out").outputMode("append").trigger(availableNow=True).start().awaitTermination()

    run()
    timed(late).coalesce(1).write.mode("append").parquet(f"{at}/in")
    run()
    return spark.read.schema(out.schema).parquet(f"{at}/out")


def with_static(events: DataFrame, static: DataFrame, key: str, static_key: str) -> DataFrame:
    at = folder(events.sparkSession)
    return appended(as_stream(timed(events), at).join(static, F.col(key) == F.col(static_key)), at)


def interval_join(left: DataFrame, right: DataFrame, key: str, hours: int) -> DataFrame:
    """(left id, right id) of rows of one key where right came up to `hours` before left; state is bounded by the watermarks."""
    at = folder(left.sparkSession)
    one = as_stream(timed(left), at, "left").withWatermark("ts", "2 hours").select(F.col(key).alias("k1"), F.col("event_id").alias("id"), F.col("ts").alias("t1"))
    two = as_stream(timed(right), at, "right").withWatermark("ts", "2 hours").select(F.col(key).alias("k2"), F.col("event_id").alias("other"), F.col("ts").alias("t2"))
    return appended(one.join(two, F.expr(f"k1 = k2 and t2 <= t1 and t2 >= t1 - interval {hours} hours")).select("id", "other"), at)


def near_duplicates(batches: list[DataFrame], k: int = 64, b: int = 16, r: int = 4) -> DataFrame:
    """(file_id) of files (file_id, text) that were kept, batch after batch: one with a band key of an earlier kept file, or of a lesser one of its batch, goes.

    Each batch meets the index of band keys by an anti join and appends its own; a batch that is run again replaces its part of the index.
    """
    spark = batches[0].sparkSession
    at = folder(spark)
    for number, rows in enumerate(batches):
        rows.select("file_id", "text").coalesce(1).write.parquet(f"{at}/in/part={number}")
    kind = "band int, key long"

    def settle(batch: DataFrame, number: int) -> None:
        keys = minhash.text_bands(batch.select("file_id", "text"), k, b, r, 5, "word")
        keys.write.mode("overwrite").parquet(f"{at}/keys/{number}")
        keys = spark.read.schema("file_id long, " + kind).parquet(f"{at}/keys/{number}")
        known = [f"{at}/index/{i}" for i in range(number)]
        if known:
            seen = keys.join(spark.read.schema(kind).parquet(*known), ["band", "key"], "left_semi").select("file_id").distinct()
            keys = keys.join(seen, "file_id", "left_anti")
        else:
            seen = None
        least = keys.groupBy("band", "key").agg(F.min("file_id").alias("first"))
        later = keys.join(least, ["band", "key"]).where("file_id <> first").select("file_id").distinct()
        keys.join(later, "file_id", "left_anti").select("band", "key").distinct().write.mode("overwrite").parquet(f"{at}/index/{number}")
        fresh = batch.select("file_id").join(later, "file_id", "left_anti")
        (fresh if seen is None else fresh.join(seen, "file_id", "left_anti")).write.mode("overwrite").parquet(f"{at}/out/{number}")

    for number in range(len(batches)):
        source = spark.readStream.schema("file_id long, text string").parquet(f"{at}/in/part={number}")
        source.writeStream.foreachBatch(lambda batch, _, number=number: settle(batch, number)).option("checkpointLocation", f"{at}/state/{number}").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("file_id long").parquet(*(f"{at}/out/{i}" for i in range(len(batches))))
