"""Decontamination of tuning data: entry points of test items and shared word n-grams.

Benchmark grams are a small side: it is broadcast only if it has at most SMALL rows, else the grams meet in a shuffle.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusmill.schema import tokens

SMALL = 200_000


def _grams(words: Column, n: int) -> Column:
    return F.array_distinct(F.when(F.size(words) >= n, F.transform(F.sequence(F.lit(1), F.size(words) - n + 1), lambda i: F.array_join(F.slice(words, i, n), " "))).otherwise(F.array().cast("array<string>")))


def gram_rows(df: DataFrame, keys: list[str], n: int) -> DataFrame:
    return df.select(*keys, tokens(F.col("text")).alias("w")).select(*keys, F.explode(_grams(F.col("w"), n)).alias("gram"))


def _side(bench: DataFrame, n: int) -> DataFrame:
    grams = gram_rows(bench, ["item_id"], n).distinct()
    return F.broadcast(grams) if grams.limit(SMALL + 1).count() <= SMALL else grams


def overlap_report(df: DataFrame, bench: DataFrame, n: int = 10) -> DataFrame:
    """(id, item_id, n_shared): distinct shared n-grams."""
    return gram_rows(df, ["id"], n).join(_side(bench, n), "gram").groupBy("id", "item_id").agg(F.count(F.lit(1)).alias("n_shared"))


def ngram_hits(df: DataFrame, bench: DataFrame, n: int = 10) -> DataFrame:
    return gram_rows(df, ["id"], n).join(_side(bench, n), "gram", "left_semi").select("id").distinct()


def drop_ngram_overlap(df: DataFrame, bench: DataFrame, n: int = 10) -> DataFrame:
    return df.join(ngram_hits(df, bench, n), "id", "left_anti")


def entry_hits(df: DataFrame, bench: DataFrame) -> DataFrame:
    """Rows with a test item's entry point; its stand-in for prose is the item's longest word, of ties the first in order."""
    words = bench.select(tokens(F.col("text")).alias("w")).where("size(w) > 0")
    entry = words.select(F.expr("array_sort(filter(w, x -> length(x) = array_max(transform(w, y -> length(y)))))[0]").alias("word")).distinct()
    return df.select("id", F.explode(F.array_distinct(tokens(F.col("text")))).alias("word")).join(F.broadcast(entry), "word", "left_semi").select("id").distinct()


def drop_entry_points(df: DataFrame, bench: DataFrame) -> DataFrame:
    return df.join(entry_hits(df, bench), "id", "left_anti")


def decontaminate(df: DataFrame, bench: DataFrame, n: int = 10) -> DataFrame:
    return df.join(entry_hits(df, bench).union(ngram_hits(df, bench, n)).distinct(), "id", "left_anti")


def sweep(df: DataFrame, bench: DataFrame, sizes: list[int]) -> DataFrame:
    return reduce(DataFrame.unionByName, (ngram_hits(df, bench, n).agg(F.lit(n).alias("n"), F.count(F.lit(1)).alias("n_docs")) for n in sizes))
