"""Recall of target pages from a crawl: classifiers, host discovery, prefix annotation, and the loop over them.

The averaged-vector classifier (operators/classifier.py) is the method; log-odds is the comparator that SQL can repeat.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusmill.operators import classifier
from corpusmill.plans.durable import settled
from corpusmill.schema import tokens


def base_host(url: Column) -> Column:
    return F.regexp_replace(F.regexp_extract(url, "^[a-z]+://([^/?#]+)", 1), "^(www|m)\\.", "")


def canonical_url(url: Column) -> Column:
    """Without scheme, query, fragment, .html and closing slashes."""
    return F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(url, "^[a-z]+://", ""), "[?#].*$", ""), "\\.html$", ""), "/+$", "")


def page_text(html: Column) -> Column:
    plain = F.regexp_replace(F.regexp_replace(html, "(?s)<(script|style|nav)[^>]*>.*?</(script|style|nav)>", " "), "<[^>]*>", " ")
    return F.trim(F.regexp_replace(plain, r"\s+", " "))


def train(seed: DataFrame) -> DataFrame:
    """(w, odds): smoothed log ratio of a word's share in positive and negative rows (text, y)."""
    words = seed.select("y", F.explode(tokens(F.col("text"))).alias("w"))
    counts = words.groupBy("w").agg(F.sum(F.col("y").cast("long")).alias("p"), F.sum(1 - F.col("y")).cast("long").alias("q"))
    totals = counts.agg(F.sum("p").alias("tp"), F.sum("q").alias("tq"), F.count(F.lit(1)).alias("v"))
    return counts.crossJoin(F.broadcast(totals)).select("w", (F.log((F.col("p") + 1.0) / (F.col("tp") + F.col("v"))) - F.log((F.col("q") + 1.0) / (F.col("tq") + F.col("v")))).alias("odds"))


def score(rows: DataFrame, model: DataFrame, parts: int = 16) -> DataFrame:
    """(id, score): mean odds of a row's known words; words are counted per row first, and a frequent word's rows are dealt to `parts` keys."""
    words = rows.select("id", F.explode(tokens(F.col("text"))).alias("w")).groupBy("id", "w").agg(F.count(F.lit(1)).alias("c"))
    dealt = words.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int"))
    wide = model.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    return dealt.join(wide, ["w", "part"]).groupBy("id").agg(F.round(F.sum(F.col("c") * F.col("odds")) / F.sum("c"), 6).alias("score"))


def log_odds(seed: DataFrame) -> Callable[[DataFrame], DataFrame]:
    model = train(seed)
    return lambda rows: score(rows, model)


def averaged(seed: DataFrame, settings: classifier.Settings = classifier.Settings()) -> Callable[[DataFrame], DataFrame]:
    model = classifier.fit(seed, settings)
    return lambda rows: classifier.score(rows, model)


def recall_many(corpora: dict[str, DataFrame], scorer: Callable[[DataFrame], DataFrame], cut: float) -> DataFrame:
    """(origin, id): rows of each corpus that score over the cut; ids are unique within a corpus only."""
    parts = [scorer(df).where(F.col("score") > cut).select(F.lit(origin).alias("origin"), "id") for origin, df in corpora.items()]
    return reduce(DataFrame.union, parts)


def discover(pages: DataFrame, hits: DataFrame, min_share: float = 0.1, min_pages: int = 1) -> DataFrame:
    """Hosts of which strictly more than min_share of the pages are hits."""
    both = pages.select("id", base_host(F.col("url")).alias("host")).join(hits.select("id", F.lit(1).alias("hit")), "id", "left")
    return both.groupBy("host").agg(F.count(F.lit(1)).alias("n_pages"), F.coalesce(F.sum("hit"), F.lit(0)).alias("n_hits")).where((F.col("n_pages") >= min_pages) & (F.col("n_hits") > F.col("n_pages") * min_share))


def expand(pages: DataFrame, hits: DataFrame, domains: DataFrame, prefixes: list[str]) -> DataFrame:
    """Pages of found hosts under an annotated path prefix that the classifier missed."""
    path = F.regexp_extract("url", "^[a-z]+://[^/?#]+([^?#]*)", 1)
    marked = pages.where(path.rlike("^(" + "|".join(prefixes) + ")(/|$)")).withColumn("host", base_host(F.col("url")))
    return marked.join(domains.select("host"), "host", "left_semi").join(hits.select("id"), "id", "left_anti")


def loop(pages: DataFrame, seed: DataFrame, prefixes: list[str], rounds: int = 3, cut: float = 0.5, fit: Callable = averaged) -> DataFrame:
    """(round, n_seed, n_hits, n_domains, n_added): train, recall, discover, annotate; what annotation adds joins the next round's seed.

    Each round's seed is settled, a page joins the seed once, and rounds end early if the seed stops growing.
    """
    rows = []
    spark = pages.sparkSession
    seed = settled(seed.select(F.col("id").cast("long").alias("id"), "text", "y", F.lit(False).alias("page")))
    for k in range(1, rounds + 1):
        hits = settled(fit(seed)(pages).where(F.col("score") > cut))
        domains = settled(discover(pages, hits))
        known = seed.where("page").select("id")
        added = settled(expand(pages, hits, domains, prefixes).join(known, "id", "left_anti").select(F.col("id").cast("long").alias("id"), "text", F.lit(1).alias("y"), F.lit(True).alias("page")))
        n = added.count()
        rows.append((k, seed.count(), hits.count(), domains.count(), n))
        if not n:
            break
        seed = settled(seed.unionByName(added))
    return spark.createDataFrame(rows, "round int, n_seed long, n_hits long, n_domains long, n_added long")
