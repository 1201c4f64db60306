"""Connected components of an edge table by alternating stars, all on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusmill.plans.durable import forget, settled


def _pairs(df: DataFrame, a: str, b: str) -> DataFrame:
    return df.select(F.col(a).alias("a"), F.col(b).alias("b"))


def _is_star_forest(edges: DataFrame) -> bool:
    """Whether each greater end has one lesser neighbour and no lesser end has a still lesser one."""
    ends = edges.select(F.col("a").alias("v"), F.lit(1).alias("up"), F.lit(0).alias("down")).union(edges.select("b", F.lit(0), F.lit(1)))
    return ends.groupBy("v").agg(F.sum("up").alias("up"), F.max("down").alias("down")).where("up > 1 or (up = 1 and down = 1)").isEmpty()


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of edges (a, b); root is the least node of its component.

    Each round points every node's larger neighbours at its least neighbour, then its smaller ones; minima are
    summed up before they are joined back, so a node with many neighbours costs no task of its own. Rounds go on until
    every component is a star about its least node, which the alternation reaches in about log2 of the longest path.
    """
    now = settled(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    while not _is_star_forest(now):
        around = now.union(_pairs(now, "b", "a"))
        least = around.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        low = _pairs(around.join(least, "a").where("b > a"), "b", "m").distinct().where("a <> b")
        least = low.groupBy("a").agg(F.min("b").alias("m"))
        small = _pairs(low.join(least, "a"), "b", "m").where("a <> b").union(_pairs(least, "a", "m")).distinct()
        before, now = now, settled(small)
        for path in {f.rsplit("/", 1)[0] for f in before.inputFiles()[:1]}:
            forget(now.sparkSession, path)
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(now.select("b", "b")).distinct()


def moved_roots(labels: DataFrame, links: DataFrame) -> DataFrame:
    """(root, to): roots of labels (node, root) that links (a, b) between nodes join with lesser ones, and those."""
    of = lambda end: labels.select(F.col("node").alias(end), F.col("root").alias("r" + end))
    between = links.join(of("a"), "a").join(of("b"), "b").where("ra <> rb")
    return components(_pairs(between, "ra", "rb")).toDF("root", "to").where("root <> to")


def relabelled(rows: DataFrame, moved: DataFrame, column: str = "root") -> DataFrame:
    """rows with the roots in a column replaced by those that they moved to."""
    to = moved.select(F.col("root").alias(column), F.col("to").alias("__to"))
    return rows.join(to, column, "left").select(*(F.coalesce("__to", column).alias(c) if c == column else c for c in rows.columns))


def merge_labels(labels: DataFrame, links: DataFrame) -> DataFrame:
    """labels (node, root) after links (a, b) between nodes: roots that links join become the least of them; settled."""
    return settled(relabelled(labels, moved_roots(labels, links)))
