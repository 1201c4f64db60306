"""Exact, repository-level and chunk-level deduplication, and their reports. Text is hashed where it is read; only ids and digests move."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusmill.schema import tokens


def digest(text: Column, fold: bool = False) -> Column:
    return F.unhex(F.sha2(F.trim(F.regexp_replace(F.lower(text), r"\s+", " ")) if fold else text, 256))


def preference(prefix: str = "") -> Column:
    """Most stars, then latest commit, then least id."""
    return F.struct(F.col(prefix + "stars"), F.col(prefix + "commit_day"), -F.col(prefix + "file_id"))


def exact_keepers(files: DataFrame, fold: bool = False) -> DataFrame:
    """(file_id) of the preferred file of each digest; one map-side combined aggregate."""
    keyed = files.select("file_id", "stars", "commit_day", digest(F.col("text"), fold).alias("digest"))
    return keyed.groupBy("digest").agg(F.max_by("file_id", preference()).alias("file_id")).select("file_id")


def exact_dedup(files: DataFrame, fold: bool = False) -> DataFrame:
    return files.join(exact_keepers(files, fold), "file_id", "left_semi")


def exact_dedup_window(files: DataFrame) -> DataFrame:
    """The same answer by ranking, kept to compare plans."""
    rank = F.row_number().over(Window.partitionBy("digest").orderBy(F.desc("stars"), F.desc("commit_day"), "file_id"))
    best = files.select("file_id", "stars", "commit_day", digest(F.col("text")).alias("digest")).withColumn("r", rank).where("r = 1").select("file_id")
    return files.join(best, "file_id", "left_semi")


def repo_keys(files: DataFrame) -> DataFrame:
    """(repo, key, stars, commit_day, n_tokens): the key is the digest of a repository's sorted file digests."""
    rows = files.select("repo", "stars", "commit_day", F.sha2("text", 256).alias("d"), F.size(tokens(F.col("text"))).cast("long").alias("t"))
    grouped = rows.groupBy("repo").agg(F.array_sort(F.collect_list("d")).alias("ds"), F.max("stars").alias("stars"), F.max("commit_day").alias("commit_day"), F.sum("t").alias("n_tokens"))
    return grouped.select("repo", F.sha2(F.array_join("ds", ","), 256).alias("key"), "stars", "commit_day", "n_tokens")


def repo_keepers(files: DataFrame) -> DataFrame:
    return repo_keys(files).groupBy("key").agg(F.max_by("repo", F.struct("stars", "commit_day", -F.col("repo"))).alias("repo")).select("repo")


def repo_dedup(files: DataFrame) -> DataFrame:
    return files.join(repo_keepers(files), "repo", "left_semi")


def repo_concat_keys(files: DataFrame) -> DataFrame:
    """Digest of the literal concatenation in path order; only for repositories well below the row limit."""
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("file_id", "text"))), lambda x: x["text"]), "\n")
    return files.groupBy("repo").agg(F.sha2(text, 256).alias("key"), F.count(F.lit(1)).alias("n_files"))


def chunks(files: DataFrame, kind: str, size: int = 400) -> DataFrame:
    if kind == "lines":
        parts = F.split("text", "\n")
    else:
        parts = F.expr(f"transform(sequence(0, greatest(cast(ceil(length(text) / {size}) as int) - 1, 0)), i -> substring(text, i * {size} + 1, {size}))")
    return files.select("file_id", F.posexplode(parts).alias("pos", "chunk"))


def chunk_dedup(files: DataFrame, kind: str = "lines", size: int = 400, least: int = 10) -> DataFrame:
    """(file_id, n_chunks, n_kept, kept_chars): a chunk longer than `least` stays only where it comes first."""
    rows = chunks(files, kind, size).select("file_id", "pos", F.length("chunk").alias("len"), F.sha2("chunk", 256).alias("d"))
    first = rows.where(F.col("len") > least).groupBy("d").agg(F.min(F.struct("file_id", "pos")).alias("first"))
    kept = rows.join(first, "d", "left").withColumn("keep", F.col("first").isNull() | (F.struct("file_id", "pos") == F.col("first")))
    return kept.groupBy("file_id").agg(F.count(F.lit(1)).alias("n_chunks"), F.sum(F.col("keep").cast("long")).alias("n_kept"), F.sum(F.when(F.col("keep"), F.col("len")).otherwise(0)).cast("long").alias("kept_chars"))


def volume(files: DataFrame) -> DataFrame:
    return files.agg(F.count(F.lit(1)).alias("n_rows"), F.coalesce(F.sum(F.size(tokens(F.col("text"))).cast("long")), F.lit(0)).alias("n_tokens"))


def level_report(files: DataFrame) -> DataFrame:
    """Rows, kept rows, kept tokens and their share: file level, repository level, file level after repository level."""
    base = volume(files).select(F.col("n_rows").alias("rows_in"), F.col("n_tokens").alias("tokens_in"))
    repos = files.select("repo").distinct().agg(F.count(F.lit(1)).alias("rows_in"))
    by_repo = repo_dedup(files)
    parts = [
        ("file", exact_dedup(files), base.select("rows_in"), None),
        ("repository", by_repo, repos, by_repo.select("repo").distinct().agg(F.count(F.lit(1)).alias("n_rows"))),
        ("repository_then_file", exact_dedup(by_repo), by_repo.agg(F.count(F.lit(1)).alias("rows_in")), None),
    ]
    out = None
    for name, kept, rows_in, n_rows in parts:
        v = volume(kept)
        v = v if n_rows is None else v.drop("n_rows").crossJoin(n_rows)
        row = v.crossJoin(rows_in).crossJoin(base.select("tokens_in")).select(F.lit(name).alias("level"), "rows_in", F.col("n_rows").alias("rows_kept"), F.col("n_tokens").alias("tokens_kept"), F.round(100.0 * F.col("n_tokens") / F.col("tokens_in"), 4).alias("token_share"))
        out = row if out is None else out.unionByName(row)
    return out


def equal_token_volume(files: DataFrame) -> DataFrame:
    """Tokens of files that equal some other file character by character."""
    rows = files.select(F.sha2("text", 256).alias("d"), F.size(tokens(F.col("text"))).cast("long").alias("t"))
    return rows.groupBy("d").agg(F.count(F.lit(1)).alias("n"), F.sum("t").alias("t")).agg(F.sum(F.when(F.col("n") > 1, F.col("t")).otherwise(0)).alias("equal_tokens"), F.sum("t").alias("all_tokens"))


def against_index(index: DataFrame, batch: DataFrame) -> DataFrame:
    """Files of batch whose digest the index (digest) does not hold, one per digest."""
    fresh = exact_dedup(batch)
    return fresh.withColumn("digest", digest(F.col("text"))).join(index.select("digest").distinct(), "digest", "left_anti").drop("digest")
