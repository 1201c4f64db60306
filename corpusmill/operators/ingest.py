"""Gates and adapters at the start of the pipeline."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Extensions of programming languages.
EXTENSIONS = {"py": "Python", "java": "Java", "js": "JavaScript", "c": "C", "cpp": "C++", "cs": "C#", "go": "Go"}


def registry(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(sorted(EXTENSIONS.items()), "ext string, language string")


def registry_values() -> str:
    return ", ".join(f"('{e}', '{n}')" for e, n in sorted(EXTENSIONS.items()))


def size_gate(files: DataFrame, max_bytes: int = 8 << 20, size_col: str = "n_bytes") -> DataFrame:
    """Files of at most max_bytes; a stored size column lets the scan skip the rest."""
    return files.where(F.col(size_col) <= max_bytes)


def language_gate(files: DataFrame, languages: DataFrame) -> DataFrame:
    return files.withColumn("ext", F.lower("ext")).join(F.broadcast(languages), "ext")


def prune_languages(files: DataFrame, labels: DataFrame, min_bytes: int, min_quality: float) -> DataFrame:
    """Files of languages with enough bytes and, over labelled files, enough mean quality."""
    scored = files.select("file_id", "lang", "n_bytes").join(labels.select(F.col("doc_id").alias("file_id"), "quality"), "file_id", "left")
    good = scored.groupBy("lang").agg(F.sum("n_bytes").alias("b"), F.coalesce(F.avg("quality"), F.lit(0.0)).alias("q")).where((F.col("b") >= min_bytes) & (F.col("q") >= min_quality))
    return files.join(F.broadcast(good.select("lang")), "lang", "left_semi")


def notebooks(turns: DataFrame) -> DataFrame:
    """(path, json): each conversation as a notebook, what the assistant says as its code cells and the rest as its notes."""
    kind = F.when(F.col("role") == "assistant", "code").otherwise("markdown").alias("cell_type")
    cell = F.struct("turn", "text", F.struct(kind, F.array(F.coalesce("text", F.lit(""))).alias("source")).alias("cell"))
    cells = F.transform(F.array_sort(F.collect_list(cell)), lambda c: c["cell"])
    return turns.groupBy("conv_id").agg(F.to_json(F.struct(cells.alias("cells"))).alias("json")).select(F.concat(F.col("conv_id").cast("string"), F.lit(".ipynb")).alias("path"), "json")


def notebook_cells(books: DataFrame) -> DataFrame:
    """(path, code, n_cells): code cells joined by an empty line."""
    cells = F.from_json("json", "struct<cells: array<struct<cell_type: string, source: array<string>>>>")["cells"]
    code = F.filter(cells, lambda c: c["cell_type"] == "code")
    return books.select("path", F.array_join(F.transform(code, lambda c: F.array_join(c["source"], "")), "\n\n").alias("code"), F.size(code).alias("n_cells"))


def merge_sources(**named: DataFrame) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), (df.withColumn("origin", F.lit(n)) for n, df in named.items()))
