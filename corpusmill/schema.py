"""Tables and the adapter that gives documents the fields of source files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def as_files(docs: DataFrame) -> DataFrame:
    """documents as source files: repository, stars, commit time and extension follow from doc_id and lang."""
    i = F.col("doc_id")
    return docs.select(
        i.alias("file_id"), F.when(i % 6 < 3, i - i % 6).otherwise(i).alias("repo"), ((i * 37 + 11) % 7).alias("stars"), (19691 - (4 - (i * 53) % 5)).alias("commit_day"),
        F.element_at(F.create_map(*(F.lit(x) for x in ("en", "py", "fr", "java", "de", "html", "es", "js"))), F.col("lang")).alias("ext"), "lang", "source", F.octet_length("text").cast("long").alias("n_bytes"), "text",
    )


def files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return as_files(table(spark, sf_dir, "documents"))


#: as_files in DuckDB SQL, as a common table expression named files.
FILES = """files as (select doc_id as file_id, case when doc_id % 6 < 3 then doc_id - doc_id % 6 else doc_id end as repo, (doc_id * 37 + 11) % 7 as stars, 19691 - (4 - (doc_id * 53) % 5) as commit_day,
 case lang when 'en' then 'py' when 'fr' then 'java' when 'de' then 'html' when 'es' then 'js' end as ext, lang, source, octet_length(encode(text))::bigint as n_bytes, text from documents)"""


def tokens(text) -> object:
    """White-space tokens, lower case."""
    return F.filter(F.split(F.lower(text), r"\s+"), lambda x: x != "")


TOKENS = r"list_filter(regexp_split_to_array(lower(text), '\s+'), lambda x: x <> '')"
