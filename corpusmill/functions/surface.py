"""The methods as SQL functions of a session."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from corpusmill.functions.bpe import token_ids
from corpusmill.operators import minhash, transform


@F.pandas_udf(T.ArrayType(T.LongType()))
def bpe_encode(texts: pd.Series) -> pd.Series:
    return texts.map(lambda t: token_ids(t).astype("int64").tolist())


@F.udtf(returnType=T.StructType([T.StructField("place", T.IntegerType()), T.StructField("shingle", T.StringType())]))
class ShingleRows:
    """Word shingles of a text with their places."""

    def eval(self, text: str, n: int):
        words = (text or "").lower().split()
        for i in range(max(0, len(words) - n + 1)):
            yield i, " ".join(words[i : i + n])


@F.udtf(returnType=T.StructType([T.StructField(n, T.StringType()) for n in ("module", "symbol", "signature")]))
class ApiCatalogue:
    """Public functions of a module of the standard library with their present signatures."""

    def eval(self, module: str):
        import importlib
        import inspect

        found = importlib.import_module(module)
        for name in sorted(n for n in dir(found) if not n.startswith("_")):
            value = getattr(found, name)
            if inspect.isfunction(value) or inspect.isbuiltin(value):
                try:
                    yield module, name, str(inspect.signature(value))
                except (TypeError, ValueError):
                    yield module, name, ""


def register(spark: SparkSession) -> None:
    """Functions bpe_encode, token_count, minhash_bands, mask_pii, html_text, shingle_rows and api_catalogue.

    Those that built-in functions express are SQL functions and stay in the JVM; the others get Arrow batches.
    """
    kernel = minhash.band_kernel(64, 16, 4, 5, "word")
    spark.udf.register("bpe_encode", bpe_encode)
    spark.udf.register("minhash_bands", kernel)
    spark.udtf.register("shingle_rows", ShingleRows)
    spark.udtf.register("api_catalogue", ApiCatalogue)
    quoted = lambda p: "r'" + p.replace("'", r"\x27") + "'"
    masked = "text"
    for kind, pattern in transform.LINEAR.items():
        masked = f"regexp_replace({masked}, {quoted(pattern)}, '<{kind}>')"
    plain = rf"regexp_replace(regexp_replace(text, '(?s)<(script|style|nav)[^>]*>.*?</(script|style|nav)>', ' '), '<[^>]*>', ' ')"
    for name, kind, body in (("mask_pii", "STRING", masked), ("html_text", "STRING", rf"trim(regexp_replace({plain}, r'\s+', ' '))"), ("token_count", "INT", r"size(filter(split(lower(text), r'\s+'), x -> x <> ''))")):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(text STRING) RETURNS {kind} RETURN {body}")

