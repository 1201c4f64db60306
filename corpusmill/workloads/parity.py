"""Compare queries with their SQL on one folder of tables: rows, columns and values."""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str):
    import duckdb

    con = duckdb.connect()
    con.execute("set timezone='UTC'")
    for name in TABLES:
        con.execute(f"create view {name} as select * from read_parquet('{sf_dir}/{name}.parquet')")
    return con


def _plain(x: object) -> object:
    if isinstance(x, float):
        return "nan" if math.isnan(x) else f"{x:.6g}"
    if isinstance(x, (list, tuple)):
        return tuple(_plain(y) for y in x)
    if isinstance(x, dict):
        return tuple(sorted((str(k), _plain(v)) for k, v in x.items()))
    if hasattr(x, "asDict"):
        return _plain(x.asDict())
    if isinstance(x, (bytes, bytearray)):
        return bytes(x)
    if hasattr(x, "is_integer") and not isinstance(x, int):
        return f"{float(x):.6g}"
    return x.isoformat() if hasattr(x, "isoformat") else x


def differences(spark: SparkSession, sf_dir: str, query: Callable[[SparkSession, str], DataFrame], sql: str) -> str:
    """Empty if both sides agree, else what differs first."""
    got = query(spark, sf_dir)
    con = connect(sf_dir)
    ref = con.execute(sql)
    names = [d[0] for d in ref.description]
    expected = ref.fetchall()
    if sorted(names) != sorted(got.columns):
        return f"columns {sorted(got.columns)} against {sorted(names)}"
    order = sorted(names)
    mine = Counter(tuple(_plain(r[c]) for c in order) for r in got.collect())
    theirs = Counter(tuple(_plain(r[names.index(c)]) for c in order) for r in expected)
    if mine == theirs:
        return ""
    return f"rows {sum(mine.values())} against {sum(theirs.values())}; only here {list((mine - theirs).items())[:2]}; only in SQL {list((theirs - mine).items())[:2]}"
