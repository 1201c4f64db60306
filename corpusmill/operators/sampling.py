"""Deterministic sampling to budgets, composition, distribution shift, and embedding spread."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

P31 = 2147483648


def unit_hash(key: Column) -> Column:
    """31 bits of the MD5 of a key: the same draw on every run."""
    return F.conv(F.substring(F.md5(key.cast("string")), 1, 8), 16, 10).cast("long") % P31


def fraction_sample(files: DataFrame, fractions: dict[str, float], key: str = "lang") -> DataFrame:
    """Keep a share of some groups and all of the others; no shuffle."""
    cut = reduce(lambda c, kv: c.when(F.col(key) == kv[0], F.lit(int(kv[1] * P31))), fractions.items(), F.when(F.lit(False), F.lit(0))).otherwise(F.lit(P31))
    return files.where(unit_hash(F.col("file_id")) < cut)


def budget_sample(files: DataFrame, budget: dict[str, int], key: str = "lang", size: str = "n_bytes") -> DataFrame:
    """As above with fractions from byte budgets: one aggregate of a row a group."""
    total = {r[0]: r[1] for r in files.groupBy(key).agg(F.sum(size)).collect()}
    return fraction_sample(files, {k: min(1.0, b / total[k]) for k, b in budget.items() if total.get(k)}, key)


def _edge(files: DataFrame, key: str, weight: Column, limit: int, cells: int = 4096) -> DataFrame:
    """files with below (whether the row's hash cell lies whole under the group's limit) and before (the weight of the cells under it).

    Hashes are counted in `cells` cells a group, so the ordered sum runs over a table of bounded size; only rows of the cell on the limit need an order.
    Rows of cells over the limit are left out.
    """
    cell = F.floor(unit_hash(F.col("file_id")) / (P31 // cells)).cast("int")
    counted = files.withColumn("__cell", cell)
    sums = counted.groupBy(key, "__cell").agg(F.sum(weight).alias("__w"))
    run = F.sum("__w").over(Window.partitionBy(key).orderBy("__cell").rowsBetween(Window.unboundedPreceding, 0))
    marked = sums.withColumn("__run", run).select(F.col(key).alias("__k"), F.col("__cell").alias("__c"), (F.col("__run") <= limit).alias("__below"), (F.col("__run") - F.col("__w")).alias("__before")).where(F.col("__before") <= limit)
    return counted.join(marked, F.col(key).eqNullSafe(F.col("__k")) & (F.col("__cell") == F.col("__c"))).drop("__k", "__c")


def _cut(marked: DataFrame, key: str, weight: Column, limit: int, columns: list[str]) -> DataFrame:
    run = F.sum(weight).over(Window.partitionBy(key, "__cell").orderBy(unit_hash(F.col("file_id")), "file_id").rowsBetween(Window.unboundedPreceding, 0))
    on = marked.where("not __below").withColumn("__sum", run + F.col("__before")).where(F.col("__sum") <= limit)
    return marked.where("__below").select(columns).union(on.select(columns))


def exact_k(files: DataFrame, k: int, key: str = "lang") -> DataFrame:
    """The k rows of each group with the least hashes of their ids."""
    return _cut(_edge(files, key, F.lit(1), k), key, F.lit(1), k, files.columns)


def running_budget(files: DataFrame, budget: int, key: str = "lang", size: str = "n_bytes") -> DataFrame:
    """Rows of each group in the order of their ids' hashes for as long as their sizes stay within the budget."""
    return _cut(_edge(files, key, F.col(size), budget), key, F.col(size), budget, files.columns)


def composition(parts: DataFrame) -> DataFrame:
    """category, source, n_tokens -> with subtotals and shares of the whole."""
    rolled = parts.rollup("category", "source").agg(F.sum("n_tokens").cast("long").alias("n_tokens"))
    whole = parts.agg(F.sum("n_tokens").alias("whole"))
    return rolled.crossJoin(F.broadcast(whole)).select("category", "source", "n_tokens", F.round(100.0 * F.col("n_tokens") / F.col("whole"), 4).alias("share"))


def divergence(a: DataFrame, b: DataFrame, dim: str) -> DataFrame:
    """Jensen-Shannon and total variation distance of a dimension's shares."""
    p = a.groupBy(dim).agg(F.count(F.lit(1)).alias("n")).crossJoin(a.agg(F.count(F.lit(1)).alias("total"))).select(dim, (F.col("n") / F.col("total")).alias("p"))
    q = b.groupBy(dim).agg(F.count(F.lit(1)).alias("n")).crossJoin(b.agg(F.count(F.lit(1)).alias("total"))).select(dim, (F.col("n") / F.col("total")).alias("q"))
    j = p.join(q, dim, "full").select(F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("q", F.lit(0.0)).alias("q")).withColumn("m", (F.col("p") + F.col("q")) / 2)
    kl = lambda x: F.when(F.col(x) > 0, F.col(x) * F.log(2.0, F.col(x) / F.col("m"))).otherwise(0.0)
    return j.agg(F.round(F.sum(kl("p") + kl("q")) / 2, 6).alias("js"), F.round(F.sum(F.abs(F.col("p") - F.col("q"))) / 2, 6).alias("tv"))


def centroid_dispersion(vectors: DataFrame) -> DataFrame:
    """Per label: rows and mean squared distance to the label's centre, from sums alone."""
    dims = vectors.select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("x").cast("double")).alias("m"), F.avg(F.col("x").cast("double") * F.col("x").cast("double")).alias("s"))
    return dims.groupBy("label").agg(F.max("n").alias("n"), F.round(F.sum(F.col("s") - F.col("m") * F.col("m")), 4).alias("dispersion"))


def covariance(vectors: DataFrame, dims: int, digits: int | None = 4) -> DataFrame:
    """Upper triangle of the covariance of the first dims dimensions: each task sums outer products, and sums meet in one aggregate."""
    import numpy as np
    import pandas as pd

    def sums(batches):
        n, x, xy = 0, np.zeros(dims), np.zeros((dims, dims))
        for batch in batches:
            if len(batch):
                rows = np.array(batch["embedding"].to_list(), np.float64)[:, :dims]
                n, x, xy = n + len(rows), x + rows.sum(axis=0), xy + rows.T @ rows
        if n:
            i, j = np.triu_indices(dims)
            yield pd.DataFrame({"i": i.astype("int32"), "j": j.astype("int32"), "n": n, "x": x[i], "y": x[j], "xy": xy[i, j]})

    total = vectors.where("embedding is not null").select("embedding").mapInPandas(sums, "i int, j int, n long, x double, y double, xy double").groupBy("i", "j").agg(*(F.sum(c).alias(c) for c in ("n", "x", "y", "xy")))
    cov = F.col("xy") / F.col("n") - F.col("x") / F.col("n") * F.col("y") / F.col("n")
    return total.select("i", "j", (cov if digits is None else F.round(cov, digits)).alias("cov"))


def pca_outliers(vectors: DataFrame, k: int = 2, z: float = 3.0) -> DataFrame:
    """(vec_id, distance) of rows whose projection lies over z deviations out; the 64 x 64 eigenproblem is the only work on the driver."""
    import numpy as np

    dims = vectors.select(F.size("embedding").alias("d")).limit(1).first()
    if dims is None:
        return vectors.select("vec_id", F.lit(0.0).alias("distance")).where(F.lit(False))
    d = dims[0]
    cov = np.zeros((d, d))
    for r in covariance(vectors, d, None).collect():
        cov[r.i, r.j] = cov[r.j, r.i] = r["cov"]
    mean = [r["m"] for r in vectors.select(F.posexplode("embedding").alias("i", "x")).groupBy("i").agg(F.avg("x").alias("m")).orderBy("i").collect()]
    values, axes = np.linalg.eigh(cov)
    parts = [F.pow(F.aggregate(F.zip_with("embedding", F.array(*(F.lit(float(v)) for v in axes[:, -1 - c])), lambda x, a: x * a), F.lit(0.0), lambda p, q: p + q) - float(np.dot(mean, axes[:, -1 - c])), 2) / float(values[-1 - c]) for c in range(k)]
    return vectors.select("vec_id", F.round(F.sqrt(reduce(lambda a, b: a + b, parts)), 4).alias("distance")).where(F.col("distance") > z)
