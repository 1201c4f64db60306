"""Word and character shingles, MinHash, banding, candidate edges, verification and fuzzy deduplication.

The small configurations are aggregates that SQL can repeat; the production kernel is one Arrow function from text to band keys,
so signatures never leave a task, and band keys are settled once. Buckets are linked to their least member first; where links are verified,
only members that are still apart in a bucket are compared further.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusmill.functions.hashing import Ranges, mix
from corpusmill.operators.components import components
from corpusmill.plans.durable import release, settled
from corpusmill.schema import tokens

#: The modulus and the recurrence of the hash constants.
P = 2147483647
#: Counts of n-grams by which rare ones come first.
SLOTS = 1 << 17


def constants(k: int) -> tuple[list[int], list[int]]:
    return [((i + 1) * 104729 * 7919) % P for i in range(k)], [((i + 1) * 15485863 + 7) % P for i in range(k)]


def shingles(text: Column, n: int = 5, unit: str = "word") -> Column:
    """Distinct n-grams; a shorter text is one shingle, an empty one has none."""
    if unit == "word":
        w = tokens(text)  # words are taken by place: a slice goes through the whole array each time
        grams = lambda w: F.when(F.size(w) == 0, F.array().cast("array<string>")).when(F.size(w) < n, F.array(F.array_join(w, " "))).otherwise(F.transform(F.sequence(F.lit(0), F.size(w) - n), lambda i: F.concat_ws(" ", *(F.get(w, i + k) for k in range(n)))))
        return F.array_distinct(F.get(F.transform(F.array(w), grams), 0))
    low = F.lower(text)  # characters are taken apart once: a substring would count its place from the start each time
    grams = lambda c: F.when(F.size(c) < n, F.array(F.array_join(c, ""))).otherwise(F.transform(F.sequence(F.lit(0), F.size(c) - n), lambda i: F.concat(*(F.get(c, i + k) for k in range(n)))))
    return F.when(low == "", F.array().cast("array<string>")).otherwise(F.array_distinct(F.get(F.transform(F.array(F.split(low, "")), grams), 0)))


def gram_hash(gram: Column) -> Column:
    """First 32 bits of the MD5, modulo P."""
    return F.conv(F.substring(F.md5(gram), 1, 8), 16, 10).cast("long") % P


def signatures(files: DataFrame, k: int = 16, n: int = 5) -> DataFrame:
    """(file_id, sig): least values of k hashes over a file's n-grams, as k minima that are combined before the exchange."""
    a, c = constants(k)
    grams = files.select("file_id", F.explode(shingles(F.col("text"), n)).alias("gram")).select("file_id", gram_hash(F.col("gram")).alias("x"))
    least = grams.groupBy("file_id").agg(*(F.min((F.col("x") * a[i] + c[i]) % P).alias(f"h{i}") for i in range(k)))
    return least.select("file_id", F.array(*(f"h{i}" for i in range(k))).alias("sig"))


def bands(sigs: DataFrame, b: int, r: int) -> DataFrame:
    keys = F.array(*(F.concat_ws("-", F.slice("sig", i * r + 1, r)) for i in range(b)))
    return sigs.select("file_id", F.posexplode(F.transform(keys, F.md5)).alias("band", "key"))


def bucket_edges(banded: DataFrame) -> DataFrame:
    """Star edges (a, b): each member of a bucket to its least one. Keys are settled, for both sides of the join need them."""
    banded = settled(banded)
    least = banded.groupBy("band", "key").agg(F.min("file_id").alias("b"), F.max("file_id").alias("last")).where("b <> last").select("band", "key", "b")
    return banded.join(least, ["band", "key"]).where("file_id <> b").select(F.col("file_id").alias("a"), "b").distinct()


def verify_edges(edges: DataFrame, files: DataFrame, percent: int, n: int = 5) -> DataFrame:
    """Edges of the similarity, by 64-bit hashes of the n-grams of files that have an edge."""
    edges = settled(edges)
    needed = edges.select(F.col("a").alias("file_id")).union(edges.select("b")).distinct()
    grams = settled(files.select("file_id", "text").join(needed, "file_id", "left_semi").select("file_id", F.transform(shingles(F.col("text"), n), lambda x: F.xxhash64(x)).alias("g")))
    both = edges.join(grams.select(F.col("file_id").alias("a"), F.col("g").alias("ga")), "a").join(grams.select(F.col("file_id").alias("b"), F.col("g").alias("gb")), "b")
    inter = F.size(F.array_intersect("ga", "gb"))
    return both.withColumn("inter", inter).withColumn("uni", F.size("ga") + F.size("gb") - F.col("inter")).where(100 * F.col("inter") >= percent * F.col("uni")).select("a", "b", "inter", "uni")


def bucket_links(banded: DataFrame, files: DataFrame, percent: int, n: int = 5) -> DataFrame:
    """Links (a, b) of the similarity between members of a bucket: all that components need.

    Stars are verified first; in buckets that still hold several components, members outside the least one are compared with those of other components.
    """
    banded = settled(banded)
    tested = settled(bucket_edges(banded))
    links = settled(verify_edges(tested, files, percent, n).select("a", "b"))
    roots = components(links).toDF("file_id", "root")
    sizes = files.select("file_id", F.size(shingles(F.col("text"), n)).alias("m"))
    rooted = settled(banded.join(roots, "file_id", "left").withColumn("root", F.coalesce("root", "file_id")).join(sizes, "file_id"))
    mixed = rooted.groupBy("band", "key").agg(F.min("root").alias("main"), F.max("root").alias("last")).where("main <> last").select("band", "key", "main")
    left = settled(rooted.join(mixed, ["band", "key"]))
    x = left.where("root <> main").select("band", "key", F.col("file_id").alias("c"), F.col("root").alias("rc"), F.col("m").alias("mc"), "main")
    y = left.select("band", "key", F.col("file_id").alias("d"), F.col("root").alias("rd"), F.col("m").alias("md"))
    fit = F.expr(f"rc <> rd and (rd = main or c < d) and 100 * least(mc, md) >= {percent} * greatest(mc, md)")
    met = x.join(y, ["band", "key"]).where(fit).select(F.greatest("c", "d").alias("a"), F.least("c", "d").alias("b")).distinct()
    more = settled(met.join(tested, ["a", "b"], "left_anti"))
    return links.union(verify_edges(more, files, percent, n).select("a", "b"))


def gram_hashes(text: str | None, n: int, unit: str) -> np.ndarray:
    """Distinct 64-bit hashes of the n-grams of words or characters; a shorter text is one gram."""
    low = (text or "").lower()
    if unit == "word":
        words = low.split()
        if not words:
            return np.empty(0, np.uint64)
        raw = " ".join(words).encode("utf-8", "surrogatepass")
        gaps = np.flatnonzero(np.frombuffer(raw, np.uint8) == 32)
        start, end = np.concatenate([[0], gaps + 1]), np.concatenate([gaps, [len(raw)]])
        wide = min(n, len(words))
        return np.unique(Ranges(raw).of(start[: len(words) - wide + 1], end[wide - 1 :]))
    points = np.frombuffer(low.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    wide = min(n, len(points))
    out = np.zeros(len(points) - wide + 1 if wide else 0, np.uint64)
    for i in range(wide):
        out = mix(out + points[i : i + len(out)] + np.uint64(1))
    return np.unique(out)


def least_values(grams: np.ndarray, k: int) -> np.ndarray:
    """k least values over the grams: each hash turns the mixed gram over and multiplies it by an odd number, modulo 2**32."""
    own = mix(np.arange(1, 2 * k + 1, dtype=np.uint64))
    turn, odd = own[:k].astype(np.uint32), own[k:].astype(np.uint32) | np.uint32(1)
    x = (mix(grams) >> np.uint64(32)).astype(np.uint32)
    sig = np.full(k, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(x), 128):
        np.minimum(sig, ((x[at : at + 128, None] ^ turn) * odd).min(axis=0), out=sig)
    return sig


def band_keys(sig: np.ndarray, b: int, r: int) -> np.ndarray:
    place = mix(np.arange(1, r + 1, dtype=np.uint64)) | np.uint64(1)
    return mix((mix(sig.reshape(b, r).astype(np.uint64)) * place).sum(axis=1, dtype=np.uint64))


def band_kernel(k: int, b: int, r: int, n: int, unit: str):
    """Arrow function from texts to band keys; k hashes in b bands of r. A text without grams has none."""

    def sketch(text: str | None) -> list[int]:
        grams = gram_hashes(text, n, unit)
        return band_keys(least_values(grams, k), b, r).view(np.int64).tolist() if len(grams) else []

    @F.pandas_udf("array<long>")
    def keys(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in batches:
            yield texts.map(sketch)

    return keys


def text_bands(files: DataFrame, k: int, b: int, r: int, n: int, unit: str) -> DataFrame:
    keys = band_kernel(k, b, r, n, unit)
    return files.select("file_id", F.posexplode(keys("text")).alias("band", "key"))


def fuzzy_edges(files: DataFrame, k: int = 2048, b: int = 16, r: int = 128, n: int = 5, unit: str = "word") -> DataFrame:
    return bucket_edges(text_bands(files, k, b, r, n, unit))


def keep_best(files: DataFrame, clusters: DataFrame) -> DataFrame:
    """files without those that their cluster (node, root) has a better one for: stars, then commit time, then least id."""
    ranked = files.select("file_id", "stars", "commit_day").join(clusters.withColumnRenamed("node", "file_id"), "file_id")
    best = ranked.groupBy("root").agg(F.max_by("file_id", F.struct("stars", "commit_day", -F.col("file_id"))).alias("best"))
    lost = ranked.join(best, "root").where("file_id <> best").select("file_id")
    return files.join(lost, "file_id", "left_anti")


def fuzzy_dedup(files: DataFrame, k: int = 2048, b: int = 16, r: int = 128, n: int = 5, unit: str = "word", verify: int | None = None) -> DataFrame:
    if verify is None:
        edges = fuzzy_edges(files, k, b, r, n, unit)
    else:
        edges = bucket_links(text_bands(files, k, b, r, n, unit), files, verify, n)
    return keep_best(files, components(edges.select("a", "b")))


def curve(levels: DataFrame, settings: list[tuple[int, int]]) -> DataFrame:
    """Chance that a pair of a similarity s of levels meets in some band, and the knee, for each (bands, rows)."""
    grid = levels.crossJoin(F.broadcast(levels.sparkSession.createDataFrame(settings, "bands int, rows int")))
    return grid.select("bands", "rows", F.round("s", 6).alias("s"), F.round(1 - F.pow(1 - F.pow("s", "rows"), "bands"), 6).alias("p"), F.round(F.pow(1.0 / F.col("bands"), 1.0 / F.col("rows")), 6).alias("knee"))


def gram_prefixes(files: DataFrame, percent: int, n: int = 5) -> DataFrame:
    """(file_id, m, cls, prefix): number of n-grams, a hash of their set, and the hashes of the rarest of them: two files of the similarity share one of these.

    Rarity is read off counts in SLOTS slots of fixed number; any order gives the same pairs.
    """
    from pyspark.sql.types import ArrayType, LongType, StructField, StructType

    words = files.select("file_id", F.array_join(tokens(F.col("text")), " ").alias("words"))

    def hashes(words: str | None) -> np.ndarray:
        if not words:
            return np.empty(0, np.uint64)
        raw = words.encode("utf-8", "surrogatepass")
        gaps = np.flatnonzero(np.frombuffer(raw, np.uint8) == 32)
        start, end = np.concatenate([[0], gaps + 1]), np.concatenate([gaps, [len(raw)]])
        wide = min(n, len(start))
        return np.unique(Ranges(raw).of(start[: len(start) - wide + 1], end[wide - 1 :]))

    def count(batches):
        held = np.zeros(SLOTS, np.int64)
        for batch in batches:
            found = np.concatenate([np.empty(0, np.uint64), *map(hashes, batch["words"])])
            held += np.bincount((found % np.uint64(SLOTS)).astype(np.int64), minlength=SLOTS)
        slots = np.flatnonzero(held)
        yield pd.DataFrame({"slot": slots, "n": held[slots]})

    counted = words.mapInPandas(count, "slot long, n long").groupBy("slot").agg(F.sum("n").alias("n")).toPandas()
    often = np.zeros(SLOTS, np.int64)
    often[counted["slot"].to_numpy(np.int64)] = counted["n"].to_numpy(np.int64)
    held = files.sparkSession.sparkContext.broadcast(often)

    def cut(batches):
        for batch in batches:
            rows = []
            for i, text in zip(batch["file_id"], batch["words"]):
                g = hashes(text)
                if len(g):
                    g = g[np.lexsort((g, held.value[(g % np.uint64(SLOTS)).astype(np.int64)]))]
                    first = len(g) - -(-len(g) * percent // 100) + 1
                    rows.append((i, len(g), int(mix(g).sum(dtype=np.uint64).view(np.int64)), g[:first].view(np.int64)))
            yield pd.DataFrame(rows, columns=["file_id", "m", "cls", "prefix"])

    schema = StructType([files.schema["file_id"], *(StructField(c, LongType()) for c in ("m", "cls")), StructField("prefix", ArrayType(LongType()))])
    return words.mapInPandas(cut, schema)


def shared_gram_pairs(files: DataFrame, percent: int, n: int = 5) -> DataFrame:
    """All pairs (a, b, inter, uni) of the similarity, exactly.

    Files of equal n-grams are one class until the end; classes that share one of their rarest n-grams are compared n-gram by n-gram.
    """
    rows = settled(gram_prefixes(files, percent, n))
    classes = settled(rows.join(rows.groupBy("cls", "m").agg(F.min("file_id").alias("rep")), ["cls", "m"]).select("file_id", "rep", "m"))
    heads = rows.join(classes.select(F.col("rep").alias("file_id")).distinct(), "file_id", "left_semi").select("file_id", "m", F.explode("prefix").alias("gram"))
    x, y = heads.toDF("a", "ma", "gram"), heads.toDF("b", "mb", "gram")
    met = x.join(y, "gram").where(f"a < b and 100 * least(ma, mb) >= {percent} * greatest(ma, mb)").select("a", "b").distinct()
    near = verify_edges(met, files, percent, n).select("a", "b", F.col("inter").cast("long").alias("inter"), F.col("uni").cast("long").alias("uni"))
    same = classes.groupBy("rep").agg(F.count(F.lit(1)).alias("k"), F.max("m").alias("m")).where("k > 1").select(F.col("rep").alias("a"), F.col("rep").alias("b"), F.col("m").alias("inter"), F.col("m").alias("uni"))
    own = lambda end: classes.select(F.col("rep").alias(end), F.col("file_id").alias("f" + end))
    pairs = near.union(same).join(own("a"), "a").join(own("b"), "b").where("a <> b or fa < fb")
    return pairs.select(F.least("fa", "fb").alias("a"), F.greatest("fa", "fb").alias("b"), "inter", "uni")


def ml_terms(files: DataFrame, tables: int = 8, features: int = 1 << 20, seed: int = 3) -> DataFrame:
    """(file_id, terms, h): the library's hashed n-grams of a file that has some, and its least value of each hash table."""
    from pyspark.ml.feature import HashingTF, MinHashLSH
    from pyspark.ml.functions import vector_to_array

    rows = files.select("file_id", shingles(F.col("text")).alias("g")).where("size(g) > 0")
    vec = HashingTF(inputCol="g", outputCol="v", numFeatures=features, binary=True).transform(rows).select("file_id", "v")
    model = MinHashLSH(inputCol="v", outputCol="h", numHashTables=tables, seed=seed).fit(vec)
    least = F.array(*(F.get(vector_to_array(F.get("h", i)), 0).cast("long") for i in range(tables)))
    return model.transform(vec).select("file_id", F.unwrap_udt("v")["indices"].alias("terms"), least.alias("h"))


def ml_pairs(files: DataFrame, percent: int = 70, features: int = 1 << 20) -> DataFrame:
    """(a, b, dist, copy): the pairs that the library's MinHash similarity join finds below the distance (100 - percent) / 100.

    Files of equal terms are one class: its least file stands for it in the pairs, and a row with copy says that file b has the terms of file a.
    The library's join sends each vector once a table and meets all of a bucket; here pairs of the similarity are found by the rarest of their terms, and
    those stay that share the least value of a table, so only ids, the terms of pairs and small hashes move. Each step lets go of the shuffles and tables
    that nothing reads again.
    """
    spark = files.sparkSession
    rows = settled(ml_terms(files, features=features))
    own = rows.select("file_id", F.xxhash64("terms").alias("k"), F.xxhash64(F.reverse("terms")).alias("l"), F.size("terms").alias("m"))
    named = own.join(own.groupBy("k", "l", "m").agg(F.min("file_id").alias("rep")), ["k", "l", "m"])
    classes = settled(named.select("rep", "file_id"))
    release(spark)
    heads = rows.join(classes.where("rep = file_id").select("file_id"), "file_id", "left_semi")

    def count(batches):
        held = np.zeros(features, np.int64)
        for batch in batches:
            held += np.bincount(batch.column(0).flatten().to_numpy(), minlength=features)
        slots = np.flatnonzero(held)
        yield pa.RecordBatch.from_arrays([pa.array(slots), pa.array(held[slots])], names=["term", "n"])

    counted = heads.select("terms").mapInArrow(count, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).toArrow()
    often = np.zeros(features, np.int64)
    often[counted.column("term").to_numpy()] = counted.column("n").to_numpy()
    held = files.sparkSession.sparkContext.broadcast(often)

    def cut(batches):
        for batch in batches:
            ids, sizes, terms = [], [], []
            for i, t in zip(batch.column(0).to_pylist(), batch.column(1)):
                t = t.values.to_numpy()
                first = t[np.lexsort((t, held.value[t]))][: len(t) - (percent * len(t) + 99) // 100 + 1]
                ids.append(np.full(len(first), i)), sizes.append(np.full(len(first), len(t))), terms.append(first)
            if ids:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), f) for c, f in ((ids, pa.int64()), (sizes, pa.int32()), (terms, pa.int32()))], names=["a", "ma", "term"])

    first = heads.select("file_id", "terms").mapInArrow(cut, "a long, ma int, term int")
    shared = settled(first.join(first.groupBy("term").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("term"), "term"))
    release(spark)
    met = shared.join(shared.select("term", F.col("a").alias("b"), F.col("ma").alias("mb")), "term").where(f"a < b and 100 * least(ma, mb) >= {percent} * greatest(ma, mb)").select("a", "b").distinct()
    h = lambda end: rows.select(F.col("file_id").alias(end), F.col("h").alias("h" + end))
    like = settled(met.join(h("a"), "a").join(h("b"), "b").where(F.exists(F.zip_with("ha", "hb", lambda x, y: x == y), lambda x: x)).select("a", "b"))
    release(spark, shared)
    terms = lambda end: rows.select(F.col("file_id").alias(end), F.col("terms").alias("t" + end))
    inter = F.size(F.array_intersect("ta", "tb"))
    both = like.join(terms("a"), "a").join(terms("b"), "b").select("a", "b", inter.alias("inter"), (F.size("ta") + F.size("tb")).alias("sizes"))
    near = settled(both.select("a", "b", (F.lit(1.0) - F.col("inter").cast("double") / (F.col("sizes") - F.col("inter"))).alias("dist")).where(F.col("dist") < (100 - percent) / 100))
    release(spark, rows, like)
    copies = classes.where("rep <> file_id").select("rep", "file_id", F.lit(0.0), F.lit(True))
    return near.select("a", "b", F.round("dist", 6).alias("dist"), F.lit(False).alias("copy")).union(copies)


def repo_fuzzy(files: DataFrame, k: int = 64, b: int = 16, r: int = 4) -> DataFrame:
    """(repo, root): near-duplicate repositories. A repository's signature is the least of its files' values, so nothing is concatenated."""
    sigs = signatures(files, k).join(files.select("file_id", "repo"), "file_id")
    least = sigs.select("repo", F.posexplode("sig").alias("i", "v")).groupBy("repo", "i").agg(F.min("v").alias("v"))
    rows = least.groupBy("repo").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda x: x["v"]).alias("sig"))
    clusters = components(bucket_edges(bands(rows.withColumnRenamed("repo", "file_id"), b, r)))
    return clusters.select(F.col("node").alias("repo"), "root")
