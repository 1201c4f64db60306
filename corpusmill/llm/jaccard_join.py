"""N-gram Jaccard join: documents whose sets of word shingles overlap by `similarity` or more, and their components.

Equal sets form one class, and classes are joined. Shingles are ordered rare first by a count sketch of fixed size over all documents (any fixed
order gives the same links; a better sketch only gives fewer candidates). A class enters the groups of its
prefix shingles. In each group every member is first compared with one leader; length, positional and suffix bounds drop pairs that
cannot reach the similarity, and each remaining pair is verified once on the whole sets. Only members of a group that are still in different components
are then compared with each other, so copies never meet in all pairs and no link between different sets is lost.

Defined results: null, empty or wordless text has an empty set and stays alone; repeated rows are copies; an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusmill.operators.components import merge_labels, moved_roots, relabelled

from .common import Members, release, settled
from .hashing import set_digest, shingle_set

#: The sketch has 2**LOG_SLOTS counters, merged in chunks.
LOG_SLOTS, CHUNK = 18, 2048
#: A prefix shingle that the sketch counts this many times above the mean has its group split in parts 1 to SPLIT; part 0 is a whole group.
HOT, SPLIT = 2_000, 16
#: Ranges of hashes whose sizes the suffix bound compares.
PARTS = 64
#: Sets that a verifying task remembers, and classes that a dealing task remembers to have sent.
REMEMBERED, SENT = 512, 1 << 18


def _texts(docs: DataFrame, id_col: str, text_col: str, unique: bool = True) -> DataFrame:
    """(key, text): ids are the keys where they are unique and not null, else hashes of id and text are."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    key = F.col(id_col).cast("long") if unique else F.xxhash64(F.col(id_col).cast("long"), text)
    return docs.select(key.alias("key"), text.cast("binary").alias("text"), F.col(id_col).cast("long").alias("id"), F.xxhash64(F.col(id_col).cast("long"), text).alias("hash"))


def _sets(batches, size: int):
    """(keys, sets, rows) in small runs of rows."""
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            yield part.column(0).to_pylist(), [shingle_set(t, size) for t in part.column(1).to_pylist()], part


def class_rows(docs: DataFrame, size: int, id_col: str, text_col: str) -> DataFrame:
    """For each row its class, set size and sizes of the set's parts."""
    schema = pa.schema([("id", pa.int64()), ("hash", pa.int64()), ("n", pa.int64()), ("cls", pa.binary()), ("parts", pa.list_(pa.int32()))])

    def run(batches):
        for _, sets, part in _sets(batches, size):
            parts = [np.bincount((s >> np.uint64(58)).astype(np.int64), minlength=PARTS).tolist() for s in sets]
            yield pa.RecordBatch.from_arrays([part.column(2), part.column(3), pa.array([len(s) for s in sets], pa.int64()), pa.array([set_digest(s) for s in sets], pa.binary()), pa.array(parts, schema.field(4).type)], schema=schema)

    return _texts(docs, id_col, text_col).mapInArrow(run, "id long, hash long, n long, cls binary, parts array<int>")


def sketch(docs: DataFrame, size: int, id_col: str, text_col: str) -> np.ndarray:
    """How often shingles of each hash range occur, summed in a tree of groups of at most 64 rows."""

    def count(batches):
        held, some = np.zeros(1 << LOG_SLOTS, np.int64), False
        for _, sets, _ in _sets(batches, size):
            some = True
            held += np.bincount(np.concatenate([s >> np.uint64(64 - LOG_SLOTS) for s in sets]).astype(np.int64), minlength=1 << LOG_SLOTS)
        if some:
            chunks = held.reshape(-1, CHUNK)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(chunks))), pa.array(list(chunks), pa.list_(pa.int64()))], names=["chunk", "counts"])

    rows = _texts(docs, id_col, text_col).mapInArrow(count, "chunk long, counts array<long>").withColumn("task", F.spark_partition_id())
    tasks = max(1, _texts(docs, id_col, text_col).rdd.getNumPartitions())
    while tasks > 1:
        rows = rows.groupBy("chunk", (F.col("task") / 64).cast("int").alias("task")).applyInPandas(_added, "chunk long, counts array<long>, task int")
        tasks = -(-tasks // 64)
    out = np.zeros(1 << LOG_SLOTS, np.int64)
    for r in rows.select("chunk", "counts").collect():
        out[r[0] * CHUNK : (r[0] + 1) * CHUNK] += r[1]
    return out


def _added(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
    return pd.DataFrame({"chunk": [key[0]], "counts": [np.sum(np.stack(rows["counts"].to_list()), axis=0)], "task": [key[1]]})


def prefix_rows(texts: DataFrame, counts: np.ndarray, size: int, percent: int) -> DataFrame:
    """(token, salt, key, n, pos) for the rarest shingles of each set that a partner must share one of."""
    held = texts.sparkSession.sparkContext.broadcast(counts)
    schema = pa.schema([("token", pa.int64()), ("salt", pa.int32()), ("key", pa.int64()), ("n", pa.int32()), ("pos", pa.int32())])

    def run(batches):
        counts = held.value
        hot = counts.mean() + HOT
        seen: set[bytes] = set()
        for keys, sets, _ in _sets(batches, size):
            cols: list[list] = [[], [], [], [], []]
            for key, s in zip(keys, sets):
                n = len(s)
                if not n or (cls := set_digest(s)) in seen:  # copies in this task add nothing
                    continue
                if len(seen) >= SENT:
                    seen.clear()
                seen.add(cls)
                often = counts[(s >> np.uint64(64 - LOG_SLOTS)).astype(np.int64)]
                first = np.lexsort((s, often))[: n - (percent * n + 99) // 100 + 1]
                for col, values in zip(cols, (s[first].view(np.int64), np.where(often[first] > hot, 1 + cls[0] % SPLIT, 0), np.full(len(first), key), np.full(len(first), n), np.arange(len(first)))):
                    col.append(values)
            if cols[2]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), type=f.type) for c, f in zip(cols, schema)], schema=schema)

    return texts.select("key", "text").mapInArrow(run, "token long, salt int, key long, n int, pos int")


def needed(n: Column, m: Column, percent: int) -> Column:
    """Least overlap of sets of n and m members that reaches the similarity."""
    return F.floor((percent * (n + m) + (99 + percent)) / (100 + percent))


def bound(n: Column, i: Column, s: Column, m: Column, j: Column, t: Column) -> Column:
    """Most overlap of two sets that share the shingle at places i and j, with s and t earlier ones that any other set has."""
    return F.least(s, t) + F.least(n - i, m - j)


def possible(pairs: DataFrame, percent: int) -> DataFrame:
    """Distinct pairs (x, y) that pass the length and positional bounds at every shared prefix shingle seen."""
    n, m = F.col("n"), F.col("m")
    close = pairs.where(100 * F.least(n, m) >= percent * F.greatest(n, m))
    return close.groupBy("x", "y", "n", "m").agg(F.min(bound(n, F.col("i"), F.col("s"), m, F.col("j"), F.col("t"))).alias("most")).where(F.col("most") >= needed(n, m, percent)).select("x", "y", "n", "m")


def verified(pairs: DataFrame, classes: DataFrame, texts: DataFrame, size: int, percent: int) -> DataFrame:
    """Of distinct pairs (x, y, n, m) those whose whole sets overlap enough, as (a, b); the suffix bound goes first, then texts meet, packed."""
    own = classes.select("rep", "parts")
    pairs = pairs.join(own.select(F.col("rep").alias("x"), F.col("parts").alias("px")), "x").join(own.select(F.col("rep").alias("y"), F.col("parts").alias("py")), "y")
    most = F.expr("aggregate(zip_with(px, py, (a, b) -> least(a, b)), 0L, (s, v) -> s + v)")
    pairs = settled(pairs.where(most >= needed(F.col("n"), F.col("m"), percent)).select("x", "y"))
    if pairs.isEmpty():
        return pairs.toDF("a", "b")
    wanted = pairs.select(F.col("x").alias("key")).union(pairs.select("y")).distinct()
    held = texts.sparkSession.sparkContext.broadcast(Members.of(wanted.select(F.xxhash64("key").alias("h")), "h"))
    schema = pa.schema([("key", pa.int64()), ("body", pa.binary())])

    def pack(batches):
        import zstandard

        members, press = held.value, zstandard.ZstdCompressor(level=3)
        for batch in batches:
            rows = np.flatnonzero(members.has(batch.column(2).to_numpy()))
            if len(rows):
                found = batch.take(pa.array(rows))
                yield pa.RecordBatch.from_arrays([found.column(0), pa.array([press.compress(t) for t in found.column(1).to_pylist()], pa.binary())], schema=schema)

    bodies = texts.select("key", "text", F.xxhash64("key").alias("h")).mapInArrow(pack, "key long, body binary")
    bodies = settled(bodies.join(wanted, "key", "left_semi").dropDuplicates(["key"]))

    def check(batches):
        import zstandard

        unpress, known = zstandard.ZstdDecompressor(), {}

        def members(key: int, body: bytes) -> np.ndarray:
            if key not in known:
                if len(known) >= REMEMBERED:
                    known.clear()
                known[key] = shingle_set(unpress.decompress(body), size)
            return known[key]

        for batch in batches:
            x, y, bx, by = (c.to_pylist() for c in batch.columns)
            keep = []
            for a, b, ba, bb in zip(x, y, bx, by):
                s, t = members(a, ba), members(b, bb)
                both = len(np.intersect1d(s, t, assume_unique=True))
                keep.append(100 * both >= percent * (len(s) + len(t) - both))
            yield pa.RecordBatch.from_arrays(batch.columns[:2], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    both = pairs.join(bodies.select(F.col("key").alias("x"), F.col("body").alias("bx")), "x").join(bodies.select(F.col("key").alias("y"), F.col("body").alias("by")), "y")
    links = settled(both.select("x", "y", "bx", "by").mapInArrow(check, "a long, b long"))
    release(texts.sparkSession, bodies, pairs)
    return links


def _ordered(x: str, y: str) -> list[Column]:
    """Columns x, n, i, s, y, m, j, t with x the lesser key."""
    swap = F.col(x) > F.col(y)
    pick = lambda a, b: F.when(swap, F.col(b)).otherwise(F.col(a))
    return [pick(x, y).alias("x"), pick(y, x).alias("y"), pick("n", "m").alias("n"), pick("m", "n").alias("m"), pick("i", "j").alias("i"), pick("j", "i").alias("j"), pick("s", "t").alias("s"), pick("t", "s").alias("t")]


def _mixed(groups: DataFrame, labels: DataFrame) -> DataFrame:
    """Rows of the groups that hold several components, with their roots, their group's leader and its root (main); settled."""
    rooted = groups.join(labels.select(F.col("node").alias("key"), "root"), "key")
    heads = rooted.groupBy("token").agg(F.min(F.struct("pos", "n", "key", "s", "root")).alias("l"), F.min("root").alias("r0"), F.max("root").alias("r1"), F.count(F.lit(1)).alias("members")).where("r0 <> r1")
    heads = heads.select("token", "members", F.col("l.key").alias("leader"), F.col("l.n").alias("leader_n"), F.col("l.pos").alias("leader_pos"), F.col("l.s").alias("leader_s"), F.col("l.root").alias("main"))
    return settled(rooted.join(heads, "token"))


def jaccard_components(docs: DataFrame, size: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: n_shingles and component_id, the smallest id that links reach from it."""
    spark = docs.sparkSession
    rows = settled(class_rows(docs, size, id_col, text_col))
    total, ids = rows.agg(F.count(F.lit(1)), F.count_distinct("id")).first()
    unique = total == ids
    rows = rows.withColumn("key", F.col("id") if unique else F.col("hash"))
    texts = _texts(docs, id_col, text_col, unique)
    classes = settled(rows.where("n > 0").groupBy("cls").agg(F.min("key").alias("rep"), F.min("id").alias("least"), F.min_by("parts", "key").alias("parts"), F.count(F.lit(1)).alias("copies")))
    alias = settled(rows.where("n > 0").join(classes.where("copies > 1").select("cls", "rep"), "cls").where("key <> rep").select("key", "rep").distinct())
    counts = sketch(docs, size, id_col, text_col)
    group = Window.partitionBy("token", "salt")
    # the member that has the shared shingle earliest has the fewest shingles of its own: it leads
    shared = prefix_rows(texts, counts, size, percent).repartition("token", "salt").withColumn("members", F.count(F.lit(1)).over(group))
    # a row alone in a part of a split group has its partners in the other parts
    shared = settled(shared.where((F.col("members") > 1) | (F.col("salt") > 0)).drop("members"))
    release(spark)
    # dealt by key once: equal rows and the places of a key are then in one partition
    shared = shared.join(alias, "key", "left").select("token", "salt", F.coalesce("rep", "key").alias("key"), "n", "pos").repartition("key").distinct()
    # shingles that no other prefix has cannot match: only the others before a place count, and a place after too many of the rest is none
    shared = shared.withColumn("s", F.row_number().over(Window.partitionBy("key").orderBy("pos", "token")) - 1).where(100 * (F.col("s") + F.col("n") - F.col("pos")) >= percent * F.col("n"))
    shared = shared.withColumns({"leader": F.min(F.struct("pos", "n", "key", "s")).over(group), "members": F.count(F.lit(1)).over(group)})
    shared = settled(shared.where((F.col("members") > 1) | (F.col("salt") > 0)).drop("members"))
    two = lambda l: [F.col(l + ".key").alias("l"), "n", F.col(l + ".n").alias("m"), F.col("pos").alias("i"), F.col(l + ".pos").alias("j"), "s", F.col(l + ".s").alias("t")]  # noqa: E731, E741
    star = shared.where("key <> leader.key").select("key", *two("leader"))
    heads = shared.where("key = leader.key").groupBy("token").agg(F.min("leader").alias("top"), F.count(F.lit(1)).alias("parts")).where("parts > 1")
    across = shared.where("key = leader.key").join(heads, "token").where("key <> top.key").select("key", *two("top"))
    tested = settled(possible(star.union(across).select(*_ordered("key", "l")), percent))
    # each class meets one leader first; then only what is still apart from a leader meets it
    first = settled(tested.groupBy("y").agg(F.min(F.struct("x", "n", "m")).alias("l")).select("l.x", "y", "l.n", "l.m"))
    release(spark, tested)
    labels = shared.select(F.col("key").alias("node"), F.col("key").alias("root")).distinct()
    labels = merge_labels(labels, verified(first, classes, texts, size, percent))
    left = _mixed(shared.select("token", "key", "n", "pos", "s"), labels)
    release(spark, shared)
    star = left.where("key <> leader and root <> main").select("key", "leader_n", "leader_pos", "leader_s", "n", "pos", "s", "leader")
    star = star.select("key", F.col("leader").alias("l"), "n", F.col("leader_n").alias("m"), F.col("pos").alias("i"), F.col("leader_pos").alias("j"), "s", F.col("leader_s").alias("t"))
    second = possible(star.select(*_ordered("key", "l")), percent).join(first.select("x", "y"), ["x", "y"], "left_anti")
    moved = settled(moved_roots(labels, verified(second, classes, texts, size, percent)))
    labels = settled(relabelled(labels, moved))
    left = left.where("members > 2")  # of two members one leads, and has met the other
    left = relabelled(relabelled(left.select("token", "key", "n", "pos", "s", "root", "main", "leader"), moved), moved, "main")
    # members of a group that are apart from its leader's component are compared with all of the group
    x = left.where("root <> main and key <> leader").select("token", F.col("key").alias("c"), "n", F.col("pos").alias("i"), "s", F.col("root").alias("rx"), "main")
    y = left.where("key <> leader").select("token", F.col("key").alias("d"), F.col("n").alias("m"), F.col("pos").alias("j"), F.col("s").alias("t"), F.col("root").alias("ry"))
    n, m = F.col("n"), F.col("m")
    # the first shared shingle of a linked pair lies this early in both sets
    early = (F.col("i") <= n - needed(n, m, percent)) & (F.col("j") <= m - needed(n, m, percent))
    fit = F.expr("rx <> ry and (ry = main or c < d)") & early & (100 * F.least(n, m) >= percent * F.greatest(n, m)) & (bound(n, F.col("i"), F.col("s"), m, F.col("j"), F.col("t")) >= needed(n, m, percent))
    met = x.join(y, "token").where(fit).select(*_ordered("c", "d"))
    # pairs with a leader are settled, so here every shared prefix shingle of a pair is seen: they and what follows the last one bound the overlap
    met = met.groupBy("x", "y", "n", "m").agg((F.count(F.lit(1)) + F.least(n - F.max("i"), m - F.max("j")) - 1).alias("most")).where(F.col("most") >= needed(n, m, percent))
    labels = merge_labels(labels, verified(met.select("x", "y", "n", "m"), classes, texts, size, percent))
    named = classes.join(labels.withColumnRenamed("node", "rep"), "rep", "left").select("cls", "least", F.coalesce("root", "rep").alias("root"))
    smallest = named.groupBy("root").agg(F.min("least").alias("component_id"))
    final = settled(named.join(smallest, "root").select("cls", "component_id"))
    release(spark, first, moved)
    out = rows.select("id", "n", "cls").join(final, "cls", "left")
    return out.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("component_id", "id").alias("component_id"))


def keep_one(docs: DataFrame, size: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each component, with its columns: the one whose id names the component. Wordless rows all stay.

    Of rows that share that id, the one with the least text stays.
    """
    found = jaccard_components(docs, size, percent, id_col, text_col).where("n_shingles > 0")
    away = found.groupBy(F.col(id_col).alias("__id")).agg(F.min("component_id").alias("__root"), F.count(F.lit(1)).alias("__n")).where("not (__id <=> __root) or __n > 1")
    text = F.col(text_col).cast("string")
    whole = docs.select(F.struct("*").alias("__row"), F.col(id_col).cast("long").alias("__key"), F.coalesce(text.rlike(r"[^\x20\x09-\x0D]"), F.lit(False)).alias("__worded"))
    joined = whole.join(away, F.col("__key").eqNullSafe(F.col("__id")), "left")
    columns = [F.col("__row")[n].alias(n) for n in docs.columns]
    once = joined.where(~F.col("__worded") | F.col("__n").isNull()).select(columns)
    again = joined.where(F.col("__worded") & (F.col("__n") > 1) & F.col("__key").eqNullSafe(F.col("__root")))
    first = again.withColumn("__rank", F.row_number().over(Window.partitionBy("__key").orderBy(F.col("__row")[text_col].cast("string")))).where("__rank = 1")
    return once.unionByName(first.select(columns))
