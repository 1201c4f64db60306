"""Benchmark decontamination as a prefix-filtered set join. Built-in functions only.

A window is ten consecutive words of a benchmark item (all words of a shorter one); its set is that of its shingles of SHINGLE words (a shorter window is
one shingle). Shingles are ordered by how often they occur in all documents. For a window to lie in a document all of its shingles must, so the
prefix that has to be joined is its rarest one. Shingles of a document that lead some window become join rows; positional and length
bounds drop those where the window would not fit, and the rest are compared word by word over the item-sized window.
Where the leading shingles are few, the documents' arrays are filtered by them and only the hits with the words around them are joined, by broadcast; where they are
many, places meet windows in a shuffle and words are fetched for the documents that have a place.
Defined results: null text has no words; a benchmark row with null text has no windows, one with a null id is an item of its own
without a name; each input row gives one row, so
repeated rows repeat; without benchmark items nothing is hit; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import settled

#: What separates words once A-Z are lower case.
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Words of a shingle.
SHINGLE = 3
#: Benchmark sides of up to this many rows and bytes are broadcast or made a set in the plan; larger ones are joined by shuffle.
SMALL, SMALL_BYTES = 100_000, 32 << 20


def words_of(text: Column) -> Column:
    """Words with only A-Z folded; ASCII texts take the quick way to the same result."""
    text = F.coalesce(text, F.lit(""))
    folded = F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))
    return F.array_remove(F.split(folded, SEPARATORS), "")


def windows_of(bench: DataFrame, size: int, item_col: str, text_col: str) -> DataFrame:
    """Distinct (item, words) windows of the items; an item is a struct of its name, so that a null name counts."""
    items = bench.select(F.struct(F.col(item_col).cast("string").alias("name")).alias("item"), words_of(F.col(text_col).cast("string")).alias("w")).where("size(w) > 0")
    return items.select("item", F.explode(F.expr(f"if(size(w) <= {size}, array(w), transform(sequence(1, size(w) - {size - 1}), i -> slice(w, i, {size})))")).alias("win")).distinct()


def shingles_of(words: str, widths: list[int]) -> Column:
    """Structs (h, pos) of an array's shingles of each width; h is a hash of the shingle's words in order.

    The array is bound to a lambda's variable, so that it is made once a row wherever the optimiser puts the expression.
    """
    kind = "array<struct<h: bigint, pos: int>>"
    one = lambda k: f"if(size(s) < {k}, cast(array() as {kind}), transform(slice(s, 1, size(s) - {k - 1}), (x, i) -> struct(xxhash64({k}, {', '.join(f's[i + {j}]' for j in range(k))}) as h, i as pos)))"
    return F.expr(f"get(transform(array({words}), s -> concat({', '.join(map(one, widths))})), 0)") if widths else F.expr(f"cast(array() as {kind})")


def _few(side: DataFrame, size: Column) -> bool:
    n, held = side.limit(SMALL + 1).agg(F.count(F.lit(1)), F.coalesce(F.sum(size), F.lit(0))).first()
    return n <= SMALL and held <= SMALL_BYTES


def keyed_windows(windows: DataFrame, docs: DataFrame, text_col: str) -> tuple[DataFrame, list[int]]:
    """Windows by content with their items, their rarest shingle's hash and its place in them; settled. And the widths of shingles."""
    by_content = settled(windows.groupBy("win").agg(F.collect_set("item").alias("items")))
    widths = sorted(r[0] for r in by_content.select(F.least(F.size("win"), F.lit(SHINGLE)).alias("k")).distinct().collect())
    cut = reduce(lambda e, k: e.when(F.least(F.size("win"), F.lit(SHINGLE)) == k, shingles_of("win", [k])), widths, F.when(F.lit(False), shingles_of("win", [])))
    tokens = settled(by_content.select("win", F.explode(cut).alias("t")).select("win", "t.h", F.col("t.pos").alias("off")))
    known = tokens.select("h").distinct()
    seen = docs.select(words_of(F.col(text_col).cast("string")).alias("w")).select(shingles_of("w", widths).alias("t"))
    if _few(known, F.lit(8)):
        keys = [r[0] for r in known.collect()]
        seen = seen.select(F.filter("t", lambda x: x["h"].isin(keys) if keys else F.lit(False)).alias("t"))
    counts = seen.select(F.explode("t").alias("t")).groupBy("t.h").agg(F.count(F.lit(1)).alias("n"))
    ranked = tokens.join(counts, "h", "left").groupBy("win").agg(F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "h", "off")).alias("rare"))
    return settled(by_content.join(ranked, "win").select("win", "items", F.col("rare.h").alias("h"), F.col("rare.off").alias("off"))), widths


def occurrences(docs: DataFrame, bench: DataFrame, id_col: str, text_col: str, item_col: str, bench_text_col: str, size: int) -> DataFrame:
    """Per distinct (id, text): how many rows have it (copies), n_words, and the sets of hit ranges and of items."""
    windows, widths = keyed_windows(windows_of(bench, size, item_col, bench_text_col), docs, text_col)
    text = F.col(text_col).cast("string")
    base = docs.select(F.col(id_col).alias("__id"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("__h1"), F.hash(F.coalesce(text, F.lit(""))).alias("__h2"), words_of(text).alias("__w"))
    places = base.withColumn("__c", shingles_of("__w", widths))
    start = F.col("pos") - F.col("off")
    fits = (start >= 0) & (start + F.size("win") <= F.col("n_words"))
    of_hit = F.struct(start.alias("s"), (start + F.size("win")).alias("e"))
    key = ["__id", "__h1", "__h2", "n_words"]
    if _few(windows, F.octet_length(F.array_join("win", " ")) + F.octet_length(F.array_join("items.name", " "))):
        leads = [r[0] for r in windows.select("h").distinct().collect()]
        picked = F.filter("__c", lambda x: x["h"].isin(leads) if leads else F.lit(False))
        near = F.expr(f"get(transform(array(__w), s -> transform(__c, x -> struct(x.h as h, x.pos as pos, slice(s, greatest(x.pos - {size - 1}, 0) + 1, {2 * size - 1}) as near))), 0)")
        head = F.expr("array(struct(cast(null as bigint) as h, -1 as pos, cast(null as array<string>) as near))")
        rows = places.withColumn("__c", picked).select("__id", "__h1", "__h2", F.size("__w").cast("long").alias("n_words"), F.explode(F.concat(head, near)).alias("x"))
        joined = rows.select(*key, "x.*").join(F.broadcast(windows), "h", "left")
        there = F.expr(f"slice(near, pos - off - greatest(pos - {size - 1}, 0) + 1, size(win)) = win")
        checked = joined.withColumn("__hit", F.when(fits, F.when(there, of_hit))).where("pos = -1 or __hit is not null")
    else:
        narrow = places.select("__id", "__h1", "__h2", F.size("__w").cast("long").alias("n_words"), F.explode("__c").alias("x")).select(*key, "x.*").distinct()
        met = narrow.join(windows, "h").where(fits).groupBy(*key).agg(F.collect_set(F.struct("win", "items", of_hit.alias("hit"))).alias("__m"))
        whole = base.select("__id", "__h1", "__h2", F.size("__w").cast("long").alias("n_words"), "__w")
        met = met.toDF("__i", "__k1", "__k2", "__n", "__m")
        same = F.col("__id").eqNullSafe(F.col("__i")) & (F.col("__h1") == F.col("__k1")) & (F.col("__h2") == F.col("__k2")) & (F.col("n_words") == F.col("__n"))
        again = whole.join(met, same, "left")
        good = F.expr("get(transform(array(__w), s -> filter(__m, x -> slice(s, x.hit.s + 1, size(x.win)) = x.win)), 0)")
        none = F.expr("array(named_struct('items', cast(null as array<struct<name: string>>), '__hit', cast(null as struct<s: int, e: int>), 'pos', -1))")
        checked = again.select(*key, F.explode(F.concat(none, F.coalesce(F.transform(good, lambda x: F.struct(x["items"].alias("items"), x["hit"].alias("__hit"), F.lit(0).alias("pos"))), F.slice(none, 1, 0)))).alias("x")).select(*key, "x.*")
    return checked.groupBy(*key).agg(
        F.sum((F.col("pos") == -1).cast("int")).alias("copies"), F.array_sort(F.collect_set("__hit")).alias("ranges"), F.array_sort(F.array_distinct(F.flatten(F.collect_set(F.when(F.col("__hit").isNotNull(), F.col("items")))))).alias("items")
    )


def contamination(docs: DataFrame, bench: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", bench_text_col: str = "text", size: int = 10) -> DataFrame:
    """One row per document: its words, how many of them lie in benchmark windows, and the items that those come from."""
    found = occurrences(docs, bench, id_col, text_col, item_col, bench_text_col, size)
    hits = F.expr("aggregate(ranges, struct(0L as c, 0 as e), (a, x) -> struct(a.c + greatest(x.e - greatest(x.s, a.e), 0) as c, greatest(a.e, x.e) as e), a -> a.c)")
    out = found.withColumn("n_hit", hits).withColumn("__copy", F.explode(F.expr("sequence(1, cast(copies as int))")))
    return out.select(F.col("__id").alias(id_col), "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items.name", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def drop_contaminated(docs: DataFrame, bench: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """Rows without any benchmark window, with their columns. Rows are matched by id and text, so ids may repeat."""
    found = occurrences(docs, bench, id_col, text_col, options.get("item_col", "item_id"), options.get("bench_text_col", "text"), options.get("size", 10))
    bad = found.where("size(ranges) > 0").select("__id", "__h1", "__h2")
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    whole = docs.select(F.struct("*").alias("__row"), F.xxhash64(text).alias("__k1"), F.hash(text).alias("__k2"))
    kept = whole.join(bad, whole["__row"][id_col].eqNullSafe(bad["__id"]) & (F.col("__k1") == F.col("__h1")) & (F.col("__k2") == F.col("__h2")), "left_anti")
    return kept.select(*(F.col("__row")[n].alias(n) for n in docs.columns))


def item_schema() -> T.StructType:
    return T.StructType([T.StructField("item_id", T.StringType()), T.StructField("text", T.StringType())])


_WORDS = r"list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '')"
CONTAMINATION_SQL = rf"""
with d as (select doc_id, row_number() over () as r, {_WORDS} as w from documents),
b as (select item_id::varchar as item, {_WORDS} as w from benchmark),
win as (select distinct item, list_slice(w, i, i + least(10, len(w)) - 1) as x from (select item, w, unnest(range(1, greatest(len(w) - 8, 2))) as i from b where len(w) > 0)),
lens as (select distinct len(x) as n from win),
g as (select r, i, n, list_slice(w, i, i + n - 1) as x from (select r, w, n, unnest(range(1, len(w) - n + 2)) as i from d, lens where len(w) >= n)),
h as (select r, item, i, n from g join win using (x)),
hit as (select r, count(distinct p) as n_hit from (select r, unnest(range(i, i + n)) as p from h) group by r),
it as (select r, count(*) as n_items, string_agg(item, ',' order by item) as s from (select distinct r, item from h) group by r)
select doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items, sha256(coalesce(s, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from d left join hit using (r) left join it using (r)
"""
