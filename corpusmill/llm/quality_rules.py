"""Quality rules from text statistics and from how many documents of a host share a line. Built-in functions only.

A line (normalised: trimmed, white space collapsed, lower case) of more than `max_docs` documents and more than `max_share` of a
host's documents is over the limit there: it leaves the text, and a document that keeps too few words is rejected. At most
(mean distinct lines of a document) / max_share lines of a host can be over the limit, so the lists are small whatever the input.
Defined results: null or empty text has no words and fails; a null host is the host named by the empty string; rows are
handled one by one, so repeated rows repeat; an empty table gives an empty result; other columns are carried untouched or ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settled

WS = r"[\x20\x09-\x0D]"
#: Host lists of up to this many hosts and line keys in all are broadcast; longer ones are joined by shuffle.
BROADCAST_HOSTS, BROADCAST_KEYS = 20_000, 1_000_000


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), rf"{WS}+"), "")


def worded_lines(text: Column) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))


def line_key(line: Column) -> Column:
    return F.xxhash64(F.lower(F.trim(F.regexp_replace(line, rf"{WS}+", " "))))


def frequent_lines(docs: DataFrame, text_col: str, host_col: str, max_docs: int, max_share: float) -> DataFrame:
    """For each host with such lines, the keys of its lines over the limit."""
    host = F.coalesce(F.col(host_col).cast("string"), F.lit("")).alias("__host")
    keyed = docs.select(host, F.array_distinct(F.transform(worded_lines(F.col(text_col)), line_key)).alias("__keys"))
    hosts = keyed.groupBy("__host").agg(F.count(F.lit(1)).alias("__docs"))
    counts = keyed.select("__host", F.explode("__keys").alias("__key")).groupBy("__host", "__key").agg(F.count(F.lit(1)).alias("__n")).where(F.col("__n") > max_docs)
    over = counts.join(hosts, "__host").where(F.col("__n") > F.col("__docs") * max_share)
    return over.groupBy("__host").agg(F.sort_array(F.collect_set("__key")).alias("__over"))


def repeated_words(words: str, size: int = 5) -> dict[str, Column]:
    """Columns to add in turn; the last, __repeat, counts the words inside windows that occur twice or more."""
    near = ", ".join(f"{words}[i + {k}]" for k in range(size))
    return {
        "__h": F.expr(f"if(size({words}) >= {size}, transform(sequence(0, size({words}) - {size}), i -> xxhash64({near})), cast(array() as array<bigint>))"),
        "__s": F.expr("if(size(array_distinct(__h)) < size(__h), array_sort(transform(__h, (x, i) -> struct(x as h, i as i))), cast(array() as array<struct<h: bigint, i: int>>))"),
        "__p": F.expr("array_sort(transform(filter(__s, (x, k) -> (k > 0 and get(__s, k - 1).h = x.h) or (k < size(__s) - 1 and get(__s, k + 1).h = x.h)), x -> x.i))"),
        "__repeat": F.expr(f"aggregate(__p, struct(0L as c, 0 as e), (a, x) -> struct(a.c + (x + {size} - greatest(x, a.e)) as c, x + {size} as e), a -> a.c)"),
    }


def assess(docs: DataFrame, text_col: str = "text", host_col: str = "source", max_docs: int = 20, max_share: float = 0.1, least_words: int = 10, least_left: float = 0.2) -> DataFrame:
    """Every row of docs as struct __row, with its statistics, __clean (the text without lines over the limit) and verdicts."""
    over = settled(frequent_lines(docs, text_col, host_col, max_docs, max_share))
    hosts, keys = over.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.size("__over")), F.lit(0))).first()
    side = F.broadcast(over) if hosts <= BROADCAST_HOSTS and keys <= BROADCAST_KEYS else over
    base = docs.select(F.struct("*").alias("__row"), F.col(text_col).cast("string").alias("__text"), F.coalesce(F.col(host_col).cast("string"), F.lit("")).alias("__host"))
    out = base.join(side, "__host", "left").withColumns({"__w": words_of(F.col("__text")), "__lines": worded_lines(F.col("__text"))})
    for name, column in repeated_words("__w").items():
        out = out.withColumn(name, column)
    is_over = lambda line: F.array_contains("__over", line_key(line))
    out = out.withColumn("__hit", F.coalesce(F.col("__over").isNotNull() & F.exists("__lines", is_over), F.lit(False)))
    out = out.withColumn("__clean", F.when(F.col("__hit"), F.array_join(F.filter(F.split("__text", "\n"), lambda x: ~is_over(x)), "\n")).otherwise(F.col("__text")))
    out = out.withColumns(
        {
            "__n_words": F.size("__w").cast("long"),
            "__word_chars": F.length(F.array_join("__w", "")).cast("long"),
            "__n_symbols": F.coalesce(F.regexp_count("__text", F.lit(r"[#*$%&|<>]")), F.lit(0)).cast("long"),
            "__n_dup_lines": (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long"),
            "__left": F.when(F.col("__hit"), F.size(words_of(F.col("__clean")))).otherwise(F.size("__w")).cast("long"),
        }
    )
    failed = (F.col("__n_words") < least_words) | (100 * F.col("__repeat") > 20 * F.col("__n_words"))
    depleted = F.col("__hit") & ((F.col("__left") < least_words) | (F.col("__left") < least_left * F.col("__n_words")))
    return out.withColumns({"__failed": failed, "__kept": ~failed & ~depleted})


def quality_report(docs: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """One row per document: its statistics, whether a base rule fails it and whether it is kept."""
    c = F.col
    return assess(docs, **options).select(
        c("__row")[id_col].alias(id_col), c("__n_words").alias("n_words"), c("__word_chars").alias("word_chars"), c("__n_symbols").alias("n_symbols"), c("__n_dup_lines").alias("n_dup_lines"),
        c("__repeat").alias("n_repeat_words"), c("__failed").alias("base_failed"), c("__kept").alias("kept"), c("__left").alias("n_words_left"),
    )


def keep_quality(docs: DataFrame, text_col: str = "text", **options) -> DataFrame:
    """The rows that the rules keep, with their columns; lines over the limit are gone from their texts."""
    judged = assess(docs, text_col=text_col, **options).select(F.inline(F.array(F.struct("__row", "__clean", "__kept"))))  # a filter must not pull the statistics in again, nested
    kept = judged.where("__kept")
    return kept.select(*(F.col("__clean").alias(n) if n == text_col else F.col("__row")[n].alias(n) for n in docs.columns))


_T = "coalesce(text, '')"
_W = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
#: The contract's columns in DuckDB SQL, for max_docs 20, max_share 0.1.
QUALITY_SQL = rf"""
with d as (select doc_id, coalesce(source, '') as host, {_T} as text, {_W} as w, row_number() over () as r from documents),
l as (select r, host, line, lower(trim(regexp_replace(line, '[\x20\x09-\x0D]+', ' ', 'g'))) as norm, len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) as lw
      from (select r, host, unnest(string_split(text, chr(10))) as line from d) where regexp_matches(line, '[^\x20\x09-\x0D]')),
lines as (select r, count(*) as n, count(distinct line) as u from l group by r),
hosts as (select host, count(*) as docs from d group by host),
over as (select host, norm from l join hosts using (host) group by host, norm, docs having count(distinct r) > 20 and count(distinct r) > docs * 0.1),
gone as (select r, sum(lw) as lost from l join over using (host, norm) group by r),
g as (select r, i, list_slice(w, i, i + 4) as x from (select r, w, unnest(range(1, len(w) - 3)) as i from d where len(w) >= 5)),
dup as (select r, i from (select r, i, count(*) over (partition by r, x) as c from g) where c > 1),
cov as (select r, count(distinct p) as n from (select r, unnest(range(i, i + 5)) as p from dup) group by r),
s as (select d.doc_id, d.r, len(w) as n_words, length(array_to_string(w, '')) as word_chars, len(regexp_extract_all(d.text, '[#*$%&|<>]')) as n_symbols,
      coalesce(lines.n - lines.u, 0) as n_dup_lines, coalesce(cov.n, 0) as n_repeat_words, coalesce(gone.lost, 0) as lost
      from d left join lines using (r) left join cov using (r) left join gone using (r))
select doc_id, n_words::bigint as n_words, word_chars::bigint as word_chars, n_symbols::bigint as n_symbols, n_dup_lines::bigint as n_dup_lines, n_repeat_words::bigint as n_repeat_words,
       (n_words < 10 or 100 * n_repeat_words > 20 * n_words) as base_failed,
       not (n_words < 10 or 100 * n_repeat_words > 20 * n_words) and not (lost > 0 and (n_words - lost < 10 or n_words - lost < 0.2 * n_words)) as kept,
       (n_words - lost)::bigint as n_words_left
from s
"""
