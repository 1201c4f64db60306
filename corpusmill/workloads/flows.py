"""Streams, sinks and the SQL surface as workloads."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpusmill.functions.surface import register
from corpusmill.operators import transform
from corpusmill.schema import TOKENS, files, table
from corpusmill.sources import stores
from corpusmill.streaming import jobs
from corpusmill.workloads.catalog import add

events = lambda s, d: table(s, d, "events")
add("stream_tumbling", lambda s, d: jobs.windows(events(s, d), F.window("ts", "1 day")), "select date_trunc('day', ts::timestamp) as start, date_trunc('day', ts::timestamp) + interval 1 day as \"end\", event_type, count(*)::bigint as n from events group by 1, 2, 3")
add(
    "stream_sliding", lambda s, d: jobs.windows(events(s, d), F.window("ts", "2 days", "1 day")),
    "with w as (select unnest([date_trunc('day', ts::timestamp), date_trunc('day', ts::timestamp) - interval 1 day]) as start, event_type from events) select start, start + interval 2 day as \"end\", event_type, count(*)::bigint as n from w group by 1, 2, 3",
)
add(
    "stream_session", lambda s, d: jobs.windows(events(s, d), F.session_window("ts", "30 minutes")),
    """with o as (select ts::timestamp as ts, event_type, lag(ts::timestamp) over (partition by event_type order by ts) as before from events), g as (select *, sum(case when before is null or ts > before + interval 30 minute then 1 else 0 end) over (partition by event_type order by ts rows unbounded preceding) as g from o)
select min(ts) as start, max(ts) + interval 30 minute as "end", event_type, count(*)::bigint as n from g group by event_type, g""",
)
add("stream_late_drop", lambda s, d: jobs.late_counts(events(s, d), events(s, d), "1 hour"))
add("stream_static_join", lambda s, d: jobs.with_static(events(s, d), table(s, d, "customer").select("c_custkey", "c_mktsegment"), "user_id", "c_custkey").select("event_id", "c_mktsegment"), "select event_id, c_mktsegment from events join customer on user_id = c_custkey")
add(
    "stream_interval_join", lambda s, d: jobs.interval_join(events(s, d).where("event_type = 'error'"), events(s, d).where("event_type = 'click'"), "user_id", 24),
    "select e.event_id as id, c.event_id as other from events e join events c on e.user_id = c.user_id and e.event_type = 'error' and c.event_type = 'click' and c.ts <= e.ts and c.ts >= e.ts - interval 24 hour",
)
add("stream_near_duplicates", lambda s, d: jobs.near_duplicates([files(s, d).where(F.col("file_id") % 4 == i) for i in range(4)]))


def roundtrip(s, d):
    """Documents through the three sinks: rows and characters by language as they come back."""
    docs = table(s, d, "documents")
    at = jobs.folder(s)
    manifest = stores.write_partitioned(docs, f"{at}/by_lang", "lang")
    stores.write_json_lines(docs, f"{at}/lines")
    stores.write_digest_buckets(docs, f"{at}/digests")
    tell = lambda name, df: df.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("text")).cast("long").alias("n_chars")).select(F.lit(name).alias("sink"), "lang", "n", "n_chars")
    back = s.read.schema(docs.schema).parquet(f"{at}/by_lang").join(manifest.select("lang"), "lang", "left_semi")
    return tell("parquet", back).unionByName(tell("json", stores.read_json_lines(s, f"{at}/lines", docs.schema))).unionByName(tell("digests", s.read.parquet(f"{at}/digests")))


add("sink_roundtrip", roundtrip, "select sink, lang, count(*)::bigint as n, sum(length(text))::bigint as n_chars from documents, (values ('parquet'), ('json'), ('digests')) t(sink) group by sink, lang")


def surface(s, d):
    register(s)
    table(s, d, "documents").createOrReplaceTempView("corpusmill_documents")
    return s.sql("select doc_id, md5(mask_pii(text)) as masked, cast(token_count(text) as bigint) as n_tokens, cast(size(minhash_bands(text)) as bigint) as n_bands from corpusmill_documents")


_masked = "text"
for _kind, _p in transform.KINDS.items():
    _masked = f"regexp_replace({_masked}, '{_p}', '<{_kind}>', 'g')"
add("sql_surface_documents", surface, f"select doc_id, md5({_masked}) as masked, len({TOKENS})::bigint as n_tokens, case when len({TOKENS}) > 0 then 16 else 0 end::bigint as n_bands from documents")


def shingle_table(s, d):
    register(s)
    table(s, d, "benchmark").createOrReplaceTempView("corpusmill_benchmark")
    return s.sql("select b.item_id, count(*) as n, min(r.shingle) as least from corpusmill_benchmark b, lateral shingle_rows(b.text, 10) r group by b.item_id")


add("sql_surface_shingles", shingle_table, f"select item_id, count(*)::bigint as n, min(g) as least from (select item_id, unnest(list_transform(range(1, len(w) - 8), lambda i: array_to_string(w[i:i+9], ' '))) as g from (select item_id, {TOKENS} as w from benchmark)) group by item_id")
