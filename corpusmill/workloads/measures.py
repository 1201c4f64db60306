"""Accuracy and cost measures, schedules, packing by running sum, and published figures as rows."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpusmill.schema import TOKENS, table, tokens
from corpusmill.workloads.catalog import add, both

both("measure_macro_average", "select model, round(avg(cast(good as double) / n), 6) as macro, round(cast(sum(good) as double) / sum(n), 6) as micro from (select d.source as model, d.lang, sum(l.quality) as good, count(*) as n from {documents} d join {labels} l on d.doc_id = l.doc_id group by d.source, d.lang) q group by model")


def pass_at_k(s, d, k: int = 5):
    """Mean over problems of 1 - C(n-c, k) / C(n, k), as a product that cannot overflow."""
    rows = table(s, d, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("event_type") == "purchase").cast("long")).alias("c"))
    miss = F.when(F.col("n") - F.col("c") < k, 0.0).otherwise(F.aggregate(F.sequence(F.col("n") - F.col("c") + 1, F.col("n")), F.lit(1.0), lambda a, i: a * (1.0 - F.lit(float(k)) / i)))
    return rows.where(F.col("n") >= k).select("user_id", F.when(F.col("c") == 0, 0.0).otherwise(F.round(1 - miss, 6)).alias("pass_at_k"))


add(
    "measure_pass_at_k", pass_at_k,
    "with r as (select user_id, count(*) as n, sum((event_type = 'purchase')::int)::bigint as c from events group by user_id) select user_id, case when c = 0 then 0 when n - c < 5 then 1 else round(1 - list_product(list_transform(range(n - c + 1, n + 1), lambda i: 1 - 5.0::double / i)), 6) end::double as pass_at_k from r where n >= 5",
)
both("measure_win_rate", "select round(avg(case when c > v then 1.0 when c = v then 0.5 else 0.0 end), 6) as win_rate, count(*) as n from (select user_id, avg(case when event_type = 'click' then value end) as c, avg(case when event_type = 'view' then value end) as v from {events} group by user_id) q where c is not null and v is not null".replace("1.0", "cast(1 as double)").replace("0.5", "cast(0.5 as double)").replace("0.0", "cast(0 as double)"))
both("measure_rate_by_language", "select d.lang, round(avg(cast(l.quality as double)), 6) as rate, count(*) as n from {documents} d join {labels} l on d.doc_id = l.doc_id group by d.lang")
both("measure_gpu_hours", "select p_brand as model, cast(sum(cast(l_quantity as double) * p_size) as double) as gpu_hours from {lineitem} join {part} on l_partkey = p_partkey group by p_brand")
both("measure_curve_compare", "select a.step, round(a.v, 6) as a, round(b.v, 6) as b, round(a.v - b.v, 6) as diff from (select event_id % 100 as step, avg(value) as v from {events} where event_type = 'click' group by 1) a join (select event_id % 100 as step, avg(value) as v from {events} where event_type = 'view' group by 1) b on a.step = b.step")
STEPS = "(select cast(1000 * i as bigint) as step from (values {}) t(i))".format(", ".join(f"({i})" for i in range(0, 201, 5)))
both("schedule_tokens", f"select step, case when step <= 130000 then step * 2048 * 4096 else cast(130000 as bigint) * 2048 * 4096 + (step - 130000) * 1024 * 8192 end as tokens from {STEPS} q")
both("schedule_wsd", f"select step, round(case when step < 2000 then 0.0003 * step / 2000 when step <= 150000 then 0.0003 else 0.0003 * power(cast(0.00001 / 0.0003 as double), (step - 150000) / cast(50000 as double)) end, 9) as lr from {STEPS} q".replace("0.0003", "cast(0.0003 as double)").replace("0.00001", "cast(0.00001 as double)"))
both("schedule_cosine", f"select step, round(case when step < 5000 then cast(0.00002 as double) * step / 5000 else cast(0.00002 as double) * 0.5 * (1 + cos(pi() * (step - 5000) / cast(195000 as double))) end, 9) as lr from {STEPS} q")
both("schedule_epochs", "select model, round(cast(total as double) / pool, 4) as epochs from (values ('1.5b', 2000.0, 500.0), ('8b', 2500.0, 714.2857)) t(model, total, pool)")
add(
    "pack_sequences", lambda s, d: table(s, d, "documents").select((F.col("doc_id") % 16).alias("shard"), "doc_id", F.size(tokens(F.col("text"))).cast("long").alias("n")).selectExpr("shard", "doc_id", "n", "coalesce(sum(n) over (partition by shard order by doc_id rows between unbounded preceding and 1 preceding), 0) as at").selectExpr("shard", "doc_id", "cast(floor(at / 4096) as bigint) as bin", "at % 4096 as offset", "n"),
    f'''with t as (select doc_id % 16 as shard, doc_id, len({TOKENS})::bigint as n from documents), u as (select *, coalesce(sum(n) over (partition by shard order by doc_id rows between unbounded preceding and 1 preceding), 0)::bigint as "at" from t) select shard, doc_id, floor("at" / 4096)::bigint as bin, "at" % 4096 as "offset", n from u''',
)
add(
    "pipeline_funnel", lambda s, d: _funnel(s, d),
    "select 'all' as stage, count(*)::bigint as n from documents union all select 'exact', count(distinct sha256(text))::bigint from documents union all select 'with_notice', count(*)::bigint from documents where regexp_matches(text, '[Ll]icensed under|MIT License')",
)


def _funnel(s, d):
    docs = table(s, d, "documents")
    one = lambda n, df: df.agg(F.lit(n).alias("stage"), F.count(F.lit(1)).alias("n"))
    return one("all", docs).union(one("exact", docs.select(F.sha2("text", 256)).distinct())).union(one("with_notice", docs.where(F.col("text").rlike("[Ll]icensed under|MIT License"))))
