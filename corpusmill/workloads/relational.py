"""Relational surface: statements that either engine runs, and streams that end with a batch's answer."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from corpusmill.schema import table
from corpusmill.workloads.catalog import add, both

D = "cast({} as double)"
both("proj_price_case", "select l_orderkey, l_linenumber, cast(floor(l_extendedprice) as bigint) as net, case when l_quantity > 30 then 'big' else 'small' end as kind from {lineitem}")
both("filter_compound", "select l_orderkey, l_linenumber from {lineitem} where l_quantity between 10 and 20 and l_returnflag in ('A', 'R') and l_linestatus like 'F%'")
both("filter_null_safe", "select o_orderkey from {orders} where o_orderpriority is not distinct from '1-URGENT'")
both("join_broadcast_star", "select r_name, n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from {region} join {nation} on n_regionkey = r_regionkey join {customer} on c_nationkey = n_nationkey join {orders} on o_custkey = c_custkey join {lineitem} on l_orderkey = o_orderkey group by r_name, n_name")
both("join_smj_fact", "select o_orderpriority, count(*) as n, round(sum(l_quantity), 2) as qty from {orders} join {lineitem} on o_orderkey = l_orderkey group by o_orderpriority")
both("join_semi", "select c_custkey from {customer} where exists (select 1 from {orders} where o_custkey = c_custkey and o_totalprice > 200000)")
both("join_anti", "select c_custkey from {customer} where not exists (select 1 from {orders} where o_custkey = c_custkey)")
both("join_left_outer", "select c_custkey, count(o_orderkey) as n from {customer} left join {orders} on o_custkey = c_custkey group by c_custkey")
both("join_full_outer", "select coalesce(a.k, b.k) as nationkey, coalesce(a.n, 0) as n_customers, coalesce(b.n, 0) as n_suppliers from (select c_nationkey as k, count(*) as n from {customer} group by 1) a full join (select s_nationkey as k, count(*) as n from {supplier} group by 1) b on a.k = b.k")


#: Pairs that a task of the theta join lists about, and rows of a brand and size that stand in one run.
TASK_PAIRS, RUN_ROWS = 10_000_000, 1_000


def theta(s, d):
    """Pairs of parts of a brand, the second dearer, sizes at most one apart: brand and size deal the rows, each left one under the three sizes that it meets.

    Left and right rows are numbered together by price, so a left row knows how many right ones are not dearer. The right ones stand in runs of RUN_ROWS by
    number; a left row meets the run where its dearer ones begin and those behind it, and only pairs of the result are made. Tasks follow the count of pairs.
    """
    part = table(s, d, "part").select("p_partkey", "p_brand", "p_retailprice", "p_size").where("p_brand is not null and p_size is not null and p_retailprice is not null")
    group = ["p_brand", "p_size"]
    sizes = part.groupBy(group).agg(F.count(F.lit(1)).alias("n"))
    listed = 1.5 * (sizes.agg(F.sum(F.col("n").cast("double") * F.col("n"))).first()[0] or 0)  # half of the pairs of each group with itself and two others of its size
    tasks = min(max(s.sparkContext.defaultParallelism, int(listed / TASK_PAIRS) + 1), 100_000)
    left = part.select("p_partkey", "p_brand", "p_retailprice", F.explode(F.array(*(F.col("p_size") + k for k in (-1, 0, 1)))).alias("p_size"), F.lit(1).alias("side"))
    both_sides = part.select(*left.columns[:-1], F.lit(0).alias("side")).union(left)
    cheaper = F.count(F.when(F.col("side") == 0, 1)).over(Window.partitionBy(group).orderBy("p_retailprice", "side").rowsBetween(Window.unboundedPreceding, 0))
    numbered = both_sides.withColumn("before", cheaper - (1 - F.col("side")))  # right rows before a row; of one price they come first
    right = numbered.where("side = 0").select(*group, F.floor(F.col("before") / RUN_ROWS).alias("run"), F.struct("before", F.col("p_partkey").alias("b")).alias("x"))
    runs = right.groupBy(*group, "run").agg(F.array_sort(F.collect_list("x"))["b"].alias("held"))
    meets = numbered.where("side = 1").join(sizes, group).where("before < n").withColumn("first", F.floor(F.col("before") / RUN_ROWS))
    meets = meets.select(F.col("p_partkey").alias("a"), *group, "before", "first", F.explode(F.sequence("first", F.floor((F.col("n") - 1) / RUN_ROWS))).alias("run"))
    held = F.when(F.col("run") > F.col("first"), F.col("held")).otherwise(F.slice("held", (F.col("before") % RUN_ROWS + 1).cast("int"), F.lit(RUN_ROWS)))
    return meets.repartition(tasks, *group, "run").join(runs.hint("shuffle_hash"), [*group, "run"]).select("a", F.explode(held).alias("b"))


add("join_theta", theta, "select a.p_partkey as a, b.p_partkey as b from part a join part b on a.p_brand = b.p_brand and a.p_retailprice < b.p_retailprice and abs(a.p_size - b.p_size) < 2")
both("join_range_bins", "select b.name, count(*) as n from {lineitem} join (values ('low', 0, 10000), ('mid', 10000, 40000), ('high', 40000, 1000000)) b(name, lo, hi) on l_extendedprice >= b.lo and l_extendedprice < b.hi group by b.name")
both("join_asof_events", "select event_id, user_id, last_view from (select event_id, user_id, event_type, max(case when event_type = 'view' then ts end) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as last_view from {events}) q where event_type = 'purchase'")
both("join_interval_events", "select e.event_id, count(*) as n from {events} e join {events} c on e.user_id = c.user_id and c.event_type = 'click' and c.ts <= e.ts and c.ts >= e.ts - interval '1' hour where e.event_type = 'error' group by e.event_id")
both("join_lateral_topk", "select c_custkey, o_orderkey, o_totalprice from (select c_custkey, o_orderkey, o_totalprice, row_number() over (partition by c_custkey order by o_totalprice desc, o_orderkey) as r from {customer} join {orders} on o_custkey = c_custkey where c_mktsegment = 'BUILDING') q where r <= 3")
both("agg_pricing_summary", "select l_returnflag, l_linestatus, round(sum(l_quantity), 2) as qty, round(sum(l_extendedprice), 2) as base, round(sum(l_extendedprice * (1 - l_discount) * (1 + l_tax)), 2) as charge, round(avg(l_discount), 6) as disc, count(*) as n from {lineitem} group by l_returnflag, l_linestatus")
both("agg_distinct", "select count(distinct l_partkey) as parts, count(distinct l_suppkey) as supps from {lineitem}")
both("agg_grouping_sets", "select l_returnflag, l_linestatus, count(*) as n from {lineitem} group by grouping sets ((l_returnflag), (l_linestatus), ())")
both("agg_cube", "select lang, source, count(*) as n from {documents} group by cube (lang, source)")
both("agg_rollup", "select year(o_orderdate) as y, month(o_orderdate) as m, round(sum(o_totalprice), 2) as total from {orders} group by rollup (year(o_orderdate), month(o_orderdate))")
both("agg_filtered", "select user_id, count(*) filter (where event_type = 'click') as clicks, count(*) filter (where event_type = 'purchase') as purchases from {events} group by user_id")
both("agg_pivot", "select user_id, sum(case when event_type = 'click' then 1 else 0 end) as click, sum(case when event_type = 'view' then 1 else 0 end) as view, sum(case when event_type = 'error' then 1 else 0 end) as error from {events} group by user_id".replace("sum(case", "count(case").replace("else 0 ", ""))
both("agg_max_by", "select o_custkey, max_by(o_orderkey, o_totalprice) as best from {orders} group by o_custkey")
both("agg_percentile", "select l_returnflag, round(median(l_extendedprice), 4) as med from {lineitem} group by l_returnflag")
both("win_rank_family", "select o_orderkey, rank() over (partition by o_orderpriority order by o_totalprice desc) as r, dense_rank() over (partition by o_orderpriority order by o_totalprice desc) as dr from {orders}".replace(" as r,", " as r,"))
both("win_running_sum", "select o_orderkey, round(sum(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows unbounded preceding), 2) as run from {orders}")
both("win_moving_rows", "select event_id, round(avg(value) over (partition by user_id order by ts, event_id rows between 3 preceding and current row), 6) as v from {events}")
both("win_range_interval", "select event_id, count(*) over (partition by user_id order by ts range between interval '24' hour preceding and current row) as n from {events}")
both("win_lag_lead", "select event_id, lag(event_type) over (partition by user_id order by ts, event_id) as prev, lead(event_type) over (partition by user_id order by ts, event_id) as next from {events}")
both("win_ntile", "select c_custkey, ntile(4) over (order by c_acctbal, c_custkey) as q from {customer}")
both("topk_global", "select o_orderkey, o_totalprice from {orders} order by o_totalprice desc, o_orderkey limit 25")
both("topk_per_group", "select lang, doc_id from (select lang, doc_id, row_number() over (partition by lang order by n_chars desc, doc_id) as r from {documents}) q where r <= 5")
both("set_union", "select c_nationkey as k from {customer} union select s_nationkey from {supplier}")
both("set_intersect", "select c_custkey as k from {customer} intersect select s_suppkey from {supplier}")
both("set_except", "select c_custkey as k from {customer} except select o_custkey from {orders}")
both("set_except_all", "select c_nationkey as k from {customer} except all select s_nationkey from {supplier}")
both("fn_string_pack", "select p_partkey, upper(p_name) as u, substring(p_name, 1, 4) as s, lpad(cast(p_size as varchar(10)), 4, '0') as l, concat_ws('-', p_brand, p_type) as c from {part}")
both("fn_levenshtein", "select p_partkey, levenshtein(p_name, p_type) as d from {part}")
both("fn_math_pack", "select l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) as a, round(power(l_discount, 2), 6) as b, greatest(l_tax, l_discount) as c from {lineitem}")
both("sub_scalar", "select o_orderkey from {orders} where o_totalprice > (select avg(o_totalprice) * 2 from {orders})")
both("sub_exists", "select o_orderkey from {orders} o where exists (select 1 from {lineitem} l where l.l_orderkey = o.o_orderkey and l.l_quantity > 45)")
both("fn_date_pack", "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, day(o_orderdate) as d from {orders}")
add("fn_json_props", lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")), "select event_id, (json_extract_string(props, '$.k'))::bigint as k from events")
add("vec_centroids", lambda s, d: table(s, d, "embeddings").select("label", F.posexplode("embedding").alias("dim", "x")).groupBy("label", "dim").agg(F.round(F.avg(F.col("x").cast("double")), 4).alias("m")), "select label, dim::int as dim, round(avg(x), 4) as m from (select label, unnest(range(64)) as dim, unnest(embedding)::double as x from embeddings) group by label, dim")
add("scan_parquet_projection", lambda s, d: table(s, d, "documents").where("lang = 'fr'").select("doc_id", "n_chars"), "select doc_id, n_chars from documents where lang = 'fr'")


def streamed(spark, sf_dir, make):
    """Run a stream over a copy of events to its end and return what it wrote."""
    from corpusmill.plans.durable import shared_folder
    import uuid

    at = f"{shared_folder(spark).rstrip('/')}/corpusmill-stream-{uuid.uuid4().hex}"
    events = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    events.write.parquet(f"{at}/in")
    source = spark.readStream.schema(events.schema).parquet(f"{at}/in")
    run = make(source).writeStream.format("parquet").option("checkpointLocation", f"{at}/state").option("path", f"{at}/out").outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.parquet(f"{at}/out")


add("stream_dedup_exact", lambda s, d: streamed(s, d, lambda e: e.withWatermark("ts", "365 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")), "select distinct user_id, event_type from events")
