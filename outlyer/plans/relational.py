"""Relational operators around the methods, on the given tables: each a DataFrame plan with its DuckDB twin."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rng import bottom_k as bottom_k_rows
from ..functions.rng import u01, u01_sql
from ..sources.planted import load as T

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


@query("select l_quantity, l_extendedprice, l_discount, l_tax from lineitem where l_quantity >= 45")
def scan_pruned(s, d) -> DataFrame:
    return T(s, d, "lineitem").where("l_quantity >= 45").select("l_quantity", "l_extendedprice", "l_discount", "l_tax")


@query("select l_orderkey, l_linenumber, l_extendedprice * (1 - l_discount) as net, l_extendedprice / l_quantity as unit from lineitem")
def feature_projection(s, d):
    return T(s, d, "lineitem").select("l_orderkey", "l_linenumber", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("net"), (F.col("l_extendedprice") / F.col("l_quantity")).alias("unit"))


@query("select o_orderkey, case when o_totalprice > 250000 then 'high' when o_totalprice > 100000 then 'mid' else 'low' end as band from orders where o_orderstatus in ('F', 'O') and o_orderpriority like '%-%' and o_totalprice between 50000 and 450000")
def predicate_mix(s, d):
    p = F.col("o_totalprice")
    return T(s, d, "orders").where(F.col("o_orderstatus").isin("F", "O") & F.col("o_orderpriority").like("%-%") & p.between(50000, 450000)).select("o_orderkey", F.when(p > 250000, "high").when(p > 100000, "mid").otherwise("low").alias("band"))


@query(f"select event_id, event_type from events where {u01_sql('sample', 'event_id')} < 0.1")
def hash_sample(s, d):
    return T(s, d, "events").where(u01("sample", "event_id") < 0.1).select("event_id", "event_type")


@query(f"select event_id, event_type from events where {u01_sql('sample', 'event_id')} < case event_type when 'purchase' then 0.5 else 0.05 end")
def stratified_sample(s, d):
    return T(s, d, "events").where(u01("sample", "event_id") < F.when(F.col("event_type") == "purchase", 0.5).otherwise(0.05)).select("event_id", "event_type")


@query(f"select event_id, event_type from (select *, row_number() over (partition by event_type order by {u01_sql('bk', 'event_type', 'event_id')}, event_id) as r from events) where r <= 7")
def bottom_k(s, d):
    return bottom_k_rows(T(s, d, "events").select("event_id", "event_type"), 7, "bk", "event_id", ["event_type"])


@query("select o_orderpriority, count(*) as n, round(sum(l_quantity), 2) as q from lineitem join orders on l_orderkey = o_orderkey group by 1")
def join_smj(s, d):
    j = T(s, d, "lineitem").select("l_orderkey", "l_quantity").hint("merge").join(T(s, d, "orders").select("o_orderkey", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


@query("select c_mktsegment, count(*) as n from orders join customer on o_custkey = c_custkey group by 1")
def join_shj(s, d):
    return T(s, d, "orders").select("o_custkey").join(T(s, d, "customer").select("c_custkey", "c_mktsegment").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("select r_name, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1")
def join_bhj(s, d):
    n = T(s, d, "nation").join(F.broadcast(T(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 rows
    return T(s, d, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@query("select coalesce(a.c_custkey, b.o_custkey) as k, a.c_acctbal as bal, b.n as n from (select * from customer where c_acctbal < 2000) a full join (select o_custkey, count(*) as n from orders where o_totalprice > 300000 group by 1) b on a.c_custkey = b.o_custkey")
def join_full_scores(s, d):
    a = T(s, d, "customer").where("c_acctbal < 2000").select("c_custkey", "c_acctbal")
    b = T(s, d, "orders").where("o_totalprice > 300000").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    return a.join(b, F.col("c_custkey") == F.col("o_custkey"), "full").select(F.coalesce("c_custkey", "o_custkey").alias("k"), F.col("c_acctbal").alias("bal"), "n")


@query("select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 490000)")
def join_semi(s, d):
    return T(s, d, "customer").select("c_custkey").join(T(s, d, "orders").where("o_totalprice > 490000").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi")


@query("select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)")
def join_anti(s, d):
    return T(s, d, "customer").select("c_custkey").join(T(s, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


@query("select e.event_id, p.ts as last_purchase from (select * from events where event_type <> 'purchase') e asof left join (select user_id, ts from events where event_type = 'purchase') p on e.user_id = p.user_id and e.ts >= p.ts")
def join_asof(s, d):
    e = T(s, d, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    e = e.withColumn("last_purchase", F.max(F.when(F.col("event_type") == "purchase", F.col("ts"))).over(w))
    return e.where("event_type <> 'purchase'").select("event_id", "last_purchase")


@query("select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_id < b.event_id and b.ts <= a.ts + interval 1 hour")
def join_interval(s, d):
    """Rows meet in buckets of an hour: an equi-join on (user, bucket), then the exact condition."""
    e = T(s, d, "events").select("event_id", "user_id", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("t"), "ts")
    b = F.floor(F.col("t") / 3600)
    left = e.select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"), F.explode(F.array(b, b + 1)).alias("h"))
    right = e.select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"), b.alias("h"))
    return left.join(right, ["user_id", "h"]).where((F.col("a") < F.col("b")) & (F.col("tb") <= F.col("ta") + F.expr("interval 1 hour"))).select("a", "b")


@query("select c.k as centre, count(*) as n, round(sum(value), 4) as total from (select unnest([2, 4, 6, 8]) * 100 as k) c join events on event_id between c.k - 150 and c.k + 150 group by 1")
def join_range(s, d):
    """A few centres: each row computes which it is near, no theta join."""
    near = F.filter(F.array(*[F.lit(k) for k in (200, 400, 600, 800)]), lambda k: F.abs(F.col("event_id") - k) <= 150)
    return T(s, d, "events").select(F.explode(near).alias("centre"), "value").groupBy("centre").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))


@query("select user_id, event_id, value from (select *, row_number() over (partition by user_id order by value desc, event_id) as r from events) where r = 1")
def lateral_topk(s, d):
    return T(s, d, "events").groupBy("user_id").agg(F.max_by(F.struct("event_id", "value"), F.struct("value", -F.col("event_id"))).alias("m")).select("user_id", "m.event_id", "m.value")


@query("select o_orderkey from orders o where o_totalprice > (select 1.9 * avg(o_totalprice) from orders)")
def scalar_subquery(s, d):
    o = T(s, d, "orders").select("o_orderkey", "o_totalprice")
    return o.crossJoin(F.broadcast(o.agg((1.9 * F.avg("o_totalprice")).alias("m")))).where("o_totalprice > m").select("o_orderkey")


@query("select event_type, count(*) as n, round(sum(value), 3) as total, round(avg(value), 6) as mean, round(stddev(value), 6) as sd from events group by 1")
def agg_basic(s, d):
    return T(s, d, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 3).alias("total"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev("value"), 6).alias("sd"))


@query("select n_regionkey, string_agg(n_name, ',' order by n_name) as names from nation group by 1")
def agg_collect(s, d):
    return T(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("names"))


@query("select cast(ts as date) as day, count(distinct user_id) as users, count(distinct event_type) as types from events group by 1")
def agg_distinct(s, d):
    return T(s, d, "events").groupBy(F.to_date("ts").alias("day")).agg(F.countDistinct("user_id").alias("users"), F.countDistinct("event_type").alias("types"))


@query()
def agg_approx(s, d):
    return T(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("median"))


@query("select event_type, round(quantile_cont(value, 0.5), 6) as median, round(quantile_cont(value, 0.75) - quantile_cont(value, 0.25), 6) as iqr from events group by 1")
def agg_percentile(s, d):
    p = lambda q: F.percentile("value", F.lit(q))
    return T(s, d, "events").groupBy("event_type").agg(F.round(p(0.5), 6).alias("median"), F.round(p(0.75) - p(0.25), 6).alias("iqr"))


@query("select o_orderstatus, arg_min(o_orderkey, o_totalprice) as cheapest, count(*) filter (o_totalprice > 300000) as high, bool_or(o_totalprice > 499000) as huge from orders group by 1")
def agg_argmin(s, d):
    p = F.col("o_totalprice")
    return T(s, d, "orders").groupBy("o_orderstatus").agg(F.min_by("o_orderkey", p).alias("cheapest"), F.count_if(p > 300000).alias("high"), F.bool_or(p > 499000).alias("huge"))


@query("select least(99, floor(value / 5))::bigint as bin, count(*) as n from events group by 1")
def agg_histogram(s, d):
    return T(s, d, "events").groupBy(F.least(F.lit(99), F.floor(F.col("value") / 5)).alias("bin")).agg(F.count(F.lit(1)).alias("n"))


@query("select o_orderstatus, o_orderpriority, count(*) as n from orders group by cube(o_orderstatus, o_orderpriority)")
def agg_cube(s, d):
    return T(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("select o_orderstatus, o_orderpriority, count(*) as n from orders group by rollup(o_orderstatus, o_orderpriority)")
def agg_rollup(s, d):
    return T(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority))")
def agg_gsets(s, d):
    return T(s, d, "orders").groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("select lang, count(*) filter (toxic = 0) as clean, count(*) filter (toxic = 1) as toxic from documents join labels using (doc_id) group by 1")
def pivot_confusion(s, d):
    return T(s, d, "documents").select("doc_id", "lang").join(T(s, d, "labels"), "doc_id").groupBy("lang").pivot("toxic", [0, 1]).count().select("lang", F.coalesce("0", F.lit(0)).alias("clean"), F.coalesce("1", F.lit(0)).alias("toxic"))


@query("select p_partkey, 'size' as feature, p_size::double as v from part union all select p_partkey, 'price', p_retailprice from part")
def unpivot_features(s, d):
    return T(s, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "feature", "v")


@query("select lang, source, count(*) as n from documents group by 1, 2 having count(*) >= 10")
def agg_having(s, d):
    return T(s, d, "documents").groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n")).where("n >= 10")


@query("select c_custkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, round(percent_rank() over w, 9) as pr, round(cume_dist() over w, 9) as cd, ntile(4) over (partition by c_nationkey order by round(c_acctbal, -3), c_custkey) as nt from customer window w as (partition by c_nationkey order by round(c_acctbal, -3), c_custkey)")
def win_rank(s, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.round("c_acctbal", -3), "c_custkey")
    return T(s, d, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.ntile(4).over(w).alias("nt"))


@query("select event_id, lag(value) over w as before, lead(value) over w as after, first_value(event_id) over w as first_id from events window w as (partition by user_id order by ts, event_id)")
def win_analytic(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return T(s, d, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"), F.first("event_id").over(w).alias("first_id"))


@query("select event_id, round(avg(value) over w, 6) as mean, count(*) over w as n from events window w as (partition by user_id order by ts, event_id rows between 9 preceding and current row)")
def win_rows(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-9, 0)
    return T(s, d, "events").select("event_id", F.round(F.avg("value").over(w), 6).alias("mean"), F.count(F.lit(1)).over(w).alias("n"))


@query("select event_id, round((value - avg(value) over w) / nullif(stddev(value) over w, 0), 5) as z from events window w as (partition by user_id order by ts, event_id rows between 20 preceding and 1 preceding)")
def rolling_zscore(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-20, -1)
    return T(s, d, "events").select("event_id", F.round((F.col("value") - F.avg("value").over(w)) / F.nullif(F.stddev("value").over(w), F.lit(0.0)), 5).alias("z"))


@query("select event_id, round(sum(value) over (partition by user_id order by ts range between interval 24 hours preceding and current row), 4) as day_sum from events")
def win_range(s, d):
    e = T(s, d, "events").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))  # whole seconds would move rows over the ends of a range
    return e.select("event_id", F.round(F.sum("value").over(Window.partitionBy("user_id").orderBy("t").rangeBetween(-86_400_000_000, 0)), 4).alias("day_sum"))


@query("with g as (select *, case when ts - lag(ts) over w > interval 1 hour then 1 else 0 end as new from events window w as (partition by user_id order by ts, event_id)), n as (select *, sum(new) over (partition by user_id order by ts, event_id) as session from g) select user_id, session::bigint as session, count(*) as n, round(sum(value), 4) as total from n group by 1, 2")
def win_sessions(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = T(s, d, "events").withColumn("new", F.coalesce((F.col("ts") > F.lag("ts").over(w) + F.expr("interval 1 hour")).cast("int"), F.lit(0)))
    return e.withColumn("session", F.sum("new").over(w)).groupBy("user_id", "session").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))


@query("select event_id, ts from events order by ts, event_id")
def sort_replay(s, d):
    return T(s, d, "events").select("event_id", "ts").orderBy("ts", "event_id")


@query("select event_id, value from events order by value desc, event_id limit 20")
def topk_global(s, d):
    return T(s, d, "events").select("event_id", "value").orderBy(F.desc("value"), "event_id").limit(20)


@query("select event_type, event_id, value from (select *, row_number() over (partition by event_type order by value desc, event_id) as r from events) where r <= 3")
def topk_group(s, d):
    w = Window.partitionBy("event_type").orderBy(F.desc("value"), "event_id")
    return T(s, d, "events").withColumn("r", F.row_number().over(w)).where("r <= 3").select("event_type", "event_id", "value")


@query("select c_nationkey as k from customer union select s_nationkey from supplier")
def set_union(s, d):
    return T(s, d, "customer").select(F.col("c_nationkey").alias("k")).union(T(s, d, "supplier").select("s_nationkey")).distinct()


@query("select user_id as k from events where value > 200 intersect select user_id from events where event_type = 'purchase'")
def set_intersect(s, d):
    e = T(s, d, "events")
    return e.where("value > 200").select(F.col("user_id").alias("k")).intersect(e.where("event_type = 'purchase'").select("user_id"))


@query("select user_id as k from events except select user_id from events where value > 200")
def set_except(s, d):
    e = T(s, d, "events")
    return e.select(F.col("user_id").alias("k")).subtract(e.where("value > 200").select("user_id"))


@query("select doc_id, length(text) as n, lower(substr(text, 1, 5)) as head, replace(source, 'src', '') as src, text like '%the%' as has from documents")
def fn_string(s, d):
    return T(s, d, "documents").select("doc_id", F.length("text").cast("long").alias("n"), F.lower(F.substring("text", 1, 5)).alias("head"), F.replace("source", F.lit("src"), F.lit("")).alias("src"), F.contains("text", F.lit("the")).alias("has"))


@query("select event_id, extract(hour from ts)::int as h, date_trunc('day', ts)::date as day, datediff('day', date '2024-01-01', ts::date)::int as dd from events")
def fn_date(s, d):
    return T(s, d, "events").select("event_id", F.hour("ts").alias("h"), F.to_date("ts").alias("day"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).alias("dd"))


@query("select event_id, round(exp(-value / 50), 6) as e, round(ln(value + 1), 6) as l, round(sqrt(value), 6) as r, floor(value)::bigint as f, greatest(value, 50) as g, round(atan2(value, 10), 6) as a from events")
def fn_math(s, d):
    v = F.col("value")
    return T(s, d, "events").select("event_id", F.round(F.exp(-v / 50), 6).alias("e"), F.round(F.log(v + 1), 6).alias("l"), F.round(F.sqrt(v), 6).alias("r"), F.floor(v).alias("f"), F.greatest(v, F.lit(50.0)).alias("g"), F.round(F.atan2(v, F.lit(10.0)), 6).alias("a"))


@query("select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 4) as norm2, len(list_filter(embedding, lambda x: x > 0)) as n_pos from embeddings")
def fn_array(s, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return T(s, d, "embeddings").select("vec_id", F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x * x), 4).alias("norm2"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("n_pos"))


@query("select event_id, cast(json_extract(props, '$.k') as int) as k from events")
def fn_json(s, d):
    return T(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))


@query("select o_orderkey, md5(o_orderkey::varchar) as h from orders")
def fn_hash(s, d):
    return T(s, d, "orders").select("o_orderkey", F.md5(F.col("o_orderkey").cast("string").cast("binary")).alias("h"))


@query("select event_id, coalesce(nullif(event_type, 'view'), 'none') as t, try_cast(props as int) as bad from events")
def fn_null(s, d):
    return T(s, d, "events").select("event_id", F.coalesce(F.nullif("event_type", F.lit("view")), F.lit("none")).alias("t"), F.col("props").try_cast("int").alias("bad"))


@query("select date_trunc('day', ts) as day, event_type, count(*) as n from events group by 1, 2")
def tumbling_counts(s, d):
    return T(s, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("day"), "event_type", "n")


@query("select st, count(*) as n from (select unnest([date_trunc('hour', ts), date_trunc('hour', ts) - interval 1 hour]) as st from events) group by 1")
def sliding_counts(s, d):
    return T(s, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "2 hours", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("st"), "n")


@query("with h as (select date_trunc('hour', ts) as hr, count(*) as n from events group by 1) select hr, list(n) over (order by hr rows between 47 preceding and current row) as shingle from h qualify row_number() over (order by hr) >= 48")
def shingle_48(s, d):
    h = T(s, d, "events").groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hr")).agg(F.count(F.lit(1)).alias("n"))
    w = Window.orderBy("hr").rowsBetween(-47, 0)  # one row an hour: 8,760 a year
    return h.select("hr", F.collect_list("n").over(w).alias("shingle")).where(F.size("shingle") == 48)


_NODES = "with recursive c as (select 1 as node, 0 as depth union all select node * 2 + b, depth + 1 from c, (values (0), (1)) t(b) where depth < 5)"


@query(f"{_NODES}, leaf as (select (o_custkey % 32)::int + 32 as leaf, count(*) as n from orders group by 1) select node, depth, sum(n)::bigint as n from c join leaf on leaf >> (5 - depth) = node group by 1, 2")
def node_paths(s, d):
    """Nodes of a binary tree of depth five by recursion, each with the ``orders`` rows under it; a row's leaf is the last bits of its customer."""
    leaf = T(s, d, "orders").groupBy(((F.col("o_custkey") % 32).cast("int") + 32).alias("leaf")).agg(F.count(F.lit(1)).alias("n"))
    return s.sql(_NODES + " select node, depth, sum(n) as n from c join {leaf} on shiftright(leaf, 5 - depth) = node group by node, depth", leaf=leaf)


@query("select o_orderkey from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_quantity = 50)")
def exists_filter(s, d):
    """A correlated EXISTS, which Catalyst rewrites to a semi join."""
    big = T(s, d, "lineitem").where((F.col("l_orderkey") == F.col("o_orderkey").outer()) & (F.col("l_quantity") == 50))
    return T(s, d, "orders").where(big.exists()).select("o_orderkey")


_SEEDS = f"select vec_id as seed, embedding as c from embeddings order by {u01_sql('seed', 'vec_id')}, vec_id limit 8"


@query(f"with s as ({_SEEDS}), m as (select e.vec_id, s.seed, round(list_sum(list_transform(list_zip(e.embedding, s.c), lambda z: pow(z[1]::double - z[2]::double, 2))), 6) as d2 from embeddings e, s) select vec_id, arg_min(seed, (d2, seed)) as seed, min(d2) as d2 from m group by 1")
def join_nearest_seed(s, d):
    """Every vector with the nearest of 8 drawn seeds: the seeds are one broadcast row, so the join is a map."""
    e = T(s, d, "embeddings").select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("e"))
    seeds = e.orderBy(u01("seed", "vec_id"), "vec_id").limit(8).agg(F.collect_list(F.struct(F.col("vec_id").alias("seed"), F.col("e").alias("c"))).alias("seeds"))
    far = lambda c: F.round(F.aggregate(F.zip_with("e", c, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda a, v: a + v), 6)
    best = F.array_min(F.transform("seeds", lambda z: F.struct(far(z["c"]).alias("d2"), z["seed"].alias("seed"))))
    return e.crossJoin(F.broadcast(seeds)).select("vec_id", best.alias("m")).select("vec_id", "m.seed", "m.d2")


@query("with g as (select *, case when ts <= lag(ts) over w + interval 1 hour then 0 else 1 end as fresh from events window w as (partition by user_id order by ts, event_id)), k as (select *, sum(fresh) over (partition by user_id order by ts, event_id) as part from g) select user_id, min(ts) as st, count(*) as n from k group by user_id, part")
def session_counts(s, d):
    return T(s, d, "events").groupBy("user_id", F.session_window(F.col("ts").cast("timestamp"), "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("st"), "n")


@query("with g as (select user_id, event_type, count(*) as n from events group by 1, 2) select user_id, coalesce(sum(n) filter (event_type = 'purchase'), 0)::bigint as purchases, (count(*) filter (n > 1))::int as repeated from g group by 1")
def fn_map(s, d):
    g = T(s, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = g.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("purchase")), F.lit(0).cast("long")).alias("purchases"), F.size(F.map_filter("m", lambda k, v: v > 1)).alias("repeated"))


@query("select p_partkey, p_retailprice, p_size from part")
def roundtrip_csv(s, d):
    """A point set through CSV text and back."""
    line = F.to_csv(F.struct("p_partkey", "p_retailprice", "p_size"))
    return T(s, d, "part").select(F.from_csv(line, "p_partkey bigint, p_retailprice double, p_size int").alias("r")).select("r.*")


@query("with q as (select event_type, quantile_cont(value, 0.95) as t from events group by 1) select event_id, (value >= t)::int as flagged from events join q using (event_type)")
def top_fraction(s, d):
    """Flags the top 5 % of each type: the cut is one exact percentile a type."""
    e = T(s, d, "events").select("event_id", "event_type", "value")
    cut = e.groupBy("event_type").agg(F.percentile("value", F.lit(0.95)).alias("t"))
    return e.join(F.broadcast(cut), "event_type").select("event_id", (F.col("value") >= F.col("t")).cast("int").alias("flagged"))


@query("select event_id, value from events where value > 150 and event_type <> 'view'")
def flagged(s, d):
    return T(s, d, "events").where("value > 150 and event_type <> 'view'").select("event_id", "value")


@query("select l_orderkey, round(case when n <= 1 then 0 when n = 2 then 1 else 2 * (ln(n - 1) + 0.5772156649015329) - 2.0 * (n - 1) / n end, 6) as c from (select l_orderkey, count(*) as n from lineitem group by 1)")
def sql_functions(s, d):
    """The average search depth as a registered SQL function: Catalyst inlines it."""
    s.sql("create or replace temporary function c_iso(n bigint) returns double return case when n <= 1 then 0D when n = 2 then 1D else 2 * (ln(n - 1) + 0.5772156649015329D) - 2D * (n - 1) / n end")
    return T(s, d, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n")).select("l_orderkey", F.round(F.expr("c_iso(n)"), 6).alias("c"))


@query("select p_partkey, round(abs(sqrt(pow(p_size, 2) + pow(p_retailprice / 100, 2)) - 20), 6) as delta from part")
def udf_scalar(s, d):
    """Residual to a circle by a vectorised Arrow function."""
    rim = F.pandas_udf(lambda x, y: ((x**2 + y**2) ** 0.5 - 20).abs(), "double")
    return T(s, d, "part").select("p_partkey", F.round(rim(F.col("p_size").cast("double"), F.col("p_retailprice") / 100), 6).alias("delta"))


_CELLS = "g as (select p_partkey % 40 as gx, p_partkey // 40 as gy from part), w as (select unnest([gx // 5, gx // 5 - 1]) as wx, gx, gy from g), v as (select wx, unnest([gy // 5, gy // 5 - 1]) as wy from w)"


@query(f"with {_CELLS} select wx, wy, count(*) as n from v where wx >= 0 and wy >= 0 group by 1, 2")
def window_assign(s, d):
    """Lattice cells in half-overlapping windows of side 10: at most four copies of a cell."""
    g = T(s, d, "part").select(F.pmod("p_partkey", F.lit(40)).alias("gx"), F.floor(F.col("p_partkey") / 40).alias("gy"))
    at = lambda c: F.explode(F.array(F.floor(F.col(c) / 5), F.floor(F.col(c) / 5) - 1))
    return g.select(at("gx").alias("wx"), "gy").select("wx", at("gy").alias("wy")).where("wx >= 0 and wy >= 0").groupBy("wx", "wy").agg(F.count(F.lit(1)).alias("n"))


@query(f"with {_CELLS} select wx, wy, count(*) as n from v where wx >= 0 and wy >= 0 group by 1, 2")
def udtf_windows(s, d):
    """The same windows by a table function called from SQL."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="wx bigint, wy bigint")
    class Windows:
        def eval(self, gx: int, gy: int):
            for x in (gx // 5, gx // 5 - 1):
                for y in (gy // 5, gy // 5 - 1):
                    if x >= 0 and y >= 0:
                        yield x, y

    s.udtf.register("assign_windows", Windows)
    cells = T(s, d, "part").select(F.pmod("p_partkey", F.lit(40)).alias("gx"), F.floor(F.col("p_partkey") / 40).alias("gy"))
    return s.sql("select wx, wy, count(*) as n from {cells} c, lateral assign_windows(c.gx, c.gy) group by wx, wy", cells=cells)
