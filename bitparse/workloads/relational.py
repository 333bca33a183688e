"""The operators around the methods, on the star schema."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from bitparse.workloads.tables import read

QUERIES, ORACLE_SQL = {}, {}


def add(name, sql, query):
    QUERIES[name], ORACLE_SQL[name] = query, sql


add(
    "join_hash_revenue", "select n_name, count(*) as n, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey group by n_name",
    lambda s, d: read(s, d, "lineitem").join(read(s, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(read(s, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue")),
)
add(
    "join_merge_orders", "select c_mktsegment, count(*) as n, count(distinct o_custkey) as customers from orders join customer on o_custkey = c_custkey group by c_mktsegment",
    lambda s, d: read(s, d, "orders").join(read(s, d, "customer").hint("merge"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.countDistinct("o_custkey").alias("customers")),
)
add("semi_join", "select c_custkey, c_mktsegment from customer where exists (select 1 from orders where o_custkey = c_custkey and o_orderstatus = 'P')", lambda s, d: read(s, d, "customer").join(read(s, d, "orders").filter("o_orderstatus = 'P'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey", "c_mktsegment"))
add("anti_join", "select c_custkey, c_mktsegment from customer where not exists (select 1 from orders where o_custkey = c_custkey)", lambda s, d: read(s, d, "customer").join(read(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey", "c_mktsegment"))


def _asof(s, d):
    """Each order with the latest event of the user of the same number up to then: one sort, no range join."""
    orders = read(s, d, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("t"), F.lit(1).alias("side"), "o_orderkey", F.lit(None).cast("long").alias("event_id"))
    events = read(s, d, "events").select(F.col("user_id").alias("k"), F.col("ts").alias("t"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("o_orderkey"), "event_id")
    seen = F.last("event_id", ignorenulls=True).over(Window.partitionBy("k").orderBy("t", "side").rowsBetween(Window.unboundedPreceding, 0))
    return orders.unionByName(events).withColumn("event_id", seen).filter("side = 1").select("o_orderkey", "event_id")


add("asof_order_event", "select o_orderkey, (select max_by(event_id, ts) from events where user_id = o_custkey and ts <= o_orderdate) as event_id from orders", _asof)


def _range(s, d):
    """Lineitems by bands of quantity: a band spans bins, so the join is on bins and then exact."""
    bands = s.createDataFrame([(k, 7.0 * k, 7.0 * k + 9.0) for k in range(8)], "band int, lo double, hi double")
    binned = bands.select("band", "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") / 5), F.floor(F.col("hi") / 5))).alias("bin"))
    rows = read(s, d, "lineitem").select("l_quantity", F.floor(F.col("l_quantity") / 5).alias("bin"))
    return rows.join(F.broadcast(binned), "bin").filter(F.col("l_quantity").between(F.col("lo"), F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


add("range_join_bands", "select b::int as band, count(*) as n from lineitem join range(0, 8) t(b) on l_quantity between 7.0 * b and 7.0 * b + 9.0 group by b", _range)
add("union_all", "select l_partkey as k from lineitem union all select p_partkey from part", lambda s, d: read(s, d, "lineitem").select(F.col("l_partkey").alias("k")).unionAll(read(s, d, "part").select("p_partkey")))
add("intersect_keys", "select o_custkey as k from orders intersect select user_id from events", lambda s, d: read(s, d, "orders").select(F.col("o_custkey").alias("k")).intersect(read(s, d, "events").select("user_id")))
add("except_keys", "select c_custkey as k from customer except select o_custkey from orders", lambda s, d: read(s, d, "customer").select(F.col("c_custkey").alias("k")).exceptAll(read(s, d, "orders").select("o_custkey").distinct()))


def _dearest():
    return Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")


add(
    "ranking_orders", "select o_orderkey, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt, round(percent_rank() over w, 6) as pr, lag(o_orderkey) over w as prev, nth_value(o_orderkey, 2) over (partition by o_custkey order by o_totalprice desc, o_orderkey rows between unbounded preceding and unbounded following) as second from orders window w as (partition by o_custkey order by o_totalprice desc, o_orderkey)",
    lambda s, d: read(s, d, "orders").select("o_orderkey", F.rank().over(_dearest()).cast("long").alias("rk"), F.dense_rank().over(_dearest()).cast("long").alias("dr"), F.ntile(4).over(_dearest()).cast("long").alias("nt"), F.round(F.percent_rank().over(_dearest()), 6).alias("pr"), F.lag("o_orderkey").over(_dearest()).alias("prev"), F.nth_value("o_orderkey", 2).over(_dearest().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second")),
)
add("topk_per_customer", "select o_custkey, o_orderkey from orders qualify row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) <= 3", lambda s, d: read(s, d, "orders").withColumn("r", F.row_number().over(_dearest())).filter("r <= 3").select("o_custkey", "o_orderkey"))
add("topk_parts", "select p_partkey, p_retailprice from part order by p_retailprice desc, p_partkey limit 10", lambda s, d: read(s, d, "part").select("p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").limit(10))
add(
    "window_frames", "select event_id, count(*) over (partition by user_id order by ts rows between 4 preceding and current row) as last5, round(sum(value) over (partition by user_id order by ts, event_id rows unbounded preceding), 4) as running from events",
    lambda s, d: read(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("ts").rowsBetween(-4, 0)).alias("last5"), F.round(F.sum("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running")),
)
_GROUPED = "count(*) as n, sum(n_chars)::bigint as chars from documents group by"
_grouped = lambda df: df.agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))
add("cube_documents", f"select lang, source, {_GROUPED} cube (lang, source)", lambda s, d: _grouped(read(s, d, "documents").cube("lang", "source")))
add("rollup_documents", f"select lang, source, {_GROUPED} rollup (lang, source)", lambda s, d: _grouped(read(s, d, "documents").rollup("lang", "source")))
add("grouping_sets_documents", f"select lang, source, {_GROUPED} grouping sets ((lang), (source))", lambda s, d: _grouped(read(s, d, "documents").groupingSets([[F.col("lang")], [F.col("source")]], "lang", "source")))
add("pivot_events", "select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'view') as view from events group by user_id", lambda s, d: read(s, d, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("click"), F.count_if(F.col("event_type") == "view").alias("view")))
add(
    "strings", "select p_partkey, upper(p_name) as up, reverse(p_name) as rev, replace(p_name, ' ', '') as tight, length(p_name)::int as n, levenshtein(p_name, p_type)::int as lev, substr(p_type, 1, 4) as pre, translate(p_brand, '#', '-') as br from part",
    lambda s, d: read(s, d, "part").select("p_partkey", F.upper("p_name").alias("up"), F.reverse("p_name").alias("rev"), F.replace("p_name", F.lit(" "), F.lit("")).alias("tight"), F.length("p_name").alias("n"), F.levenshtein("p_name", "p_type").alias("lev"), F.substring("p_type", 1, 4).alias("pre"), F.translate("p_brand", "#", "-").alias("br")),
)
add("dates", "select o_orderkey, date_trunc('month', o_orderdate)::timestamp as month, epoch_us(o_orderdate) as us, year(o_orderdate)::int as y from orders", lambda s, d: read(s, d, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").alias("month"), F.unix_micros(F.col("o_orderdate").cast("timestamp")).alias("us"), F.year("o_orderdate").alias("y")))
add("json_props", "select cast(json_extract_string(props, '$.k') as int) as k, count(*) as n from events group by 1", lambda s, d: read(s, d, "events").groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(F.count("*").alias("n")))
add("variant_props", "select cast(json_extract_string(props, '$.k') as int) as k, round(avg(value), 6) as mean from events group by 1", lambda s, d: read(s, d, "events").groupBy(F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")).agg(F.round(F.avg("value"), 6).alias("mean")))
add("distinct_exact", "select count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem", lambda s, d: read(s, d, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers")))
add("lateral_words", "select w, count(*) as n from (select unnest(string_split(p_name, ' ')) as w from part) group by w", lambda s, d: read(s, d, "part").select(F.explode(F.split("p_name", " ")).alias("w")).groupBy("w").agg(F.count("*").alias("n")))
QUERIES["sample_by"] = lambda s, d: read(s, d, "documents").sampleBy("lang", {"en": 0.1, "fr": 0.5}, 7).groupBy("lang").count()
