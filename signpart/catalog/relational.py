"""Queries of the relational operators around the methods, each with its SQL."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from signpart import tables, workloads
from signpart.catalog import graphs
from signpart.catalog.replay import replay
from signpart.functions import expressions
from signpart.sources import readers

QUERIES: dict = {}
ORACLES: dict = {}


def _query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return tables.table(spark, d, name)


# ---- scans and sinks

for _name, _key in (("region", "r_regionkey"), ("nation", "n_nationkey"), ("customer", "c_custkey"), ("supplier", "s_suppkey"), ("part", "p_partkey"), ("orders", "o_orderkey"), ("lineitem", "l_orderkey"), ("events", "event_id"), ("documents", "doc_id"), ("labels", "doc_id"), ("embeddings", "vec_id"), ("pages", "page_id"), ("benchmark", "item_id"), ("conversations", "conv_id")):
    QUERIES[f"op_scan_{_name}"] = lambda s, d, name=_name, key=_key: _t(s, d, name).agg(F.count(F.lit(1)).alias("n"), F.min(key).alias("low"), F.max(key).alias("high"))
    ORACLES[f"op_scan_{_name}"] = f"select count(*) as n, min({_key}) as low, max({_key}) as high from {_name}"

for _format in ("csv", "json", "orc"):
    QUERIES[f"op_round_trip_{_format}"] = lambda s, d, f=_format: readers.round_trip(_t(s, d, "nation"), f)
    ORACLES[f"op_round_trip_{_format}"] = "select n_nationkey, n_name, n_regionkey from nation"


@_query("op_round_trip_text", "select r_name as value from region")
def op_round_trip_text(spark, d):
    return readers.round_trip(_t(spark, d, "region").select(F.col("r_name").alias("value")), "text")


@_query("op_edge_list_source", f"select u, v, w from ({graphs._PART_SUPPLIER})")
def op_edge_list_source(spark, d):
    """The graph of parts and suppliers as lines of text, larger end first and each after a remark, and read back."""
    path = tables.shared_folder(spark)
    edges = workloads.part_supplier(spark, d)
    edges.select(F.explode(F.array(F.concat_ws(" ", F.lit("#"), "edge_id"), F.concat_ws(" ", "v", "u", "w"))).alias("value")).write.text(path)
    return readers.edge_list(spark, path).select("u", "v", "w")


_PLANTED = """
with sites as (select cy, cx, (cy + 2) * 10 + cx + 2 as name, (cy * 73856093 + cx * 19349663) as t from (select unnest(range(-2, 8)) as cy) a, (select unnest(range(-2, 8)) as cx) b),
placed as (select cy, cx, name, cy * 12 + ((t % 1000003 + 1000003) % 1000003) % 12 as sy, cx * 12 + (((t % 1000003 + 1000003) % 1000003) // 12) % 12 as sx from sites),
pixels as (select p // 64 as y, p % 64 as x from (select unnest(range(0, 4096)) as p)),
truth as (select y * 64 + x as pix, arg_min(name, ((y - sy) * (y - sy) + (x - sx) * (x - sx), name)) as gt from pixels join placed on abs(cy - y // 12) <= 2 and abs(cx - x // 12) <= 2 group by 1)
select gt, count(*) as n, min(pix) as low, max(pix) as high from lineitem join truth on pix = l_orderkey * 31 % 64 * 64 + l_partkey % 64 group by gt
"""


@_query("op_planted_source", _PLANTED)
def op_planted_source(spark, d):
    """Lines by the planted site of the pixel that their order and part fall on."""
    readers.register(spark)
    planted = spark.read.format("planted_raster").option("height", 64).option("width", 64).load()
    lines = _t(spark, d, "lineitem").groupBy(((F.col("l_orderkey") * 31 % 64) * 64 + F.col("l_partkey") % 64).alias("pix")).agg(F.count(F.lit(1)).alias("c"))
    return lines.join(planted, "pix").groupBy("gt").agg(F.sum("c").alias("n"), F.min("pix").alias("low"), F.max("pix").alias("high"))


@_query("op_partitioned_sink", "select l_returnflag, count(*) as n from lineitem where l_returnflag = 'R' group by 1")
def op_partitioned_sink(spark, d):
    path = tables.shared_folder(spark)
    _t(spark, d, "lineitem").select("l_orderkey", "l_returnflag").repartition("l_returnflag").write.partitionBy("l_returnflag").parquet(path)
    return spark.read.parquet(path).where("l_returnflag = 'R'").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"))


@_query("op_bucketed_sink", "select count(*) as n from lineitem join orders on l_orderkey = o_orderkey")
def op_bucketed_sink(spark, d):
    left, right = (f"signpart_{uuid.uuid4().hex}" for _ in range(2))
    _t(spark, d, "lineitem").select("l_orderkey").repartition(8, "l_orderkey").write.bucketBy(8, "l_orderkey").sortBy("l_orderkey").saveAsTable(left)
    _t(spark, d, "orders").select("o_orderkey").repartition(8, "o_orderkey").write.bucketBy(8, "o_orderkey").sortBy("o_orderkey").saveAsTable(right)
    return spark.table(left).join(spark.table(right), F.col("l_orderkey") == F.col("o_orderkey")).agg(F.count(F.lit(1)).alias("n"))


@_query("op_catalog_sql", "select n_name from nation where n_regionkey = 2")
def op_catalog_sql(spark, d):
    _t(spark, d, "nation").createOrReplaceTempView("signpart_nation")
    return spark.sql("SELECT n_name FROM signpart_nation WHERE n_regionkey = :r", args={"r": 2})


# ---- projection, filters, conditions


@_query("op_projection", "select o_orderkey as id, (o_totalprice * 100)::bigint % 7 as r, o_orderpriority || '!' as p from orders")
def op_projection(spark, d):
    return _t(spark, d, "orders").select(F.col("o_orderkey").alias("id"), ((F.col("o_totalprice") * 100).cast("decimal(20,0)").cast("long") % 7).alias("r"), F.concat("o_orderpriority", F.lit("!")).alias("p"))


ORACLES["op_projection"] = "select o_orderkey as id, (o_totalprice * 100)::decimal(20,0)::bigint % 7 as r, o_orderpriority || '!' as p from orders"


@_query("op_filter", "select l_orderkey, l_linenumber from lineitem where l_quantity between 10 and 20 and l_returnflag in ('A', 'R') and l_shipdate < timestamp '1996-01-01' and l_linestatus like 'F%'")
def op_filter(spark, d):
    return _t(spark, d, "lineitem").where("l_quantity between 10 and 20 and l_returnflag in ('A', 'R') and l_shipdate < timestamp_ntz'1996-01-01' and l_linestatus like 'F%'").select("l_orderkey", "l_linenumber")


@_query("op_three_valued_logic", "select count(*) filter (where not (x = 1)) as n_not, count(*) filter (where x is distinct from 1) as n_distinct, count(*) as n from (select case when n_nationkey % 3 = 0 then null else n_regionkey end as x from nation)")
def op_three_valued_logic(spark, d):
    x = _t(spark, d, "nation").select(F.when(F.col("n_nationkey") % 3 != 0, F.col("n_regionkey")).alias("x"))
    return x.agg(F.count_if(~(F.col("x") == 1)).alias("n_not"), F.count_if(~F.col("x").eqNullSafe(1)).alias("n_distinct"), F.count(F.lit(1)).alias("n"))


@_query("op_conditional", "select l_returnflag, sum(case when l_quantity > 25 then 1 else 0 end)::bigint as high, min(coalesce(nullif(l_linestatus, 'F'), '-')) as s, min(least(l_orderkey, l_partkey)) as a, max(greatest(l_orderkey, l_partkey)) as b from lineitem group by 1")
def op_conditional(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.sum(F.when(F.col("l_quantity") > 25, 1).otherwise(0)).alias("high"), F.min(F.coalesce(F.nullif("l_linestatus", F.lit("F")), F.lit("-"))).alias("s"), F.min(F.least("l_orderkey", "l_partkey")).alias("a"), F.max(F.greatest("l_orderkey", "l_partkey")).alias("b"))


# ---- joins


@_query("op_join_broadcast", "select n_name, count(*) as n from supplier join nation on s_nationkey = n_nationkey group by 1")
def op_join_broadcast(spark, d):
    nation = tables.sized_broadcast(_t(spark, d, "nation"), 10_000)
    return _t(spark, d, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


for _hint in ("merge", "shuffle_hash"):
    QUERIES[f"op_join_{_hint}"] = lambda s, d, h=_hint: _t(s, d, "lineitem").join(_t(s, d, "orders").hint(h), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("q"))
    ORACLES[f"op_join_{_hint}"] = "select o_orderpriority, count(*) as n, sum(l_quantity::bigint)::bigint as q from lineitem join orders on l_orderkey = o_orderkey group by 1"

for _how in ("left", "right", "full"):
    QUERIES[f"op_join_{_how}"] = lambda s, d, how=_how: _t(s, d, "customer").join(_t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), how).agg(F.count(F.lit(1)).alias("n"), F.count("o_orderkey").alias("with_order"), F.count("c_custkey").alias("with_customer"))
    ORACLES[f"op_join_{_how}"] = f"select count(*) as n, count(o_orderkey) as with_order, count(c_custkey) as with_customer from customer {_how} join orders on c_custkey = o_custkey"

for _how, _word in (("left_semi", "semi"), ("left_anti", "anti")):
    QUERIES[f"op_join_{_word}"] = lambda s, d, how=_how: _t(s, d, "part").join(_t(s, d, "lineitem").where("l_quantity > 49"), F.col("p_partkey") == F.col("l_partkey"), how).select("p_partkey")
    ORACLES[f"op_join_{_word}"] = f"select p_partkey from part where {'' if _word == 'semi' else 'not '}exists (select 1 from lineitem where l_partkey = p_partkey and l_quantity > 49)"


@_query("op_join_theta", "select a.n_nationkey as a, b.n_nationkey as b from nation a join nation b on a.n_regionkey < b.n_regionkey and a.n_name > b.n_name")
def op_join_theta(spark, d):
    """A nested loop over 25 rows."""
    a, b = _t(spark, d, "nation").alias("a"), _t(spark, d, "nation").alias("b")
    return a.join(b, F.expr("a.n_regionkey < b.n_regionkey and a.n_name > b.n_name")).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b"))


@_query("op_join_range", "select a.event_id as a, b.event_id as b from events a join events b on b.ts > a.ts and b.ts <= a.ts + interval 15 minutes and a.event_type = 'purchase' and b.event_type = 'error'")
def op_join_range(spark, d):
    """Events within a quarter of an hour, by equal buckets of that width and the one before."""
    events = _t(spark, d, "events").select("event_id", "event_type", "ts", F.expr("timestampdiff(MINUTE, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts) div 15").alias("slot"))
    a = events.where("event_type = 'purchase'").select(F.col("event_id").alias("a"), F.col("ts").alias("at"), F.explode(F.array("slot", F.col("slot") + 1)).alias("slot"))
    b = events.where("event_type = 'error'").select(F.col("event_id").alias("b"), F.col("ts").alias("bt"), "slot")
    return a.join(b, "slot").where("bt > at and bt <= at + interval 15 minutes").select("a", "b")


@_query("op_join_asof", "select event_id, last_purchase from (select event_id, event_type, max(case when event_type = 'purchase' then event_id end) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as m, last_value(case when event_type = 'purchase' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as last_purchase from events) where event_type = 'error'")
def op_join_asof(spark, d):
    """The latest purchase of the same user before each error."""
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    bought = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    return _t(spark, d, "events").withColumn("last_purchase", F.last(bought, ignorenulls=True).over(before)).where("event_type = 'error'").select("event_id", "last_purchase")


@_query("op_join_shifted", "select count(*) as n from events a join events b on b.event_id = a.event_id + 1 and b.user_id <> a.user_id")
def op_join_shifted(spark, d):
    e = _t(spark, d, "events").select("event_id", "user_id")
    return e.join(e.select((F.col("event_id") - 1).alias("event_id"), F.col("user_id").alias("next_user")), "event_id").where("user_id <> next_user").agg(F.count(F.lit(1)).alias("n"))


# ---- aggregation


@_query("op_aggregate", "select l_returnflag, count(*) as n, sum(l_quantity::bigint)::bigint as q, min(l_extendedprice) as low, max(l_extendedprice) as high, round(avg(l_quantity), 6) as mean from lineitem group by 1")
def op_aggregate(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("q"), F.min("l_extendedprice").alias("low"), F.max("l_extendedprice").alias("high"), F.round(F.avg("l_quantity"), 6).alias("mean"))


@_query("op_aggregate_distinct", "select l_returnflag, count(distinct l_suppkey) as suppliers, sum(distinct l_quantity::bigint)::bigint as q from lineitem group by 1")
def op_aggregate_distinct(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_suppkey").alias("suppliers"), F.sum_distinct(F.col("l_quantity").cast("long")).alias("q"))


@_query("op_aggregate_approximate", "select true as near_count, true as near_median")
def op_aggregate_approximate(spark, d):
    e = _t(spark, d, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.countDistinct("user_id").alias("b"), F.percentile_approx("value", 0.5, 10000).alias("p"), F.percentile("value", 0.5).alias("q"))
    return e.select((F.abs(F.col("a") - F.col("b")) <= 0.1 * F.col("b")).alias("near_count"), (F.abs(F.col("p") - F.col("q")) <= 0.05 * F.abs(F.col("q")) + 0.5).alias("near_median"))


@_query("op_aggregate_ordered", "select o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) as largest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) as smallest, array_to_string(list_sort(list(o_orderkey)), ',') as orders from orders group by 1")
def op_aggregate_ordered(spark, d):
    key = F.struct("o_totalprice", "o_orderkey")
    return _t(spark, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", key).alias("largest"), F.min_by("o_orderkey", key).alias("smallest"), F.concat_ws(",", F.sort_array(F.collect_list("o_orderkey"))).alias("orders"))


@_query("op_aggregate_statistics", "select l_returnflag, round(stddev_samp(l_quantity), 6) as sd, round(corr(l_quantity, l_extendedprice), 6) as r, round(regr_slope(l_extendedprice, l_quantity), 4) as slope from lineitem group by 1")
def op_aggregate_statistics(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"))


for _kind in ("rollup", "cube"):
    QUERIES[f"op_{_kind}"] = lambda s, d, k=_kind: getattr(_t(s, d, "lineitem"), k)("l_returnflag", "l_linestatus").agg(F.grouping_id().cast("long").alias("g"), F.count(F.lit(1)).alias("n"))
    ORACLES[f"op_{_kind}"] = f"select l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::bigint as g, count(*) as n from lineitem group by {_kind}(l_returnflag, l_linestatus)"


@_query("op_grouping_sets", "select l_returnflag, l_linestatus, count(*) as n from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())")
def op_grouping_sets(spark, d):
    _t(spark, d, "lineitem").createOrReplaceTempView("signpart_lineitem")
    return spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM signpart_lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


@_query("op_pivot", "select user_id, count(*) filter (where event_type = 'purchase') as purchase, count(*) filter (where event_type = 'error') as error from events group by 1")
def op_pivot(spark, d):
    return _t(spark, d, "events").groupBy("user_id").pivot("event_type", ["purchase", "error"]).agg(F.count(F.lit(1))).select("user_id", F.coalesce("purchase", F.lit(0)).alias("purchase"), F.coalesce("error", F.lit(0)).alias("error"))


@_query("op_unpivot", "select s_suppkey, 'nation' as what, s_nationkey::bigint as x from supplier union all select s_suppkey, 'key', s_suppkey from supplier")
def op_unpivot(spark, d):
    s = _t(spark, d, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("nation"), F.col("s_suppkey").alias("key"))
    return s.unpivot("s_suppkey", ["nation", "key"], "what", "x")


# ---- windows, order, sets


@_query("op_window_ranks", "select o_orderkey, row_number() over w as rn, rank() over w2 as r, dense_rank() over w2 as dr, ntile(4) over w as q, round(percent_rank() over w2, 6) as pr from orders window w as (partition by o_orderpriority order by o_totalprice, o_orderkey), w2 as (partition by o_orderpriority order by o_custkey)")
def op_window_ranks(spark, d):
    w, w2 = Window.partitionBy("o_orderpriority").orderBy("o_totalprice", "o_orderkey"), Window.partitionBy("o_orderpriority").orderBy("o_custkey")
    return _t(spark, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w2).alias("r"), F.dense_rank().over(w2).alias("dr"), F.ntile(4).over(w).alias("q"), F.round(F.percent_rank().over(w2), 6).alias("pr"))


@_query("op_window_neighbours", "select conv_id, turn, lag(length(text)) over w as before, lead(role) over w as next_role, first_value(role) over w as first_role, nth_value(role, 2) over (partition by conv_id order by turn rows between unbounded preceding and unbounded following) as second_role from conversations window w as (partition by conv_id order by turn)")
def op_window_neighbours(spark, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _t(spark, d, "conversations").select("conv_id", "turn", F.lag(F.length("text")).over(w).alias("before"), F.lead("role").over(w).alias("next_role"), F.first("role").over(w).alias("first_role"), F.nth_value("role", 2).over(whole).alias("second_role"))


@_query("op_window_frames", "select o_orderkey, sum(o_orderkey) over (partition by o_custkey order by o_orderkey rows between 2 preceding and current row)::bigint as last_three, count(*) over (partition by o_custkey order by o_orderkey range between 1000 preceding and current row) as near from orders")
def op_window_frames(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return _t(spark, d, "orders").select("o_orderkey", F.sum("o_orderkey").over(w.rowsBetween(-2, 0)).alias("last_three"), F.count(F.lit(1)).over(w.rangeBetween(-1000, 0)).alias("near"))


@_query("op_top_k", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20")
def op_top_k(spark, d):
    return _t(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@_query("op_offset", "select o_orderkey from orders order by o_orderkey limit 5 offset 100")
def op_offset(spark, d):
    return _t(spark, d, "orders").orderBy("o_orderkey").offset(100).limit(5).select("o_orderkey")


@_query("op_top_k_per_group", "select o_custkey, o_orderkey from orders qualify row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) <= 3")
def op_top_k_per_group(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return _t(spark, d, "orders").withColumn("n", F.row_number().over(w)).where("n <= 3").select("o_custkey", "o_orderkey")


for _op, _sql in (("union", "union all"), ("intersect", "intersect"), ("exceptAll", "except all"), ("intersectAll", "intersect all")):
    QUERIES[f"op_set_{_op.lower()}"] = lambda s, d, op=_op: getattr(_t(s, d, "part").select(F.col("p_partkey").alias("k")), op)(_t(s, d, "lineitem").select(F.col("l_partkey").alias("k")))
    ORACLES[f"op_set_{_op.lower()}"] = f"select p_partkey as k from part {_sql} select l_partkey from lineitem"


@_query("op_dedup", "select min(doc_id) as doc_id, md5(text) as h from documents group by text")
def op_dedup(spark, d):
    docs = _t(spark, d, "documents").select("doc_id", F.md5("text").alias("h"))
    return docs.groupBy("h").agg(F.min("doc_id").alias("doc_id"))


@_query("op_sample_by_hash", "select l_orderkey, l_linenumber, l_partkey from lineitem where (l_orderkey * 73856093 + l_partkey * 19349663) % 10 < 3")
def op_sample_by_hash(spark, d):
    """A sampling operator: three tenths by an arithmetic hash."""
    return _t(spark, d, "lineitem").where((F.col("l_orderkey") * 73856093 + F.col("l_partkey") * 19349663) % 10 < 3).select("l_orderkey", "l_linenumber", "l_partkey")


@_query("op_subqueries", "select o_orderkey from orders o where o_totalprice > (select avg(o_totalprice) from orders) and exists (select 1 from lineitem where l_orderkey = o.o_orderkey and l_quantity > 45) and o_custkey in (select c_custkey from customer where c_acctbal > 0)")
def op_subqueries(spark, d):
    for name in ("orders", "lineitem", "customer"):
        _t(spark, d, name).createOrReplaceTempView(f"signpart_{name}")
    return spark.sql("SELECT o_orderkey FROM signpart_orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM signpart_orders) AND EXISTS (SELECT 1 FROM signpart_lineitem WHERE l_orderkey = o.o_orderkey AND l_quantity > 45) AND o_custkey IN (SELECT c_custkey FROM signpart_customer WHERE c_acctbal > 0)")


@_query("op_lateral", "select n_name, x.s as s from nation, lateral (select count(*) as s from supplier where s_nationkey = n_nationkey) x")
def op_lateral(spark, d):
    for name in ("nation", "supplier"):
        _t(spark, d, name).createOrReplaceTempView(f"signpart_{name}")
    return spark.sql("SELECT n_name, x.s FROM signpart_nation, LATERAL (SELECT count(*) AS s FROM signpart_supplier WHERE s_nationkey = n_nationkey) x")


@_query("op_recursive", "with recursive c as materialized (select l_linenumber as k, count(*) as c from lineitem group by 1), r(n, f, lines) as (select k, 1::bigint, c from c where k = 1 union all select n + 1, f * (n + 1), lines + c from r join c on k = n + 1) select n, f, lines from r")
def op_recursive(spark, d):
    """From one line number to the next: its factorial, and the lines so far."""
    tables.written(_t(spark, d, "lineitem").groupBy(F.col("l_linenumber").alias("k")).agg(F.count(F.lit(1)).alias("c"))).createOrReplaceTempView("signpart_numbers")
    return spark.sql("WITH RECURSIVE r(n, f, lines) AS (SELECT k, 1L, c FROM signpart_numbers WHERE k = 1 UNION ALL SELECT n + 1, f * (n + 1), lines + c FROM r JOIN signpart_numbers ON k = n + 1) SELECT n, f, lines FROM r")


# ---- functions


@_query("op_strings", "select page_id, lower(substr(url, 1, 8)) as a, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host, length(regexp_replace(html, '<[^>]*>', '', 'g')) as n, array_to_string(list_slice(string_split(url, '/'), 1, 3), '|') as p, md5(url) as m, sha256(url) as s, levenshtein(substr(url, 1, 30), substr(url, 5, 30)) as l from pages")
def op_strings(spark, d):
    return _t(spark, d, "pages").select("page_id", F.lower(F.substring("url", 1, 8)).alias("a"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", "")).alias("n"), F.concat_ws("|", F.slice(F.split("url", "/"), 1, 3)).alias("p"), F.md5("url").alias("m"), F.sha2("url", 256).alias("s"), F.levenshtein(F.substring("url", 1, 30), F.substring("url", 5, 30)).alias("l"))


@_query("op_dates", "select o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as m, datediff('day', date '1992-01-01', o_orderdate::date) as days, extract(year from o_orderdate)::int as y, strftime(o_orderdate + interval 10 days, '%Y-%m-%d') as later from orders")
def op_dates(spark, d):
    return _t(spark, d, "orders").select("o_orderkey", F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("m"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date")).alias("days"), F.year("o_orderdate").alias("y"), F.date_format(F.col("o_orderdate") + F.expr("interval 10 days"), "yyyy-MM-dd").alias("later"))


@_query("op_math", "select event_id, round(ln(1 + abs(value)), 6) as l, round(exp(-abs(value) / 1000), 6) as e, round(sqrt(abs(value)), 6) as s, floor(value)::bigint as f, round(pow(value, 2), 4) as p, ((event_id - 500) % 7 + 7) % 7 as m from events")
def op_math(spark, d):
    v = F.col("value")
    return _t(spark, d, "events").select("event_id", F.round(F.log(1 + F.abs(v)), 6).alias("l"), F.round(F.exp(-F.abs(v) / 1000), 6).alias("e"), F.round(F.sqrt(F.abs(v)), 6).alias("s"), F.floor(v).alias("f"), F.round(F.pow(v, F.lit(2)), 4).alias("p"), F.pmod(F.col("event_id") - 500, F.lit(7)).alias("m"))


@_query("op_arrays", "select vec_id, len(list_filter(embedding, lambda x: x > 0)) as positive, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 4) as q, list_max(embedding)::double as top, list_position(embedding, list_max(embedding)) as at from embeddings")
def op_arrays(spark, d):
    e = F.col("embedding")
    square = F.aggregate(F.transform(e, lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return _t(spark, d, "embeddings").select("vec_id", F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.round(square, 4).alias("q"), F.array_max(e).cast("double").alias("top"), F.array_position(e, F.array_max(e)).cast("int").alias("at"))


@_query("op_array_sets", "select conv_id, array_to_string(list_sort(list_distinct(list(role))), ',') as roles, len(list_intersect(list_distinct(list(role)), ['user', 'system'])) as k from conversations group by 1")
def op_array_sets(spark, d):
    roles = _t(spark, d, "conversations").groupBy("conv_id").agg(F.collect_set("role").alias("r"))
    return roles.select("conv_id", F.concat_ws(",", F.sort_array("r")).alias("roles"), F.size(F.array_intersect("r", F.array(F.lit("user"), F.lit("system")))).cast("long").alias("k"))


@_query("op_maps", "select user_id, sum(n)::bigint as n, count(*) as kinds from (select user_id, event_type, count(*) as n from events group by 1, 2) group by 1")
def op_maps(spark, d):
    per = _t(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("n"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


@_query("op_json", "select event_id, json_valid(props) as ok, len(json_keys(props)) as k from events")
def op_json(spark, d):
    return _t(spark, d, "events").select("event_id", F.schema_of_variant(F.try_parse_json("props")).isNotNull().alias("ok"), F.size(F.json_object_keys("props")).cast("long").alias("k"))


@_query("op_hash_arithmetic", "select user_id, " + "((((user_id * 73856093 + event_id * 19349663 + 83492791) % 1000003) * ((user_id * 73856093 + event_id * 19349663 + 83492791) % 1000003)) % 1000003) % 10007" + " as h from events")
def op_hash_arithmetic(spark, d):
    return _t(spark, d, "events").select("user_id", expressions.noise(F.col("user_id"), F.col("event_id"), F.lit(1)).alias("h"))


@_query("op_not_a_number", "select count(*) filter (where isnan(x)) as nan, count(*) filter (where isinf(x)) as inf, count(*) filter (where x is null) as nothing, count(*) as n from (select case n_nationkey % 4 when 0 then 'nan'::double when 1 then 'infinity'::double when 2 then null else 1.0 end as x from nation)")
def op_not_a_number(spark, d):
    k = F.col("n_nationkey") % 4
    x = F.when(k == 0, F.lit(float("nan"))).when(k == 1, F.lit(float("inf"))).when(k == 3, F.lit(1.0))
    return _t(spark, d, "nation").select(x.alias("x")).agg(F.count_if(F.isnan("x")).alias("nan"), F.count_if(F.col("x") == float("inf")).alias("inf"), F.count_if(F.col("x").isNull()).alias("nothing"), F.count(F.lit(1)).alias("n"))


# ---- functions of one's own


@_query("udf_sql_functions", "select least(o_orderkey, o_custkey) as a, greatest(o_orderkey, o_custkey) as b from orders")
def udf_sql_functions(spark, d):
    expressions.register_sql_functions(spark)
    _t(spark, d, "orders").createOrReplaceTempView("signpart_orders")
    return spark.sql("SELECT pair_low(o_orderkey, o_custkey) AS a, pair_high(o_orderkey, o_custkey) AS b FROM signpart_orders")


@_query("udf_arrow_scalar", "select vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double))), 6) as norm from embeddings")
def udf_arrow_scalar(spark, d):
    @F.pandas_udf("double")
    def norm(v: pd.Series) -> pd.Series:
        return v.map(lambda x: float((x.astype("float64") ** 2).sum() ** 0.5))

    return _t(spark, d, "embeddings").select("vec_id", F.round(norm("embedding"), 6).alias("norm"))


@_query("udf_grouped_map", "select o_custkey, count(*) as n, max(o_totalprice) - min(o_totalprice) as span from orders group by 1")
def udf_grouped_map(spark, d):
    def span(frame: pd.DataFrame) -> pd.DataFrame:
        p = frame["o_totalprice"]
        return pd.DataFrame({"o_custkey": [frame["o_custkey"].iloc[0]], "n": [len(frame)], "span": [p.max() - p.min()]})

    return _t(spark, d, "orders").select("o_custkey", "o_totalprice").groupBy("o_custkey").applyInPandas(span, "o_custkey long, n long, span double")


@_query("udf_aggregate", "select l_returnflag, round(sum(l_quantity * l_quantity) / sum(l_quantity), 6) as m from lineitem group by 1")
def udf_aggregate(spark, d):
    @F.pandas_udf("double")
    def weighted(q: pd.Series) -> float:
        return float((q * q).sum() / q.sum())

    return _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(weighted("l_quantity"), 6).alias("m"))


@_query("udf_table_function", replay(graphs._ORDERS) + "select g, v, cluster from labels")
def udf_table_function(spark, d):
    from signpart.functions import table_functions

    table_functions.register(spark)
    workloads.order_lines(spark, d).select("g", "edge_id", "u", "v", "w").createOrReplaceTempView("signpart_order_edges")
    return spark.sql("SELECT g, v, cluster FROM signed_partition(TABLE(signpart_order_edges) PARTITION BY g)")


@_query("udf_cogrouped_map", "select n_nationkey, (select count(*) from customer where c_nationkey = n_nationkey) as customers, (select count(*) from supplier where s_nationkey = n_nationkey) as suppliers from nation")
def udf_cogrouped_map(spark, d):
    def both(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"n_nationkey": [key[0]], "customers": [len(a)], "suppliers": [len(b)]})

    a = _t(spark, d, "customer").select(F.col("c_nationkey").alias("k"), "c_custkey")
    b = _t(spark, d, "supplier").select(F.col("s_nationkey").alias("k"), "s_suppkey")
    found = a.groupBy("k").cogroup(b.groupBy("k")).applyInPandas(both, "n_nationkey int, customers long, suppliers long")
    return _t(spark, d, "nation").select("n_nationkey").join(found, "n_nationkey", "left").select("n_nationkey", F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))
