"""Queries of the streaming operators; the SQL is that of the same question to the whole table."""

from __future__ import annotations

from pyspark.sql import functions as F

from signpart import tables, workloads
from signpart.catalog import graphs
from signpart.catalog.replay import replay
from signpart.streaming import streams

QUERIES: dict = {}
ORACLES: dict = {}


def _query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def _text(column: str = "start"):
    return F.date_format(column, "yyyy-MM-dd HH:mm:ss").alias(column)


#: Windows that the last watermark closes: those that end at most at the latest time less an hour.
_CLOSED = "(select max(ts) - interval 1 hour from events)"


@_query("stream_tumbling", "select strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') as start, event_type, count(*) as n, sum(round(value * 100)::bigint)::bigint as cents from events group by 1, 2")
def stream_tumbling(spark, d):
    """Complete mode: every window, closed or not."""
    out = streams.drained(streams.tumbling(streams.event_stream(spark, d)), "complete")
    last = out.agg(F.max("__batch")).first()[0]
    return out.where(F.col("__batch") == last).select(_text(), "event_type", "n", "cents")


@_query("stream_tumbling_append", f"select strftime(s, '%Y-%m-%d %H:%M:%S') as start, event_type, n from (select date_trunc('hour', ts) as s, event_type, count(*) as n from events group by 1, 2) where s + interval 1 hour <= {_CLOSED}")
def stream_tumbling_append(spark, d):
    """Append mode: the windows that the watermark has closed."""
    return streams.drained(streams.tumbling(streams.event_stream(spark, d))).select(_text(), "event_type", "n")


@_query("stream_sliding", "select strftime(s, '%Y-%m-%d %H:%M:%S') as start, count(*) as n from (select date_trunc('hour', ts) as s from events union all select date_trunc('hour', ts) - interval 1 hour from events) group by 1")
def stream_sliding(spark, d):
    out = streams.drained(streams.sliding(streams.event_stream(spark, d)), "complete")
    last = out.agg(F.max("__batch")).first()[0]
    return out.where(F.col("__batch") == last).select(_text(), "n")


@_query("stream_sessions", f"""
with marked as (select user_id, ts, case when ts < lag(ts) over w + interval 30 minutes then 0 else 1 end as fresh from events window w as (partition by user_id order by ts)),
numbered as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as k from marked),
runs as (select user_id, min(ts) as s, max(ts) + interval 30 minutes as e, count(*) as n from numbered group by user_id, k)
select user_id, strftime(s, '%Y-%m-%d %H:%M:%S') as start, n from runs where e <= {_CLOSED}""")
def stream_sessions(spark, d):
    return streams.drained(streams.sessions(streams.event_stream(spark, d))).select("user_id", _text(), "n")


@_query("stream_dedup", "select count(*) as n, count(distinct event_id) as ids from events")
def stream_dedup(spark, d):
    return streams.drained(streams.deduplicated(streams.event_stream(spark, d))).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("event_id").alias("ids"))


@_query("stream_static_join", "select c_mktsegment, count(*) as n from events join customer on c_custkey = user_id group by 1")
def stream_static_join(spark, d):
    users = tables.table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return streams.drained(streams.with_users(streams.event_stream(spark, d), users)).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@_query("stream_stream_join", "select a.event_id as purchase, b.event_id as error from events a join events b on a.user_id = b.user_id and a.event_type = 'purchase' and b.event_type = 'error' and b.ts > a.ts and b.ts <= a.ts + interval 15 minutes")
def stream_stream_join(spark, d):
    return streams.drained(streams.errors_after_purchases(streams.event_stream(spark, d)))


_DAY_EDGES = """
select g, u, v, sum(case when event_type = 'error' then -3 else 1 end)::double as w
from (select g, lag(user_id) over (partition by g, event_type, h order by user_id) as u, user_id as v, event_type
      from (select distinct (epoch(ts) / 86400)::bigint as g0, floor(epoch(ts) / 86400)::bigint as g, user_id, event_type, date_trunc('hour', ts) as h from events))
where u is not null group by g, u, v having sum(case when event_type = 'error' then -3 else 1 end) <> 0
"""


def _day_edges(spark, d):
    """(t, day, edge_id, u, v, w): the pairs of users of each day, at the day's end."""
    from pyspark.sql.window import Window

    events = tables.table(spark, d, "events").select("user_id", "event_type", F.date_trunc("hour", "ts").alias("h"), F.expr("timestampdiff(DAY, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts)").alias("day")).distinct()
    follow = Window.partitionBy("day", "event_type", "h").orderBy("user_id")
    rows = events.select("day", F.lag("user_id").over(follow).alias("u"), F.col("user_id").alias("v"), "event_type").where("u is not null")
    w = F.sum(F.when(F.col("event_type") == "error", -3).otherwise(1)).cast("double")
    made = rows.groupBy("day", "u", "v").agg(w.alias("w")).where("w <> 0")
    return made.select(F.timestamp_seconds(F.col("day") * 86400 + 86399).alias("t"), "day", F.xxhash64("u", "v").alias("edge_id"), "u", "v", "w")


@_query("stream_partition_windows", replay(_DAY_EDGES.replace("(epoch(ts) / 86400)::bigint as g0, ", "")) + ", kept as (select max(g) as m from e0) select g as day, v, cluster from labels, kept where g <= m - 3")
def stream_partition_windows(spark, d):
    """Days that are closed well before the end of the stream."""
    edges = tables.written(_day_edges(spark, d))
    path = streams.in_order(edges, F.col("day"), 6)
    stream = spark.readStream.schema(edges.schema).option("maxFilesPerTrigger", 1).parquet(path)
    last = edges.agg(F.max("day")).first()[0]
    return streams.drained(streams.partition_windows(stream)).where(F.col("day") <= last - 3)


@_query("stream_warm_start", replay(graphs._NATION) + "select v, cluster from labels")
def stream_warm_start(spark, d):
    """The nations' edges in three batches of falling |w|."""
    return streams.follow(spark, tables.written(workloads.places(spark, d)))


@_query("stream_edges_by_batch", "select count(*) as n from (select user_id from events)")
def stream_edges_by_batch(spark, d):
    """A file stream in update mode: rows per batch add up to the table."""
    counts = streams.event_stream(spark, d).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    out = streams.drained(counts, "update")
    return out.groupBy("event_type").agg(F.max("n").alias("n")).agg(F.sum("n").alias("n"))


