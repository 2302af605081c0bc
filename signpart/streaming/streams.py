"""Streams of events and edges: windows, late rows, state, and partitions that follow."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from signpart import kernels, schemas, tables
from signpart.functions.expressions import pair
from signpart.operators import components, graph, partition


def event_stream(spark: SparkSession, sf_dir: str, files: int = 8) -> DataFrame:
    """The events as a stream of files in order of time, one file a batch, with a column t in UTC."""
    path = in_order(tables.table(spark, sf_dir, "events"), F.expr("timestampdiff(SECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts)"), files)
    stream = spark.readStream.schema(schemas.TABLES["events"]).option("maxFilesPerTrigger", 1).parquet(path)
    return stream.withColumn("t", F.col("ts").cast("timestamp"))


def in_order(rows: DataFrame, key: Column, files: int) -> str:
    """A folder of about ``files`` files of rising ``key``, written one after the other: a file stream follows the times of writing."""
    spark, path = rows.sparkSession, tables.shared_folder(rows.sparkSession)
    keyed = rows.withColumn("__key", key.cast("double"))
    cuts = sorted(set(keyed.stat.approxQuantile("__key", [i / files for i in range(1, files)], 0.2 / files)))
    for low, high in zip([None, *cuts], [*cuts, None]):
        part = keyed if low is None else keyed.where(F.col("__key") > low)
        part = part if high is None else part.where(F.col("__key") <= high)
        part.drop("__key").coalesce(1).write.mode("append").parquet(path)
    return path


def drained(stream: DataFrame, mode: str = "append", sink: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Runs a stream over what there is and returns the result table, written to the shared folder.

    append goes to a file sink, whose commit log makes it exactly once; update and
    complete are kept batch by batch, later batches replacing earlier ones.
    """
    spark = stream.sparkSession
    folder = tables.shared_folder(spark)
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True)
    if sink is not None:
        writer.foreachBatch(sink).start().awaitTermination()
        return stream.sparkSession.range(0)
    if mode == "append":
        writer.format("parquet").start(f"{folder}/out").awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{folder}/out")

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("__batch", F.lit(number)).write.mode("overwrite").parquet(f"{folder}/out/batch={number:09d}")

    writer.foreachBatch(keep).start().awaitTermination()
    return spark.read.parquet(f"{folder}/out").drop("batch")


def tumbling(events: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """(start, event_type, n, cents) of windows."""
    windowed = events.withWatermark("t", late).groupBy(F.window("t", width), "event_type")
    return windowed.agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents")).select(F.col("window.start").alias("start"), "event_type", "n", "cents")


def sliding(events: DataFrame) -> DataFrame:
    """(start, n) of two-hour windows every hour."""
    return events.withWatermark("t", "1 hour").groupBy(F.window("t", "2 hours", "1 hour")).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, n) of runs of events with smaller gaps."""
    return events.withWatermark("t", "1 hour").groupBy("user_id", F.session_window("t", gap)).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    """The first row of each event_id, as far back as the watermark."""
    return events.withWatermark("t", "1 hour").dropDuplicatesWithinWatermark(["event_id"])


def with_users(events: DataFrame, users: DataFrame) -> DataFrame:
    """A join of the stream with a static table of users."""
    return events.join(users, "user_id")


def errors_after_purchases(events: DataFrame, minutes: int = 15) -> DataFrame:
    """(purchase, error): a join of two streams: errors of a user within ``minutes`` after a purchase."""
    a = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("u"), F.col("t").alias("ta")).withWatermark("ta", "1 hour")
    b = events.where("event_type = 'error'").select(F.col("event_id").alias("error"), F.col("user_id").alias("w"), F.col("t").alias("tb")).withWatermark("tb", "1 hour")
    return a.join(b, F.expr(f"u = w and tb > ta and tb <= ta + interval {minutes} minutes")).select("purchase", "error")


def partition_windows(edges: DataFrame, late: str = "1 hour") -> DataFrame:
    """(day, v, cluster) of a stream of (t, day, edge_id, u, v, w): a day's edges are kept, and partitioned when the day is closed."""

    def on_rows(key, frames, state: GroupState):
        if state.hasTimedOut:
            rows = list(zip(*state.get)) if state.exists else []
            state.remove()
            if rows:
                edge_id, u, v, w = zip(*rows)
                out = kernels.greedy(u, v, w, edge_id)
                yield pd.DataFrame({"day": int(key[0]), "v": list(out.labels), "cluster": list(out.labels.values())})
            return
        kept = [list(x) for x in state.get] if state.exists else [[], [], [], []]
        for frame in frames:
            for column, name in zip(kept, ("edge_id", "u", "v", "w")):
                column += frame[name].tolist()
        state.update(tuple(kept))
        # Two days after its start a day is closed under a watermark of an hour.
        state.setTimeoutTimestamp(int(max((int(key[0]) + 2) * 86_400_000, state.getCurrentWatermarkMs() + 1)))

    state = "edge_id array<bigint>, u array<bigint>, v array<bigint>, w array<double>"
    marked = edges.withWatermark("t", late)
    return marked.groupBy("day").applyInPandasWithState(on_rows, "day bigint, v bigint, cluster bigint", state, "append", GroupStateTimeout.EventTimeTimeout)


class GrowingPartition:
    """Labels that follow a stream of edges.

    Batches that come in falling |w| go on from the state, which equals the greedy
    over everything.  A batch with an edge that should have come earlier re-solves
    the components of the attractions that it touches, from the edges kept; all
    others keep their labels.  Each batch's edges are written once.
    """

    def __init__(self, spark: SparkSession, cap: int = partition.CAP):
        self.spark, self.cap = spark, cap
        self.paths: list[str] = []
        self.state = partition.State.empty(spark)
        self.lowest: float | None = None

    @property
    def edges(self) -> DataFrame:
        return self.spark.read.schema(schemas.EDGES).parquet(*self.paths)

    def add(self, batch: DataFrame, number: int = 0) -> None:
        path = tables.shared_folder(self.spark)
        batch = tables.written(batch.select(*schemas.EDGES.names), path)
        low, high = batch.agg(F.min(F.abs("w")), F.max(F.abs("w"))).first()
        if high is None:
            return
        self.paths.append(path)
        if self.lowest is None or high < self.lowest:
            self.state = partition.run_bands(batch, [partition.Band()], self.state, self.cap)
        else:
            self.state = self._resolved(batch)
        self.lowest = low if self.lowest is None else min(low, self.lowest)

    def _resolved(self, batch: DataFrame) -> partition.State:
        """The state after solving the touched components anew; between them and the others there are only repulsions."""
        edges, old = self.edges, self.state
        component = tables.written(components.components(edges.where("w > 0"), graph.vertices(edges)))
        hit = component.join(graph.vertices(batch), "v", "left_semi").select("cluster").distinct()
        touched = tables.written(component.join(hit, "cluster", "left_semi").select("v"))
        is_u, is_v = touched.select(F.col("v").alias("u"), F.lit(True).alias("at_u")), touched.select("v", F.lit(True).alias("at_v"))
        ends = edges.join(is_u, "u", "left").join(is_v, "v", "left").where("at_u or at_v")
        ends = tables.written(ends.select(*schemas.EDGES.names, (F.col("at_u") & F.col("at_v")).alias("inner")).fillna(False, ["inner"]))
        new = partition.run_bands(ends.where("inner").drop("inner"), [partition.Band()], partition.State.empty(self.spark), self.cap)
        labels = tables.written(old.labels.join(touched, "v", "left_anti").select("v", "cluster").unionByName(new.labels.select("v", "cluster")))
        # A cluster is named by a vertex of its own, so its name tells whether it was touched.
        kept = old.exclusions.join(touched.withColumnRenamed("v", "a"), "a", "left_anti").join(touched.withColumnRenamed("v", "b"), "b", "left_anti").select("a", "b")
        a, b = pair("cu", "cv")
        across = components.relabelled(ends.where("not inner").drop("inner"), labels).select(a.alias("a"), b.alias("b"))
        return partition.State(labels, tables.written(kept.unionByName(new.exclusions.select("a", "b")).unionByName(across).distinct()))

    def labels(self) -> DataFrame:
        everyone = graph.vertices(self.edges)
        return everyone.join(self.state.labels, "v", "left").select("v", F.coalesce("cluster", "v").alias("cluster"))


def follow(spark: SparkSession, edges: DataFrame, batches: int = 3) -> DataFrame:
    """Labels after streaming the edges in falling |w|, a band a batch."""
    path = tables.shared_folder(spark)
    for k, band in enumerate(partition.equal_bands(edges, batches)):
        band.of(edges).coalesce(1).write.parquet(f"{path}/{k:03d}-{uuid.uuid4().hex}")
    growing = GrowingPartition(spark)
    folders = spark.read.schema(schemas.EDGES).option("recursiveFileLookup", "true").parquet(path).select("*", "_metadata.file_path")
    for name in sorted({r[0].rsplit("/", 1)[0] for r in folders.select("file_path").distinct().collect()}):  # as many as there are batches
        stream = spark.readStream.schema(schemas.EDGES).parquet(name)
        drained(stream, sink=growing.add)
    return growing.labels()
