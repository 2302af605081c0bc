"""Building signed graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signpart import schemas
from signpart.functions.expressions import order_key, pair


def build(pairs: DataFrame, collapse: bool = False) -> DataFrame:
    """Edges from (u, v, w[, channel]) rows: lesser end first, no loops, no zero weights.

    A weight that is null, NaN or infinite raises when the edge is read.
    ``collapse`` keeps only the first edge of each pair in processing order, which
    gives the same labels (after contraction no later edge of a pair can matter).
    edge_id is a hash of the edge, so it doesn't depend on the partitioning.
    """
    u, v = pair("u", "v")
    channel = F.col("channel") if "channel" in pairs.columns else F.lit(None).cast("int")
    finite = F.col("w").isNotNull() & ~F.isnan("w") & (F.abs("w") < F.lit(float("inf")))
    weight = F.when(finite, F.col("w")).otherwise(F.raise_error(F.lit("a weight isn't a finite number")).cast("double"))
    checked = pairs.select(pairs["u"].cast("long").alias("u"), pairs["v"].cast("long").alias("v"), pairs["w"].cast("double").alias("w"), channel.cast("int").alias("channel")).withColumn("w", weight)
    clean = checked.select(u.alias("u"), v.alias("v"), "w", "channel").where("u <> v and w <> 0")
    edges = clean.withColumn("edge_id", F.xxhash64("u", "v", F.coalesce("channel", F.lit(-1)))).select(*schemas.EDGES.names)
    return collapsed(edges) if collapse else edges


def collapsed(edges: DataFrame) -> DataFrame:
    """The first edge of each pair in processing order; combined before the shuffle."""
    first = F.min_by(F.struct("edge_id", "w", "channel"), order_key())
    return edges.groupBy("u", "v").agg(first.alias("e")).select("e.edge_id", "u", "v", "e.w", "e.channel")


def vertices(edges: DataFrame, extra: DataFrame | None = None) -> DataFrame:
    """(v) of all ends, and of ``extra`` for isolated vertices."""
    ends = edges.select(F.explode(F.array("u", "v")).alias("v"))
    return (ends if extra is None else ends.unionByName(extra.select(F.col("v").cast("long").alias("v")))).distinct()


def summary(edges: DataFrame) -> DataFrame:
    """One row: edges, attractive and repulsive ones, distinct weights, total weights."""
    return edges.agg(
        F.count(F.lit(1)).alias("n_edges"),
        F.count_if(F.col("w") > 0).alias("n_attractive"),
        F.count_if(F.col("w") < 0).alias("n_repulsive"),
        F.countDistinct(F.abs("w")).alias("n_weights"),
        F.coalesce(F.sum(F.abs("w")), F.lit(0.0)).alias("total_abs"),
    )
