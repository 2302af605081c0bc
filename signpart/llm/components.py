"""Connected components of links, labelled with the least id, by alternating star rewrites."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signpart.llm import store


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """One rewrite of (u, v) links with u < v; each vertex's neighbours are joined to the least of them.

    The large form sees both directions and moves the larger neighbours, the
    small form sees the smaller neighbours only.  The least neighbour is an
    aggregate that is combined before the shuffle, and the join splits a vertex
    with very many links.
    """
    back = edges.select(F.col("v").alias("a"), F.col("u").alias("b"))
    seen = back.unionByName(edges.select(F.col("u").alias("a"), F.col("v").alias("b"))) if large else back
    least = seen.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
    moved = seen.join(least, "a")
    if large:
        out = moved.where("b > a").select(F.col("m").alias("u"), F.col("b").alias("v"))
    else:
        out = moved.where("b <> m").select(F.col("m").alias("u"), F.col("b").alias("v")).unionByName(least.where("m <> a").select(F.col("m").alias("u"), F.col("a").alias("v")))
    return out.where("u < v").distinct()


def components(links: DataFrame, left: str = "u", right: str = "v", most_rounds: int = 60) -> DataFrame:
    """(id, component_id) of every id in a link; component_id is the least id that links reach.

    Each round is written to the shared folder.  It stops when a round changes
    nothing, which a count and an order-free checksum tell.
    """
    spark = links.sparkSession
    u, v = F.least(left, right).cast("long"), F.greatest(left, right).cast("long")
    edges = store.written(links.select(u.alias("u"), v.alias("v")).where("u < v").distinct())

    def state(df: DataFrame):
        return tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    before = state(edges)
    if before[0] == 0:
        return spark.createDataFrame([], "id long, component_id long")
    for _ in range(most_rounds):
        edges = store.written(_stars(_stars(edges, True), False))
        after = state(edges)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"links did not settle in {most_rounds} rounds")
    return edges.select(F.col("v").alias("id"), F.col("u").alias("component_id")).unionByName(edges.select(F.col("u").alias("id"), F.col("u").alias("component_id")).distinct())
