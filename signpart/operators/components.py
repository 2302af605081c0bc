"""Connected components and maximum spanning forests by distributed rounds."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signpart import kernels, schemas, tables
from signpart.functions.expressions import pair
from signpart.operators.graph import vertices as ends_of

#: Edges up to which one task solves a graph alone.
SMALL = 1_000_000


def _rewrite(edges: DataFrame, both: bool) -> DataFrame:
    """Joins each vertex's neighbours to the least of them: the larger ones if ``both``, else the smaller ones.

    The least neighbour is combined before the shuffle, and the join back to a
    vertex with very many edges can be split by Spark.
    """
    down = edges.select(F.col("v").alias("a"), F.col("u").alias("b"))
    seen = down.unionByName(edges.select(F.col("u").alias("a"), F.col("v").alias("b"))) if both else down
    least = seen.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
    rows = seen.join(least, "a")
    if both:
        out = rows.where("b > a").select(F.col("m").alias("u"), F.col("b").alias("v"))
    else:
        out = rows.where("b <> m").select(F.col("m").alias("u"), F.col("b").alias("v")).unionByName(least.where("m <> a").select(F.col("m").alias("u"), F.col("a").alias("v")))
    return out.where("u < v").distinct()


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def _by_stars(edges: DataFrame, most_rounds: int) -> DataFrame:
    """Alternating star rewrites, each written to the shared folder, until nothing changes."""
    before = _state(edges)
    for _ in range(most_rounds):
        edges = tables.written(_rewrite(_rewrite(edges, True), False))
        now = _state(edges)
        if now == before:
            return edges.select("v", F.col("u").alias("cluster")).unionByName(edges.select(F.col("u").alias("v"), F.col("u").alias("cluster")).distinct())
        before = now
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")


def _by_ranges(edges: DataFrame, n: int, small: int, most_rounds: int) -> DataFrame:
    """Ranges of edges are solved by a task each, then the graph of the ranges' clusters, tied by the vertices that several ranges have.

    That graph is small where near ids are near in the graph, as in rasters; where
    it isn't, the stars take it over.
    """

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest = kernels.Forest()
        find, up = forest.find, forest.up
        for batch in batches:
            for a, b in zip(batch["u"].to_pylist(), batch["v"].to_pylist()):
                ra, rb = find(a), find(b)
                if ra < rb:
                    up[rb] = ra
                elif rb < ra:
                    up[ra] = rb
        vertices = list(up)
        for k in range(0, len(vertices), 1 << 16):
            some = vertices[k : k + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array([find(x) for x in some], pa.int64())], ["v", "near"])

    ranges = max(2, -(-n // max(1, small // 4)))
    found = tables.written(edges.repartitionByRange(ranges, "u", "v").mapInArrow(solve, "v long, near long"))
    first = tables.written(found.groupBy("v").agg(F.min("near").alias("near"), F.max("near").alias("last")))
    shared = first.where("near <> last").select("v", F.col("near").alias("u"))
    ties = tables.written(found.join(shared, "v").where("near <> u").select("u", F.col("near").alias("v")).distinct())
    left = ties.count()
    if left <= small:
        among = _alone(ties)
    else:
        among = _by_ranges(ties, left, small, most_rounds) if left <= n // 2 else _by_stars(ties, most_rounds)
    among = among.select(F.col("v").alias("near"), "cluster")
    return first.join(among, "near", "left").select("v", F.coalesce("cluster", "near").alias("cluster"))


def _alone(edges: DataFrame) -> DataFrame:
    """The labels by one task."""

    def solve(frame: pd.DataFrame) -> pd.DataFrame:
        forest = kernels.Forest()
        for a, b in zip(frame["u"].tolist(), frame["v"].tolist()):
            ra, rb = forest.find(a), forest.find(b)
            if ra != rb:
                forest.up[max(ra, rb)] = min(ra, rb)
        found = forest.labels(set(forest.up))
        return pd.DataFrame({"v": list(found), "cluster": list(found.values())}, dtype="int64")

    return edges.groupBy().applyInPandas(solve, schemas.ddl(schemas.LABELS))


def components(links: DataFrame, vertices: DataFrame | None = None, small: int = SMALL, most_rounds: int = 80) -> DataFrame:
    """(v, cluster) with cluster the least vertex that links reach.

    A small graph is one task; else ranges of edges are solved side by side and tied together.
    """
    u, v = pair("u", "v")
    edges = tables.written(links.select(u.alias("u"), v.alias("v")).where("u < v"))
    labels = _alone(edges) if tables.at_most(edges, small) else tables.written(_by_ranges(edges, edges.count(), small, most_rounds))
    if vertices is None:
        return labels
    alone = vertices.select("v").join(labels, "v", "left_anti").select("v", F.col("v").alias("cluster"))
    return labels.unionByName(alone)


def relabelled(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """edges with cu and cv, the clusters of their ends; an end without a label is its own cluster."""
    cu = labels.select(F.col("v").alias("u"), F.col("cluster").alias("__cu"))
    cv = labels.select("v", F.col("cluster").alias("__cv"))
    joined = edges.join(cu, "u", "left").join(cv, "v", "left")
    return joined.select(*edges.columns, F.coalesce("__cu", "u").alias("cu"), F.coalesce("__cv", "v").alias("cv"))


def max_spanning_forest(edges: DataFrame, small: int = SMALL, most_rounds: int = 64) -> DataFrame:
    """The edges of the maximum spanning forest by w and the total order.

    Rounds: each component picks its first leaving edge, the picked edges join
    components, inner edges go.  The strict total order rules out cycles.
    """
    edges = tables.written(edges.select(*schemas.EDGES.names))
    if tables.at_most(edges, small):

        def solve(frame: pd.DataFrame) -> pd.DataFrame:
            return frame[kernels.spanning_forest(frame["u"], frame["v"], frame["w"], frame["edge_id"])][schemas.EDGES.names]

        return edges.groupBy().applyInPandas(solve, edges.schema)
    best = F.struct((-F.col("w")).alias("k0"), F.col("u").alias("k1"), F.col("v").alias("k2"), F.col("edge_id").alias("k3"))
    row = F.struct(*schemas.EDGES.names)
    labels = ends_of(edges).withColumn("cluster", F.col("v"))
    left, kept = edges, edges.limit(0)
    for _ in range(most_rounds):
        crossing = tables.written(relabelled(left, labels).where("cu <> cv"))
        if crossing.isEmpty():
            return kept
        picks = crossing.select(F.explode(F.array("cu", "cv")).alias("c"), best.alias("k"), row.alias("e")).groupBy("c").agg(F.min_by("e", "k").alias("e")).select("e.*").distinct()
        kept = tables.written(kept.unionByName(picks))
        labels = tables.written(components(kept.select("u", "v"), ends_of(edges), small))
        left = crossing.select(*schemas.EDGES.names)
    raise RuntimeError(f"the forest did not settle in {most_rounds} rounds")
