"""Multicut baselines: exact on tiny graphs, greedy contraction, vertex moves, lifted edges, superpixels."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signpart import kernels, tables
from signpart.baselines import raster_multicut
from signpart.functions.expressions import log_odds, pair
from signpart.operators import components as comp
from signpart.operators import graph, grouped, hierarchy, tiles
from signpart.operators.raster import Shape


def log_odds_edges(edges: DataFrame, scale: float = 10000.0, eps: float = 1e-6) -> DataFrame:
    """Edges whose weight is the log-odds cost of their affinity |w| / scale, as a multiple of ``kernels.GRAIN``; zero costs go."""
    cost = log_odds(F.abs("w") / F.lit(scale), F.col("w") > 0, eps)
    return edges.select("edge_id", "u", "v", cost.alias("w"), "channel").withColumn("w", raster_multicut.grained()).where("w <> 0")


def _solve(u, v, w, method: str, rounds: int) -> dict[int, int]:
    order = np.lexsort((w, v, u))
    u, v, w = (x[order].tolist() for x in (u, v, w))
    if method in ("gaec", "kl"):
        labels = kernels.contraction(u, v, w)
    elif method == "fixation":
        return kernels.contraction(u, v, w, by_size=True)
    elif method == "kl_singletons":
        labels = {int(x): int(x) for x in set(u) | set(v)}
    else:
        raise ValueError("method is kl, kl_singletons, gaec or fixation")
    return labels if method == "gaec" else kernels.moves(u, v, w, labels, most_rounds=rounds)


def _in_tiles(edges: DataFrame, shape: Shape, local, rounds: int, improved: bool = True, start: DataFrame | None = None) -> DataFrame:
    """(g, v, cluster) of a raster's edges with its slice as g: contraction (of local edges) unless ``start`` has it, then moves, tile by tile."""
    edges = tables.written(edges.select("edge_id", "u", "v", "w", (F.lit(True) if local is None else local).alias("local")))
    if start is None:
        joined = raster_multicut.contraction(edges.where("local"), shape)
        labels = graph.vertices(edges).join(joined, "v", "left").select("v", F.coalesce("cluster", "v").alias("cluster"))
    else:
        labels = start.select("v", "cluster")
    if improved:
        labels = raster_multicut.moves(edges, labels, shape, local is not None, rounds)
    return labels.select(F.expr(f"v div {shape.height * shape.width}").alias("g"), "v", "cluster")


def multicut(edges: DataFrame, by: str | None = None, method: str = "kl", rounds: int = 50, shape: Shape | None = None, start: DataFrame | None = None) -> DataFrame:
    """(g, v, cluster) of each graph in column ``by`` (a slice, an order …), which must fit a task; without it, one graph.

    With the ``shape`` of the raster whose slices they are, what is too large for a task goes tile by tile (kl and gaec);
    there, ``start`` spares kl a contraction that gaec has made of the same edges.
    """
    if shape is not None and method in ("kl", "gaec") and not tables.at_most(edges, raster_multicut.ALONE):
        return _in_tiles(edges, shape, None, rounds, method == "kl", start)
    keyed = edges.withColumn("g", (F.col(by) if by else F.lit(0)).cast("long"))
    return grouped.labels_per_group(keyed, ["u", "v", "w"], lambda u, v, w: _solve(u, v, w, method, rounds))


def by_components(edges: DataFrame, method: str = "gaec") -> DataFrame:
    """(v, cluster): solves each component of the positive costs; no merge that gains crosses them."""
    labels = tables.written(comp.components(edges.where("w > 0"), graph.vertices(edges)))
    ends = comp.relabelled(edges, labels).where("cu = cv").select("u", "v", "w", F.col("cu").alias("c"))
    solved = multicut(ends, "c", method).select("v", "cluster")
    return labels.select("v").join(solved, "v", "left").select("v", F.coalesce("cluster", "v").alias("cluster"))


def lifted_multicut(edges: DataFrame, is_local, by: str | None = None, rounds: int = 50, shape: Shape | None = None) -> DataFrame:
    """(g, v, cluster): edges that aren't local add to the cost, but clusters are connected by local edges.

    Starts from the contraction of the local edges, which is feasible.  ``shape`` is that of ``multicut``.
    """
    if shape is not None and not tables.at_most(edges, raster_multicut.ALONE):
        return _in_tiles(edges, shape, is_local, rounds)
    keyed = edges.select((F.col(by) if by else F.lit(0)).cast("long").alias("g"), "u", "v", "w", is_local.alias("local"))

    def run(u, v, w, local) -> dict[int, int]:
        order = np.lexsort((w, v, u))
        u, v, w, local = (x[order] for x in (u, v, w, local))
        start = kernels.contraction(u[local], v[local], w[local], vertices=set(u.tolist()) | set(v.tolist()))
        return kernels.moves(u.tolist(), v.tolist(), w.tolist(), start, local=local.tolist(), most_rounds=rounds)

    return grouped.labels_per_group(keyed, ["u", "v", "w", "local"], run)


def multicut_exact(edges: DataFrame, most: int = 9) -> DataFrame:
    """(cand, cost): the labelings of least multicut cost among all set partitions of a tiny graph."""
    names = graph.vertices(edges)
    candidates = hierarchy.all_labelings(names, most)
    return hierarchy.qp_minimizers(edges, candidates, [1]).select("cand", F.col("value").alias("cost"))


def contracted_costs(costs: DataFrame, superpixels: DataFrame) -> DataFrame:
    """(u, v, w, n): costs between superpixels, added up; combined before the shuffle."""
    ends = comp.relabelled(costs, superpixels).where("cu <> cv")
    a, b = pair("cu", "cv")
    return ends.groupBy(a.alias("u"), b.alias("v")).agg(F.sum("w").alias("w"), F.count(F.lit(1)).alias("n"))


def superpixel_lifted(local: DataFrame, far: DataFrame, superpixels: DataFrame) -> DataFrame:
    """(v, cluster) of pixels: superpixels, costs between them, then the lifted multicut of that graph.

    Long-range costs count as lifted only between superpixels that don't touch.
    """
    costs = [contracted_costs(c, superpixels).select("u", "v", F.lit(k).alias("local"), "w") for c, k in ((local, True), (far, False))]
    return superpixels_joined(costs[0].unionByName(costs[1]), superpixels).select("v", "cluster")


def superpixels_joined(costs: DataFrame, superpixels: DataFrame) -> DataFrame:
    """superpixels (cluster, more…) with the clusters of the lifted multicut of their costs (u, v, local, w); long-range costs of those that touch go."""
    costs = tables.written(costs)
    near = costs.where("local")
    lifted = costs.where("not local").join(near.select("u", "v"), ["u", "v"], "left_anti").select(*near.columns)
    solved = tables.written(lifted_multicut(near.unionByName(lifted), F.col("local")).select(F.col("v").alias("s"), F.col("cluster").alias("c")))
    joined = superpixels.join(tables.sized_broadcast(solved, tiles.RENAMED), superpixels["cluster"] == F.col("s"), "left")
    return joined.withColumn("cluster", F.coalesce("c", "cluster")).select(*superpixels.columns)


