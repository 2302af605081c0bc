"""Single linkage: agglomeration that needs a stopping rule."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signpart.functions.expressions import order_key
from signpart.operators import components as comp
from signpart.operators import graph


def single_linkage(edges: DataFrame, clusters: int | None = None, least: float | None = None) -> DataFrame:
    """(v, cluster): the maximum spanning forest of the attractions, cut below ``least``, or at its lightest edges until there are ``clusters``."""
    everyone = graph.vertices(edges)
    tree = comp.max_spanning_forest(edges.where("w > 0"))
    if least is not None:
        return comp.components(tree.where(F.col("w") >= least), everyone)
    keep = max(0, everyone.count() - int(clusters))
    return comp.components(tree.orderBy(order_key()).limit(keep), everyone)
