"""The partition as a table function of SQL."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from signpart import kernels


@udtf(returnType="g bigint, v bigint, cluster bigint")
class SignedPartition:
    """signed_partition(TABLE(edges) PARTITION BY g): edges with columns g, edge_id, u, v, w; each g is a graph that fits a task."""

    def __init__(self):
        self.rows = []

    def eval(self, row):
        self.rows.append((row["g"], row["edge_id"], row["u"], row["v"], row["w"]))

    def terminate(self):
        if self.rows:
            g, edge_id, u, v, w = zip(*self.rows)
            for x, cluster in kernels.greedy(u, v, w, edge_id).labels.items():
                yield g[0], x, cluster


def register(spark: SparkSession) -> None:
    spark.udtf.register("signed_partition", SignedPartition)
