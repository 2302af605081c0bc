"""Level-wise optimisation: lexicographic argmin, ties, scales and the powered family."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from signpart import kernels, schemas, tables
from signpart.operators import components as comp
from signpart.operators import graph


def lexi_argmin(candidates: DataFrame, levels: list[str]) -> DataFrame:
    """All candidates that are least in the first level, among those least in the second, and so on."""
    best = candidates.agg(F.min(F.struct(*levels)).alias("__best"))
    return candidates.join(F.broadcast(best), F.struct(*levels) == F.col("__best")).drop("__best")  # best is one row


def lexi_argmin_by_filters(candidates: DataFrame, levels: list[str]) -> DataFrame:
    """The same by one filter after the other."""
    candidates = tables.written(candidates)
    for level in levels:
        least = candidates.agg(F.min(level).alias("__least"))
        candidates = tables.written(candidates.join(F.broadcast(least), F.col(level) == F.col("__least")).drop("__least"))  # least is one row
    return candidates


def scales(edges: DataFrame) -> DataFrame:
    """(k, size, scale, n_edges): level 0 has scale 1; level k the k-th largest |w| over twice the largest.

    One row per distinct |w|; the rank is a window over that table.
    """
    levels = edges.groupBy(F.abs("w").alias("size")).agg(F.count(F.lit(1)).alias("n_edges"))
    ranked = levels.select((F.row_number().over(Window.orderBy(F.desc("size")))).cast("long").alias("k"), "size", (F.col("size") / (2 * F.max("size").over(Window.partitionBy()))).alias("scale"), "n_edges")
    n = edges.agg(F.count(F.lit(1)).alias("n_edges"))
    first = n.select(F.lit(0).cast("long").alias("k"), F.lit(None).cast("double").alias("size"), F.lit(1.0).alias("scale"), "n_edges")
    return first.unionByName(ranked)


def all_labelings(vertices: DataFrame, most: int = 9) -> DataFrame:
    """(cand, v, cluster): every set partition of at most ``most`` vertices, clusters named by their least vertex.

    Grows labels vertex by vertex: each may join one of the clusters so far or
    start the next.
    """
    if vertices.count() > most:
        raise ValueError(f"the labelings of more than {most} vertices are too many")
    order = [r[0] for r in vertices.select("v").distinct().orderBy("v").collect()]  # at most ``most`` rows
    spark = vertices.sparkSession
    rows = spark.range(1).select(F.array().cast("array<int>").alias("labels"))
    for _ in order:
        top = F.coalesce(F.array_max("labels"), F.lit(-1))
        rows = rows.select(F.explode(F.transform(F.sequence(F.lit(0), top + 1), lambda c: F.array_append("labels", c))).alias("labels"))
    names = F.array(*(F.lit(x).cast("long") for x in order))
    least = F.transform("labels", lambda c: F.get(names, (F.array_position("labels", c) - 1).cast("int")))
    numbered = rows.select(F.concat_ws(",", "labels").alias("cand"), least.alias("clusters"))
    return numbered.select("cand", F.posexplode("clusters").alias("i", "cluster")).select("cand", F.get(names, F.col("i")).alias("v"), "cluster")


def q_values(edges: DataFrame, candidates: DataFrame) -> DataFrame:
    """(cand, k, q): dropped edges of each level k (1 is the largest |w|) under each candidate (cand, v, cluster)."""
    level = scales(edges).where("k > 0").select("k", "size")
    rows = edges.join(F.broadcast(tables.written(level)) if tables.at_most(level, 10_000) else level, F.abs("w") == F.col("size")).select("k", "u", "v", "w")
    cu = candidates.select("cand", F.col("v").alias("u"), F.col("cluster").alias("cu"))
    cv = candidates.select("cand", "v", F.col("cluster").alias("cv"))
    dropped = rows.join(cu, "u").join(cv, ["cand", "v"])
    return dropped.groupBy("cand", "k").agg(F.sum(((F.col("w") > 0) != (F.col("cu") == F.col("cv"))).cast("long")).alias("q"))


def qp_minimizers(edges: DataFrame, candidates: DataFrame, powers: list[int]) -> DataFrame:
    """(p, cand, value): the candidates of least powered cost for each p; integer weights, exact decimals."""
    cu = candidates.select("cand", F.col("v").alias("u"), F.col("cluster").alias("cu"))
    cv = candidates.select("cand", "v", F.col("cluster").alias("cv"))
    out = None
    from signpart.operators.objective import _power

    joined = edges.join(cu, "u").join(cv, ["cand", "v"]).withColumn("x", ((F.col("w") > 0) != (F.col("cu") == F.col("cv"))).cast("int"))
    for p in powers:
        cost = joined.groupBy("cand").agg(F.coalesce(F.sum(F.when(F.col("x") == 1, _power(p))), F.lit(0).cast("decimal(38,0)")).alias("c"))
        least = cost.agg(F.min("c").alias("__least"))
        row = cost.join(F.broadcast(least), F.col("c") == F.col("__least")).select(F.lit(p).alias("p"), "cand", F.col("c").cast("string").alias("value"))  # least is one row
        out = row if out is None else out.unionByName(row)
    return out


def candidate_of(labels: DataFrame) -> str:
    """The candidate name (restricted growth of labels in vertex order) of a small labeling."""
    seen: dict[int, int] = {}
    return ",".join(str(seen.setdefault(r["cluster"], len(seen))) for r in labels.orderBy("v").collect())


def settling_power(edges: DataFrame, labels: DataFrame, candidates: DataFrame, most: int = 16) -> int | None:
    """The least power from which up to ``most`` the only minimiser is the given labeling."""
    wanted = candidate_of(labels)
    rows = qp_minimizers(edges, candidates, list(range(1, most + 1))).collect()
    per = {p: {r["cand"] for r in rows if r["p"] == p} for p in range(1, most + 1)}
    settled = None
    for p in range(most, 0, -1):
        if per[p] != {wanted}:
            break
        settled = p
    return settled


def partition_levelwise(edges: DataFrame, exact_limit: int = 9, cap: int = 2_000_000) -> DataFrame:
    """(v, cluster, tie_exact): ties solved exactly where a component of the attractions is small enough.

    With distinct |w| in a component the greedy result is the optimum.  With ties
    the labelings of components up to ``exact_limit`` vertices are compared level
    by level; larger ones fall back to the total order and say so.  A repulsion
    across components is always active and takes no part.
    """
    labels = tables.written(comp.components(edges.where("w > 0"), graph.vertices(edges)))
    ends = tables.written(comp.relabelled(edges, labels).where("cu = cv").select(*schemas.EDGES.names, F.col("cu").alias("c")))
    size = labels.groupBy(F.col("cluster").alias("c")).agg(F.count(F.lit(1)).alias("n_vertices"))
    stats = ends.groupBy("c").agg(F.count(F.lit(1)).alias("n"), F.countDistinct(F.abs("w")).alias("levels")).join(size, "c")
    kinds = tables.written(stats.select("c", "n", F.when(F.col("n") == F.col("levels"), "unique").when(F.col("n_vertices") <= exact_limit, "exact").otherwise("order").alias("kind")))
    if kinds.where(F.col("n") > cap).isEmpty() is False:
        raise ValueError("a component exceeds the cap of a task; use the banded strategy, which follows the total order")

    def solve(frame: pd.DataFrame) -> pd.DataFrame:
        kind = frame["kind"].iloc[0]
        cols = [frame[c].tolist() for c in ("u", "v", "w")]
        if kind == "exact":
            out = kernels.exact_levels(*cols, vertices=(), most=exact_limit)
        else:
            out = kernels.greedy(*cols, frame["edge_id"].tolist()).labels
        return pd.DataFrame({"v": list(out), "cluster": list(out.values()), "tie_exact": kind != "order"})

    solved = ends.join(kinds.select("c", "kind"), "c").groupBy("c").applyInPandas(solve, "v long, cluster long, tie_exact boolean")
    return labels.select("v").join(solved, "v", "left").select("v", F.coalesce("cluster", "v").alias("cluster"), F.coalesce("tie_exact", F.lit(True)).alias("tie_exact"))
