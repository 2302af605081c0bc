"""Questions about a state: connected, excluded, consistent, bad cycles, certificates."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signpart import kernels, schemas, tables
from signpart.functions.expressions import order_key, pair
from signpart.operators import components as comp
from signpart.operators import graph


def connected(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """(u, v) rows with ``connected``: whether both ends have one cluster."""
    ends = comp.relabelled(pairs.select("u", "v"), labels)
    return ends.select("u", "v", (F.col("cu") == F.col("cv")).alias("connected"))


def exclusions(active: DataFrame, labels: DataFrame) -> DataFrame:
    """Distinct pairs of clusters (a, b) that an active repulsion keeps apart."""
    ends = comp.relabelled(active.where("w < 0").select("u", "v"), labels)
    a, b = pair("cu", "cv")
    return ends.select(a.alias("a"), b.alias("b")).distinct()


def excluded(pairs: DataFrame, labels: DataFrame, apart: DataFrame) -> DataFrame:
    """(u, v) rows with ``excluded``: whether their clusters are kept apart."""
    ends = comp.relabelled(pairs.select("u", "v"), labels)
    a, b = pair("cu", "cv")
    marked = apart.select("a", "b", F.lit(True).alias("__x")).distinct()
    return ends.withColumns({"a": a, "b": b}).join(marked, ["a", "b"], "left").select("u", "v", F.coalesce("__x", F.lit(False)).alias("excluded"))


def bad_cycles(active: DataFrame) -> DataFrame:
    """The active repulsions (edge_id, u, v, w) whose ends are joined by active attractions: each closes a bad cycle."""
    labels = comp.components(active.where("w > 0"))
    return comp.relabelled(active.where("w < 0").select("edge_id", "u", "v", "w"), labels).where("cu = cv").select("edge_id", "u", "v", "w")


def is_consistent(active: DataFrame) -> DataFrame:
    """One row: violations, and whether there are none."""
    return bad_cycles(active).agg(F.count(F.lit(1)).alias("violations")).select("violations", (F.col("violations") == 0).alias("consistent"))


def witness_paths(active: DataFrame, most_steps: int = 12) -> DataFrame:
    """(edge_id, path): for each bad cycle one shortest path of attractions between the ends, as far as ``most_steps``.

    Grows paths from all bad edges at once, one step a round, and keeps the least
    path for each edge and vertex reached.
    """
    bad = tables.written(bad_cycles(active))
    steps = active.where("w > 0").select(F.explode(F.array(F.struct(F.col("u").alias("x"), F.col("v").alias("y")), F.struct(F.col("v").alias("x"), F.col("u").alias("y")))).alias("s")).select("s.x", "s.y")
    front = bad.select("edge_id", F.col("u").alias("x"), F.col("v").alias("goal"), F.array("u").alias("path"))
    seen, found = front.select("edge_id", "x"), None
    for _ in range(most_steps):
        grown = front.join(steps, "x").select("edge_id", F.col("y").alias("x"), "goal", F.concat("path", F.array("y")).alias("path")).join(seen, ["edge_id", "x"], "left_anti")
        front = tables.written(grown.groupBy("edge_id", "x", "goal").agg(F.min("path").alias("path")))
        if front.isEmpty():
            break
        done = front.where("x = goal").select("edge_id", "path")
        found = done if found is None else found.unionByName(done)
        seen = tables.written(seen.unionByName(front.select("edge_id", "x")))
        front = front.join(done.select("edge_id"), "edge_id", "left_anti")
    return found if found is not None else bad.select("edge_id", F.array("u").alias("path")).limit(0)


def covers_bad_cycles(edges: DataFrame, indicator: DataFrame) -> DataFrame:
    """One row, ``covered``: whether the indicator (edge_id, x) has a 1 on every bad cycle of the graph."""
    kept = edges.join(indicator.where("x = 0").select("edge_id"), "edge_id", "left_semi")
    return is_consistent(kept).select(F.col("consistent").alias("covered"))


def addable(edges: DataFrame, initial: DataFrame) -> DataFrame:
    """Edges outside a consistent active set that could be added alone without a bad cycle."""
    rest = edges.join(initial.select("edge_id"), "edge_id", "left_anti")
    labels = tables.written(comp.components(initial.where("w > 0"), graph.vertices(edges)))
    apart = exclusions(initial, labels).withColumn("__x", F.lit(True))
    ends = comp.relabelled(rest, labels)
    a, b = pair("cu", "cv")
    state = ends.withColumns({"a": a, "b": b}).join(apart, ["a", "b"], "left")
    blocked = F.coalesce(F.col("__x"), F.lit(False))
    return state.where(F.when(F.col("w") < 0, F.col("cu") != F.col("cv")).otherwise(~blocked)).select(*edges.columns)


def classify_initial(edges: DataFrame, initial: DataFrame) -> DataFrame:
    """One row: consistent, incomplete, n_addable."""
    more = addable(edges, initial).agg(F.count(F.lit(1)).alias("n_addable"))
    return is_consistent(initial).crossJoin(more).select("consistent", (F.col("n_addable") > 0).alias("incomplete"), "n_addable")  # one row each


def first_step(edges: DataFrame, initial: DataFrame) -> DataFrame:
    """The first addable edge in processing order."""
    return addable(edges, initial).orderBy(order_key()).limit(1).select(*schemas.EDGES.names)


def by_first_steps(edges: DataFrame, initial: DataFrame, steps: int) -> DataFrame:
    """The active set (edge_id, u, v, w) after adding the first addable edge ``steps`` times: the greedy as a recursion.

    A step is a job over all edges; it is the definition to compare with, for small graphs.
    """
    active = tables.written(initial.select("edge_id", "u", "v", "w"))
    for _ in range(steps):
        step = tables.written(first_step(edges, active).select("edge_id", "u", "v", "w"))
        if step.isEmpty():
            break
        active = tables.written(active.unionByName(step))
    return active


def certificate(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(violation, n): what speaks against ``labels`` being the greedy partition; all zero exactly if it is.

    Three conditions, each local to a cluster or a pair of clusters: the induced
    active set has no bad cycle; every attraction between clusters has an earlier
    repulsion whose ends are joined to its ends by earlier attractions; every
    repulsion inside a cluster has its ends joined by earlier attractions.  "Joined
    by earlier" is a question to the order in which a cluster's spanning tree grows,
    and is answered per cluster (or pair of clusters) from the tree edges alone.
    """
    ends = tables.written(comp.relabelled(edges, labels))
    order = ("k0", "u", "v", "edge_id")

    def grow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The tree edges of each cluster, and a row with w = 0 for each inner repulsion whose ends weren't joined before it."""
        at, forest = None, kernels.Forest()
        for batch in batches:
            keep, w = [], []
            for k, (c, u, v, weight) in enumerate(zip(*(batch[x].to_pylist() for x in ("c", "u", "v", "w")))):
                if c != at:
                    at, forest = c, kernels.Forest()
                p, q = forest.find(u), forest.find(v)
                if p == q:
                    continue
                if weight > 0:
                    forest.up[q] = p
                keep.append(k)
                w.append(max(weight, 0.0))
            rows = batch.take(pa.array(keep, pa.int64()))
            yield pa.RecordBatch.from_arrays([*(rows[x] for x in ("edge_id", "u", "v", "c")), pa.array(w, pa.float64())], ["edge_id", "u", "v", "c", "w"])

    inner = ends.where("cu = cv").select("edge_id", "u", "v", "w", F.col("cu").alias("c"), (-F.abs("w")).alias("k0"))
    made = tables.written(inner.repartition("c").sortWithinPartitions("c", *order).mapInArrow(grow, "edge_id long, u long, v long, c long, w double"))
    trees, inside = made.where("w > 0"), made.where("w = 0").agg(F.count(F.lit(1)).alias("n"))
    # A cluster is joined if its trees are one tree.
    sizes = labels.groupBy("cluster").agg(F.count(F.lit(1)).alias("size"))
    grown_by = trees.groupBy(F.col("c").alias("cluster")).agg(F.count(F.lit(1)).alias("links"))
    split = sizes.join(grown_by, "cluster", "left").where(F.col("size") - 1 > F.coalesce("links", F.lit(0))).agg(F.count(F.lit(1)).alias("n"))

    # Attractions between clusters, with the repulsions and trees of both their clusters.
    a, b = pair("cu", "cv")
    across = ends.where("cu <> cv").select("edge_id", "u", "v", "w", a.alias("a"), b.alias("b"))
    sides = across.where("w > 0").select("a", "b").distinct()
    grown = sides.select("a", "b", F.explode(F.array("a", "b")).alias("c")).join(trees, "c").select("edge_id", "u", "v", "w", "a", "b", F.lit(True).alias("tree"))
    met = across.join(sides, ["a", "b"], "left_semi").select("edge_id", "u", "v", "w", "a", "b", F.lit(False).alias("tree"))

    def unblocked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """How many attractions nothing blocked when their turn came."""
        at, run, n = None, kernels.Greedy(), 0
        for batch in batches:
            for x, y, u, v, weight, is_tree in zip(*(batch[c].to_pylist() for c in ("a", "b", "u", "v", "w", "tree"))):
                if (x, y) != at:
                    at, run = (x, y), kernels.Greedy()
                p, q = run.forest.find(u), run.forest.find(v)
                if is_tree:
                    run.join(p, q)
                elif weight < 0:
                    run.apart.setdefault(p, set()).add(q)
                    run.apart.setdefault(q, set()).add(p)
                else:
                    n += q not in run.apart.get(p, ())
        yield pa.RecordBatch.from_pydict({"n": [n]})

    dealt = grown.unionByName(met).withColumn("k0", -F.abs("w")).repartition("a", "b").sortWithinPartitions("a", "b", *order)
    between = dealt.select("a", "b", "u", "v", "w", "tree").mapInArrow(unblocked, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
    parts = (("cluster_not_joined", split), ("inner_repulsion_not_joined_before", inside), ("outer_attraction_not_blocked", between))
    out = None
    for name, n in parts:
        row = n.select(F.lit(name).alias("violation"), F.col("n").cast("long").alias("n"))
        out = row if out is None else out.unionByName(row)
    return out


def partition_by_cycles(edges: DataFrame) -> DataFrame:
    """(edge_id, u, v, w, active) by testing each edge for bad cycles; small graphs, independent of the main kernel."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        taken = kernels.greedy_by_cycles(*(frame[c].tolist() for c in ("u", "v", "w", "edge_id")))
        return frame.assign(active=[int(t) for t in taken])[schemas.ACTIVE.names]

    return edges.groupBy().applyInPandas(run, schemas.ddl(schemas.ACTIVE))
