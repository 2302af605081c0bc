"""Scores, costs, levels and rasters."""

import pytest
from pyspark.sql import functions as F

from signpart import kernels, workloads
from signpart.operators import affinity, graph, hierarchy, metrics, objective, partition, raster
from tests.conftest import random_edges


def test_scores_are_one_exactly_for_equal_partitions(spark):
    truth = spark.createDataFrame([(i, i % 3) for i in range(12)], "pix long, gt long")
    renamed = spark.createDataFrame([(i, 50 - i % 3) for i in range(12)], "v long, cluster long")
    row = metrics.scores(renamed, truth, "m").first()
    assert (row["pair"], row["info"], row["n_clusters"]) == (1.0, 1.0, 3)
    merged = spark.createDataFrame([(i, 0) for i in range(12)], "v long, cluster long")
    worse = metrics.scores(merged, truth, "m").first()
    assert worse["pair"] < 1 and worse["info"] < 1


def test_perfect_predictions_lose_half_a_dice(spark):
    rows = spark.createDataFrame([(0, False, 1.0, 1), (0, False, 0.0, 0), (1, True, 0.0, 0), (1, True, 1.0, 1), (2, False, 0.0, 0)], "channel int, attract boolean, p double, target int")
    assert {r["channel"]: r["loss"] for r in metrics.dice_loss(rows).collect()} == {0: -0.5, 1: -0.5, 2: 0.0}


def test_worked_example_powers(spark):
    edges = workloads.example(spark)
    candidates = hierarchy.all_labelings(graph.vertices(edges))
    assert candidates.select("cand").distinct().count() == 203
    best = {(r["p"], r["value"]) for r in hierarchy.qp_minimizers(edges, candidates, [1, 2, 3]).collect()}
    assert best == {(1, "21"), (2, "261"), (3, "3071")}
    labels = partition.partition(edges, strategy="kernel").labels
    assert hierarchy.settling_power(edges, labels, candidates, most=5) == 3
    assert objective.min_dominant_power(edges, 32) == 8
    assert objective.multicut_cost(edges, labels).first()["cost"] == 29


@pytest.mark.parametrize("seed", [1, 2])
def test_powered_optimum_at_a_dominant_power_is_the_greedy(spark, seed):
    edges = graph.build(spark.createDataFrame(random_edges(5, 8, seed), "u long, v long, w double, channel int"), collapse=True)
    p = objective.min_dominant_power(edges, 16)
    labels = partition.partition(edges, strategy="kernel").labels
    best = [r["cand"] for r in hierarchy.qp_minimizers(edges, hierarchy.all_labelings(graph.vertices(edges)), [p]).collect()]
    assert best == [hierarchy.candidate_of(labels)]


def test_levelwise_flags_large_ties(spark):
    edges = graph.build(spark.createDataFrame(random_edges(12, 40, 3, distinct=False), "u long, v long, w double, channel int"))
    flags = {r["tie_exact"] for r in hierarchy.partition_levelwise(edges, exact_limit=4).collect()}
    assert False in flags
    small = graph.build(spark.createDataFrame(random_edges(6, 10, 3, distinct=False), "u long, v long, w double, channel int"))
    e = small.toPandas()
    found = {r["v"]: r["cluster"] for r in hierarchy.partition_levelwise(small).collect()}
    sizes = sorted({abs(x) for x in e.w}, reverse=True)
    drop = lambda lab: [sum((w > 0) != (lab[u] == lab[v]) for u, v, w in zip(e.u, e.v, e.w) if abs(w) == s) for s in sizes]
    assert drop(found) == drop(kernels.exact_levels(e.u, e.v, e.w, vertices=()))


def test_grid_stays_inside_and_strides(spark):
    shape = raster.Shape(2, 6, 7)
    offsets = raster.pattern("compact", ring=3, deep=True)
    pairs = raster.neighbour_pairs(shape.pixels(spark), shape, offsets).collect()
    want = 0
    for o in offsets:
        for z in range(2):
            for y in range(6):
                for x in range(7):
                    inside = z + o.dz < 2 and 0 <= y + o.dy < 6 and 0 <= x + o.dx < 7
                    want += inside and y % o.stride == 0 and x % o.stride == 0
    assert len(pairs) == want and all(0 <= r["other"] < 2 * 6 * 7 for r in pairs)


def test_symmetries_average_back_at_the_pairs(spark):
    shape = raster.Shape(1, 6, 6)
    offsets = raster.pattern("compact", ring=3)
    pairs = raster.neighbour_pairs(shape.pixels(spark), shape, offsets)
    rows = pairs.select(F.least("pix", "other").alias("u"), F.greatest("pix", "other").alias("v"), "channel", "attract", F.lit(1).cast("long").alias("target"))
    out = affinity.average_over_symmetries(rows, lambda r: r.withColumn("a", F.lit(4).cast("long")), shape, offsets)
    assert {(r["total"], r["copies"]) for r in out.collect()} == {(28, 7)}


def test_elastic_stays_near(spark):
    shape = raster.Shape(1, 16, 16)
    far = affinity.elastic(shape.pixels(spark), shape).where("abs(y - source div 16) > 3 or abs(x - source % 16) > 3")
    assert far.isEmpty()


def test_log_odds_are_monotone_in_affinity(spark):
    from signpart.functions.expressions import log_odds

    rows = [log for (log,) in spark.range(1, 100).select(log_odds(F.col("id") / 100.0, F.lit(True))).collect()]
    assert rows == sorted(rows)


def _least_power(sizes, limit=400):
    """In integers."""
    sizes = sorted(sizes)
    for p in range(1, limit):
        if all(sizes[k] ** p > sum(x**p for x in sizes[:k]) for k in range(len(sizes))):
            return p
    return None


@pytest.mark.parametrize("sizes", [(100, 101, 102, 10**9), (1, 2, 3), (3, 4, 5), (1, 2, 4, 8, 16), (7,), (5, 6, 7, 8, 9), tuple(2**k for k in range(200))])
@pytest.mark.parametrize("each", [100_000, 2])
def test_least_dominant_power_is_exact(spark, monkeypatch, sizes, each):
    """With sizes far apart, with equal sums, and in several ranges of sizes."""
    if len(sizes) > 9 and each == 2:
        pytest.skip("a hundred ranges")
    monkeypatch.setattr(objective, "LEVELS_OF_A_TASK", each)
    edges = graph.build(spark.createDataFrame([(k, k + 1, float(x if k % 2 else -x), 0) for k, x in enumerate(sizes)], "u long, v long, w double, channel int"))
    p = _least_power(sizes)
    assert objective.is_dominant_power(edges, p).first()["dominant"]
    assert p == 1 or not objective.is_dominant_power(edges, p - 1).first()["dominant"]


def test_ties_are_never_dominated(spark):
    edges = graph.build(spark.createDataFrame([(0, 1, 5.0, 0), (1, 2, -5.0, 0)], "u long, v long, w double, channel int"))
    assert not objective.is_dominant_power(edges, 100).first()["dominant"] and objective.min_dominant_power(edges, 64) is None
    assert objective.is_dominant_power(edges.limit(0), 3).first()["dominant"]


def test_scores_of_several_labelings_are_those_of_each(spark):
    """One plan for all, a labeling without any true label among them."""
    rows = [(k, (7 * i + k) % (3 + k), None if k == 2 or i % 5 == 0 else i // 9) for k in range(3) for i in range(60)]
    table = spark.createDataFrame(rows, "k int, cluster long, gt long")
    got = metrics.scores_by(table, "k")
    for r in got.collect():
        assert tuple(r)[1:] == tuple(metrics.scores_of(table.where(f"k = {r.k}").select("cluster", "gt"), "one").first())[1:]
    assert got.count() == 3 and "NestedLoop" not in got._jdf.queryExecution().toString()
