"""Graphs settled tile by tile give what one kernel gives for the whole graph."""

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from signpart import kernels, tables, workloads
from signpart.baselines import multicut, watershed
from signpart.operators import affinity, graph, partition, raster, seeded, tiles
from tests.conftest import DATA, random_edges


def _places(*sizes):
    return [lambda c, n=n, k=k: F.floor((c + F.lit(k * n // 3)) / F.lit(n)) for k, n in enumerate(sizes)]


def _near(n, m, seed):
    """Random edges, most of them between near vertices, with many equal weights."""
    rows = []
    for u, v, w, k in random_edges(n, m, seed, distinct=seed % 2 == 0):
        v = v if k % 5 == 0 else min(n - 1, u + 1 + v % 4)
        rows += [(u, v, w, k)] if u < v else []
    return rows


def _labels(df):
    return {r.v: r.cluster for r in df.collect()}


def test_tiles_partition_as_one_kernel_does(spark, monkeypatch):
    monkeypatch.setattr(tiles, "FEW", 0)
    for seed in (1, 2):
        edges = tables.written(graph.build(spark.createDataFrame(_near(120, 420, seed), "u long, v long, w double, channel int")))
        e = edges.toPandas()
        want = kernels.greedy(e.u, e.v, e.w, e.edge_id).labels
        assert _labels(partition.partition(edges, places=_places(10, 25, 60), cap=40 if seed == 1 else 10_000).labels) == want
        if seed == 1:
            continue
        first = e.sort_values("w", key=lambda w: -w.abs()).head(40)
        start = spark.createDataFrame(first[["u", "v", "w"]][kernels_active(first)].reset_index(drop=True))
        rest = edges.join(spark.createDataFrame(first[["edge_id"]]), "edge_id", "left_anti")
        assert _labels(partition.partition(rest, initial=start, places=_places(10, 25)).labels) == _labels(partition.partition(rest, initial=start, strategy="kernel").labels)


def kernels_active(frame):
    return [d in kernels.ACTIVE["full"] for d in kernels.greedy(frame.u, frame.v, frame.w, frame.edge_id).decisions]


def test_tiles_flood_as_one_kernel_does(spark, monkeypatch):
    monkeypatch.setattr(tiles, "FEW", 0)
    rows = [(u, v, abs(w), k) for u, v, w, k in _near(120, 420, 5)]
    edges = graph.build(spark.createDataFrame(rows, "u long, v long, w double, channel int"))
    seeds = spark.createDataFrame([(x, x % 7) for x in range(0, 120, 9)], "v long, seed long")
    assert _labels(seeded.seeded_partition(edges, seeds, places=_places(10, 25, 60), small=50)) == _labels(seeded.seeded_partition(edges, seeds))


def test_raster_affinities_need_no_join(spark):
    """Flat and deep, wide pattern: the pairs of the truth, joined; the same sites in all of them."""
    for depth, name in ((1, "compact"), (2, "layered")):
        shape, _ = workloads.raster_shape(spark, DATA, depth)
        offsets = raster.pattern(name, deep=depth > 1)
        made = workloads.raster_affinities(spark, DATA, offsets, depth=depth)
        assert "Join" not in made._jdf.queryExecution().toString()
        truth = tables.written(workloads.raster_truth(spark, DATA, depth))
        pairs = raster.neighbour_pairs(truth.select("pix", "z", "y", "x"), shape, offsets).select(F.least("pix", "other").alias("u"), F.greatest("pix", "other").alias("v"), "channel", "attract")
        want, got = raster.edge_targets(pairs, truth), tables.written(made.select("u", "v", "channel", "attract", "target"))
        assert got.count() == want.count()
        assert want.exceptAll(got).isEmpty()


def test_blocks_are_smoothed_and_searched_without_joins_of_pixels(spark):
    """Blocks much smaller than the raster, with a hole: the same as on one array."""
    shape, rnd = raster.Shape(1, 300, 290), np.random.default_rng(3)
    h = rnd.integers(0, 4, (300, 290))
    y, x = np.nonzero(rnd.random(h.shape) < 0.98)
    pixels = spark.createDataFrame(pd.DataFrame({"pix": y * 290 + x, "z": 0 * y, "y": y, "x": x, "b": h[y, x]}))
    smoothed = raster.smooth(pixels, "b", 2, shape)
    assert "Join" not in smoothed._jdf.queryExecution().toString()
    there = np.zeros(h.shape, dtype=bool)
    there[y, x] = True
    s = np.where(there, h, 0)
    for _ in range(2):
        s = np.where(there, np.pad(s, ((0, 0), (1, 1)))[:, :-2] + 2 * s + np.pad(s, ((0, 0), (1, 1)))[:, 2:], 0)
        s = np.where(there, np.pad(s, ((1, 1), (0, 0)))[:-2] + 2 * s + np.pad(s, ((1, 1), (0, 0)))[2:], 0)
    assert {r.pix: r.s for r in smoothed.collect()} == dict(zip((y * 290 + x).tolist(), s[y, x].tolist()))
    walls = pixels.where("b = 3")
    far = watershed.distance_transform(pixels, shape, 3).agg(F.sum("d")).first()[0]
    assert far == int(kernels.distance_transform((h == 3) & there)[y, x].sum()) and walls.count() > 0


def test_plateaus_across_blocks(spark):
    shape = raster.Shape(1, 4, 600)
    low = lambda y, x: 0 if y == 1 and 250 <= x < 520 else 0 if (y, x) == (3, 5) else 1
    pixels = spark.createDataFrame([(y * 600 + x, 0, y, x, low(y, x)) for y in range(4) for x in range(600)], "pix long, z long, y long, x long, b long")
    got = {r.pix: r.seed for r in raster.regional_extrema(pixels, "b", shape).collect()}
    assert got == {600 + x: 850 for x in range(250, 520)} | {1805: 1805}


def test_raster_is_partitioned_where_its_edges_are_made(spark, monkeypatch):
    """No edge and no pixel is sent to a tile; the clusters and the truth of the graph of all edges."""
    shape, _ = workloads.raster_shape(spark, DATA)
    edges, truth, _ = workloads.raster_edges(spark, DATA)
    e = edges.toPandas()
    want = kernels.greedy(e.u, e.v, e.w, e.edge_id, vertices=range(shape.height * shape.width)).labels
    sites = {r.pix: r.gt for r in truth.collect()}
    monkeypatch.setattr(workloads.raster, "TILE", 1 << 12)
    rows = tables.written(workloads.raster_tiles(spark, DATA, raster.pattern("compact", ring=5)))
    got = partition.finish_tiles(rows, shape.places(1 << 13)).collect()
    assert {r.v: r.cluster for r in got} == want
    assert {r.v: r.value for r in got} == sites
    assert rows.where(F.col("kind") <= tiles.ACROSS).count() < len(e) // 2


def test_watersheds_by_blocks_flood_as_the_whole_raster_does(spark):
    """Holes, and plateaus across blocks; where a distance is longer than a block sees, it says so."""
    shape, rnd = raster.Shape(1, 200, 280), np.random.default_rng(5)
    b = rnd.integers(0, 6, (200, 280)) * 2000
    y, x = np.nonzero(rnd.random(b.shape) < 0.97)
    pixels = tables.written(spark.createDataFrame(pd.DataFrame({"pix": y * 280 + x, "z": 0 * y, "y": y, "x": x, "b": b[y, x].astype(float)})))
    s = tables.written(raster.smooth(tables.written(watershed.distance_transform(pixels, shape, 9000)), "d", 1, shape))
    want = watershed._flooded(pixels, shape, raster.regional_extrema(s, "s", shape, "max"))
    assert _labels(watershed.watershed_distance(pixels, shape, 9000, 1)) == _labels(want)
    assert watershed._watershed(pixels, shape, lambda block: (block.values["b"], False), 1, "min") is None


def test_air_bridges_in_blocks_are_those_of_the_edges(spark):
    """Clusters in many parts, across blocks; no edge is joined."""
    shape, _ = workloads.raster_shape(spark, DATA)
    offsets = raster.pattern("compact", ring=5)
    labels = tables.written(workloads.raster_truth(spark, DATA).select(F.col("pix").alias("v"), F.col("gt").alias("value"), (F.col("gt") % 3).alias("cluster")))
    edges = affinity.to_edges(workloads.raster_affinities(spark, DATA, offsets[:2]))
    want = {tuple(r) for r in raster.air_bridges(labels.select("v", "cluster"), edges).collect()}
    assert len(want) == 3 and {tuple(r) for r in workloads.raster_air_bridges(labels, shape, offsets).collect()} == want


def test_watersheds_of_several_choices_are_those_of_each(spark):
    """The choices as slices of one raster, with the value that pixels carry; where blocks don't see enough, each by itself."""
    shape, rnd = raster.Shape(1, 200, 280), np.random.default_rng(7)
    for most in (6, 3):  # the second has no boundary of 9000, so distances are too long for a block
        b = rnd.integers(0, most, (200, 280)) * 2000
        y, x = np.nonzero(rnd.random(b.shape) < 0.97)
        pixels = tables.written(spark.createDataFrame(pd.DataFrame({"pix": y * 280 + x, "z": 0 * y, "y": y, "x": x, "b": b[y, x].astype(float), "value": y * x % 11})))
        choices = [(9000, 1), (None, 2), (7000, 2)] if most == 6 else [(9000, 1), (None, 1)]
        got = tables.written(watershed.watersheds(pixels, shape, choices)).toPandas()
        for k, (least, radius) in enumerate(choices):
            one = watershed.watershed_minima(pixels, shape, radius) if least is None else watershed.watershed_distance(pixels, shape, least, radius)
            some = got[got.choice == k]
            assert dict(zip(some.v, some.cluster)) == _labels(one)
            assert (some.value == some.v // 280 * (some.v % 280) % 11).all()


def test_costs_between_clusters_by_blocks_are_those_of_the_edges(spark):
    """Without an edge that is written: the same sums as by joins of the log-odds edges."""
    shape, _ = workloads.raster_shape(spark, DATA)
    offsets, truth = raster.pattern("layered"), tables.written(workloads.raster_truth(spark, DATA))
    labels = tables.written(truth.select(F.col("pix").alias("v"), F.col("gt").alias("value"), (F.col("pix") - F.col("y") % 7 * shape.width - F.col("x") % 9).alias("cluster")))
    costs = multicut.log_odds_edges(affinity.to_edges(workloads.raster_affinities(spark, DATA, offsets)))
    want = {}
    for local in (True, False):
        for r in multicut.contracted_costs(costs.where((F.col("channel") < 2) == local), labels).collect():
            want[r.u, r.v, local] = r.w
    made = workloads.raster_cluster_costs(labels, shape, offsets)
    got = {(r.u, r.v, r.local): r.w for r in made.collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-6 for k in want)
    assert "Join" not in made._jdf.queryExecution().toString()
