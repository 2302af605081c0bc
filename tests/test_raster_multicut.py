"""Multicuts tile by tile: the contraction of one kernel, and moves that leave it nothing to do."""

import random

import pytest
from pyspark.sql import functions as F

from signpart import kernels, tables, workloads
from signpart.baselines import multicut, raster_multicut
from signpart.operators import affinity, raster
from tests.conftest import DATA


def _corner(spark, pixels=60):
    """(costs with local, shape) of a corner of the planted raster, and its costs as lists."""
    shape, _ = workloads.raster_shape(spark, DATA)
    edges = affinity.to_edges(workloads.raster_affinities(spark, DATA, raster.pattern("layered")))
    inside = lambda c: (F.floor(F.col(c) / shape.width) < pixels) & (F.col(c) % shape.width < pixels)
    costs = tables.written(multicut.log_odds_edges(edges.where(inside("u") & inside("v"))).withColumn("local", F.col("channel") < 2))
    e = costs.toPandas().sort_values(["u", "v", "w"])
    return costs, shape, (e.u.tolist(), e.v.tolist(), e.w.tolist(), e.local.tolist())


def _labels(df):
    return {r.v: r.cluster for r in df.collect()}


def test_a_part_settles_what_the_whole_contraction_does():
    """Random graphs in two parts: joins that hold in the whole, final clusters that are those of the whole."""
    settled = 0
    for seed in range(120):
        rnd = random.Random(seed)
        n, costs = rnd.randint(6, 40), {}
        for _ in range(3 * n):
            a = rnd.randrange(n - 1)
            costs[a, min(n - 1, a + rnd.randint(1, 4))] = rnd.randint(-6, 6) if seed % 2 else round(rnd.gauss(0.3, 2) / kernels.GRAIN) * kernels.GRAIN
        edges = [(a, b, float(c)) for (a, b), c in costs.items()]
        want = kernels.contraction(*zip(*edges), vertices=range(n))
        cut, label = rnd.randint(2, n - 2), list(range(n))
        for part in (range(cut), range(cut, n)):
            some = [(a, b, c) for a, b, c in edges if a in part or b in part]
            if not some:
                continue
            least, opened, _ = kernels.contraction_within(n, *(list(x) for x in zip(*some)), [x not in part for x in range(n)])
            for x in part:
                label[x] = least[x]
                if not opened[least[x]]:
                    settled += 1
                    assert {y for y in part if least[y] == least[x]} == {y for y in range(n) if want[y] == want[x]}
        assert all(want[x] == want[label[x]] for x in range(n))
    assert settled > 500


@pytest.mark.parametrize("lifted, side", [(False, 24), (True, 40)])
def test_tiles_leave_one_kernel_nothing_to_do(spark, monkeypatch, lifted, side):
    """Tiles that are small beside clusters, and larger ones; no task is given the whole raster."""
    monkeypatch.setattr(raster_multicut, "SIDE", side)
    monkeypatch.setattr(raster_multicut, "ALONE", 2_000)
    costs, shape, (u, v, w, local) = _corner(spark)
    near = [k for k, x in enumerate(local) if x or not lifted]
    want = kernels.contraction([u[k] for k in near], [v[k] for k in near], [w[k] for k in near], vertices=set(u) | set(v))
    start = raster_multicut.contraction(costs.where("local") if lifted else costs, shape)
    assert {x: c for x, c in want.items() if x != c} == _labels(start)
    solved = multicut.lifted_multicut(costs, F.col("local"), shape=shape) if lifted else multicut.multicut(costs, shape=shape)
    rows = solved.collect()
    got = {r.v: r.cluster for r in rows}
    assert len(rows) == len(got) and got.keys() == want.keys() and {r.g for r in rows} == {0}
    assert kernels.cut_cost(u, v, w, got) <= kernels.cut_cost(u, v, w, want) + 1e-6
    assert kernels.moves(u, v, w, got, local=local if lifted else None) == got
    if not lifted:
        contracted = tables.written(multicut.multicut(costs, method="gaec", shape=shape))
        assert _labels(contracted) == want
        assert _labels(multicut.multicut(costs, shape=shape, start=contracted)) == got
