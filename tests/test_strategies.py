"""The distributed strategies against the kernel, and the edges of the input."""

import pytest

from signpart import kernels, tables
from signpart.operators import components, graph, partition, predicates, seeded
from tests.conftest import random_edges


def built(spark, rows):
    return graph.build(spark.createDataFrame(rows, "u long, v long, w double, channel int"))


def labels_of(df):
    return {r["v"]: r["cluster"] for r in df.collect()}


def reference(edges):
    e = edges.toPandas()
    return kernels.greedy(e.u, e.v, e.w, e.edge_id)


@pytest.mark.parametrize("options", [{"strategy": "kernel"}, {"strategy": "component"}, {"strategy": "component", "cap": 60}, {"strategy": "banded", "bands": 3}, {"strategy": "dominance"}], ids=str)
def test_strategies_agree(spark, options):
    edges = built(spark, random_edges(30, 80, 11, distinct=False))
    assert labels_of(partition.partition(edges, **options).labels) == reference(edges).labels


def test_a_band_beyond_the_cap_is_cut(spark):
    edges = built(spark, random_edges(25, 90, 5))
    assert labels_of(partition.partition(edges, strategy="banded", bands=1, cap=70).labels) == reference(edges).labels


@pytest.mark.parametrize("mode", ["tree", "full"])
def test_active_set(spark, mode):
    edges = built(spark, random_edges(20, 60, 2))
    e, out = edges.toPandas(), reference(edges)
    active = {r["edge_id"]: r["active"] for r in partition.partition(edges, mode=mode, strategy="kernel").active().collect()}
    assert active == {k: int(d in kernels.ACTIVE[mode]) for k, d in zip(e.edge_id, out.decisions)}


def test_certificate_accepts_the_result_and_nothing_else(spark):
    edges = built(spark, random_edges(14, 40, 8))
    labels = partition.partition(edges, strategy="kernel").labels
    assert {r["n"] for r in predicates.certificate(edges, labels).collect()} == {0}
    found = labels_of(labels)
    moved = max(x for x, c in found.items() if x != c)  # leaves a cluster of several
    for change in (f"case when v = {moved} then 99 else cluster end", "0"):
        wrong = labels.selectExpr("v", f"cast({change} as long) as cluster")
        assert sum(r["n"] for r in predicates.certificate(edges, wrong).collect()) > 0


def test_seeded_forms_agree(spark):
    edges = built(spark, random_edges(20, 60, 4))
    seeds = spark.createDataFrame([(0, 0), (5, 1), (9, 2)], "v long, seed long")
    assert labels_of(seeded.seeded_partition(edges, seeds)) == labels_of(seeded.seeded_by_hub(edges, seeds))


def test_distributed_components_and_forest_equal_one_task(spark):
    edges = built(spark, [(a, b, abs(w), c) for a, b, w, c in random_edges(60, 70, 9)])
    assert labels_of(components.components(edges, graph.vertices(edges), small=1)) == labels_of(components.components(edges, graph.vertices(edges)))
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(components.max_spanning_forest(edges, small=1)) == rows(components.max_spanning_forest(edges))


def test_empty_isolated_loops_and_zeros(spark):
    empty = built(spark, [])
    assert partition.partition(empty, strategy="kernel").labels.count() == 0
    alone = spark.createDataFrame([(7,), (8,)], "v long")
    edges = built(spark, [(1, 1, 5.0, 0), (1, 2, 0.0, 1), (3, 2, 4.0, 2)])
    assert edges.count() == 1
    assert labels_of(partition.partition(edges, alone, strategy="kernel").labels) == {2: 2, 3: 2, 7: 7, 8: 8}


@pytest.mark.parametrize("weight", [float("nan"), float("inf"), None])
def test_weights_that_are_not_numbers_raise(spark, weight):
    with pytest.raises(Exception, match="finite"):
        built(spark, [(1, 2, weight, 0)]).collect()


def test_string_ids_are_refused(spark):
    from signpart import schemas

    with pytest.raises(TypeError):
        schemas.require(spark.createDataFrame([("a", "b", 1.0)], "u string, v string, w double"), schemas.EDGES, "a graph")


def test_first_steps_rebuild_the_active_set(spark):
    edges = tables.written(built(spark, [(0, 1, 9.0, 0), (1, 2, -8.0, 1), (0, 2, 7.0, 2), (2, 3, 6.0, 3)]))
    steps = predicates.by_first_steps(edges, edges.limit(0), 4)
    active = partition.partition(edges, strategy="kernel").active().where("active = 1")
    assert {r["edge_id"] for r in steps.collect()} == {r["edge_id"] for r in active.collect()}


def test_following_a_stream_of_edges(spark):
    from signpart.streaming import streams

    edges = built(spark, random_edges(12, 30, 6))
    growing = streams.GrowingPartition(spark)
    rows = edges.orderBy("v").collect()
    for part in (rows[:10], rows[10:20], rows[20:]):  # out of order: earlier edges come late
        growing.add(spark.createDataFrame(part, edges.schema))
    assert labels_of(growing.labels()) == reference(edges).labels


def test_late_edges_leave_other_components_alone(spark):
    from signpart.streaming import streams

    # Three groups that attract inside and repel across; batches in turn late and in order.
    rows = [(10 * g + a, 10 * g + b, float(s * (100 - 7 * a - 3 * b - g)), 0) for g in range(3) for a, b, s in ((0, 1, 1), (1, 2, 1), (0, 2, -1), (2, 3, 1), (1, 3, -1))]
    rows += [(1, 12, -40.5, 0), (2, 23, -30.5, 0), (13, 22, -20.5, 0)]
    later = [[r for r in rows if r[0] < 10], [r for r in rows if 10 <= r[0] < 20], [r for r in rows if r[0] >= 20], [(3, 10, 99.5, 0)], [(13, 20, 1.5, 0), (3, 23, 0.5, 0)]]
    growing, seen = streams.GrowingPartition(spark), []
    for batch in later:
        seen += batch
        growing.add(built(spark, batch))
        assert labels_of(growing.labels()) == reference(built(spark, seen)).labels


def _labels_by_kernel(links, vertices):
    forest = kernels.Forest()
    for a, b in links:
        ra, rb = forest.find(a), forest.find(b)
        forest.up[max(ra, rb)] = min(ra, rb)
    return forest.labels(vertices)


def test_components_of_ranges(spark):
    """A long path needs no rounds over all its edges, and graphs without near ids come out too."""
    path = [(k, k + 1) for k in range(3000) if k % 500 != 499]
    made = components.components(spark.createDataFrame(path, "u long, v long"), small=400, most_rounds=1)
    assert labels_of(made) == _labels_by_kernel(path, range(3000))
    far = [(u * 7919 % 1000, v * 104729 % 1000) for u, v, _, _ in random_edges(1000, 700, 3)]
    links = [(a, b) for a, b in far if a != b]
    made = components.components(spark.createDataFrame(links, "u long, v long"), spark.range(1000).withColumnRenamed("id", "v"), small=50)
    assert labels_of(made) == _labels_by_kernel(links, range(1000))


def test_pixels_choose_among_the_sites_around(spark):
    """Without a join of pixels to sites; the same sites as by trying all."""
    from signpart import workloads
    from tests.conftest import DATA

    made = workloads.raster_truth(spark, DATA)
    assert "Join" not in made._jdf.queryExecution().toString()
    _, across = workloads.raster_shape(spark, DATA)
    cell = workloads.CELL
    sites = [(r.vec_id, *((p * cell) + int((x + 1) / 2 * cell // 1) for p, x in zip(divmod(r.vec_id, across), r.embedding[:2]))) for r in tables.table(spark, DATA, "embeddings").collect()]
    rows = made.where("pix % 1999 = 0").collect()
    assert len(rows) == -(-((across * cell) ** 2) // 1999)
    for r in rows:
        assert r.gt == min(((r.y - y) ** 2 + (r.x - x) ** 2, k) for k, y, x in sites if abs(k // across - r.y // cell) <= 2 and abs(k % across - r.x // cell) <= 2)[1]


def test_certificate_streams_its_clusters(spark):
    """No call for each cluster or pair of clusters, and the counts of a wrong labeling by hand."""
    rows = [(0, 1, 9.0), (1, 2, -8.0), (2, 3, 7.0), (0, 3, -6.0), (4, 5, 5.0), (3, 4, 4.0)]
    edges = graph.build(spark.createDataFrame(rows, "u long, v long, w double"))
    given = lambda pairs: spark.createDataFrame(pairs, "v long, cluster long")
    counts = lambda made: {r.violation: r.n for r in made.collect()}
    right = predicates.certificate(edges, given([(0, 0), (1, 0), (2, 2), (3, 2), (4, 2), (5, 2)]))
    assert "Pandas" not in right._jdf.queryExecution().toString()
    assert set(counts(right).values()) == {0}
    wrong = counts(predicates.certificate(edges, given([(0, 0), (1, 0), (2, 0), (3, 0), (4, 4), (5, 5)])))
    assert wrong == {"cluster_not_joined": 1, "inner_repulsion_not_joined_before": 2, "outer_attraction_not_blocked": 2}
