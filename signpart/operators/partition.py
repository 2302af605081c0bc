"""The signed greedy partition of a DataFrame of edges, and what follows from its labels.

Strategies, all with the same result:

* kernel: one task solves the graph; for graphs of a checked size.
* component: the components of the attractive edges never interact, so they are
  packed into bins of bounded size and solved side by side.
* banded: the processing order is cut in bands; each band is contracted by the
  labels so far and solved with the exclusions between its clusters.  A band whose
  largest component is too large for a task is cut again.
* dominance: rounds in which every edge that nothing can overtake is applied at once.
* tiles, for graphs whose vertices have places: a tile settles what edges to other tiles
  can't change, larger tiles take over the rest, and bands what no tile settles.
* auto: kernel if the graph is small, else component, with banded for the
  components that are too large for a bin.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signpart import kernels, schemas, tables
from signpart.functions.expressions import order_key, pair
from signpart.operators import components as comp
from signpart.operators import graph, grouped, tiles

#: Edges (with exclusions) that one task takes.
CAP = 2_000_000


@dataclass
class State:
    """What has been decided so far: labels of touched vertices, and pairs of clusters kept apart."""

    labels: DataFrame
    exclusions: DataFrame

    @staticmethod
    def empty(spark) -> State:
        return State(spark.createDataFrame([], schemas.ddl(schemas.LABELS)), spark.createDataFrame([], schemas.ddl(schemas.EXCLUSIONS)))


@dataclass
class Result:
    """labels (v, cluster) of all vertices, and the edges they came from."""

    edges: DataFrame
    labels: DataFrame
    mode: str

    def active(self) -> DataFrame:
        return active_set(self.edges, self.labels, self.mode)


# ---- what follows from labels


def active_set(edges: DataFrame, labels: DataFrame, mode: str = "full") -> DataFrame:
    """edges with ``active`` 1 or 0.

    An attraction is active in full mode exactly if its ends share a cluster, a
    repulsion exactly if they don't; tree mode keeps the maximum spanning forest
    of the inner attractions.  So labels are the whole answer.
    """
    ends = comp.relabelled(edges, labels)
    full = (F.col("w") > 0) == (F.col("cu") == F.col("cv"))
    if mode == "full":
        return ends.select("edge_id", "u", "v", "w", full.cast("int").alias("active"))
    if mode != "tree":
        raise ValueError("mode is 'tree' or 'full'")
    inner = ends.where("w > 0 and cu = cv").select(*edges.columns)
    tree = comp.max_spanning_forest(inner).select("edge_id", "u", "v", F.lit(1).alias("__tree"))
    joined = ends.join(tree, ["edge_id", "u", "v"], "left")
    active = F.when(F.col("w") > 0, F.coalesce("__tree", F.lit(0))).otherwise(full.cast("int"))
    return joined.select("edge_id", "u", "v", "w", active.alias("active"))


def state_of_active(active: DataFrame) -> State:
    """Labels and exclusions of a given active set of (u, v, w) rows; raises if it contradicts itself."""
    labels = tables.written(comp.components(active.where("w > 0")))
    ends = comp.relabelled(active.where("w < 0").select("u", "v"), labels)
    a, b = pair("cu", "cv")
    apart = tables.written(ends.select(a.alias("a"), b.alias("b")).distinct())
    if not apart.where("a = b").isEmpty():
        raise ValueError("the given active set joins two clusters that it keeps apart")
    return State(labels, apart)


# ---- kernels on bins


def _solve_bins(edges: DataFrame, exclusions: DataFrame, of: list[str]) -> tuple[DataFrame, DataFrame]:
    """(labels, exclusions) of the bins: edges and exclusions carry the same bin columns ``of``.

    The result is one table of rows (kind, a, b), written once: kind 0 a label,
    kind 1 an exclusion.
    """

    def solve(e: pd.DataFrame, x: pd.DataFrame) -> pd.DataFrame:
        out = kernels.greedy(e["u"], e["v"], e["w"], e["edge_id"], start_exclusions=zip(x["a"].tolist(), x["b"].tolist()))
        rows = [(0, a, b) for a, b in out.labels.items()] + [(1, a, b) for a, b in out.exclusions]
        return pd.DataFrame(rows, columns=["kind", "a", "b"]).astype({"kind": "int32", "a": "int64", "b": "int64"})

    both = edges.groupBy(*of).cogroup(exclusions.groupBy(*of)).applyInPandas(solve, "kind int, a long, b long")
    made = tables.written(both)
    return made.where("kind = 0").select(F.col("a").alias("v"), F.col("b").alias("cluster")), made.where("kind = 1").select("a", "b")


def _packed(edges: DataFrame, exclusions: DataFrame, cap: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(edges with bin, exclusions with bin, sizes of components beyond the cap).

    Components of the attractions are packed by size class: tiny ones share bins by
    hash, so that a bin holds about ``cap`` edges.  Edges across components keep
    ends apart that never meet and aren't needed for the labels.
    """
    labels = tables.written(comp.components(edges.where("w > 0")))
    ends = comp.relabelled(edges, labels).where("cu = cv")
    sizes = ends.groupBy(F.col("cu").alias("c")).agg(F.count(F.lit(1)).alias("n"))
    sizes = tables.written(sizes)
    total = sizes.agg(F.sum("n")).first()[0] or 0
    bins = max(1, int(-(-total // max(1, cap // 2))))
    bin_of = sizes.select("c", "n", F.when(F.col("n") * 4 > cap, F.col("c")).otherwise(-1 - F.pmod(F.xxhash64("c"), F.lit(bins))).alias("bin"))
    placed = ends.join(bin_of, ends["cu"] == bin_of["c"]).select(*edges.columns, "bin", "n", "c")
    apart = comp.relabelled(exclusions.select(F.col("a").alias("u"), F.col("b").alias("v")), labels).where("cu = cv")
    apart = apart.join(bin_of, apart["cu"] == bin_of["c"]).select(F.col("u").alias("a"), F.col("v").alias("b"), "bin", "n")
    return tables.written(placed), tables.written(apart), sizes.where(F.col("n") > cap)


# ---- bands


@dataclass(frozen=True)
class Band:
    """|w| in (low, high]; within one |w|, u in (u_low, u_high]. None: no bound."""

    high: float | None = None
    low: float | None = None
    u_low: int | None = None
    u_high: int | None = None

    def of(self, edges: DataFrame) -> DataFrame:
        size = F.abs("w")
        for bound, test in ((self.high, lambda b: size <= b), (self.low, lambda b: size > b), (self.u_low, lambda b: F.col("u") > b), (self.u_high, lambda b: F.col("u") <= b)):
            if bound is not None:
                edges = edges.where(test(F.lit(bound)))
        return edges


def equal_bands(edges: DataFrame, n: int) -> list[Band]:
    """About n bands of equal size from approximate quantiles of |w|; any cuts give the same result."""
    cuts = edges.select(F.abs("w").alias("s")).stat.approxQuantile("s", [i / n for i in range(1, n)], 0.2 / n) if n > 1 else []
    cuts = sorted(set(cuts), reverse=True)
    bounds = [None, *cuts, None]
    return [Band(high, low) for high, low in zip(bounds, bounds[1:])]


def _halves(band: Band, edges: DataFrame) -> list[Band]:
    """A band in two, first half first: by |w|, or by u where all |w| are equal."""
    low, middle, high = edges.select(F.min(F.abs("w")), F.percentile_approx(F.abs("w"), 0.5), F.max(F.abs("w"))).first()
    if low < high:
        cut = middle if middle < high else low
        return [Band(band.high, cut, band.u_low, band.u_high), Band(cut, band.low, band.u_low, band.u_high)]
    low, middle, high = edges.select(F.min("u"), F.percentile_approx("u", 0.5), F.max("u")).first()
    if low == high:
        raise ValueError("the edges of one vertex with one |w| exceed the cap of a task")
    cut = middle if middle < high else low
    return [Band(band.high, band.low, band.u_low, cut), Band(band.high, band.low, cut, band.u_high)]


def _relabel_pairs(pairs: DataFrame, merges: DataFrame) -> DataFrame:
    ends = comp.relabelled(pairs.select(F.col("a").alias("u"), F.col("b").alias("v")), merges)
    a, b = pair("cu", "cv")
    return ends.select(a.alias("a"), b.alias("b")).distinct()


def contracted(edges: DataFrame, state: State) -> DataFrame:
    """The edges between clusters of the state: inner and settled ones go, parallel ones collapse to the first."""
    ends = comp.relabelled(edges, state.labels).where("cu <> cv")
    a, b = pair("cu", "cv")
    # The processing order is that of the original ends; it decides which parallel edge counts.
    first = F.min_by(F.struct("edge_id", "u", "v", "w"), order_key())
    pairs = ends.groupBy(a.alias("a"), b.alias("b")).agg(first.alias("e"))
    return pairs.join(state.exclusions, ["a", "b"], "left_anti").select("a", "b", "e.edge_id", F.col("e.u").alias("ou"), F.col("e.v").alias("ov"), "e.w")


def _numbered(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("edge_id"), F.col("a").alias("u"), F.col("b").alias("v"), "w", F.col("ou").alias("__ou"), F.col("ov").alias("__ov"))


def _solve_ordered(edges: DataFrame, exclusions: DataFrame, of: list[str]) -> tuple[DataFrame, DataFrame]:
    """_solve_bins for contracted edges, whose order is that of their original ends."""

    def solve(e: pd.DataFrame, x: pd.DataFrame) -> pd.DataFrame:
        order = kernels.priority(e["__ou"], e["__ov"], e["w"], e["edge_id"])
        e = e.iloc[order]
        sign = (e["w"] > 0).to_numpy()
        rank = (len(e) - pd.RangeIndex(len(e)).to_numpy()).astype(float)
        out = kernels.greedy(e["u"].to_numpy(), e["v"].to_numpy(), rank * (2 * sign - 1), e["edge_id"].to_numpy(), start_exclusions=zip(x["a"].tolist(), x["b"].tolist()))
        rows = [(0, a, b) for a, b in out.labels.items()] + [(1, a, b) for a, b in out.exclusions]
        return pd.DataFrame(rows, columns=["kind", "a", "b"]).astype({"kind": "int32", "a": "int64", "b": "int64"})

    made = tables.written(edges.groupBy(*of).cogroup(exclusions.groupBy(*of)).applyInPandas(solve, "kind int, a long, b long"))
    return made.where("kind = 0").select(F.col("a").alias("v"), F.col("b").alias("cluster")), made.where("kind = 1").select("a", "b")


def run_bands(edges: DataFrame, bands: list[Band], state: State, cap: int = CAP) -> State:
    """The state after all bands, in their order; each band's state is written, so a job can go on from any."""
    queue = list(bands)
    while queue:
        band = queue.pop(0)
        live = tables.written(_numbered(contracted(band.of(edges), state)))
        touched = graph.vertices(live)
        near = state.exclusions.join(touched.withColumnRenamed("v", "a"), "a", "left_semi").join(touched.withColumnRenamed("v", "b"), "b", "left_semi")
        near = tables.written(near)
        if tables.at_most(live.select("u").unionAll(near.select("a")), cap):
            merges, apart = _solve_ordered(live.withColumn("bin", F.lit(0)), near.withColumn("bin", F.lit(0)), ["bin"])
            outside = state.exclusions.join(near, ["a", "b"], "left_anti")
        else:
            placed, binned, large = _packed(live, near, cap)
            if not large.isEmpty():
                queue[:0] = _halves(band, live)
                continue
            merges, apart = _solve_ordered(placed, binned, ["bin"])
            # Repulsions across components stay apart for good; they come back as exclusions.
            a, b = pair("u", "v")
            across = live.where("w < 0").select(a.alias("a"), b.alias("b"))
            apart = apart.unionByName(across)
            outside = state.exclusions
        apart = _relabel_pairs(apart.unionByName(outside), merges).where("a <> b")
        old = state.labels.select("v", F.col("cluster").alias("was")).join(merges.select(F.col("v").alias("was"), F.col("cluster").alias("now")), "was", "left").select("v", F.coalesce("now", "was").alias("cluster"))
        new = merges.join(state.labels, "v", "left_anti")
        state = State(tables.written(old.unionByName(new)), tables.written(apart))
    return state


# ---- dominance


def dominance_rounds(edges: DataFrame, state: State, most_rounds: int) -> tuple[State, bool]:
    """Applies every edge that nothing can overtake, round by round; (state, whether all edges are settled).

    A repulsion that is first at either end is active now; an attraction that is
    first at both ends, or at an end without exclusions, merges now.
    """
    for _ in range(most_rounds):
        live = tables.written(contracted(edges, state))
        if live.isEmpty():
            return state, True
        key = F.struct((-F.abs(F.col("w"))).alias("k0"), F.col("ou").alias("k1"), F.col("ov").alias("k2"), F.col("edge_id").alias("k3"))
        first = live.select(F.explode(F.array("a", "b")).alias("c"), key.alias("k")).groupBy("c").agg(F.min("k").alias("k"))
        bound = state.exclusions.select(F.explode(F.array("a", "b")).alias("c")).distinct().withColumn("held", F.lit(True))
        ends = first.join(bound, "c", "left").select("c", "k", F.coalesce("held", F.lit(False)).alias("held"))
        ea = ends.select(F.col("c").alias("a"), F.col("k").alias("ka"), F.col("held").alias("ha"))
        eb = ends.select(F.col("c").alias("b"), F.col("k").alias("kb"), F.col("held").alias("hb"))
        at = live.withColumn("k", key).join(ea, "a").join(eb, "b")
        top_a, top_b = F.col("k") == F.col("ka"), F.col("k") == F.col("kb")
        ready = tables.written(at.where(F.when(F.col("w") < 0, top_a | top_b).otherwise((top_a & top_b) | (top_a & ~F.col("ha")) | (top_b & ~F.col("hb")))).select("a", "b", "w"))
        merges = tables.written(comp.components(ready.where("w > 0").select(F.col("a").alias("u"), F.col("b").alias("v"))))
        apart = _relabel_pairs(state.exclusions.unionByName(ready.where("w < 0").select("a", "b")), merges)
        old = state.labels.select("v", F.col("cluster").alias("was")).join(merges.select(F.col("v").alias("was"), F.col("cluster").alias("now")), "was", "left").select("v", F.coalesce("now", "was").alias("cluster"))
        state = State(tables.written(old.unionByName(merges.join(state.labels, "v", "left_anti"))), tables.written(apart))
    return state, False


# ---- the method


def partition(edges: DataFrame, vertices: DataFrame | None = None, mode: str = "full", strategy: str = "auto", initial: DataFrame | None = None, bands: int = 8, cap: int = CAP, most_rounds: int = 400, places: list[tiles.Place] | None = None, complete: bool = False) -> Result:
    """Labels of all vertices (v, cluster) under the signed greedy partition.

    ``places`` are the tiles of a vertex, smaller ones first; with them, auto is
    tiles.  ``complete`` says that ``vertices`` has all ends of edges, once each.

    ``initial`` is an active set of (u, v, w) edges to start from (a warm start);
    its edges should not be among ``edges`` again.
    """
    spark = edges.sparkSession
    state = State.empty(spark) if initial is None else state_of_active(initial)
    everyone = vertices.select(F.col("v").cast("long").alias("v")) if complete else graph.vertices(edges, vertices)
    if initial is not None:
        everyone = everyone.unionByName(graph.vertices(initial)).distinct()
    if strategy == "auto" and places:
        strategy = "tiles"
    if strategy == "auto":
        from signpart.plans import planner

        strategy = planner.choose(edges, cap, initial is not None)
    if strategy == "kernel":
        state = _one_task(edges, state)
    elif strategy == "component":
        state = _by_component(edges, state, bands, cap)
    elif strategy == "banded":
        state = run_bands(edges, equal_bands(edges, bands), state, cap)
    elif strategy == "tiles":
        state = _by_tiles(edges, state if initial is not None else None, places or [], bands, cap)
    elif strategy == "dominance":
        state, done = dominance_rounds(edges, state, most_rounds)
        if not done:
            state = run_bands(edges, equal_bands(edges, bands), state, cap)
    else:
        raise ValueError("strategy is auto, kernel, component, banded, dominance or tiles")
    labels = everyone.join(state.labels, "v", "left").select("v", F.coalesce("cluster", "v").alias("cluster"))
    return Result(edges, labels, mode)


def _one_task(edges: DataFrame, state: State) -> State:
    """The whole graph in one task; for graphs whose size was checked."""
    live = _numbered(contracted(edges, state)).withColumn("bin", F.lit(0))
    merges, apart = _solve_ordered(live, state.exclusions.withColumn("bin", F.lit(0)), ["bin"])
    old = state.labels.select("v", F.col("cluster").alias("was")).join(merges.select(F.col("v").alias("was"), F.col("cluster").alias("now")), "was", "left").select("v", F.coalesce("now", "was").alias("cluster"))
    return State(tables.written(old.unionByName(merges.join(state.labels, "v", "left_anti"))), apart)


def _by_tiles(edges: DataFrame, state: State | None, places: list[tiles.Place], bands: int, cap: int) -> State:
    """Tiles of growing size; what is too large for a task in the end goes through the bands."""
    if not places:
        raise ValueError("tiles need the places of vertices")
    if state is None:
        live, apart = edges.select("u", "v", F.col("u").alias("ou"), F.col("v").alias("ov"), "edge_id", "w"), None
    else:
        live, apart = tables.written(contracted(edges, state).select(F.col("a").alias("u"), F.col("b").alias("v"), "ou", "ov", "edge_id", "w")), state.exclusions
    merges, rest, kept, done = tiles.settle(live, places, cap, apart)
    old = merges if state is None else state.labels.select("v", F.col("cluster").alias("was")).join(merges.select(F.col("v").alias("was"), F.col("cluster").alias("now")), "was", "left").select("v", F.coalesce("now", "was").alias("cluster")).unionByName(merges.join(state.labels, "v", "left_anti"))
    state = State(tables.written(old), kept if kept is not None else State.empty(edges.sparkSession).exclusions)
    return state if done else _banded_rest(rest, state, bands, cap)


def finish_tiles(made: DataFrame, places: list[tiles.Place], bands: int = 8, cap: int = CAP) -> DataFrame:
    """(v, value, cluster) of all vertices, from the written rows of tiles that carried a value (``tiles.solved``)."""
    merges, rest, kept, done = tiles.settle_rest(made, places, cap)
    labels = tiles.labelled(made, merges)
    if done:
        return labels
    state = _banded_rest(rest, State(tables.written(labels.select("v", "cluster")), kept), bands, cap)
    return labels.select("v", "value").join(state.labels, "v")


def _banded_rest(rest: DataFrame, state: State, bands: int, cap: int) -> State:
    """What no tile settles, by bands; rest has the ends that the order goes by."""
    rest = rest.select("edge_id", F.col("ou").alias("u"), F.col("ov").alias("v"), "w", F.lit(None).cast("int").alias("channel"))
    return run_bands(rest, equal_bands(rest, bands), state, cap)


def _by_component(edges: DataFrame, state: State, bands: int, cap: int) -> State:
    """Components side by side; those beyond the cap together in bands."""
    live = tables.written(_numbered(contracted(edges, state)))
    placed, apart, large = _packed(live, state.exclusions, cap)
    merges, kept = _solve_ordered(placed.where(F.col("n") <= cap), apart.where(F.col("n") <= cap), ["bin"])
    old = state.labels.select("v", F.col("cluster").alias("was")).join(merges.select(F.col("v").alias("was"), F.col("cluster").alias("now")), "was", "left").select("v", F.coalesce("now", "was").alias("cluster"))
    state = State(tables.written(old.unionByName(merges.join(state.labels, "v", "left_anti"))), tables.written(kept.unionByName(_relabel_pairs(state.exclusions, merges)).distinct()))
    if large.isEmpty():
        return state
    # Their ends carry the labels so far, so the original edges of these components go through the bands.
    rest = placed.where(F.col("n") > cap).select("edge_id", F.col("__ou").alias("u"), F.col("__ov").alias("v"), "w", F.lit(None).cast("int").alias("channel"))
    return run_bands(rest, equal_bands(rest, bands), state, cap)


# ---- traces and counters


def trace(edges: DataFrame, by: str | None = None) -> DataFrame:
    """(g, rank, u, v, w, decision) of every edge, in groups ``by`` a column that are separate graphs."""
    keyed = edges.withColumn("g", F.col(by) if by else F.lit(0).cast("long"))

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        out = kernels.greedy(frame["u"], frame["v"], frame["w"], frame["edge_id"])
        order = kernels.priority(frame["u"], frame["v"], frame["w"], frame["edge_id"])
        made = frame.assign(decision=out.decisions).iloc[order]
        return made.assign(rank=range(1, len(made) + 1))[["g", "rank", "u", "v", "w", "decision"]]

    return keyed.select("g", *schemas.EDGES.names).groupBy("g").applyInPandas(run, "g long, rank long, u long, v long, w double, decision string")


def counters(edges: DataFrame) -> DataFrame:
    """Counts of decisions from a trace: (decision, n)."""
    return trace(edges).groupBy("decision").agg(F.count(F.lit(1)).alias("n"))


def probe_cost(edges: DataFrame, small: int = comp.SMALL) -> DataFrame:
    """(counter, n) of the kernel's work: merges, exclusions, look-ups, and set members moved in merges.

    Graphs that no edge ties together count by themselves, so the counters are
    sums over the components of all edges.  A task streams its edges in processing
    order and holds clusters and exclusions of one component, never the edges.
    """
    edges = tables.written(edges.select(*schemas.EDGES.names))
    parts = tables.written(comp.components(edges, small=small))
    placed = edges.join(parts.select(F.col("v").alias("u"), F.col("cluster").alias("c")), "u")
    key = order_key()
    dealt = placed.repartition("c").sortWithinPartitions("c", *(key.getField(f"k{i}") for i in range(4))).select("c", "u", "v", "w")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, at, process = dict.fromkeys(kernels.Greedy().count, 0), None, kernels.Greedy()
        for batch in batches:
            c, (u, v, w) = batch["c"].to_numpy(), (batch[x].to_pylist() for x in ("u", "v", "w"))
            cuts = [0, *(np.flatnonzero(c[1:] != c[:-1]) + 1).tolist(), len(c)]
            for a, b in zip(cuts, cuts[1:]):
                if a < b and c[a] != at:
                    total = {k: n + process.count[k] for k, n in total.items()}
                    at, process = c[a], kernels.Greedy()
                process.take(u[a:b], v[a:b], w[a:b])
        total = {k: n + process.count[k] for k, n in total.items()}
        yield pa.RecordBatch.from_pydict({"counter": list(total), "n": list(total.values())})

    names = edges.sparkSession.createDataFrame([(k, 0) for k in kernels.Greedy().count], "counter string, n long")
    return dealt.mapInArrow(run, "counter string, n long").unionByName(names).groupBy("counter").agg(F.sum("n").alias("n"))


def partition_groups(edges: DataFrame, by: str) -> DataFrame:
    """(g, v, cluster) where each value of ``by`` is a separate graph; a group must fit a task."""

    rows = edges.withColumn("g", F.col(by))
    return grouped.labels_per_group(rows, ["u", "v", "w", "edge_id"], lambda u, v, w, e: kernels.greedy(u, v, w, e).labels)
