"""Graphs with a place for each vertex, settled tile by tile.

A tile solves its own edges side by side with the others and settles what no edge
to another tile can change (``kernels.greedy_within``, ``kernels.flood_within``).
The rest is a smaller graph of clusters, which larger tiles take over; the last tile
is everything, and by then only what lies along the borders is left.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from signpart import kernels, tables
from signpart.functions.expressions import order_key, pair
from signpart.operators import components as comp

Place = Callable[[Column], Column]

#: Rows that aren't worth more than one tile.
FEW = 50_000
#: Rows of renamed clusters that may be sent to all executors.
RENAMED = 1_000_000
#: Kinds of rows that go to a tile and come from it.
INNER, ACROSS, APART, APART_OUTSIDE, SEED, LABEL = range(6)
ROW = "kind int, a long, b long, ou long, ov long, edge_id long, w double"
_EDGE = ("ou", "ov", "edge_id", "w")


def everywhere(c: Column) -> Column:
    """One tile for all."""
    return F.lit(0).cast("long")


def to_tiles(live: DataFrame, place: Place) -> DataFrame:
    """(tile, row…) of edges: one row for an inner edge, one for each end of another."""
    tu, tv = place(F.col("u")), place(F.col("v"))
    row = lambda tile, kind, a, b: F.struct(tile.alias("tile"), F.lit(kind).alias("kind"), F.col(a).alias("a"), F.col(b).alias("b"))
    inner, across = F.array(row(tu, INNER, "u", "v")), F.array(row(tu, ACROSS, "u", "v"), row(tv, ACROSS, "v", "u"))
    return live.select(F.explode(F.when(tu == tv, inner).otherwise(across)).alias("r"), *_EDGE).select("r.*", *_EDGE)


def _pairs_to_tiles(apart: DataFrame, place: Place) -> DataFrame:
    sent = to_tiles(apart.select(F.col("a").alias("u"), F.col("b").alias("v"), *(F.lit(0).cast("double" if c == "w" else "long").alias(c) for c in _EDGE)), place)
    return sent.withColumn("kind", F.when(F.col("kind") == INNER, APART).otherwise(APART_OUTSIDE))


def made_rows(blocks: list[tuple[int, list]]) -> pa.Table:
    """Rows of (kind, columns a, b and perhaps the edge's)."""
    schema = pa.schema([("kind", pa.int32()), *((c, pa.int64()) for c in ("a", "b", "ou", "ov", "edge_id")), ("w", pa.float64())])
    parts = []
    for kind, columns in blocks:
        n = len(columns[0])
        full = columns + [np.zeros(n, np.int64)] * (5 - min(5, len(columns))) + ([np.zeros(n)] if len(columns) < 6 else [])
        parts.append(pa.Table.from_arrays([pa.array(np.full(n, kind, np.int32)), *(pa.array(c) for c in full)], schema=schema))
    return pa.concat_tables(parts)


def solved(flood: bool, edge: dict[str, np.ndarray], others: dict[int, tuple[np.ndarray, np.ndarray]], carried: tuple[np.ndarray, np.ndarray] | None = None) -> pa.Table:
    """The rows that a tile makes of its edges (kind, a, b, ou, ov, edge_id, w) and the pairs and seeds in ``others``.

    With ``carried`` (vertices, a value of each) every vertex of the tile has a LABEL row, with its value in ou; else those that get another name.
    """
    order = np.lexsort((edge["edge_id"], edge["ov"], edge["ou"], -np.abs(edge["w"])))
    edge = {c: x[order] for c, x in edge.items()}
    kind, a, b, none = edge["kind"], edge["a"], edge["b"], (np.zeros(0, np.int64),) * 2
    others = {k: others.get(k, none) for k in (APART, APART_OUTSIDE, SEED)}
    here = np.unique(np.concatenate([a, b[kind == INNER], *others[APART], others[APART_OUTSIDE][0], others[SEED][0]]) if carried is None else carried[0])
    at = lambda x: np.searchsorted(here, x)
    u, v = at(a), np.where(kind == INNER, at(b), -1)
    if flood:
        marks = np.full(len(here), -1, np.int64)
        marks[at(others[SEED][0])] = others[SEED][1]
        least, waiting = kernels.flood_within(len(here), u.tolist(), v.tolist(), marks.tolist())
    else:
        start = zip(*(at(x).tolist() for x in others[APART]))
        least, waiting, apart = kernels.greedy_within(len(here), u.tolist(), v.tolist(), (edge["w"] > 0).tolist(), start, at(others[APART_OUTSIDE][0]).tolist())
    cluster = here[np.array(least, dtype=np.int64)] if len(here) else here
    moved = cluster != here
    blocks = [(LABEL, [here[moved], cluster[moved]] if carried is None else [carried[0], cluster[at(carried[0])], carried[1]])]
    if flood:
        marked = marks >= 0
        blocks.append((SEED, list(np.unique(np.stack([cluster[marked], marks[marked]]), axis=1))))
    else:
        pairs = np.array(sorted(apart), dtype=np.int64).reshape(-1, 2)
        blocks.append((APART, [here[pairs[:, 0]], here[pairs[:, 1]]]))
    left = np.array(waiting, dtype=np.int64)
    for k in (INNER, ACROSS):
        some = left[kind[left] == k]
        a_now = cluster[u[some]]
        b_now = cluster[v[some]] if k == INNER else b[some]
        if k == INNER:
            # Parallel edges: the first in order decides.
            ends = np.stack([np.minimum(a_now, b_now), np.maximum(a_now, b_now)])
            first = np.sort(np.unique(ends, axis=1, return_index=True)[1]) if len(some) else np.zeros(0, np.int64)
            some, a_now, b_now = some[first], a_now[first], b_now[first]
        blocks.append((k, [a_now, b_now, *(edge[c][some] for c in _EDGE)]))
    return made_rows(blocks)


def _solver(flood: bool):
    def solve(rows: pa.Table) -> pa.Table:
        col = {c: rows[c].to_numpy() for c in ("kind", "a", "b", *_EDGE)}
        is_edge = col["kind"] <= ACROSS
        others = {k: (col["a"][col["kind"] == k], col["b"][col["kind"] == k]) for k in (APART, APART_OUTSIDE, SEED)}
        return solved(flood, {c: x[is_edge] for c, x in col.items()}, others)

    return solve


def _open_edges(made: DataFrame, apart: DataFrame | None) -> DataFrame:
    """The open edges between clusters, the first of each pair, without pairs known to be apart."""
    across = made.where(F.col("kind") == ACROSS).groupBy(*_EDGE).agg(F.min("a").alias("a"), F.max("a").alias("b"))
    a, b = pair("a", "b")
    rows = made.where(F.col("kind") == INNER).select(a.alias("a"), b.alias("b"), *_EDGE).unionByName(across)
    first = F.min_by(F.struct(*_EDGE), order_key("w", "ou", "ov", "edge_id"))
    left = rows.groupBy("a", "b").agg(first.alias("e"))
    if apart is not None:
        left = left.join(apart, ["a", "b"], "left_anti")
    return left.select(F.col("a").alias("u"), F.col("b").alias("v"), "e.*")


def labelled(made: DataFrame, renamed: DataFrame) -> DataFrame:
    """(v, value, cluster) of the vertices that solved tiles have LABEL rows for, after the renaming of their clusters."""
    then = tables.sized_broadcast(tables.written(renamed.select(F.col("v").alias("b"), F.col("cluster").alias("then"))), RENAMED)
    return made.where(F.col("kind") == LABEL).join(then, "b", "left").select(F.col("a").alias("v"), F.col("ou").alias("value"), F.coalesce("then", "b").alias("cluster"))


def followed(steps: list[DataFrame]) -> DataFrame:
    """(v, cluster) of all vertices that a step renamed, from the (v, cluster) of each step."""
    out = steps[-1]
    for step in reversed(steps[:-1]):
        then = out.select(F.col("v").alias("cluster"), F.col("cluster").alias("then"))
        out = step.join(then, "cluster", "left").select("v", F.coalesce("then", "cluster").alias("cluster")).unionByName(out)
    return out


def settle(live: DataFrame, places: list[Place], cap: int, apart: DataFrame | None = None, seeds: DataFrame | None = None) -> tuple[DataFrame, DataFrame, DataFrame | None, bool]:
    """(labels that differ from the vertex, open edges, exclusions or seeds of open clusters, whether nothing is open).

    live has (u, v, ou, ov, edge_id, w) with the ends that the order goes by; with
    ``seeds`` (v, seed) it is a flood, else the signed greedy partition from ``apart``
    (a, b).  One tile takes everything as soon as that is at most ``cap`` rows.
    """
    flood = seeds is not None
    side = seeds.select(F.col("v").alias("a"), F.col("seed").alias("b")) if flood else apart
    return _settled(live, side, places, cap, min(cap, FEW), flood)


def settle_rest(made: DataFrame, places: list[Place], cap: int, flood: bool = False) -> tuple[DataFrame, DataFrame, DataFrame, bool]:
    """The same for what tiles that were solved where their edges are made leave over; takes their rows, written.

    The labels rename clusters that ``made`` has LABEL rows for.
    """
    return _settled(*_left(made, flood), places, cap, cap, flood)


def _left(made: DataFrame, flood: bool, kept: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(open edges, exclusions or seeds) after a tile's rows; ``kept`` are exclusions that no tile has."""
    if flood:
        live = tables.written(_open_edges(made, None))
        # The seed of a cluster that no open edge names can't matter later.
        ends = live.select(F.explode(F.array("u", "v")).alias("a")).distinct()
        return live, tables.written(made.where(F.col("kind") == SEED).select("a", "b").join(ends, "a", "left_semi"))
    inside = made.where(F.col("kind") == APART).select("a", "b")
    side = tables.written(inside if kept is None else inside.unionByName(kept).distinct())
    return tables.written(_open_edges(made, side)), side


def _settled(live: DataFrame, side: DataFrame | None, places: list[Place], cap: int, first_cap: int, flood: bool) -> tuple[DataFrame, DataFrame, DataFrame | None, bool]:
    steps, tried = [], [*places, None]
    for k, place in enumerate(tried):
        rows = live.select("u") if side is None else live.select("u").unionAll(side.select("a"))
        if tables.at_most(rows, cap if k else first_cap):
            place = everywhere
        elif place is None:
            break
        rows = to_tiles(live, place)
        if flood:
            none = {c: F.lit(0).cast("double" if c == "w" else "long").alias(c) for c in _EDGE}
            rows = rows.unionByName(side.select(place(F.col("a")).alias("tile"), F.lit(SEED).alias("kind"), "a", "b", *none.values()))
        elif side is not None:
            rows = rows.unionByName(_pairs_to_tiles(side, place))
        made = tables.written(rows.groupBy("tile").applyInArrow(_solver(flood), ROW))
        labels = made.where(F.col("kind") == LABEL).select(F.col("a").alias("v"), F.col("b").alias("cluster"))
        steps.append(labels)
        if place is everywhere:
            return followed(steps), live, None, True
        kept = None
        if side is not None and not flood:
            away = comp.relabelled(side.where(place(F.col("a")) != place(F.col("b"))).select(F.col("a").alias("u"), F.col("b").alias("v")), labels)
            a, b = pair("cu", "cv")
            kept = away.select(a.alias("a"), b.alias("b"))
        live, side = _left(made, flood, kept)
    renamed = followed(steps) if steps else live.select(F.col("u").alias("v"), F.col("u").alias("cluster")).where("false")
    return renamed, live, side, False
