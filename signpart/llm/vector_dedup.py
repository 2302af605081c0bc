"""Near-duplicate vectors with an inverted multi-index.

Unit vectors are cut in halves, and each half has a codebook of its own, fitted on
a bounded sample; the pairs of codes form a grid of cells.  Every vector is indexed
in the cell of its two nearest codes.  A search visits the cells in the order of
the summed distances of their codes (multi-sequence order: from the nearest pair,
the next pair always has a neighbour already visited) and stops after as many
cells as reach the target recall.  That number is measured on a bounded set of
queries, which are vectors that the codebooks were not fitted on: each is compared
with all vectors of the table, and the number is the least at which the mean share
of a query's links that is found reaches the target, for each size of
neighbourhood on its own, so that large groups can't hide small ones.  Where too
few queries of small groups have links, partners planted at the threshold itself
must be found too.  If the number exceeds a bound, the grid gets fewer, larger
cells and is measured again; the last grid can be visited as a whole.  A small
table is one cell, which is exact.

All candidates of a visited cell are verified with the cosine in double precision.
Links are counted and joined per cell, never listed: a task returns the number of
links of each vector and a spanning forest of the links it saw.  A link that is
found from both ends counts once, because each member knows which cells it visits
itself.  Equal vectors are one class with a multiplicity.  Cells with many members
or many probes are cut in tiles and slices.

Defined cases: a null or zero vector, and one with null or non-finite components,
links with nothing; so do vectors of different lengths among each other; rows with
equal vec_id and vector count as copies; an empty table gives an empty result; of
the input only vec_id and embedding are read, so labels play no part.
"""

from __future__ import annotations

import logging
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from signpart.llm import store
from signpart.llm.arrowmap import arrow_map
from signpart.llm.components import components

#: Bounds of the vectors that codebooks are fitted on, and of those that the number of visits is; queries of a round.
SAMPLE, QUERIES, ROUND = 8192, 16384, 4096
TARGET_RECALL = 0.995
#: Least numbers of links of the sizes of neighbourhoods; in those below SMALL_GROUPS at least SEEN queries are wanted.
SIZES, SMALL_GROUPS, SEEN = (1, 2, 8, 64), 8, 400
#: Up to so many vectors are one cell.
EXACT_ROWS = 2048
#: Vectors wanted in a cell; members of a tile and probes of a slice of a cell.
PER_CELL, TILE, SLICE = 24, 256, 256
#: Beyond MOST_VISITS the grid gets coarser; one of MOST_VISITS cells always suffices.
MOST_CODES, MOST_VISITS = 1024, 256

_log = logging.getLogger(__name__)


def _codebook(points: np.ndarray, codes: int, rounds: int = 12, seed: int = 5) -> np.ndarray:
    """Cluster centres by Lloyd's rounds from distinct points."""
    distinct = np.unique(points, axis=0)
    rng = np.random.default_rng(seed)
    centres = distinct[rng.permutation(len(distinct))[: max(1, codes)]].copy()
    for _ in range(rounds):
        near = _distances(points, centres).argmin(axis=1)
        sums = np.zeros_like(centres)
        np.add.at(sums, near, points)
        n = np.bincount(near, minlength=len(centres))
        centres[n > 0] = sums[n > 0] / n[n > 0, None]
    return centres


def _distances(points: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return np.maximum((points**2).sum(1)[:, None] - 2 * points @ centres.T + (centres**2).sum(1), 0)


@dataclass(frozen=True)
class Grid:
    """Codebooks of both halves and the number of cells that a search visits."""

    half: int
    first: np.ndarray
    second: np.ndarray
    visits: int
    #: (least links of a query, queries with so many, recall of their links at ``visits``); 0 links: planted partners.
    measured: tuple[tuple[int, float, float], ...] = ()

    def nearest(self, x: np.ndarray, visits: int | None = None) -> np.ndarray:
        """The cells that a search of each row visits, in order; the first is its own.

        The multi-sequence order is that of the summed distances; a pair of ranks
        (i, j) can only be among the first T if (i+1)(j+1) <= T, so only those
        pairs are looked at.
        """
        visits = min(visits or self.visits, len(self.first) * len(self.second))
        d1, d2 = _distances(x[:, : self.half], self.first), _distances(x[:, self.half :], self.second)
        o1, o2 = (np.argsort(d, axis=1, kind="stable")[:, :visits] for d in (d1, d2))
        s1, s2 = np.take_along_axis(d1, o1, 1), np.take_along_axis(d2, o2, 1)
        ranks = np.asarray([(i, j) for i in range(o1.shape[1]) for j in range(o2.shape[1]) if (i + 1) * (j + 1) <= visits])
        total = s1[:, ranks[:, 0]] + s2[:, ranks[:, 1]]
        order = np.argsort(total, axis=1, kind="stable")[:, :visits]
        picked = ranks[order]
        return np.take_along_axis(o1, picked[:, :, 0], 1) * len(self.second) + np.take_along_axis(o2, picked[:, :, 1], 1)


def codebooks(sample: np.ndarray, codes: int) -> Grid:
    half = sample.shape[1] // 2
    return Grid(half, _codebook(sample[:, :half], codes), _codebook(sample[:, half:], codes), 1)


def _rank_table(grid: Grid, queries: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted keys (query, cell) of the first ``most`` cells of each query, and their ranks from 1."""
    cells = np.concatenate([grid.nearest(queries[a : a + 512], most) for a in range(0, len(queries), 512)])
    keys = (np.arange(len(cells))[:, None] * (len(grid.first) * len(grid.second)) + cells).ravel()
    order = np.argsort(keys)
    return keys[order], np.tile(np.arange(1, cells.shape[1] + 1), len(cells))[order]


def _ranks(table: tuple[np.ndarray, np.ndarray], keys: np.ndarray, most: int) -> np.ndarray:
    """The ranks of keys (query, cell); most + 1 for those that are not in the table."""
    at = np.minimum(np.searchsorted(table[0], keys), len(table[0]) - 1)
    return np.where(table[0][at] == keys, table[1][at], most + 1)


def planted_ranks(grid: Grid, queries: np.ndarray, threshold: float, most: int) -> np.ndarray:
    """The ranks of the cells of partners at cosine ``threshold``, away from each query at random and towards another query."""
    rng = np.random.default_rng(11)
    found = []
    table = _rank_table(grid, queries, most)
    for towards in (rng.normal(size=queries.shape), np.roll(queries, 1, axis=0)):
        side = towards - (towards * queries).sum(1)[:, None] * queries
        long = np.sqrt((side**2).sum(1))
        ok = long > 1e-9
        partner = threshold * queries[ok] + max(0.0, 1 - threshold**2) ** 0.5 * side[ok] / long[ok, None]
        cell = np.concatenate([grid.nearest(partner[a : a + 512], 1)[:, 0] for a in range(0, len(partner), 512)] or [np.zeros(0, int)])
        found.append(_ranks(table, np.flatnonzero(ok) * (len(grid.first) * len(grid.second)) + cell, most))
    return np.concatenate(found)


def visits_for(shares: dict[int, np.ndarray], recall: float) -> int:
    """The least number of visits at which each size of neighbourhood reaches the recall.

    ``shares[size][r]`` is the sum, over the queries of that size, of the shares of
    a query's links that lie in its r-th cell.  The last entry stands for all cells
    beyond; the result points there if the target is not reached before.
    """
    return max((int(np.argmax(np.cumsum(x) >= recall * x.sum() - 1e-9)) for x in shares.values() if x.sum()), default=1)


def _link_shares(classes: DataFrame, grid: Grid, ids: np.ndarray, queries: np.ndarray, threshold: float, most: int) -> dict[int, np.ndarray]:
    """By size of neighbourhood, what visits_for() takes: each query is compared with all vectors."""
    spark = classes.sparkSession
    length, n_cells = queries.shape[1], len(grid.first) * len(grid.second)
    held = spark.sparkContext.broadcast((grid, ids, queries, _rank_table(grid, queries, most)))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grid, ids, queries, table = held.value
        for batch in batches:
            x_id = batch.column(0).to_numpy()
            x = np.frombuffer(b"".join(batch.column(1).to_pylist()), dtype="<f8").reshape(-1, length)
            for b in range(0, len(x), 1024):
                part, part_id = x[b : b + 1024], x_id[b : b + 1024]
                own = grid.nearest(part, 1)[:, 0]
                for a in range(0, len(queries), 512):
                    i, j = np.nonzero(queries[a : a + 512] @ part.T >= threshold)
                    i = i + a
                    other = ids[i] != part_id[j]
                    keys, n = np.unique(i[other] * n_cells + own[j[other]], return_counts=True)
                    if len(keys):
                        yield pa.RecordBatch.from_arrays([pa.array((keys // n_cells).astype(np.int32)), pa.array(_ranks(table, keys, most).astype(np.int32)), pa.array(n.astype(np.int64))], names=["q", "rank", "n"])

    hits = classes.select("class_id", "unit").transform(arrow_map, compare, "q int, rank int, n long").groupBy("q", "rank").agg(F.sum("n").alias("n"))
    total = hits.groupBy("q").agg(F.sum("n").alias("total"))
    size = F.lit(SIZES[0])
    for least in SIZES[1:]:
        size = F.when(F.col("total") >= least, least).otherwise(size)
    rows = hits.join(total, "q").groupBy(size.alias("size"), "rank").agg(F.sum(F.col("n") / F.col("total")).alias("share")).collect()
    shares = {r["size"]: np.zeros(most + 2) for r in rows}
    for r in rows:
        shares[r["size"]][r["rank"]] = r["share"]
    held.unpersist()
    return shares


def fit(classes: DataFrame, rows: int, threshold: float, recall: float = TARGET_RECALL) -> Grid:
    """Codebooks sized for ``rows`` vectors of one length, and the visits that reach the recall over the whole table."""
    trained = min(SAMPLE, rows // 2)
    picked = classes.orderBy(F.xxhash64("class_id"), "class_id").limit(trained + min(QUERIES, rows - trained)).select("class_id", "unit").collect()
    vectors = np.stack([np.frombuffer(r["unit"], dtype="<f8") for r in picked])
    if rows <= EXACT_ROWS or vectors.shape[1] < 2:
        return codebooks(vectors[:1], 1)
    sample, queries, ids = vectors[:trained], vectors[trained:], np.asarray([r["class_id"] for r in picked[trained:]])
    codes = int(min(MOST_CODES, max(1, (rows / PER_CELL) ** 0.5), len(sample)))
    while True:
        grid = codebooks(sample, codes)
        most = min(MOST_VISITS, len(grid.first) * len(grid.second))
        shares: dict[int, np.ndarray] = {}
        few = True
        for a in range(0, len(queries), ROUND):
            for size, x in _link_shares(classes, grid, ids[a : a + ROUND], queries[a : a + ROUND], threshold, most).items():
                shares[size] = shares.get(size, 0) + x
            few = sum(x.sum() for size, x in shares.items() if size < SMALL_GROUPS) < SEEN
            if not few:
                break
        if few:
            shares[0] = np.bincount(planted_ranks(grid, queries[:ROUND], threshold, most), minlength=most + 2).astype(float)
        visits = max(visits_for(shares, recall), min(4, most))
        if visits <= most:
            measured = tuple((size, float(x.sum()), float(x[: visits + 1].sum() / x.sum())) for size, x in sorted(shares.items()) if x.sum())
            _log.info("%d vectors, %d x %d cells, %d visits; links, queries, recall: %s", rows, len(grid.first), len(grid.second), visits, measured)
            return replace(grid, visits=visits, measured=measured)
        codes = max(1, min(codes, max(len(grid.first), len(grid.second))) // 2)


def _unit(batch_col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(usable rows, unit vectors as an object array of rows)."""
    rows, vectors = [], []
    for i, v in enumerate(batch_col.to_pylist()):
        if v is None or not len(v) or any(c is None for c in v):
            continue
        x = np.asarray(v, dtype=np.float64)
        big = np.abs(x).max() if np.isfinite(x).all() else 0.0
        if big > 0:
            x = x / big
            rows.append(i)
            vectors.append(x / np.sqrt((x * x).sum()))
    return np.asarray(rows, dtype=np.int64), vectors


def unit_classes(vectors: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(members, classes): vec_id with its class, and each class's unit vector and number of members.

    Equal vectors are one class, named by its least vec_id.
    """

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, units = _unit(batch.column(1))
            out: list = [None] * batch.num_rows
            for r, u in zip(rows, units):
                out[r] = u.astype("<f8").tobytes()
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(out, pa.binary())], names=["vec_id", "unit"])

    made = store.written(vectors.select("vec_id", "embedding").transform(arrow_map, make, "vec_id long, unit binary").withColumns({"k1": F.xxhash64("unit"), "k2": F.md5("unit")}))
    usable = made.where("unit is not null and vec_id is not null")
    classes = store.written(usable.groupBy("k1", "k2").agg(F.min(F.struct("vec_id", "unit")).alias("x"), F.count(F.lit(1)).alias("copies")).select("k1", "k2", F.col("x.vec_id").alias("class_id"), F.col("x.unit").alias("unit"), "copies"))
    members = made.select("vec_id", F.when(F.col("unit").isNotNull(), F.col("k1")).alias("k1"), F.when(F.col("unit").isNotNull(), F.col("k2")).alias("k2")).join(classes.select("k1", "k2", "class_id", "copies"), ["k1", "k2"], "left").select("vec_id", "class_id", "copies")
    return members, classes


def _forest(a: np.ndarray, b: np.ndarray) -> list[tuple[int, int]]:
    """A spanning forest of links."""
    up: dict[int, int] = {}

    def root(x: int) -> int:
        while up.get(x, x) != x:
            up[x] = up.get(up[x], up[x])
            x = up[x]
        return x

    out = []
    for x, y in zip(a.tolist(), b.tolist()):
        rx, ry = root(x), root(y)
        if rx != ry:
            up[max(rx, ry)] = min(rx, ry)
            out.append((x, y))
    return out


def _search(classes: DataFrame, length: int, threshold: float, recall: float) -> DataFrame:
    """(u, v, n): v null: u has n links more; else u and v link. For classes of one vector length."""
    spark = classes.sparkSession
    rows = classes.count()
    grid = fit(classes, rows, threshold, recall)
    held = spark.sparkContext.broadcast(grid)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.frombuffer(b"".join(batch.column(1).to_pylist()), dtype="<f8").reshape(-1, length)
            for a in range(0, len(x), 1024):
                cells = held.value.nearest(x[a : a + 1024])
                part = batch.slice(a, 1024)
                ends = np.arange(len(cells) + 1, dtype=np.int32) * cells.shape[1]
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(3)), pa.ListArray.from_arrays(pa.array(ends), pa.array(cells.ravel().astype(np.int64)))], names=["class_id", "unit", "copies", "cells"])

    placed = store.written(classes.select("class_id", "unit", "copies").transform(arrow_map, place, "class_id long, unit binary, copies long, cells array<long>"))
    own = F.element_at("cells", 1)
    # A cell's members are cut in tiles and its probes in slices; each tile meets each
    # slice in a group of its own.  The table has at most MOST_CODES**2 rows.
    parts = lambda most: F.ceil(F.count(F.lit(1)) / F.lit(most)).cast("int")
    by_members = placed.groupBy(own.alias("cell")).agg(parts(TILE).alias("tiles"))
    by_probes = placed.select(F.explode("cells").alias("cell")).groupBy("cell").agg(parts(SLICE).alias("slices"))
    grid_parts = store.written(by_members.join(by_probes, "cell"))
    part_of = lambda n: F.pmod(F.xxhash64("class_id"), F.col(n)).cast("int")
    each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    members = placed.withColumn("cell", own).join(grid_parts, "cell").withColumn("tile", part_of("tiles")).withColumn("slice", each("slices")).select("cell", "tile", "slice", F.lit(True).alias("member"), "class_id", "unit", "copies", "cells")
    probes = placed.withColumn("cell", F.explode("cells")).join(grid_parts, "cell").withColumn("slice", part_of("slices")).withColumn("tile", each("tiles")).select("cell", "tile", "slice", F.lit(False).alias("member"), "class_id", "unit", "copies", F.slice("cells", 1, 1).alias("cells"))

    def compare(group: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Members come first; then the probes, batch by batch."""
        kept: list[pa.RecordBatch] = []
        m = None
        for batch in group:
            is_member = batch.column(3).to_numpy(zero_copy_only=False)
            n = int(is_member.sum())
            if n:
                kept.append(batch.slice(0, n))
            if n == batch.num_rows:
                continue
            if m is None:
                both = pa.Table.from_batches(kept).combine_chunks() if kept else batch.slice(0, 0)
                m_id = both.column("class_id").to_numpy()
                m_copies = both.column("copies").to_numpy()
                m = np.frombuffer(b"".join(both.column("unit").to_pylist()), dtype="<f8").reshape(-1, length)
                m_cells = np.asarray(both.column("cells").to_pylist(), dtype=np.int64).reshape(len(m_id), -1)
            probe = batch.slice(n)
            p_id, p_copies = probe.column(4).to_numpy(), probe.column(6).to_numpy()
            p = np.frombuffer(b"".join(probe.column(5).to_pylist()), dtype="<f8").reshape(-1, length)
            p_own = np.asarray(probe.column(7).to_pylist(), dtype=np.int64).ravel()
            for a in range(0, len(p), 512):
                i, j = np.nonzero(p[a : a + 512] @ m.T >= threshold)
                i = i + a
                other = p_id[i] != m_id[j]
                i, j = i[other], j[other]
                if not len(i):
                    continue
                # The member counts the link here only if it won't visit the probe's cell itself.
                unseen = ~(m_cells[j] == p_own[i][:, None]).any(axis=1)
                ids = np.concatenate([p_id[i], m_id[j][unseen]])
                more = np.concatenate([m_copies[j], p_copies[i][unseen]])
                vec, at = np.unique(ids, return_inverse=True)
                count = np.bincount(at, weights=more).astype(np.int64)
                pairs = _forest(p_id[i], m_id[j])
                yield pa.RecordBatch.from_arrays(
                    [pa.array([*vec.tolist(), *(x for x, _ in pairs)], pa.int64()), pa.array([None] * len(vec) + [y for _, y in pairs], pa.int64()), pa.array([*count.tolist(), *(0 for _ in pairs)], pa.int64())],
                    names=["u", "v", "n"],
                )

    both = members.unionByName(probes)
    dealt = both.repartition(max(store.shuffle_partitions(spark), 8), "cell", "tile", "slice").sortWithinPartitions("cell", "tile", "slice", F.desc("member"))

    def by_tile(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Cuts the sorted rows of a partition at the tiles."""
        at, group = None, []
        for batch in batches:
            keys = np.stack([batch.column(i).to_numpy().astype(np.int64) for i in range(3)])
            new = np.flatnonzero(np.concatenate([[True], (keys[:, 1:] != keys[:, :-1]).any(axis=0)]))
            for a, b in zip(new, [*new[1:], batch.num_rows]):
                key = tuple(keys[:, a])
                if key != at:
                    yield from compare(iter(group))
                    at, group = key, []
                group.append(batch.slice(a, b - a))
        yield from compare(iter(group))

    return store.written(dealt.transform(arrow_map, by_tile, "u long, v long, n long"))


def near_vectors(vectors: DataFrame, threshold: float = 0.95, recall: float = TARGET_RECALL) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every vector."""
    members, classes = unit_classes(vectors)
    found = None
    # One search for each vector length; equal lengths are the rule.
    for row in classes.groupBy(F.length("unit").alias("bytes")).count().orderBy("bytes").collect():
        part = _search(classes.where(F.length("unit") == row["bytes"]), row["bytes"] // 8, threshold, recall)
        found = part if found is None else found.unionByName(part)
    if found is None:
        return members.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    links = found.where("v is null").groupBy(F.col("u").alias("__u")).agg(F.sum("n").alias("n"))
    label = components(found.where("v is not null").select("u", "v"))
    joined = members.join(links, members["class_id"] == links["__u"], "left").join(label, members["class_id"] == label["id"], "left")
    component = F.coalesce("component_id", "class_id", "vec_id")
    n_links = F.coalesce("n", F.lit(0)) + F.coalesce(F.col("copies") - 1, F.lit(0))
    return joined.select("vec_id", n_links.cast("long").alias("n_links"), component.alias("component_id"), (F.col("vec_id") == component).alias("kept"))


def op2_vector_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(store.table(spark, sf_dir, "embeddings"))


OP2_SQL = r"""
with recursive v as (
  select vec_id, embedding::double[] as e from embeddings
  where embedding is not null and len(list_filter(embedding, lambda c: c is null or not isfinite(c))) = 0
), unit as (
  select vec_id, list_transform(e, lambda c: c / sqrt(list_sum(list_transform(e, lambda d: d * d)))) as e from v where list_sum(list_transform(e, lambda d: d * d)) > 0
), ways as (
  select a.vec_id as u, b.vec_id as v from unit a join unit b on a.vec_id <> b.vec_id and len(a.e) = len(b.e) and list_inner_product(a.e, b.e) >= 0.95
), counts as (select u, count(*) as n from ways group by u),
reach(id, other) as (select vec_id, vec_id from embeddings union select r.id, w.v from reach r join ways w on r.other = w.u)
select x.vec_id, coalesce(any_value(n), 0)::bigint as n_links, min(r.other) as component_id, min(r.other) = x.vec_id as kept
from embeddings x left join counts on counts.u = x.vec_id join reach r on r.id = x.vec_id group by x.vec_id
"""
