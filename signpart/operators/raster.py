"""Graphs of rasters: neighbourhood patterns, targets, masks, bridges.

A pixel is a row (pix, z, y, x, …); pix = (z * height + y) * width + x, so the id
of a neighbour is arithmetic and needs no join.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from signpart import kernels, schemas, tables
from signpart.functions.expressions import pair
from signpart.operators import components as comp


@dataclass(frozen=True)
class Offset:
    """One channel: a displacement, whether it attracts, and the stride of the pixels that have it."""

    channel: int
    dz: int
    dy: int
    dx: int
    attract: bool
    stride: int = 1


#: Pixels of a tile, about, and of the side of a block.
TILE, BLOCK = 1 << 18, 256
#: The most pixels along the side of a block that floods.
SIDE = 512
#: Pixels that are dealt to blocks at once.
PIECE = 1 << 20


@dataclass(frozen=True)
class Shape:
    depth: int
    height: int
    width: int

    def places(self, pixels: int = TILE) -> list[Callable[[Column], Column]]:
        """Tiles of a pixel through all slices, each side twice that before; borders don't lie on those before."""
        area, side, longest = self.height * self.width, max(1, math.isqrt(max(1, pixels // self.depth))), max(self.height, self.width)

        def place(size: int, shift: int) -> Callable[[Column], Column]:
            rank = lambda c: (c + F.lit(shift)) / F.lit(size)
            return lambda c: F.floor(rank(F.floor((c % area) / self.width))) * F.lit(longest + 1) + F.floor(rank(c % self.width))

        steps = range(max(1, math.ceil(math.log2(max(1.0, longest / side)))))
        return [place(side << k, ((side << k) // 2 - (side >> k)) if k else 0) for k in steps]

    def pixels(self, spark: SparkSession) -> DataFrame:
        area = self.height * self.width
        pix = F.col("id")
        return spark.range(self.depth * area).select(pix.alias("pix"), F.expr(f"id div {area}").alias("z"), F.expr(f"(id % {area}) div {self.width}").alias("y"), (pix % self.width).alias("x"))


def pattern(name: str = "compact", ring: int = 9, far: int = 27, stride: int = 2, deep: bool = False) -> list[Offset]:
    """Direct neighbours attract; longer offsets repel and exist for each ``stride``-th pixel of both axes.

    compact: one ring.  layered: a ring and its far copy, for thick objects.  deep
    adds the next slice: straight down attracts, and the diagonals down repel.
    """
    if name not in ("compact", "layered"):
        raise ValueError("pattern is compact or layered")
    moves = [(0, 0, 1, True), (0, 1, 0, True)]
    rings = [ring] if name == "compact" else [ring, far]
    for r in rings:
        d = max(1, (r * 2) // 3)
        moves += [(0, 0, r, False), (0, r, 0, False), (0, d, d, False), (0, d, -d, False)]
    if deep:
        moves += [(1, 0, 0, True), (1, ring, 0, False), (1, -ring, 0, False), (1, 0, ring, False), (1, 0, -ring, False)]
    return [Offset(i, dz, dy, dx, attract, 1 if attract else stride) for i, (dz, dy, dx, attract) in enumerate(moves)]


def pattern_table(spark: SparkSession, offsets: list[Offset]) -> DataFrame:
    rows = [(o.channel, o.dz, o.dy, o.dx, o.attract, o.stride) for o in offsets]
    return spark.createDataFrame(rows, "channel int, dz int, dy int, dx int, attract boolean, stride int")


def neighbour_pairs(pixels: DataFrame, shape: Shape, offsets: list[Offset]) -> DataFrame:
    """pixels' columns with (channel, attract, other): the neighbours inside the raster.

    Bounds and strides are tested before the rows are made.
    """
    options = []
    for o in offsets:
        inside = (F.col("z") + o.dz < shape.depth) & (F.col("y") + o.dy).between(0, shape.height - 1) & (F.col("x") + o.dx).between(0, shape.width - 1)
        if o.stride > 1:
            inside = inside & (F.col("y") % o.stride == 0) & (F.col("x") % o.stride == 0)
        step = (o.dz * shape.height + o.dy) * shape.width + o.dx
        options.append(F.when(inside, F.struct(F.lit(o.channel).alias("channel"), F.lit(o.attract).alias("attract"), (F.col("pix") + F.lit(step)).alias("other"))))
    listed = F.array_compact(F.array(*options))
    return pixels.withColumn("__n", F.explode(listed)).select(*pixels.columns, "__n.channel", "__n.attract", "__n.other")


def grid_edges(pixels: DataFrame, shape: Shape, offsets: list[Offset], maps: str = "maps") -> DataFrame:
    """Edges from the pixels' array column of affinities, one entry per channel: +a if it attracts, -a if not; zeros go."""
    pairs = neighbour_pairs(pixels.select("pix", "z", "y", "x", maps), shape, offsets)
    a = F.get(F.col(maps), F.col("channel")).cast("double")
    u, v = pair("pix", "other")
    rows = pairs.select(u.alias("u"), v.alias("v"), F.when(F.col("attract"), a).otherwise(-a).alias("w"), "channel").where("w <> 0")
    return rows.withColumn("edge_id", F.xxhash64("u", "v", "channel")).select(*schemas.EDGES.names)


@dataclass(frozen=True)
class Block:
    """A part of one slice with its margin: pixels that the table has, their values, and which of them the block answers for."""

    z: int
    y: int
    x: int
    present: np.ndarray
    own: np.ndarray
    values: dict[str, np.ndarray]
    shape: Shape

    def pix(self) -> np.ndarray:
        rows, columns = self.present.shape
        y, x = self.y + np.arange(rows, dtype=np.int64)[:, None], self.x + np.arange(columns, dtype=np.int64)[None, :]
        return (self.z * self.shape.height + y) * self.shape.width + x

    def rows(self, **more: np.ndarray) -> dict[str, np.ndarray]:
        """(pix, z, y, x, more…) of the block's own pixels."""
        y, x = np.nonzero(self.own & self.present)
        return {"pix": self.pix()[y, x], "z": np.full(len(y), self.z, np.int64), "y": y + self.y, "x": x + self.x} | {k: a[y, x] for k, a in more.items()}


def over_blocks(pixels: DataFrame, values: list[str], shape: Shape, margin: int, solve: Callable[[Block], dict[str, np.ndarray] | pa.Table], schema: str, side: int = BLOCK) -> DataFrame:
    """What ``solve`` makes of blocks of side x side pixels that see ``margin`` pixels around them; takes (pix, z, y, x, values…).

    Neighbours within the margin need no join: pixels go, packed, to the blocks that see them.
    """
    if not 0 <= margin < side:
        raise ValueError("the margin of a block is less than its side")

    kinds = {f.name: np.dtype("float64" if f.dataType.typeName() == "double" else "int64") for f in pixels.select(*values).schema}
    across = -(-shape.width // side)

    def pieces(z: np.ndarray, y: np.ndarray, x: np.ndarray, held: list[np.ndarray]) -> pa.RecordBatch:
        """A row for each block that sees some of the pixels: their places in it and their values, packed."""
        first_y, last_y, first_x, last_x = (f for c, limit in ((y, shape.height), (x, shape.width)) for f in (np.maximum(c - margin, 0) // side, np.minimum(c + margin, limit - 1) // side))
        out = []
        for dy in range(int((last_y - first_y).max()) + 1):
            for dx in range(int((last_x - first_x).max()) + 1):
                by, bx = first_y + dy, first_x + dx
                some = np.flatnonzero((by <= last_y) & (bx <= last_x))
                key = (z[some] * shape.height + by[some]) * across + bx[some]
                order = np.argsort(key, kind="stable")
                some, key = some[order], key[order]
                cuts = [0, *(np.flatnonzero(key[1:] != key[:-1]) + 1).tolist(), len(key)]
                for i, j in zip(cuts, cuts[1:]):
                    if i < j:
                        k = some[i:j]
                        out.append((int(z[k[0]]), int(by[k[0]]), int(bx[k[0]]), *(np.ascontiguousarray(c[k]).tobytes() for c in (y.astype(np.int32), x.astype(np.int32), *held))))
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if n < 3 else pa.binary()) for n, c in enumerate(zip(*out))], names)

    names = ["z", "by", "bx", "at_y", "at_x", *(f"held{n}" for n in range(len(kinds)))]

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting, n = [], 0
        for batch in batches:
            if batch.num_rows:
                waiting.append([batch[c].to_numpy(zero_copy_only=False) for c in ("z", "y", "x", *kinds)])
                n += batch.num_rows
            if n >= PIECE:
                z, y, x, *held = (np.concatenate(c) for c in zip(*waiting))
                yield pieces(z, y, x, [c.astype(k) for c, k in zip(held, kinds.values())])
                waiting, n = [], 0
        if n:
            z, y, x, *held = (np.concatenate(c) for c in zip(*waiting))
            yield pieces(z, y, x, [c.astype(k) for c, k in zip(held, kinds.values())])

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        z, by, bx = (int(k.as_py()) for k in key)
        y0, x0 = max(0, by * side - margin), max(0, bx * side - margin)
        y1, x1 = min(shape.height, (by + 1) * side + margin), min(shape.width, (bx + 1) * side + margin)
        present = np.zeros((y1 - y0, x1 - x0), dtype=bool)
        own = np.zeros_like(present)
        own[by * side - y0 : (by + 1) * side - y0, bx * side - x0 : (bx + 1) * side - x0] = True
        unpacked = lambda c, kind: np.concatenate([np.frombuffer(b.as_py(), kind) for b in rows[c]])
        at = unpacked("at_y", np.int32) - y0, unpacked("at_x", np.int32) - x0
        present[at] = True
        held = {}
        for n, (name, kind) in enumerate(kinds.items()):
            held[name] = np.zeros(present.shape, kind)
            held[name][at] = unpacked(f"held{n}", kind)
        made = solve(Block(z, y0, x0, present, own, held, shape))
        return made if isinstance(made, pa.Table) else pa.table({k: pa.array(a) for k, a in made.items()})

    packed = ", ".join(f"{c} {'long' if n < 3 else 'binary'}" for n, c in enumerate(names))
    blocks = min(4096, shape.depth * -(-shape.height // side) * across)
    return pixels.select("z", "y", "x", *values).mapInArrow(deal, packed).repartition(blocks, "z", "by", "bx").groupBy("z", "by", "bx").applyInArrow(run, schema)


def edge_targets(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """(u, v, channel, attract) rows with ``target``: 1 if an attracting pair has one true label, or a repelling pair two."""
    gu, gv = truth.select(F.col("pix").alias("u"), F.col("gt").alias("gu")), truth.select(F.col("pix").alias("v"), F.col("gt").alias("gv"))
    same = F.col("gu") == F.col("gv")
    return pairs.join(gu, "u").join(gv, "v").select("u", "v", "channel", "attract", F.when(F.col("attract"), same).otherwise(~same).cast("long").alias("target"))


def boundary_map(attractions: DataFrame, scale: float = 10000.0) -> DataFrame:
    """(pix, b): the strongest boundary a pixel has, b = scale - w over its attractive edges; takes edges."""
    ends = attractions.where("w > 0").select(F.explode(F.array("u", "v")).alias("pix"), (F.lit(scale) - F.col("w")).alias("b"))
    return ends.groupBy("pix").agg(F.max("b").alias("b"))


def labels_from_membrane(pixels: DataFrame, shape: Shape) -> DataFrame:
    """(v, cluster): components of the pixels with membrane false, in each slice, over direct neighbours."""
    direct = [Offset(0, 0, 0, 1, True), Offset(1, 0, 1, 0, True)]
    free = pixels.where(~F.col("membrane")).select("pix", "z", "y", "x")
    pairs = neighbour_pairs(free, shape, direct).select(F.col("pix").alias("u"), F.col("other").alias("v"))
    inner = pairs.join(free.select(F.col("pix").alias("v")), "v", "left_semi").select("u", "v")
    return comp.components(inner, free.select(F.col("pix").alias("v")))


def air_bridges(labels: DataFrame, local_edges: DataFrame) -> DataFrame:
    """(cluster, parts): clusters that local attractive edges don't hold together."""
    inner = comp.relabelled(local_edges.where("w > 0"), labels).where("cu = cv").select("u", "v")
    parts = comp.components(inner, labels.select("v")).withColumnRenamed("cluster", "part")
    return labels.join(parts, "v").groupBy("cluster").agg(F.countDistinct("part").alias("parts")).where("parts > 1")


def air_bridges_in_blocks(pixels: DataFrame, shape: Shape, held: Callable[[Block, tuple, tuple, int], np.ndarray], values: list[str]) -> DataFrame:
    """``air_bridges`` of pixels (z, y, x, cluster, values…) whose local edges are between direct neighbours of a slice.

    held(block, near, far, axis) tells which pairs have an attractive edge (axis 0: along x).
    """

    def solve(block: Block) -> dict[str, np.ndarray]:
        """(cluster, part in the block) of the block's parts (other = -1), and what ties parts to other blocks' pixels."""
        own, pix, c = block.own & block.present, block.pix(), block.values["cluster"]
        place, inner, across = np.arange(own.size).reshape(own.shape), [], []
        for axis, (near, far) in enumerate(((np.s_[:, :-1], np.s_[:, 1:]), (np.s_[:-1], np.s_[1:]))):
            tied = block.present[near] & block.present[far] & (c[near] == c[far]) & held(block, near, far, axis)
            mine = tied & own[near] & own[far]
            inner.append((place[near][mine], place[far][mine]))
            for here, there in ((near, far), (far, near)):
                out = tied & own[here] & ~own[there]
                across.append((place[here][out], place[there][out]))
        root, name = kernels.least_joined(own.size, *(np.concatenate(x) for x in zip(*inner))), pix.ravel()
        parts = np.flatnonzero(own.ravel() & (root == np.arange(own.size)))
        here, there = (np.concatenate(x) for x in zip(*across))
        rows = (c.ravel()[parts], name[parts], np.full(len(parts), -1, np.int64)), (c.ravel()[here], name[here], name[root[here]]), (c.ravel()[here], name[root[here]], name[there])
        return {k: np.concatenate(x) for k, x in zip(("cluster", "part", "other"), zip(*rows))}

    made = tables.written(over_blocks(pixels, ["cluster", *values], shape, 1, solve, "cluster long, part long, other long"))
    whole = tables.written(comp.components(made.where("other >= 0 and part <> other").select(F.col("part").alias("u"), F.col("other").alias("v"))))
    parts = made.where("other = -1").select("cluster", "part").join(whole.select(F.col("v").alias("part"), F.col("cluster").alias("first")), "part", "left")
    return parts.groupBy("cluster").agg(F.countDistinct(F.coalesce("first", "part")).alias("parts")).where("parts > 1")


def smoothed(s: np.ndarray, present: np.ndarray, radius: int) -> np.ndarray:
    """``radius`` rounds of the kernel 1 2 1 along both axes; right where the array holds ``radius`` pixels around."""
    s = np.where(present, s, 0)
    for _ in range(radius):
        for axis in (1, 0):
            padded = np.pad(s, [(1, 1) if axis == k else (0, 0) for k in (0, 1)])
            n = s.shape[axis]
            low, high = (padded[k : k + n] if axis == 0 else padded[:, k : k + n] for k in (0, 2))
            s = np.where(present, low + 2 * s + high, 0)
    return s


def smooth(pixels: DataFrame, value: str, radius: int, shape: Shape) -> DataFrame:
    """(pix, z, y, x, s): ``radius`` rounds of the integer binomial kernel 1 2 1 along y and x; outside counts as 0."""

    def solve(block: Block) -> dict[str, np.ndarray]:
        return block.rows(s=smoothed(block.values["s"], block.present, radius))

    rows = pixels.select("pix", "z", "y", "x", F.col(value).cast("long").alias("s"))
    return over_blocks(rows, ["s"], shape, radius, solve, "pix long, z long, y long, x long, s long", max(BLOCK, radius + 1))


def regional_extrema(pixels: DataFrame, value: str, shape: Shape, kind: str = "min") -> DataFrame:
    """(pix, seed): the pixels of each plateau without a lower (or higher) direct neighbour; seed is its least pixel."""

    def solve(block: Block) -> dict[str, np.ndarray]:
        """Own pixels that a neighbour beats (other = -1), those that none does (-2), and own pairs of equal pixels."""
        h, there, own = block.values["h"], block.present, block.own & block.present
        pix, beaten, flat = block.pix(), np.zeros(own.shape, dtype=bool), []
        for axis in (0, 1):
            a, b = ((slice(0, -1), slice(1, None)) if axis == 0 else (np.s_[:, :-1], np.s_[:, 1:]))
            both = there[a] & there[b]
            less = h[a] < h[b] if kind == "min" else h[a] > h[b]
            equal = h[a] == h[b]
            beaten[b] |= both & less
            beaten[a] |= both & ~less & ~equal
            mine = both & equal & own[a]
            flat.append((pix[a][mine], pix[b][mine]))
        rows = [(pix[own & beaten], -1), (pix[own & ~beaten], -2)]
        first = np.concatenate([x for x, _ in rows] + [x for x, _ in flat])
        other = np.concatenate([np.full(len(x), k, np.int64) for x, k in rows] + [x for _, x in flat])
        return {"pix": first, "other": other}

    made = tables.written(over_blocks(pixels.select("pix", "z", "y", "x", F.col(value).alias("h")), ["h"], shape, 1, solve, "pix long, other long"))
    plateau = comp.components(made.where("other >= 0").select(F.col("pix").alias("u"), F.col("other").alias("v")))
    beaten, free = made.where("other = -1").select(F.col("pix").alias("v")), made.where("other = -2").select(F.col("pix").alias("v"))
    lost = plateau.join(beaten, "v", "left_semi").select("cluster").distinct()
    kept = plateau.join(lost, "cluster", "left_anti").select(F.col("v").alias("pix"), F.col("cluster").alias("seed"))
    alone = free.join(plateau, "v", "left_anti").select(F.col("v").alias("pix"), F.col("v").alias("seed"))
    return kept.unionByName(alone)
