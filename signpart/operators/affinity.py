"""Affinities: a planted predictor, a learned one, augmentation and averaging at test time."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signpart.functions.expressions import noise, planted_affinity
from signpart.operators.raster import Offset, Shape

#: The eight symmetries of a square as (swap axes, flip y, flip x); the identity is first.
SYMMETRIES = [(s, fy, fx) for s in (False, True) for fy in (False, True) for fx in (False, True)]


def planted(targets: DataFrame, level: int) -> DataFrame:
    """(u, v, channel, attract, target) rows with affinity ``a`` 0 … 10000: the target with ``level``/10000 of noise."""
    return targets.withColumn("a", planted_affinity(F.col("target"), F.col("u"), F.col("v"), F.col("channel").cast("long"), level))


def planted_values(target: np.ndarray, u: np.ndarray, v: np.ndarray, channel: int, level: int) -> np.ndarray:
    """``planted`` on arrays, for tasks that hold the pairs as arrays."""
    t = (u * 73856093 + v * 19349663 + channel * 83492791) % 1000003
    return (10000 - level) * target + level * (t * t % 1000003 % 10007) // 10007


def to_edges(affinities: DataFrame) -> DataFrame:
    """Edges +a and -a of affinities; zeros go."""
    w = F.when(F.col("attract"), F.col("a")).otherwise(-F.col("a")).cast("double")
    return affinities.where("a <> 0").select(F.xxhash64("u", "v", "channel").alias("edge_id"), "u", "v", w.alias("w"), F.col("channel").cast("int").alias("channel"))


def fit_affinity(rows: DataFrame, features: list[str]):
    """A logistic model per channel of (channel, target, features…): {channel: model}.  Stands in for a network."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    made = VectorAssembler(inputCols=features, outputCol="features").transform(rows)
    channels = [r[0] for r in rows.select("channel").distinct().orderBy("channel").collect()]  # as many as the pattern has
    return {c: LogisticRegression(labelCol="target", maxIter=20).fit(made.where(F.col("channel") == c)) for c in channels}


def predict_affinity(models: dict, rows: DataFrame, features: list[str]) -> DataFrame:
    """rows with ``p``, the predicted probability of the target."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.functions import vector_to_array

    made = VectorAssembler(inputCols=features, outputCol="features").transform(rows)
    out = None
    for channel, model in models.items():
        part = model.transform(made.where(F.col("channel") == channel)).withColumn("p", vector_to_array("probability")[1]).select(*rows.columns, "p")
        out = part if out is None else out.unionByName(part)
    return out


def moved(shape: Shape, swap: bool, flip_y: bool, flip_x: bool) -> tuple[F.Column, F.Column]:
    """(y, x) of a pixel of a square slice after swapping the axes and then flipping."""
    if swap and shape.height != shape.width:
        raise ValueError("only square slices can be turned")
    y, x = (F.col("x"), F.col("y")) if swap else (F.col("y"), F.col("x"))
    return (F.lit(shape.height - 1) - y if flip_y else y), (F.lit(shape.width - 1) - x if flip_x else x)


def augment(pixels: DataFrame, shape: Shape, swap: bool, flip_y: bool, flip_x: bool) -> DataFrame:
    """pixels at their new places: a rotation by 90 degrees is a swap and a flip."""
    y, x = moved(shape, swap, flip_y, flip_x)
    pix = (F.col("z") * shape.height + F.col("y")) * shape.width + F.col("x")
    rest = [c for c in pixels.columns if c not in ("pix", "y", "x")]
    return pixels.select(y.alias("y"), x.alias("x"), *rest).withColumn("pix", pix).select("pix", "z", "y", "x", *[c for c in rest if c != "z"])


def elastic(pixels: DataFrame, shape: Shape, cell: int = 8, reach: int = 2) -> DataFrame:
    """(pix, z, y, x, source): where each pixel takes its value from under a smooth warp.

    Displacements of -reach … reach are noise of the corners of coarse cells, and
    are mixed bilinearly inside; all in integers.
    """

    def displaced(axis: int) -> F.Column:
        cy, cx = F.floor(F.col("y") / cell), F.floor(F.col("x") / cell)
        fy, fx = F.col("y") - cy * cell, F.col("x") - cx * cell
        corner = lambda dy, dx: noise(cy + dy, cx + dx, F.lit(axis).cast("long")) % (2 * reach + 1) - reach
        total = corner(0, 0) * (cell - fy) * (cell - fx) + corner(0, 1) * (cell - fy) * fx + corner(1, 0) * fy * (cell - fx) + corner(1, 1) * fy * fx
        return F.floor((total + (cell * cell) // 2) / (cell * cell)).cast("long")

    clip = lambda c, top: F.greatest(F.lit(0).cast("long"), F.least(F.lit(top - 1).cast("long"), c))
    sy, sx = clip(F.col("y") + displaced(0), shape.height), clip(F.col("x") + displaced(1), shape.width)
    return pixels.select("pix", "z", "y", "x", ((F.col("z") * shape.height + sy) * shape.width + sx).alias("source"))


def average_over_symmetries(rows: DataFrame, predictor, shape: Shape, offsets: list[Offset], count: int = 7) -> DataFrame:
    """(u, v, attract, a): affinities averaged over ``count`` transformed copies, back at the original pairs.

    ``predictor(rows)`` maps (u, v, channel, attract, target) to rows with ``a``; a
    pair of pixels is the same pair wherever a copy puts it, so its ends are
    moved, predicted and moved back in one projection.
    """
    area = shape.height * shape.width
    out = None
    for k, (swap, fy, fx) in enumerate(SYMMETRIES[:count]):

        def there(c: str):
            z, y, x = F.expr(f"{c} div {area}"), F.expr(f"({c} % {area}) div {shape.width}"), F.col(c) % shape.width
            y, x = (x, y) if swap else (y, x)
            y = F.lit(shape.height - 1) - y if fy else y
            x = F.lit(shape.width - 1) - x if fx else x
            return (z * shape.height + y) * shape.width + x

        copy = rows.select(F.col("u").alias("ou"), F.col("v").alias("ov"), there("u").alias("pu"), there("v").alias("pv"), "channel", "attract", "target")
        copy = copy.select("ou", "ov", F.least("pu", "pv").alias("u"), F.greatest("pu", "pv").alias("v"), "channel", "attract", "target")
        made = predictor(copy).select(F.col("ou").alias("u"), F.col("ov").alias("v"), "channel", "attract", F.lit(k).alias("copy"), "a")
        out = made if out is None else out.unionByName(made)
    return out.groupBy("u", "v", "channel", "attract").agg(F.sum("a").alias("total"), F.count(F.lit(1)).alias("copies"))
