"""Costs of labelings and active sets."""

from __future__ import annotations

from collections.abc import Iterator
from decimal import Context, Decimal, localcontext
from fractions import Fraction

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signpart import tables
from signpart.functions.expressions import order_key
from signpart.operators import components as comp


def indicator(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """edges with x: 1 if the edge disagrees with the labels (is not active), else 0."""
    ends = comp.relabelled(edges, labels)
    return ends.select(*edges.columns, ((F.col("w") > 0) != (F.col("cu") == F.col("cv"))).cast("int").alias("x"))


def multicut_cost(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: cost, the sum of |w| over the edges that disagree."""
    return indicator(edges, labels).agg(F.coalesce(F.sum(F.abs("w") * F.col("x")), F.lit(0.0)).alias("cost"))


def _power(p: int):
    """|w|**p of integer weights as an exact decimal."""
    size = F.abs("w").cast("decimal(38,0)")
    out = F.lit(1).cast("decimal(38,0)")
    for _ in range(p):
        out = (out * size).cast("decimal(38,0)")
    return out


def powered_cost(edges: DataFrame, labels: DataFrame, p: int) -> DataFrame:
    """One row (p, cost) with |w|**p in place of |w|: exact for integer weights, as text; null beyond 38 digits."""
    return indicator(edges, labels).where("x = 1").agg(F.coalesce(F.sum(_power(p)), F.lit(0).cast("decimal(38,0)")).alias("c")).select(F.lit(p).alias("p"), F.col("c").cast("string").alias("cost"))


def active_energy(active: DataFrame, p: int) -> DataFrame:
    """One row (p, energy): minus the sum of |w|**p over the active edges, as text."""
    total = active.where("active = 1").agg(F.coalesce(F.sum(_power(p)), F.lit(0).cast("decimal(38,0)")).alias("c"))
    return total.select(F.lit(p).alias("p"), F.when(F.col("c") == 0, "0").otherwise(F.concat(F.lit("-"), F.col("c").cast("string"))).alias("energy"))


def level_sums(edges: DataFrame) -> DataFrame:
    """(s, n): the distinct |w| and how many edges have each."""
    return edges.groupBy(F.abs("w").alias("s")).agg(F.count(F.lit(1)).alias("n"))


#: Distinct sizes that one task takes, decimal digits that it reckons with, and margins below which sizes are compared as integers.
LEVELS_OF_A_TASK, DIGITS, CLOSE = 100_000, 60, Decimal(10) ** -45
#: Sizes with so small a margin that are compared, and how many smaller ones are looked at for each at a time.
EXACT_LEVELS, EXACT_STEP = 64, 4096


def _steps(sizes: list[float], counts: list[int], p: int, share: Decimal) -> Iterator[tuple[Decimal, Decimal]]:
    """For rising sizes: (sum of all smaller sizes, that sum and the size's own edges), both in units of size**p; ``share`` is the first."""
    total, last = share, None
    for size, n in zip(sizes, counts):
        if last is not None:
            share = total * (Decimal(last) / Decimal(size)) ** p
        total = share + n
        yield share, total
        last = size


def _exactly_larger(levels: DataFrame, size: float, p: int) -> bool:
    """Whether size**p exceeds the sum over all smaller sizes, in integers: every double is a fraction with a power of two below."""
    whole, below = size.as_integer_ratio()
    left, bound = Fraction(whole**p, below**p), size
    while True:
        part = levels.where(F.col("s") < F.lit(bound)).orderBy(F.desc("s")).limit(EXACT_STEP).collect()
        for r in part:
            a, b = r["s"].as_integer_ratio()
            left -= r["n"] * Fraction(a**p, b**p)
            if left <= 0:
                return False
        if len(part) < EXACT_STEP:
            return True
        bound = part[-1]["s"]


def _exact_context():
    return localcontext(Context(prec=DIGITS, Emin=-(10**15), Emax=10**15))


def _judged_powers(levels: DataFrame, powers: list[int]) -> list[tuple[int, int, float | None, bool]]:
    """(p, ties, least margin, dominant) of each power, from the written table of sizes."""
    n = levels.count()
    if not n:
        return [(p, 0, None, True) for p in powers]
    ranges = -(-n // LEVELS_OF_A_TASK)
    cuts = sorted(set(levels.stat.approxQuantile("s", [k / ranges for k in range(1, ranges)], 0.1 / ranges))) if ranges > 1 else []
    of_range = F.lit(0)
    for cut in cuts:
        of_range = of_range + (F.col("s") > F.lit(cut)).cast("int")
    ranged = levels.withColumn("k", of_range)
    incoming: dict[tuple[int, int], str] = {(0, p): "0" for p in powers}

    def ends(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("s")
        sizes, counts, rows = part["s"].tolist(), part["n"].tolist(), []
        with _exact_context():
            for p in powers:
                *_, (_, total) = _steps(sizes, counts, p, Decimal(0))
                rows.append((int(part["k"].iloc[0]), p, sizes[0], sizes[-1], str((Decimal(sizes[0]) / Decimal(sizes[-1])) ** p), str(total)))
        return pd.DataFrame(rows, columns=["k", "p", "low", "high", "factor", "total"])

    if ranges > 1:
        found = ranged.groupBy("k").applyInPandas(ends, "k int, p int, low double, high double, factor string, total string").collect()  # a row for each range and power
        with _exact_context():
            for p in powers:
                total, last = Decimal(0), None
                for r in sorted((r for r in found if r["p"] == p), key=lambda r: r["k"]):
                    share = Decimal(0) if last is None else total * (Decimal(last) / Decimal(r["low"])) ** p
                    incoming[r["k"], p] = str(share)
                    total, last = share * Decimal(r["factor"]) + Decimal(r["total"]), r["high"]

    def margins(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("s")
        sizes, counts, rows = part["s"].tolist(), part["n"].tolist(), []
        with _exact_context():
            for p in powers:
                found = [1 - share for share, _ in _steps(sizes, counts, p, Decimal(incoming[int(part["k"].iloc[0]), p]))]
                close = [s for s, m in zip(sizes, found) if abs(m) < CLOSE]
                rows.append((p, float(min(found)), any(m <= -CLOSE for m in found), sum(c > 1 for c in counts), close[: EXACT_LEVELS + 1]))
        return pd.DataFrame(rows, columns=["p", "margin", "behind", "ties", "close"])

    out, judged = ranged.groupBy("k").applyInPandas(margins, "p int, margin double, behind boolean, ties long, close array<double>").collect(), []
    for p in powers:
        mine = [r for r in out if r["p"] == p]
        ties, close = sum(r["ties"] for r in mine), sorted(x for r in mine for x in r["close"])
        dominant = not ties and not any(r["behind"] for r in mine)
        if dominant and len(close) > EXACT_LEVELS:
            raise ValueError(f"more than {EXACT_LEVELS} weights are within {CLOSE} of the sum of the smaller ones at power {p}")
        judged.append((p, ties, min(r["margin"] for r in mine), dominant and all(_exactly_larger(levels, x, p) for x in close)))
    return judged


def dominant_power_margin(edges: DataFrame, *powers: int) -> DataFrame:
    """(p, ties, least_margin, dominant) of each power.

    p is dominant if no two edges weigh the same and every |w|**p exceeds the sum
    of all smaller ones.  In units of the own size**p nothing overflows or gets
    lost: with r the ratio of a size to the next larger one, the sum below the next
    is (sum + n) * r**p.  That is a chain of affine steps, so ranges of sizes are
    reckoned side by side, their ends are chained, and a second pass has the
    margins inside each range.  Margins too small for the digits are settled in
    integers.
    """
    rows = _judged_powers(tables.written(level_sums(edges)), list(powers))
    return edges.sparkSession.createDataFrame(rows, "p int, ties long, least_margin double, dominant boolean")


def is_dominant_power(edges: DataFrame, *powers: int) -> DataFrame:
    """(p, dominant) of each power."""
    return dominant_power_margin(edges, *powers).select("p", "dominant")


def min_dominant_power(edges: DataFrame, limit: int = 1024, at_once: int = 16) -> int | None:
    """The least dominant power up to ``limit``, by search with several powers a pass (a larger power stays dominant); None if there is none."""
    levels, low, high = tables.written(level_sums(edges)), 0, None
    while high is None or high - low > 1:
        top = limit if high is None else high - 1
        tried = sorted({low + -(-(top - low) * k // at_once) for k in range(1, at_once + 1)})
        judged = [(p, dominant) for p, _, _, dominant in _judged_powers(levels, tried)]
        found = [p for p, dominant in judged if dominant]
        if high is None and not found:
            return None
        high = min(found, default=high)
        low = max((p for p, dominant in judged if not dominant), default=low)
    return high


def lexi_better(first: DataFrame, second: DataFrame) -> DataFrame:
    """One row, ``better``: which of two active sets (edge_id, u, v, w) has the first edge, in processing order, that the other lacks."""
    a = first.select("edge_id", "u", "v", "w", F.lit(1).alias("in_a"))
    b = second.select("edge_id", "u", "v", "w", F.lit(1).alias("in_b"))
    differing = a.join(b, ["edge_id", "u", "v", "w"], "full").where("in_a is null or in_b is null")
    best = differing.agg(F.min_by(F.when(F.col("in_a") == 1, "first").otherwise("second"), order_key()).alias("better"))
    return best.select(F.coalesce("better", F.lit("equal")).alias("better"))


def dominant_edges(edges: DataFrame) -> DataFrame:
    """Attractions that weigh at least as much as all other edges of one of their ends together.

    The cut around a single vertex is one of many, so this is a sufficient test.
    """
    sums = edges.select(F.explode(F.array("u", "v")).alias("x"), F.abs("w").alias("s")).groupBy("x").agg(F.sum("s").alias("s"))
    su, sv = sums.select(F.col("x").alias("u"), F.col("s").alias("su")), sums.select(F.col("x").alias("v"), F.col("s").alias("sv"))
    return edges.where("w > 0").join(su, "u").join(sv, "v").where("2 * w >= least(su, sv)").select("edge_id", "u", "v", "w")
