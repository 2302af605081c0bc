"""Column expressions of signed edges; all run inside generated code."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def order_key(w: str = "w", u: str = "u", v: str = "v", edge_id: str = "edge_id") -> Column:
    """Ascending in processing order: larger |w| first, then u, v, edge_id."""
    return F.struct((-F.abs(F.col(w))).alias("k0"), F.col(u).alias("k1"), F.col(v).alias("k2"), F.col(edge_id).alias("k3"))


def pair(a, b) -> tuple[Column, Column]:
    """The pair with its lesser end first."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return F.least(a, b), F.greatest(a, b)


def noise(u, v, channel) -> Column:
    """Deterministic integer noise 0 … 10006 of a vertex pair and channel, the same in every engine."""
    t = (u * F.lit(73856093) + v * F.lit(19349663) + channel * F.lit(83492791)) % F.lit(1000003)
    return ((t * t) % F.lit(1000003)) % F.lit(10007)


def planted_affinity(target, u, v, channel, level: int) -> Column:
    """Affinity 0 … 10000: the target, with a share of ``level``/10000 of noise."""
    share = F.lit(level).cast("long") * noise(u, v, channel)
    return F.lit(10000 - level).cast("long") * target + ((share - share % F.lit(10007)) / F.lit(10007)).cast("long")


def log_odds(affinity: Column, attract: Column, eps: float = 1e-6) -> Column:
    """Cost of cutting an edge: ln(p/(1-p)) of attraction p; of repulsion p, ln((1-p)/p). p is kept in [eps, 1-eps]."""
    p = F.greatest(F.least(affinity, F.lit(1 - eps)), F.lit(eps))
    return F.when(attract, F.log(p / (1 - p))).otherwise(F.log((1 - p) / p))


def register_sql_functions(spark: SparkSession) -> None:
    """SQL forms for users of spark.sql, as temporary SQL functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pair_low(a BIGINT, b BIGINT) RETURNS BIGINT RETURN least(a, b)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pair_high(a BIGINT, b BIGINT) RETURNS BIGINT RETURN greatest(a, b)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edge_log_odds(p DOUBLE, attract BOOLEAN) RETURNS DOUBLE RETURN CASE WHEN attract THEN ln(greatest(least(p, 0.999999D), 0.000001D) / (1 - greatest(least(p, 0.999999D), 0.000001D))) ELSE ln((1 - greatest(least(p, 0.999999D), 0.000001D)) / greatest(least(p, 0.999999D), 0.000001D)) END")
