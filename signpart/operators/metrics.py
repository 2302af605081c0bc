"""Scores and losses."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signpart import tables


def contingency(labels: DataFrame, truth: DataFrame) -> DataFrame:
    """(cluster, gt, n) of pixels with a true label; the only table that the scores shuffle."""
    joined = labels.join(truth.where("gt is not null").select(F.col("pix").alias("v"), "gt"), "v")
    return joined.groupBy("cluster", "gt").agg(F.count(F.lit(1)).alias("n"))


def _squares(table: DataFrame, key: str | None) -> DataFrame:
    sums = table if key is None else table.groupBy(key).agg(F.sum("n").alias("n"))
    n = F.col("n").cast("decimal(19,0)")
    return sums.agg(F.coalesce(F.sum(n * n), F.lit(0)).cast("double").alias("q"))


def rand_score(table: DataFrame, alpha: float = 0.5) -> DataFrame:
    """One row (pair, precision, recall) of a contingency table: shared pairs over the weighted pairs of both sides."""
    both, seg, gt = (_squares(table, k).select(F.col("q").alias(name)) for k, name in ((None, "both"), ("cluster", "seg"), ("gt", "true_")))
    one = both.crossJoin(seg).crossJoin(gt)  # one row each
    part = lambda d: F.when(d > 0, F.col("both") / d).otherwise(F.lit(1.0))
    return one.select(F.round(part(F.lit(alpha) * F.col("seg") + F.lit(1 - alpha) * F.col("true_")), 6).alias("pair"), F.round(part(F.col("seg")), 6).alias("precision"), F.round(part(F.col("true_")), 6).alias("recall"))


def info_score(table: DataFrame, alpha: float = 0.5) -> DataFrame:
    """One row (info, variation): mutual information over the weighted entropies, and the raw variation of information."""
    total = table.agg(F.sum("n").cast("double").alias("t"))

    def entropy(key: str | None, name: str) -> DataFrame:
        sums = table if key is None else table.groupBy(key).agg(F.sum("n").alias("n"))
        p = F.col("n") / F.col("t")
        return sums.crossJoin(F.broadcast(total)).agg(F.coalesce(-F.sum(p * F.log(p)), F.lit(0.0)).alias(name))  # total is one row

    one = entropy(None, "joint").crossJoin(entropy("cluster", "seg")).crossJoin(entropy("gt", "true_"))  # one row each
    shared = F.col("seg") + F.col("true_") - F.col("joint")
    mean = F.lit(alpha) * F.col("true_") + F.lit(1 - alpha) * F.col("seg")
    return one.select(F.round(F.when(mean > 1e-12, shared / mean).otherwise(F.lit(1.0)), 6).alias("info"), F.round(2 * F.col("joint") - F.col("seg") - F.col("true_"), 6).alias("variation"))


def scores(labels: DataFrame, truth: DataFrame, method: str) -> DataFrame:
    """One row (method, n_clusters, pair, info)."""
    table = tables.written(contingency(labels, truth))
    return _scored(labels.agg(F.countDistinct("cluster").alias("n_clusters")), table, method)


def scores_of(labelled: DataFrame, method: str) -> DataFrame:
    """The same of rows (cluster, gt) of all pixels, gt null where there is no true label; no pixel is joined."""
    table = tables.written(labelled.groupBy("cluster", "gt").agg(F.count(F.lit(1)).alias("n")))
    return _scored(table.agg(F.countDistinct("cluster").alias("n_clusters")), table.where("gt is not null"), method)


def scores_by(labelled: DataFrame, by: str) -> DataFrame:
    """(by, n_clusters, pair, info) of rows (by, cluster, gt), gt null where there is no true label: ``scores_of`` of each, in one plan."""
    table = tables.written(labelled.groupBy(by, "cluster", "gt").agg(F.count(F.lit(1)).alias("n")))
    known = table.where("gt is not null")
    sums = known.select(by, F.lit("joint").alias("part"), "n")
    for key, part in (("cluster", "seg"), ("gt", "true")):
        sums = sums.unionByName(known.groupBy(by, key).agg(F.sum("n").alias("n")).select(by, F.lit(part).alias("part"), "n"))
    n, p = F.col("n").cast("decimal(19,0)"), F.col("n") / F.col("t")
    totals = known.groupBy(by).agg(F.sum("n").cast("double").alias("t"))
    of = lambda value, part: F.coalesce(F.sum(F.when(F.col("part") == part, value)).cast("double"), F.lit(0.0))
    parts = sums.join(totals, by).groupBy(by).agg(*(of(n * n, k).alias(f"q_{k}") for k in ("joint", "seg", "true")), *((-of(p * F.log(p), k)).alias(f"h_{k}") for k in ("joint", "seg", "true")))
    both, mean = (F.col("q_seg") + F.col("q_true")) / 2, (F.col("h_seg") + F.col("h_true")) / 2
    pair = F.when(both > 0, F.col("q_joint") / both).otherwise(F.lit(1.0))
    info = F.when(mean > 1e-12, (F.col("h_seg") + F.col("h_true") - F.col("h_joint")) / mean).otherwise(F.lit(1.0))
    return table.groupBy(by).agg(F.countDistinct("cluster").alias("n_clusters")).join(parts, by, "left").select(by, "n_clusters", F.round(pair, 6).alias("pair"), F.round(info, 6).alias("info"))


def _scored(n: DataFrame, table: DataFrame, method: str) -> DataFrame:
    return n.crossJoin(rand_score(table).select("pair")).crossJoin(info_score(table).select("info")).select(F.lit(method).alias("method"), "n_clusters", "pair", "info")  # one row each


def split_merge_report(table: DataFrame, seeds: DataFrame | None = None) -> DataFrame:
    """One row: segments, true regions, split regions, merged segments."""
    per_gt = table.groupBy("gt").agg(F.count(F.lit(1)).alias("k")).agg(F.count(F.lit(1)).alias("n_regions"), F.count_if(F.col("k") > 1).alias("split_regions"))
    per_seg = table.groupBy("cluster").agg(F.count(F.lit(1)).alias("k")).agg(F.count(F.lit(1)).alias("n_segments"), F.count_if(F.col("k") > 1).alias("merged_segments"))
    return per_seg.crossJoin(per_gt).select("n_segments", "n_regions", "split_regions", "merged_segments")  # one row each


def seeds_per_region(seeds: DataFrame, truth: DataFrame) -> DataFrame:
    """(gt, n_seeds) of every true region."""
    found = seeds.join(truth, "pix").groupBy("gt").agg(F.countDistinct("seed").alias("n"))
    return truth.select("gt").where("gt is not null").distinct().join(found, "gt", "left").select("gt", F.coalesce("n", F.lit(0)).alias("n_seeds"))


def dice_loss(rows: DataFrame, one: float = 1) -> DataFrame:
    """(channel, attract, loss) of (channel, attract, p, target) out of ``one``: minus overlap over energy, of complements where it attracts; 0 if empty."""
    flip = lambda c: F.when(F.col("attract"), one - F.col(c)).otherwise(F.col(c))
    p, t = flip("p"), flip("target")
    sums = rows.groupBy("channel", "attract").agg(F.sum(p * t).alias("o"), F.sum(p * p + t * t).alias("e"))
    return sums.select("channel", "attract", F.when(F.col("e") > 0, -F.col("o") / F.col("e")).otherwise(F.lit(0.0)).alias("loss"))


def total_dice_loss(rows: DataFrame, one: float = 1) -> DataFrame:
    """One row: the losses of all channels, added up."""
    return dice_loss(rows, one).agg(F.coalesce(F.sum("loss"), F.lit(0.0)).alias("loss"))


def edge_losses(rows: DataFrame, eps: float = 1e-6) -> DataFrame:
    """One row: error rate at one half, mean cross-entropy, mean squared error of (p, target)."""
    p = F.greatest(F.least(F.col("p"), F.lit(1 - eps)), F.lit(eps))
    entropy = -(F.col("target") * F.log(p) + (1 - F.col("target")) * F.log(1 - p))
    wrong = ((F.col("p") >= 0.5).cast("int") != F.col("target")).cast("int")
    return rows.agg(F.round(F.avg(wrong), 6).alias("error_rate"), F.round(F.avg(entropy), 6).alias("cross_entropy"), F.round(F.avg((F.col("p") - F.col("target")) * (F.col("p") - F.col("target"))), 6).alias("squared_error"))


def fit_log(curve: DataFrame) -> DataFrame:
    """One row (slope, intercept, r2): seconds per edge against ln(edges) of (n_edges, seconds)."""
    rows = curve.select(F.log(F.col("n_edges").cast("double")).alias("x"), (F.col("seconds") / F.col("n_edges")).alias("y"))
    return rows.agg(F.regr_slope("y", "x").alias("slope"), F.regr_intercept("y", "x").alias("intercept"), F.regr_r2("y", "x").alias("r2"))
