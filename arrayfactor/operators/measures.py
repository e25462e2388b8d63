"""Accuracy measures on scored cells (label ``y``, score ``score``), by group where wanted."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def auc(scores: DataFrame, by: Sequence[str] = (), score: str = "score", digits: int | None = None) -> DataFrame:
    """Area under the curve with mid-ranks for ties, from counts per distinct score: exact."""
    s = F.round(score, digits) if digits is not None else F.col(score)
    counts = scores.groupBy(*by, s.alias("s")).agg(F.sum(F.when(F.col("y") > 0, 1).otherwise(0)).alias("ones"), F.sum(F.when(F.col("y") > 0, 0).otherwise(1)).alias("zeros"))
    # zeros below each score; without groups in two passes over ranges of it, so that no task sees all scores
    if by:
        window = Window.partitionBy(*by).orderBy("s").rowsBetween(Window.unboundedPreceding, -1)
        ranked = counts.withColumn("below", F.coalesce(F.sum("zeros").over(window), F.lit(0)))
    else:
        ranked = _prefix(counts)
    return ranked.groupBy(*by).agg((F.sum(F.col("ones") * (F.col("below") + F.col("zeros") / 2)) / (F.sum("ones").cast("double") * F.sum("zeros"))).alias("auc"))


def _prefix(counts: DataFrame, ranges: int = 256) -> DataFrame:
    """Running count of zeros below each score without a single-task window: quantile ranges, their totals, then inside."""
    edges = counts.agg(F.percentile_approx("s", F.lit([i / ranges for i in range(1, ranges)]), 10_000).alias("edges"))
    ranged = counts.join(F.broadcast(edges), F.lit(True)).withColumn("range", F.size(F.filter("edges", lambda e: e < F.col("s")))).drop("edges")
    totals = ranged.groupBy("range").agg(F.sum("zeros").alias("n")).withColumn("ahead", F.sum("n").over(Window.orderBy("range")) - F.col("n")).drop("n")
    inside = F.coalesce(F.sum("zeros").over(Window.partitionBy("range").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return ranged.join(F.broadcast(totals), "range").withColumn("below", F.col("ahead") + inside)


def auc_binned(scores: DataFrame, by: Sequence[str] = (), bins: int = 10_000, low: float = 0.0, high: float = 1.0, score: str = "score") -> DataFrame:
    """The same on equal bins of the score's range: hash aggregation only."""
    at = F.least(F.greatest(F.floor((F.col(score) - low) / (high - low) * bins), F.lit(0)), F.lit(bins - 1))
    counts = scores.groupBy(*by, at.alias("s")).agg(F.sum(F.when(F.col("y") > 0, 1).otherwise(0)).alias("ones"), F.sum(F.when(F.col("y") > 0, 0).otherwise(1)).alias("zeros"))
    below = F.coalesce(F.sum("zeros").over(Window.partitionBy(*by).orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return counts.withColumn("below", below).groupBy(*by).agg((F.sum(F.col("ones") * (F.col("below") + F.col("zeros") / 2)) / (F.sum("ones").cast("double") * F.sum("zeros"))).alias("auc"))


def summarize(aucs: DataFrame) -> DataFrame:
    """Mean, standard deviation and number over repeated runs."""
    return aucs.agg(F.avg("auc").alias("mean_auc"), F.stddev_samp("auc").alias("sd_auc"), F.count("auc").alias("runs"))


def rmse(scores: DataFrame, score: str = "score", baseline: str | None = None) -> DataFrame:
    """Root mean square error, and its share of a baseline score's."""
    err = F.sqrt(F.avg((F.col("y") - F.col(score)) ** 2))
    out = [err.alias("rmse")]
    if baseline:
        out.append((err / F.sqrt(F.avg((F.col("y") - F.col(baseline)) ** 2))).alias("ratio"))
    return scores.agg(*out)


def log_loss(scores: DataFrame, prob: str = "prob", least: float = 1e-9) -> DataFrame:
    p = F.least(F.greatest(F.col(prob), F.lit(least)), F.lit(1 - least))
    return scores.agg((-F.avg(F.when(F.col("y") > 0, F.log(p)).otherwise(F.log(1 - p)))).alias("log_loss"))


def scaling_curve(times: DataFrame, base: int) -> DataFrame:
    """(machines, seconds, relative, speedup): run time over the base's, and the inverse."""
    at = times.filter(F.col("machines") == base).select(F.col("seconds").alias("s0"))
    return times.join(F.broadcast(at), F.lit(True)).select("machines", "seconds", (F.col("seconds") / F.col("s0")).alias("relative"), (F.col("s0") / F.col("seconds")).alias("speedup"))
