"""Rank against frequency: the true curve, and the one that a sample shows."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window as W, functions as F

from .exact import ranked


def rank_curve(sample: DataFrame) -> DataFrame:
    """(key, w, rank_hat): for each sampled key the estimated number of keys at least as frequent."""
    over = W.orderBy(F.col("w").desc()).rangeBetween(W.unboundedPreceding, W.currentRow)
    return sample.select("key", "w", F.sum(1 / F.col("p_incl")).over(over).alias("rank_hat"))


def rank_curve_true(hist: DataFrame) -> DataFrame:
    """(w, rank): keys at least as frequent as w."""
    return ranked(hist).select("w", F.col("last_rank").cast("bigint").alias("rank"))


def rank_curve_error(sample: DataFrame, hist: DataFrame) -> DataFrame:
    """(points, mean_error, max_error, lowest): absolute log ratios of ranks at sampled frequencies, and the lowest of these."""
    both = rank_curve(sample).select("w", "rank_hat").distinct().join(rank_curve_true(hist), "w")
    e = F.abs(F.log(F.col("rank_hat") / F.col("rank")))
    return both.agg(F.count("*").alias("points"), F.avg(e).alias("mean_error"), F.max(e).alias("max_error"), F.min("w").alias("lowest"))


def threshold_curve(sample: DataFrame, thresholds: Sequence[float]) -> DataFrame:
    """(t, estimate): keys with w >= t for a grid of thresholds, in one pass over the sample."""
    each = F.array(*[F.struct(F.lit(float(t)).alias("t"), F.when(F.col("w") >= t, 1 / F.col("p_incl")).otherwise(0.0).alias("v")) for t in thresholds])
    return sample.select(F.inline(each)).groupBy("t").agg(F.sum("v").alias("estimate"))
