"""Estimates from a sample (key, w, p_incl): each sampled key stands for 1 / p_incl keys."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, functions as F

from ..functions.frequency import FrequencyFunction


def estimate(sample: DataFrame, f: FrequencyFunction) -> DataFrame:
    return sample.withColumn("f_hat", f("w") / F.col("p_incl"))


def estimate_statistic(sample: DataFrame, f: FrequencyFunction) -> DataFrame:
    return sample.agg(F.coalesce(F.sum(f("w") / F.col("p_incl")), F.lit(0.0)).alias("estimate"))


def estimate_domain(sample: DataFrame, f: FrequencyFunction, domain: Column | None = None, by: Sequence[str] = ()) -> DataFrame:
    rows = sample if domain is None else sample.where(domain)
    return (rows.groupBy(*by) if by else rows).agg(F.sum(f("w") / F.col("p_incl")).alias("estimate"))


def estimate_linear(sample: DataFrame, f: FrequencyFunction, coefficients: DataFrame, name: str = "coef") -> DataFrame:
    return sample.join(coefficients, "key").agg(F.sum(F.col(name) * f("w") / F.col("p_incl")).alias("estimate"))


def estimate_many(sample: DataFrame, functions: Sequence[FrequencyFunction], by: Sequence[str] = ()) -> DataFrame:
    """One row for each function (and domain), in one pass over the sample."""
    each = F.array(*[F.struct(F.lit(f.name).alias("f"), (f("w") / F.col("p_incl")).alias("v")) for f in functions])
    return sample.select(*by, F.inline(each)).groupBy("f", *by).agg(F.sum("v").alias("estimate"))


def variance_hat(sample: DataFrame, f: FrequencyFunction) -> DataFrame:
    """Unbiased estimate of the sum of the keys' variances."""
    p = F.col("p_incl")
    return sample.agg(F.coalesce(F.sum(f("w") * f("w") * (1 - p) / (p * p)), F.lit(0.0)).alias("variance"))
