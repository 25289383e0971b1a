"""Bottom-k samples of aggregated keys: PPSWOR, priority and uniform, and their merging.

A sample of size k keeps the k keys of smallest seed; the k-th is the threshold of the
other k - 1. If there are fewer than k keys, all are in the sample with chance 1.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..functions.frequency import FrequencyFunction, moment
from ..functions.seeds import draw, inclusion


def seeded(freq: DataFrame, weight: Column, salt: str | Column = "s", scheme: str = "ppswor", fast: bool = False) -> DataFrame:
    """``freq`` with h (the draw), weight, and seed = h / weight (null where the weight is 0)."""
    out = freq.withColumn("h", draw(F.col("key"), salt, scheme, fast)).withColumn("weight", weight)
    return out.withColumn("seed", F.when(F.col("weight") > 0, F.col("h") / F.col("weight")))


def bottom_k(rows: DataFrame, k: int, seed: str = "seed") -> DataFrame:
    """The k rows of smallest seed, ties by key: each task keeps k rows, then one merges them."""
    return rows.where(F.col(seed).isNotNull()).orderBy(seed, "key").limit(k)


def strict(sketch: DataFrame, k: int, scheme: str = "ppswor") -> DataFrame:
    """From the k kept rows: the k - 1 (or all, if fewer were found) inside, with tau and p_incl."""
    whole = W.partitionBy()  # over the k kept rows only
    tau = F.when(F.count("*").over(whole) >= k, F.max("seed").over(whole))
    out = sketch.withColumn("tau", tau).withColumn("_at", F.row_number().over(W.orderBy("seed", "key")))
    out = out.where(F.col("tau").isNull() | (F.col("_at") < k)).drop("_at")
    return out.withColumn("p_incl", inclusion(scheme, F.col("weight"), F.col("tau")))


def sample(freq: DataFrame, f: FrequencyFunction, k: int, salt: str = "s", scheme: str = "ppswor", fast: bool = False) -> DataFrame:
    """(key, w, h, weight, seed, tau, p_incl) of a sample by weight f(w)."""
    if k < 1:
        raise ValueError("k must be 1 or more")
    return strict(bottom_k(seeded(freq, f("w"), salt, scheme, fast), k), k, scheme)


def ppswor(freq: DataFrame, k: int, q: float = 1, salt: str = "s") -> DataFrame:
    return sample(freq, moment(q), k, salt, "ppswor")


def priority(freq: DataFrame, k: int, q: float = 1, salt: str = "s") -> DataFrame:
    return sample(freq, moment(q), k, salt, "priority")


def uniform(freq: DataFrame, k: int, salt: str = "s", scheme: str = "ppswor") -> DataFrame:
    return sample(freq, moment(0), k, salt, scheme)


def thresholds(rows: DataFrame, k: int, by: Sequence[str] = (), seed: str = "seed") -> DataFrame:
    """The two order statistics from which every key's leave-one-out threshold follows: (k_th, k_before) for each group.

    A key of the k - 1 smallest has the k-th as its threshold, another one the (k - 1)-th;
    missing ones are null, that is, infinite. With k of 1 or less nothing is included.
    """
    window = W.partitionBy(*by).orderBy(seed, "key")
    some = rows.where(F.col(seed).isNotNull()).select(*by, "key", seed).withColumn("_at", F.row_number().over(window)).where(F.col("_at") <= k)
    at = lambda i: F.min(F.when(F.col("_at") == i, F.col(seed)))
    return (some.groupBy(*by) if by else some.groupBy()).agg(at(k).alias("k_th"), at(k - 1).alias("k_before"))


def threshold_of(seed: Column, k_th: Column, k_before: Column, k: int) -> Column:
    if k <= 1:
        return F.lit(0.0)
    return F.when(k_before.isNull() | (seed <= k_before), k_th).otherwise(k_before)


def merge(sketches: Sequence[DataFrame], k: int, f: FrequencyFunction, scheme: str = "ppswor") -> DataFrame:
    """One sketch from sketches of parts with disjoint keys, or of equal keys whose frequencies add.

    Sketches of unaggregated parts only merge exactly for weights that need no sum (uniform
    samples, advice); for f(w) the parts must split by key.
    """
    rows = reduce(DataFrame.unionByName, [s.select("key", "w", "h") for s in sketches])
    again = rows.groupBy("key").agg(F.sum("w").alias("w"), F.min("h").alias("h"))
    again = again.withColumn("weight", f("w")).withColumn("seed", F.when(F.col("weight") > 0, F.col("h") / F.col("weight")))
    return bottom_k(again, k)
