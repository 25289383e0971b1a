"""Samples from unaggregated elements, without the shuffle of all keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..functions.frequency import FrequencyFunction
from ..functions.seeds import exp_of, inclusion, unit_seed
from ..plans.lineage import cut
from .bottomk import bottom_k

#: Held keys up to which they are broadcast to the second pass.
HELD_KEYS = 200_000


def element_seeds(elements: DataFrame, element_id: str, salt: str = "s") -> DataFrame:
    """(key, seed): each key's smallest Exp(1) / value over its elements, which is Exp(w) in distribution.

    The element id must be the same on a retry: a column of the data, never a row counter.
    """
    e = exp_of(unit_seed(F.concat(F.col(element_id).cast("string"), F.lit("|"), F.col("key")), salt)) / F.col("value")
    return elements.select("key", e.alias("seed")).groupBy("key").agg(F.min("seed").alias("seed"))


def ppswor_by_elements(elements: DataFrame, k: int, element_id: str, salt: str = "s") -> DataFrame:
    """First pass: (key, seed, tau) of the k - 1 keys of an l_1 sample, and the k-th seed as tau."""
    from pyspark.sql import Window as W

    kept = bottom_k(element_seeds(elements, element_id, salt), k)
    whole = W.partitionBy()
    out = kept.withColumn("tau", F.when(F.count("*").over(whole) >= k, F.max("seed").over(whole)))
    return out.where("tau is null or seed < tau")


def two_pass(elements: DataFrame, kept: DataFrame) -> DataFrame:
    """Second pass: exact frequencies of the kept keys only; p_incl of their l_1 sample."""
    rows = elements.join(F.broadcast(kept.select("key")), "key", "left_semi").groupBy("key").agg(F.sum("value").alias("w"))
    return rows.join(F.broadcast(kept), "key").withColumn("p_incl", inclusion("ppswor", F.col("w"), F.col("tau")))


def sample_and_hold(elements: DataFrame, tau: float, element_id: str, salt: str = "s") -> DataFrame:
    """(key, c): keys that entered at rate ``tau`` for each unit of value, and what was counted from then on.

    A key's elements are taken in order of ``element_id``, and an element's draw is a hash
    of that id and the key, so retries and other partitions change nothing. The first pass
    holds only elements that could enter, about tau times the mass; the second adds up what
    follows a key's entry. Both are summed before the shuffle, so a hot key is one row a task.
    """
    wait = exp_of(unit_seed(F.concat(F.col("at").cast("string"), F.lit("|"), F.col("key")), salt)) / F.lit(float(tau))
    rows = elements.select("key", F.col("value").cast("double").alias("value"), F.col(element_id).alias("at"))
    tries = rows.select("key", "at", (F.col("value") - wait).alias("left")).where("left > 0")
    held = tries.groupBy("key").agg(F.min(F.struct("at", "left")).alias("entry"))
    held = cut(held.select("key", F.col("entry.at").alias("since"), F.col("entry.left").alias("left")))
    side = F.broadcast(held) if held.count() <= HELD_KEYS else held
    later = rows.join(side.select("key", "since"), "key").where(F.col("at") > F.col("since")).select("key", F.col("value").alias("c"))
    return later.unionByName(held.select("key", F.col("left").alias("c"))).groupBy("key").agg(F.sum("c").alias("c"))


def hold_estimate(held: DataFrame, f: FrequencyFunction, slope: FrequencyFunction, tau: float) -> DataFrame:
    """Unbiased for f with f(0) = 0: sum of f(c) + f'(c) / tau."""
    return held.agg(F.sum(f("c") + slope("c") / tau).alias("estimate"))
