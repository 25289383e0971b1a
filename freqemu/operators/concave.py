"""Samples for capping functions and for all concave sublinear functions at once."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window as W, functions as F

from ..functions.frequency import cap
from ..functions.seeds import draw, inclusion
from ..plans.lineage import cut
from .bottomk import bottom_k, sample, seeded, strict, threshold_of, thresholds
from .exact import ONE_TASK, histogram
from .overhead import concave_weights


def cap_sample(freq: DataFrame, t: float, k: int, salt: str = "s") -> DataFrame:
    return sample(freq, cap(t), k, salt)


def concave_probabilities(freq: DataFrame) -> DataFrame:
    """(key, w, v, p): weight v and share p of the multi-objective scheme; equal frequencies have equal weights."""
    v = concave_weights(cut(histogram(freq))).select("w", "m", "v")
    total = v.agg(F.sum(F.col("m") * F.col("v")).alias("_all"))
    return _looked_up(freq, v).crossJoin(F.broadcast(total)).select("key", "w", "v", (F.col("v") / F.col("_all")).alias("p"))


def _looked_up(freq: DataFrame, v: DataFrame) -> DataFrame:
    """``freq`` with the weight v of its frequency. Most keys share a few small frequencies, so
    frequencies are broadcast: all of them, or the ONE_TASK that most keys have."""
    each = v.select("w", "m", "v")
    if each.count() <= ONE_TASK:
        return freq.join(F.broadcast(each.drop("m")), "w")
    least = each.orderBy(F.col("m").desc()).limit(ONE_TASK).agg(F.min("m")).first()[0]
    common, rare = each.where(F.col("m") > least).drop("m"), each.where(F.col("m") <= least).drop("m")
    found = freq.join(F.broadcast(common), "w", "left")
    return found.where("v is not null").unionByName(found.where("v is null").drop("v").join(rare, "w").select("w", *[c for c in freq.columns if c != "w"], "v"))


def concave_sample(freq: DataFrame, k: int, salt: str = "s", scheme: str = "ppswor") -> DataFrame:
    rows = concave_probabilities(freq)
    return strict(bottom_k(seeded(rows, F.col("v"), salt, scheme), k), k, scheme)


def cap_grid(freq: DataFrame, base: float = 4.0) -> list[float]:
    """1, base, base^2, ... up to the first that no frequency exceeds."""
    top = freq.agg(F.max("w")).first()[0]
    grid = [1.0]
    while top is not None and grid[-1] < top:
        grid.append(grid[-1] * base)
    return grid


def multi_cap_sample(freq: DataFrame, k: int, caps: Sequence[float] | None = None, salt: str = "s", scheme: str = "ppswor") -> DataFrame:
    """Union of coordinated samples, one for each cap: (key, w, p_incl) with the largest of the samples' chances.

    A mergeable stand-in for ``concave_sample``: the caps are a geometric grid over the range
    of frequencies, so the scheme asks for no rank. A key is in the union if it is in any sample, and as all
    samples share its draw, its chance is the largest one.
    """
    grid = F.explode(F.array(*[F.lit(float(t)) for t in caps or cap_grid(freq)]))
    rows = freq.select("key", "w", grid.alias("t")).withColumn("weight", F.least("w", "t"))
    rows = rows.withColumn("h", draw(F.col("key"), salt, scheme)).withColumn("seed", F.col("h") / F.col("weight"))
    window = W.partitionBy("t").orderBy("seed", "key")
    kept = rows.withColumn("_at", F.row_number().over(window)).where(F.col("_at") <= k)
    tau = thresholds(kept.select("t", "key", "seed"), k, ["t"])
    union = kept.where((F.col("_at") < k) | (F.col("_at") == k)).select("key", "w", "h").distinct()
    each = union.crossJoin(F.broadcast(tau)).withColumn("weight", F.least("w", "t"))
    each = each.withColumn("seed", F.col("h") / F.col("weight"))
    limit = threshold_of(F.col("seed"), F.col("k_th"), F.col("k_before"), k)
    each = each.withColumn("p", inclusion(scheme, F.col("weight"), limit)).withColumn("inside", limit.isNull() | (F.col("seed") < limit))
    return each.groupBy("key", "w").agg(F.max("p").alias("p_incl"), F.max("inside").alias("inside")).where("inside").drop("inside")
