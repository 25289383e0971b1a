"""Sources of advice: past frequencies, a learned model, noise for ablations, a heavy-hitter oracle."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..functions.frequency import power
from ..functions.seeds import unit_seed
from .exact import frequencies


def past_frequency(elements: DataFrame, period: Column | None = None) -> DataFrame:
    """(key, advice): exact frequencies over an earlier period."""
    rows = elements if period is None else elements.where(period)
    return frequencies(rows).withColumnRenamed("w", "advice")


def noisy_advice(freq: DataFrame, spread: float, salt: str = "noise") -> DataFrame:
    """(key, advice) = w times 2 to a power in [-spread, spread], drawn by a hash of the key; 0 is exact advice."""
    factor = F.pow(F.lit(2.0), F.lit(float(spread)) * (2 * unit_seed(F.col("key"), salt) - 1))
    return freq.select("key", (F.col("w") * factor).alias("advice"))


def null_advice(freq: DataFrame) -> DataFrame:
    return freq.select("key", F.lit(0.0).alias("advice"))


def heavy_hitter_advice(past: DataFrame, q: float, phi: float, high: float = 1e6) -> DataFrame:
    """(key, advice): ``high`` for the past's heavy hitters, 0 for others."""
    total = past.agg(F.sum(power(F.col("w"), q)).alias("_all"))
    rows = past.crossJoin(F.broadcast(total))
    return rows.select("key", F.when(power(F.col("w"), q) >= phi * F.col("_all"), high).otherwise(0.0).alias("advice"))


FEATURES = ("f_length", "f_seen", "f_past", "f_digits", "f_vowels")


def key_features(freq: DataFrame, past: DataFrame) -> DataFrame:
    """``freq`` with features of the key and of its earlier frequency."""
    seen = past.select("key", F.col("w").alias("_past"))
    rows = freq.join(seen, "key", "left")
    return rows.withColumns({
        "f_length": F.length("key").cast("double"),
        "f_seen": F.col("_past").isNotNull().cast("double"),
        "f_past": F.log1p(F.coalesce("_past", F.lit(0.0))),
        "f_digits": F.length(F.regexp_replace("key", "[^0-9]", "")).cast("double"),
        "f_vowels": F.length(F.regexp_replace("key", "[^aeiou]", "")).cast("double"),
    }).drop("_past")


def learned_advice(train: DataFrame, earlier: DataFrame, target: DataFrame, past: DataFrame, rounds: int = 20) -> DataFrame:
    """(key, advice) for the keys of ``target``: a regression of log(1 + w) on key features.

    Trained on ``train`` (key, w) with ``earlier`` as its past, applied to ``target`` with
    ``past``. A key has one prediction, never below 0.
    """
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import GBTRegressor

    gather = VectorAssembler(inputCols=list(FEATURES), outputCol="x")
    rows = gather.transform(key_features(train, earlier).withColumn("y", F.log1p("w")))
    model = GBTRegressor(featuresCol="x", labelCol="y", maxIter=rounds, maxDepth=4, seed=7).fit(rows.select("x", "y"))
    out = model.transform(gather.transform(key_features(target, past)))
    return out.select("key", F.greatest(F.lit(0.0), F.expm1("prediction")).alias("advice"))
