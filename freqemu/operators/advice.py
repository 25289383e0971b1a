"""Sampling by advice: a per-key prediction steers the sample, two other parts insure it.

A sketch has three parts: the k_h keys of largest advice, surely included; k_p keys by
seeds h / f(advice); k_u keys by seeds h. Frequencies of stored keys are exact. The draw
h is a hash of the key, so the parts share it and a stored key is stored once.

Ties of advice are broken by h, then by key, so that the sketch depends on neither order
nor partitioning of the elements. Keys with f(advice) = 0 never compete by advice. A part
of size 0 or 1 never includes; a part with fewer keys than its size includes all of them.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..functions.frequency import FrequencyFunction
from ..functions.seeds import draw


def attach(freq: DataFrame, advice: DataFrame) -> DataFrame:
    """``freq`` with advice; keys without a prediction have 0."""
    return freq.join(advice.select("key", F.col("advice").cast("double").alias("advice")), "key", "left").withColumn("advice", F.coalesce("advice", F.lit(0.0)))


def seeded(rows: DataFrame, f: FrequencyFunction, scheme: str = "ppswor", salt: str | Column = "s") -> DataFrame:
    """(key, w, advice, h, fa, r): r is null where f(advice) is 0."""
    out = rows.withColumn("h", draw(F.col("key"), salt, scheme))
    out = out.withColumn("fa", F.when(F.col("advice") > 0, f("advice")).otherwise(0.0))
    return out.withColumn("r", F.when(F.col("fa") > 0, F.col("h") / F.col("fa")))


def cut_sketch(rows: DataFrame, kh: int, kp: int, ku: int) -> DataFrame:
    """The sketch of seeded rows (one for each key): ``rows`` with in_top, in_advice, in_uniform.

    Every part is found by a limit, in which each task keeps as many rows as the part and
    k_h more: the top keys are taken out of the others' candidates afterwards.
    """
    order = [F.col("advice").desc(), F.col("h"), F.col("key")]
    false = F.lit(False)
    tagged = [
        rows.orderBy(*order).limit(kh).withColumns({"a": F.lit(1), "b": F.lit(0), "c": F.lit(0)}),
        rows.where("r is not null").orderBy("r", "key").limit(kp + kh if kp else 0).withColumns({"a": F.lit(0), "b": F.lit(1), "c": F.lit(0)}),
        rows.orderBy("h", "key").limit(ku + kh if ku else 0).withColumns({"a": F.lit(0), "b": F.lit(0), "c": F.lit(1)}),
    ]
    found = reduce(DataFrame.unionByName, tagged)
    one = found.groupBy("key").agg(*[F.first(c).alias(c) for c in rows.columns if c != "key"], F.max("a").alias("a"), F.max("b").alias("b"), F.max("c").alias("c"))
    # at most 3 k_h + k_p + k_u rows from here on
    by_r = F.row_number().over(W.partitionBy(((F.col("a") == 0) & (F.col("b") == 1)).alias("x")).orderBy("r", "key"))
    by_h = F.row_number().over(W.partitionBy(((F.col("a") == 0) & (F.col("c") == 1)).alias("x")).orderBy("h", "key"))
    marked = one.withColumn("in_top", F.col("a") == 1)
    marked = marked.withColumn("in_advice", F.when((F.col("a") == 0) & (F.col("b") == 1), by_r <= kp).otherwise(false))
    marked = marked.withColumn("in_uniform", F.when((F.col("a") == 0) & (F.col("c") == 1), by_h <= ku).otherwise(false))
    return marked.where("in_top or in_advice or in_uniform").drop("a", "b", "c")


def advice_sketch(elements: DataFrame, advice: DataFrame, f: FrequencyFunction, kh: int, kp: int, ku: int, scheme: str = "ppswor", salt: str = "s") -> DataFrame:
    from .exact import frequencies

    return cut_sketch(seeded(attach(frequencies(elements), advice), f, scheme, salt), kh, kp, ku)


def merge_advice(sketches: Sequence[DataFrame], kh: int, kp: int, ku: int) -> DataFrame:
    """The sketch of the union of the parts behind ``sketches``, equal to one over all elements.

    A key of the union's sketch is in the sketch of every part that holds it, with all its
    weight there: it beats fewer rivals in a part than in the union, and a part's top keys
    include all of the union's top keys that it holds.
    """
    rows = reduce(DataFrame.unionByName, [s.select("key", "w", "advice", "h", "fa", "r") for s in sketches])
    return cut_sketch(rows.groupBy("key").agg(F.sum("w").alias("w"), *[F.first(c).alias(c) for c in ("advice", "h", "fa", "r")]), kh, kp, ku)


def order_statistics(rows: DataFrame, kp: int, ku: int, by: Sequence[str] = ()) -> DataFrame:
    """The (k-1)-th and k-th smallest r and h over ``rows`` (none of them in the top part): p1, p2, u1, u2, null if missing."""
    order_r, order_h = W.partitionBy(*by).orderBy("r", "key"), W.partitionBy(*by).orderBy("h", "key")
    at_r = rows.where("r is not null").select(*by, "key", "r").withColumn("i", F.row_number().over(order_r)).where(F.col("i") <= max(kp, 1))
    at_h = rows.select(*by, "key", "h").withColumn("i", F.row_number().over(order_h)).where(F.col("i") <= max(ku, 1))
    pick = lambda c, i: F.min(F.when(F.col("i") == i, F.col(c)))
    a = at_r.groupBy(*by).agg(pick("r", kp - 1).alias("p1"), pick("r", kp).alias("p2"))
    b = at_h.groupBy(*by).agg(pick("h", ku - 1).alias("u1"), pick("h", ku).alias("u2"))
    return b.join(a, list(by), "left") if by else b.crossJoin(a)


def with_thresholds(rows: DataFrame, kp: int, ku: int) -> DataFrame:
    """Adds tau_p and tau_u (null: infinite) and p_incl from p1, p2, u1, u2; ``rows`` are not in the top part."""

    def loo(x, first, second, k):
        if k <= 1:
            return F.lit(0.0)
        return F.when(F.col(x).isNotNull() & (F.col(first).isNull() | (F.col(x) <= F.col(first))), F.col(second)).otherwise(F.col(first))

    out = rows.withColumn("tau_p", loo("r", "p1", "p2", kp)).withColumn("tau_u", loo("h", "u1", "u2", ku))
    reach = F.when(F.col("fa") <= 0, 0.0).when(F.col("tau_p").isNull(), F.lit(None).cast("double")).otherwise(F.col("fa") * F.col("tau_p"))
    out = out.withColumn("_a", reach).withColumn("limit", F.when(F.col("_a").isNull() | F.col("tau_u").isNull(), F.lit(None).cast("double")).otherwise(F.greatest("_a", "tau_u")))
    return out.drop("_a")


def chance(limit: Column, scheme: str) -> Column:
    return F.when(limit.isNull(), F.lit(1.0)).otherwise(-F.expm1(-limit) if scheme == "ppswor" else F.least(F.lit(1.0), limit))


def advice_estimate(sketch: DataFrame, f: FrequencyFunction, kp: int, ku: int, scheme: str = "ppswor") -> DataFrame:
    """(key, w, in_top, limit, p_incl, f_hat) of the strictly included keys; any f is estimated without bias."""
    top = sketch.where("in_top").select("key", "w", "in_top", F.lit(None).cast("double").alias("limit"), F.lit(1.0).alias("p_incl"), f("w").alias("f_hat"))
    rest = sketch.where("not in_top").select("key", "w", "h", "fa", "r", "in_top")
    rest = with_thresholds(rest.crossJoin(F.broadcast(order_statistics(rest, kp, ku))), kp, ku)
    by_h = F.lit(ku > 1) & (F.col("tau_u").isNull() | (F.col("h") < F.col("tau_u")))
    by_r = F.lit(kp > 1) & F.col("r").isNotNull() & (F.col("tau_p").isNull() | (F.col("r") < F.col("tau_p")))
    p = chance(F.col("limit"), scheme)
    return top.unionByName(rest.where(by_h | by_r).select("key", "w", "in_top", "limit", p.alias("p_incl"), (f("w") / p).alias("f_hat")))


def size_for(k: int, cp: float, cu: float, h: int = 0) -> tuple[int, int, int]:
    """Sizes (k_h, k_p, k_u) that keep the variance of an ideal sample of k keys."""
    up = lambda x: -int(-x // 1)
    return h, (up(k * cp) + 2 if cp > 0 else 0), (up(k * cu) + 2 if cu > 0 else 0)


def advice_quality(rows: DataFrame, f: FrequencyFunction, h: int, cu: float) -> DataFrame:
    """(cp): the least c_p for which every key outside the h largest advices keeps its share
    within max(c_p * advice share, c_u / n); infinite if a key without advice violates the second."""
    v = rows.select("key", f("w").alias("fw"), F.when(F.col("advice") > 0, f("advice")).otherwise(0.0).alias("fa"), "advice")
    sums = v.agg(F.sum("fw").alias("sw"), F.sum("fa").alias("sa"), F.count("*").alias("n"))
    if h:
        bar = v.orderBy(F.col("advice").desc(), "key").limit(h).agg(F.min("advice").alias("bar"))
        v = v.crossJoin(F.broadcast(bar)).where("advice < bar")
    v = v.crossJoin(F.broadcast(sums)).where(F.col("fw") / F.col("sw") > cu / F.col("n"))
    need = F.when(F.col("fa") > 0, (F.col("fw") / F.col("sw")) / (F.col("fa") / F.col("sa"))).otherwise(float("inf"))
    return v.agg(F.coalesce(F.max(need), F.lit(0.0)).alias("cp"))


def advice_ratio(rows: DataFrame, f: FrequencyFunction) -> DataFrame:
    """(low, high, cp): the range of f(advice) / f(w); scaled to a least of 1, advice is good to within cp = high / low."""
    ratio = F.when(F.col("advice") > 0, f("advice")).otherwise(0.0) / f("w")
    return rows.agg(F.min(ratio).alias("low"), F.max(ratio).alias("high")).withColumn("cp", F.when(F.col("low") > 0, F.col("high") / F.col("low")))


def advice_variance_bound(rows: DataFrame, f: FrequencyFunction, kp: int, ku: int) -> DataFrame:
    """(key, by_advice, by_uniform, bound): each part's variance bound for a key; the sketch has the smaller."""
    v = rows.select("key", f("w").alias("fw"), F.when(F.col("advice") > 0, f("advice")).otherwise(0.0).alias("fa"))
    sums = v.agg(F.sum("fa").alias("sa"), F.count("*").alias("n"))
    v = v.crossJoin(F.broadcast(sums))
    a = F.when(F.col("fa") > 0, F.col("fw") ** 2 * F.col("sa") / F.col("fa") / (kp - 2)) if kp > 2 else F.lit(None).cast("double")
    u = F.col("fw") ** 2 * F.col("n") / (ku - 2) if ku > 2 else F.lit(None).cast("double")
    return v.select("key", a.alias("by_advice"), u.alias("by_uniform")).withColumn("bound", F.least("by_advice", "by_uniform"))
