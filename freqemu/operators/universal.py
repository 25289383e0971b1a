"""Universal samples: schemes that serve every monotone function at once.

A scheme's universal emulation overhead is its overhead for the worst monotone function;
the worst functions are the thresholds [frequency >= w_i].
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from .bottomk import bottom_k, strict
from ..functions.seeds import draw
from .exact import global_rank, ranked
from .overhead import Scheme, weighted


def harmonic(n: Column) -> Column:
    """H_n: summed up to 10,000, then by its expansion (good to 1e-16 there)."""
    n = n.cast("double")
    small = F.aggregate(F.sequence(F.lit(1), F.least(n, F.lit(10_000.0)).cast("int")), F.lit(0.0), lambda a, i: a + F.lit(1.0) / i)
    large = F.log(n) + F.lit(0.5772156649015329) + 1 / (2 * n) - 1 / (12 * n * n)
    return F.when(n <= 10_000, small).otherwise(large)


def ranked_chances(hist: DataFrame, scheme: Scheme) -> DataFrame:
    """(w, m, first_rank, last_rank, prefix, tail, q)."""
    rows = ranked(hist)
    v = weighted(hist, scheme).select(F.col("w").alias("_w"), "v")
    rows = rows.join(v, F.col("w") == F.col("_w")).drop("_w")
    total = rows.agg(F.sum(F.col("m") * F.col("v")).alias("_all"))
    return rows.crossJoin(F.broadcast(total)).withColumn("q", F.col("v") / F.col("_all")).drop("_all", "v")


def universal_emulation(hist: DataFrame, scheme: Scheme, ties: str = "rank") -> DataFrame:
    """Largest 1 / (i q_i). ties='exact' takes for i the number of keys at least as frequent."""
    i = F.col("first_rank" if ties == "rank" else "last_rank")
    return ranked_chances(hist, scheme).agg(F.max(1 / (i * F.col("q"))).alias("universal"))


def universal_estimation(hist: DataFrame, scheme: Scheme, ties: str = "rank") -> DataFrame:
    """Largest mean over the first i keys of 1 / (i q_j).

    In a block of equal frequencies the value is (A + t c) / (B + t)^2 after t of its keys;
    it is largest at an end or beside its stationary point B - 2 A / c.
    """
    rows = ranked_chances(hist, scheme)
    before = W.orderBy(F.col("w").desc()).rowsBetween(W.unboundedPreceding, -1)
    rows = rows.withColumn("c", 1 / F.col("q")).withColumn("A", F.coalesce(F.sum(F.col("m") / F.col("q")).over(before), F.lit(0.0)))
    base = F.col("first_rank") - 1
    m = F.col("m").cast("double")
    at = lambda t: (F.col("A") + t * F.col("c")) / F.pow(base + t, F.lit(2.0))
    if ties == "exact":
        return rows.agg(F.max(at(m)).alias("estimation"))
    still = base - 2 * F.col("A") / F.col("c")
    inside = lambda t: F.greatest(F.lit(1.0), F.least(m, t.cast("double")))
    return rows.agg(F.max(F.greatest(at(F.lit(1.0)), at(m), at(inside(F.floor(still))), at(inside(F.ceil(still))))).alias("estimation"))


def universal_bruteforce(hist: DataFrame, scheme: Scheme) -> DataFrame:
    """The definition, over all thresholds at frequencies that occur: quadratic in their number."""
    rows = ranked_chances(hist, scheme).select("w", "m", "q")
    t, r = rows.select(F.col("w").alias("t")), rows
    counts = t.join(r, F.col("w") >= F.col("t")).groupBy("t").agg(F.sum("m").alias("n"), F.max(1 / F.col("q")).alias("worst"))
    return counts.agg(F.max(F.col("worst") / F.col("n")).alias("universal"))


def universal_probabilities(freq: DataFrame) -> DataFrame:
    """(key, w, rank, p) of the ideal universal sample, p = 1 / (rank H_n)."""
    rows = global_rank(freq)
    h_n = rows.agg(harmonic(F.count("*")).alias("_h"))
    return rows.crossJoin(F.broadcast(h_n)).select("key", "w", "rank", (1 / (F.col("rank") * F.col("_h"))).alias("p"))


def universal_sample(freq: DataFrame, k: int, salt: str = "s", scheme: str = "ppswor") -> DataFrame:
    """A sample by weight 1 / rank: serves every monotone function with overhead H_n."""
    rows = universal_probabilities(freq).withColumn("h", draw(F.col("key"), salt, scheme)).withColumn("weight", 1 / F.col("rank"))
    return strict(bottom_k(rows.withColumn("seed", F.col("h") / F.col("weight")), k), k, scheme)


def tail_condition(hist: DataFrame) -> DataFrame:
    """c: the least of i w_i over the sum of all rarer frequencies, i < n. The first key of equals attains it."""
    rest = F.col("tail") + (F.col("m") - 1) * F.col("w")
    return ranked(hist).where(rest > 0).agg(F.min(F.col("first_rank") * F.col("w") / rest).alias("c"))


def concave_universal_bound(hist: DataFrame) -> DataFrame:
    """(norm, c, bound): the concave sample's universal overhead is at most norm (1 + 1/c)."""
    norm = weighted(hist, "concave").agg(F.sum(F.col("m") * F.col("v")).alias("norm"))
    return norm.crossJoin(tail_condition(hist)).select("norm", "c", (F.col("norm") * (1 + 1 / F.col("c"))).alias("bound"))


def zipf_range_universal(overhead: float, n: int, p1: float, p2: float) -> tuple[float, float, float]:
    """(alpha_low, alpha_high, bound): a sample that serves all moments from p1 to p2 with
    ``overhead`` is universal on Zipf vectors of exponents 1/p2 to 1/p1."""
    h_n = sum(1.0 / i for i in range(1, n + 1)) if n <= 10_000 else __import__("math").log(n) + 0.5772156649015329 + 1 / (2 * n)
    return 1 / p2, 1 / p1, overhead * h_n
