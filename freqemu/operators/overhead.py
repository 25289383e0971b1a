"""Overheads: how many times more keys one sampling scheme needs to stand in for another.

Inputs are histograms (w, m). A scheme gives every frequency a weight v; its single-draw
chance is q = v / sum(m v). For a target function the ideal chance is p = f / sum(m f).
Moments are computed on w / w_1, so that high powers neither overflow nor lose the top.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, functions as F

from ..functions.frequency import FrequencyFunction, power
from ..functions.seeds import wr_inclusion
from .exact import ranked

Scheme = FrequencyFunction | float | str


def scaled(hist: DataFrame) -> DataFrame:
    """``hist`` with u = w / w_1."""
    top = hist.agg(F.max("w").alias("_top"))
    return hist.crossJoin(F.broadcast(top)).withColumn("u", F.col("w") / F.col("_top")).drop("_top")


def concave_weights(hist: DataFrame) -> DataFrame:
    """v = w over the sum of all frequencies cut off at w: serves every concave sublinear function."""
    return ranked(hist).withColumn("v", F.col("w") / (F.col("last_rank") * F.col("w") + F.col("tail")))


def weighted(hist: DataFrame, scheme: Scheme) -> DataFrame:
    """``hist`` with u and v. A scheme is an exponent, a function, 'concave' or 'uniform'."""
    if scheme == "concave":
        return scaled(concave_weights(hist))
    rows = scaled(hist)
    if scheme == "uniform":
        return rows.withColumn("v", F.lit(1.0))
    if isinstance(scheme, FrequencyFunction):
        return rows.withColumn("v", scheme("w") if scheme.exponent is None else power(F.col("u"), scheme.exponent))
    return rows.withColumn("v", power(F.col("u"), float(scheme)))


def value_of(f: FrequencyFunction) -> Column:
    return f("w") if f.exponent is None else power(F.col("u"), f.exponent)


def chances(hist: DataFrame, functions: Sequence[FrequencyFunction], scheme: Scheme) -> DataFrame:
    """(w, m, u, q, p0, p1, ...): the scheme's chance and each function's ideal chance for one key."""
    rows = weighted(hist, scheme)
    for i, f in enumerate(functions):
        rows = rows.withColumn(f"f{i}", value_of(f))
    sums = [F.sum(F.col("m") * F.col("v")).alias("_v")] + [F.sum(F.col("m") * F.col(f"f{i}")).alias(f"_f{i}") for i in range(len(functions))]
    rows = rows.crossJoin(F.broadcast(rows.agg(*sums)))
    keep = [c for c in rows.columns if c in ("first_rank", "last_rank", "tail")]
    return rows.select("w", "m", "u", *keep, (F.col("v") / F.col("_v")).alias("q"), *[(F.col(f"f{i}") / F.col(f"_f{i}")).alias(f"p{i}") for i in range(len(functions))])


def overheads(hist: DataFrame, functions: Sequence[FrequencyFunction], scheme: Scheme) -> DataFrame:
    """(f, emulation, estimation): the largest p/q, and the mean of p/q under p."""
    rows = chances(hist, functions, scheme)
    aggs = []
    for i in range(len(functions)):
        ratio = F.when(F.col(f"p{i}") > 0, F.col(f"p{i}") / F.col("q")).otherwise(0.0)
        aggs += [F.max(ratio).alias(f"emu{i}"), F.sum(F.col("m") * F.col(f"p{i}") * ratio).alias(f"est{i}")]
    pairs = F.array(*[F.struct(F.lit(f.name).alias("f"), F.col(f"emu{i}").alias("emulation"), F.col(f"est{i}").alias("estimation")) for i, f in enumerate(functions)])
    return rows.agg(*aggs).select(F.inline(pairs))


def all_overheads(hist: DataFrame, powers: Sequence[float], schemes: Sequence[float | str] = (1.0, 2.0, "concave")) -> DataFrame:
    """One row of every scheme's overheads, from one ranking of the histogram and two aggregations.

    For scheme s (l1, l2, concave): s_p and s_p_est for each power p, the universal overhead
    s_universal, s_exact with ties counted whole, and s_norm; beside them n and c, the least
    of i w_i over the sum of rarer frequencies.
    """
    name = lambda q: q if isinstance(q, str) else f"l{q:g}"
    m, u = F.col("m"), F.col("u")
    weight = {name(q): F.col("w") / (F.col("last_rank") * F.col("w") + F.col("tail")) if q == "concave" else power(u, float(q)) for q in schemes}
    rows = scaled(ranked(hist)).select("*", *[v.alias(f"v_{k}") for k, v in weight.items()], *[power(u, p).alias(f"f_{p}") for p in powers])
    sums = rows.agg(F.sum("m").alias("n"), *[F.sum(m * F.col(f"v_{k}")).alias(f"V_{k}") for k in weight], *[F.sum(m * F.col(f"f_{p}")).alias(f"F_{p}") for p in powers])
    sums = sums.select("n", *[F.col(f"V_{k}").alias(f"{k}_norm") for k in weight], *[F.col(f"F_{p}").alias(f"total_{p}") for p in powers])
    rest = F.col("tail") + (m - 1) * F.col("w")
    out = [F.max("n").alias("n"), F.min(F.when(rest > 0, F.col("first_rank") * F.col("w") / rest)).alias("c")]
    for k in weight:
        q = F.col(f"v_{k}") / F.col(f"{k}_norm")
        out += [F.max(1 / (F.col("first_rank") * q)).alias(f"{k}_universal"), F.max(1 / (F.col("last_rank") * q)).alias(f"{k}_exact"), F.max(f"{k}_norm").alias(f"{k}_norm")]
        for p in powers:
            share = F.col(f"f_{p}") / F.col(f"total_{p}")
            ratio = F.when(share > 0, share / q).otherwise(0.0)
            out += [F.max(ratio).alias(f"{k}_{p}"), F.sum(m * share * ratio).alias(f"{k}_{p}_est")]
    return rows.crossJoin(F.broadcast(sums)).agg(*out)


def family_overhead(hist: DataFrame, functions: Sequence[FrequencyFunction], scheme: Scheme) -> DataFrame:
    """The worst emulation overhead over ``functions``: also that of their non-negative combinations."""
    return overheads(hist, functions, scheme).agg(F.max("emulation").alias("emulation"))


def chain(hist: DataFrame, target: FrequencyFunction, middle: Scheme, actual: Scheme) -> DataFrame:
    """(direct, first, second): overhead of ``actual`` for the target never exceeds first * second."""
    a = chances(hist, [target], middle).select("w", "m", F.col("q").alias("mid"), "p0")
    b = chances(hist, [], actual).select("w", "q")
    rows = a.join(b, "w")
    return rows.agg(F.max(F.col("p0") / F.col("q")).alias("direct"), F.max(F.col("p0") / F.col("mid")).alias("first"), F.max(F.col("mid") / F.col("q")).alias("second"))


def lp_by_lq(hist: DataFrame, pairs: Sequence[tuple[float, float]]) -> DataFrame:
    """(p, q, overhead, bound) of l_p targets under l_q samples, in closed form.

    For p >= q the largest ratio is at the most frequent key, else at the rarest; bound is
    the sum of (w/w_1)^q, which does not depend on p and holds only for p >= q.
    """
    ends = hist.agg(F.max("w").alias("_hi"), F.min("w").alias("_lo"))
    rows = hist.crossJoin(F.broadcast(ends))
    aggs = []
    for i, (p, q) in enumerate(pairs):
        base = F.col("w") / F.col("_hi" if p >= q else "_lo")
        aggs += [F.sum(F.col("m") * power(base, q)).alias(f"q{i}"), F.sum(F.col("m") * power(base, p)).alias(f"p{i}")]
    out = F.array(*[
        F.struct(F.lit(float(p)).alias("p"), F.lit(float(q)).alias("q"), (F.col(f"q{i}") / F.col(f"p{i}")).alias("overhead"),
                 (F.col(f"q{i}") if p >= q else F.lit(None).cast("double")).alias("bound"))
        for i, (p, q) in enumerate(pairs)
    ])
    return rows.agg(*aggs).select(F.inline(out))


def worst_case_bound(n: Column, p: float) -> Column:
    """Of l_2 samples for l_p, whatever the frequencies: an upper bound, p >= 2."""
    return F.pow(n.cast("double"), F.lit(1.0 - 2.0 / p))


def near_uniform_bound(hist: DataFrame, p: float) -> DataFrame:
    """(w_1 / w_n)^p: of l_0 and l_1 samples for l_p with p >= 1."""
    return hist.agg(F.pow(F.max("w") / F.min("w"), F.lit(float(p))).alias("bound"))


def benchmark_key_variance(hist: DataFrame, f: FrequencyFunction, k: int) -> DataFrame:
    """(w, m, variance): the bound f(w) * ||f|| / k on each key's variance under ideal sampling."""
    rows = hist.withColumn("f", f("w"))
    total = rows.agg(F.sum(F.col("m") * F.col("f")).alias("_all"))
    return rows.crossJoin(F.broadcast(total)).select("w", "m", (F.col("f") * F.col("_all") / k).alias("variance"))


def benchmark_domain_variance(freq: DataFrame, f: FrequencyFunction, domain: Column, k: int) -> DataFrame:
    return freq.agg((F.sum(F.when(domain, f("w")).otherwise(0.0)) * F.sum(f("w")) / k).alias("variance"))


def emulated_domain_variance(freq: DataFrame, f: FrequencyFunction, scheme: FrequencyFunction, domain: Column, k: int) -> DataFrame:
    """The same under another scheme: times the largest p/q inside the domain."""
    rows = freq.withColumn("f", f("w")).withColumn("v", scheme("w")).withColumn("inside", domain)
    sums = rows.agg(F.sum("f").alias("_f"), F.sum("v").alias("_v"))
    ratio = (F.col("f") / F.col("_f")) / (F.col("v") / F.col("_v"))
    rows = rows.crossJoin(F.broadcast(sums)).where("inside")
    return rows.agg((F.max(ratio) * F.sum("f") * F.max("_f") / k).alias("variance"), F.max(ratio).alias("overhead"))


def benchmark_nrmse(k: float) -> float:
    return k**-0.5


def size_for_nrmse(epsilon: float) -> int:
    return -int(-(epsilon**-2) // 1)


def effective_k(scheme: str, k: int, stores_threshold: bool = True) -> int:
    """Denominator of the variance bound: k draws with replacement; of a bottom-k sketch the
    stored threshold is not a sample, and leave-one-out costs one more."""
    if scheme == "wr":
        return k
    return k - 2 if stores_threshold else k - 1


def wr_key_variance(hist: DataFrame, f: FrequencyFunction, scheme: Scheme, k: int) -> DataFrame:
    """(w, m, p_incl, variance, bound): exact f^2 (1/p - 1), and its bound f^2 / (k q)."""
    rows = chances(hist, [], scheme).withColumn("p_incl", wr_inclusion(F.col("q"), k)).withColumn("f", f("w"))
    return rows.select("w", "m", "p_incl", (F.col("f") ** 2 * (1 / F.col("p_incl") - 1)).alias("variance"), (F.col("f") ** 2 / (k * F.col("q"))).alias("bound"))
