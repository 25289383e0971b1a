"""Heavy hitters, Zipf fits and the combinations of data, functions and overhead that they support."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..functions.frequency import FrequencyFunction, power
from .exact import global_rank, ranked
from .overhead import Scheme, family_overhead, lp_by_lq, scaled


def heavy_hitters(freq: DataFrame, q: float, phi: float, definition: str = "power") -> DataFrame:
    """(key, w, share): keys with w^q >= phi ||w||_q^q, or, by 'norm', w >= phi ||w||_q. At most 1/phi (1/phi^q) rows."""
    total = freq.agg(F.sum(power(F.col("w"), q)).alias("_all"))
    rows = freq.crossJoin(F.broadcast(total)).withColumn("share", power(F.col("w"), q) / F.col("_all"))
    return rows.where(F.col("share") >= (phi if definition == "power" else phi**q)).select("key", "w", "share")


def dataset_profile(hist: DataFrame) -> DataFrame:
    """(n, ln_n, l1_first, l1_second, l2_first, l2_second, alpha): one row."""
    two = hist.orderBy(F.col("w").desc()).limit(2)
    pair = two.agg(F.max("w").alias("a"), F.min("w").alias("b"), F.max_by("m", "w").alias("ma"))
    second = F.when(F.col("ma") > 1, F.col("a")).otherwise(F.col("b"))
    sums = hist.agg(F.sum("m").alias("n"), F.sum(F.col("m") * F.col("w")).alias("s1"), F.sum(F.col("m") * F.col("w") * F.col("w")).alias("s2"))
    out = sums.crossJoin(pair).crossJoin(fit_zipf(hist))
    return out.select(
        F.col("n").cast("bigint").alias("n"), F.log(F.col("n").cast("double")).alias("ln_n"),
        (F.col("a") / F.col("s1")).alias("l1_first"), (second / F.col("s1")).alias("l1_second"),
        (F.col("a") * F.col("a") / F.col("s2")).alias("l2_first"), (second * second / F.col("s2")).alias("l2_second"), "alpha",
    )


def _log_sums(first: Column, last: Column) -> tuple[Column, Column]:
    """Sums of ln r and (ln r)^2 over the ranks of a block: term by term up to 2,000 of them, by Euler-Maclaurin beyond."""
    few = (last - first) < 2000
    seq = F.sequence(first, F.when(few, last).otherwise(first))
    s1 = F.aggregate(seq, F.lit(0.0), lambda a, r: a + F.log(r.cast("double")))
    s2 = F.aggregate(seq, F.lit(0.0), lambda a, r: a + F.log(r.cast("double")) * F.log(r.cast("double")))
    a, b = first.cast("double"), last.cast("double")
    la, lb = F.log(a), F.log(b)
    e1 = (b * lb - b) - (a * la - a) + (la + lb) / 2 + (1 / b - 1 / a) / 12
    e2 = (b * lb * lb - 2 * b * lb + 2 * b) - (a * la * la - 2 * a * la + 2 * a) + (la * la + lb * lb) / 2 + (2 * lb / b - 2 * la / a) / 12
    return F.when(few, s1).otherwise(e1), F.when(few, s2).otherwise(e2)


def fit_zipf(hist: DataFrame, top: int | None = None) -> DataFrame:
    """alpha: minus the least-squares slope of ln w on ln rank over all (or the first ``top``) ranks.

    Blocks of equal frequencies enter through their sums of ln rank, so no key is ranked.
    """
    rows = ranked(hist)
    last = F.col("last_rank") if top is None else F.least(F.col("last_rank"), F.lit(top))
    rows = rows.where(F.col("first_rank") <= (F.lit(top) if top else F.col("first_rank"))).withColumn("_last", last.cast("bigint"))
    s1, s2 = _log_sums(F.col("first_rank").cast("bigint"), F.col("_last"))
    rows = rows.select((F.col("_last") - F.col("first_rank") + 1).cast("double").alias("c"), F.log("w").alias("y"), s1.alias("x1"), s2.alias("x2"))
    t = rows.agg(F.sum("c").alias("c"), F.sum("x1").alias("x"), F.sum("x2").alias("xx"), F.sum(F.col("c") * F.col("y")).alias("y"), F.sum(F.col("x1") * F.col("y")).alias("xy"))
    slope = (F.col("c") * F.col("xy") - F.col("x") * F.col("y")) / (F.col("c") * F.col("xx") - F.col("x") * F.col("x"))
    return t.select(F.when(F.col("c") * F.col("xx") - F.col("x") * F.col("x") > 1e-9, -slope).otherwise(0.0).alias("alpha"))


def zipf_frequencies(spark: SparkSession, n: int, alpha: float, w1: float = 1.0, partitions: int | None = None) -> DataFrame:
    """(key, w) with w_i = w_1 / i^alpha."""
    rows = spark.range(1, n + 1, 1, partitions) if partitions else spark.range(1, n + 1)
    return rows.select(F.col("id").cast("string").alias("key"), (F.lit(float(w1)) * F.pow(F.col("id").cast("double"), F.lit(-float(alpha)))).alias("w"))


def zipf_like(freq: DataFrame, alpha: float, w1: float | None = None) -> DataFrame:
    """(key, w): the keys of ``freq`` with Zipf frequencies by their ranks, the first with ``w1`` or its own."""
    ranks = freq if "rank" in freq.columns else global_rank(freq)
    top = freq.agg((F.max("w") if w1 is None else F.lit(float(w1))).alias("_top"))
    return ranks.crossJoin(F.broadcast(top)).select("key", (F.col("_top") * F.pow(F.col("rank").cast("double"), F.lit(-float(alpha)))).alias("w"))


def subzipf_c(hist: DataFrame, alpha: float) -> DataFrame:
    """c: the least with w_i <= c w_1 / i^alpha for all i; reached at the last key of equals."""
    rows = scaled(ranked(hist))
    return rows.agg(F.max(F.col("u") * F.pow(F.col("last_rank").cast("double"), F.lit(float(alpha)))).alias("c"))


def generalized_harmonic(n: int, s: float) -> float:
    """Sum of i^-s for i up to n: term by term up to 100,000, by Euler-Maclaurin beyond."""
    m = min(n, 100_000)
    total = math.fsum(i**-s for i in range(1, m + 1))
    if n == m:
        return total
    whole = math.log(n / m) if s == 1 else (n ** (1 - s) - m ** (1 - s)) / (1 - s)
    return total + whole + (n**-s - m**-s) / 2


def harmonic_terms(freq: DataFrame, exponents: Sequence[float]) -> DataFrame:
    """(s, value): the same sums over the ranks of the keys of ``freq``, in one pass."""
    rank = F.col("rank").cast("double")
    one = global_rank(freq).agg(*[F.sum(F.pow(rank, F.lit(-float(x)))).alias(f"s{i}") for i, x in enumerate(exponents)])
    return one.select(F.inline(F.array(*[F.struct(F.lit(float(x)).alias("s"), F.col(f"s{i}").alias("value")) for i, x in enumerate(exponents)])))


def zeta_bound(s: float) -> float:
    """An upper bound on the sum over all i: 1.65 from s = 2 on."""
    if s <= 1:
        return math.inf
    return 1.65 if s >= 2 else generalized_harmonic(100_000, s) + 100_000 ** (1 - s) / (s - 1)


def subzipf_phi(c: float, alpha: float, n: int, q: float) -> float:
    """Share of the top key under l_q that a sub-Zipf vector has at least, if q alpha >= 1."""
    if q * alpha < 1:
        raise ValueError("q * alpha must be 1 or more")
    return 1 / (c**q * generalized_harmonic(n, alpha * q))


#: Rows of the table of supported combinations: q, least alpha, least p, and whether the factor is 1.65 or 1 + ln n.
SUPPORTED = ((1.0, 2.0, 1.0, True), (1.0, 1.0, 1.0, False), (2.0, 1.0, 2.0, True), (2.0, 0.5, 2.0, False))


def supported_combinations(hist: DataFrame, p: float = 3.0) -> DataFrame:
    """(q, alpha, least_p, c, bound, measured): each row's bound beside the measured overhead for moment p."""
    rows = scaled(ranked(hist)).withColumn("r", F.col("last_rank").cast("double"))
    cs = [F.max(F.col("u") * F.pow("r", F.lit(a))).alias(f"c{i}") for i, (_, a, _, _) in enumerate(SUPPORTED)]
    sums = [F.sum(F.col("m") * power(F.col("u"), q)).alias(f"s{q:g}") for q in (1.0, 2.0)]
    one = rows.agg(F.sum("m").cast("double").alias("n"), F.sum(F.col("m") * power(F.col("u"), p)).alias("sp"), *cs, *sums)
    table = F.array(*[
        F.struct(
            F.lit(q).alias("q"), F.lit(a).alias("alpha"), F.lit(least).alias("least_p"), F.col(f"c{i}").alias("c"),
            ((F.lit(1.65) if fixed else 1 + F.log("n")) * F.pow(F.col(f"c{i}"), F.lit(q))).alias("bound"), (F.col(f"s{q:g}") / F.col("sp")).alias("measured"),
        )
        for i, (q, a, least, fixed) in enumerate(SUPPORTED)
    ])
    return one.select(F.inline(table))


def heavy_hitter_combination(hist: DataFrame, q: float, epsilon: float) -> DataFrame:
    """(q, phi, overhead, size): an l_q sample of that size serves all moments p >= q, and combinations, with error epsilon."""
    phi = scaled(hist).agg((1 / F.sum(F.col("m") * power(F.col("u"), q))).alias("phi"))
    return phi.select(F.lit(float(q)).alias("q"), "phi", (1 / F.col("phi")).alias("overhead"), F.ceil(F.round(1 / F.col("phi") / epsilon**2, 6)).cast("bigint").alias("size"))


def tradeoff(hist: DataFrame, exponents: Sequence[float]) -> DataFrame:
    """(q, phi, overhead): a larger q has a larger top share but serves fewer moments (p >= q)."""
    return lp_by_lq(hist, [(q, q) for q in exponents]).select("q", (1 / F.col("bound")).alias("phi"), F.col("bound").alias("overhead"))


def certify(sample: DataFrame, q: float, norm_q: Column | float, k: int) -> DataFrame:
    """(r, certified, chance): the largest share of a sampled key; the sample is as good as an
    ideal one of k * r keys for every p >= q; chance that a with-replacement sample of k
    draws holds the key behind r, at least.

    ``norm_q`` is the sum of w^q: a running total for q = 1, an estimate from a linear
    sketch or a second pass for q = 2.
    """
    norm = F.lit(float(norm_q)) if not isinstance(norm_q, Column) else norm_q
    r = F.max(power(F.col("w"), q) / norm)
    return sample.agg(r.alias("r")).select("r", (k * F.col("r")).alias("certified"), (1 - F.exp(-k * F.col("r"))).alias("chance"))


def zipf_universal(hist: DataFrame, alpha: float) -> DataFrame:
    """An l_{1/alpha} sample's universal overhead: H_n on a Zipf vector of that exponent."""
    from .universal import universal_emulation

    return universal_emulation(hist, 1.0 / alpha)


@dataclass(frozen=True)
class Combination:
    """Frequencies that satisfy ``holds``, functions, and the overhead that a scheme has on them."""

    holds: Callable[[DataFrame], bool]
    functions: Sequence[FrequencyFunction]
    overhead: float
    scheme: Scheme

    def check(self, hist: DataFrame) -> bool:
        """Whether the claim is true of one vector: either it is not covered, or the measured overhead is no larger."""
        if not self.holds(hist):
            return True
        worst = family_overhead(hist, self.functions, self.scheme).first()["emulation"]
        return worst <= self.overhead * (1 + 1e-9)
