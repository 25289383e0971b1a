"""Exact frequencies and statistics: the ground truth, and the histogram that overheads need."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..functions.frequency import FrequencyFunction, power

#: Distinct frequencies up to which one task ranks the histogram.
ONE_TASK = 1_000_000


def frequencies(elements: DataFrame) -> DataFrame:
    """(key, w): one shuffle, summed on the map side first, so hot keys cost one row a task."""
    return elements.groupBy("key").agg(F.sum("value").alias("w")).where("w > 0")


def frequencies_in_order(elements: DataFrame, *order: str) -> DataFrame:
    """As ``frequencies``, for values with fractions: a key's values are added one after another in ``order``.

    Sums of doubles depend on the order in their last bits, and these part keys of equal
    frequency. The running sum never falls, as values are positive, so its largest is the whole.
    A key's rows stream through one task, which may spill them.
    """
    along = W.partitionBy("key").orderBy(*order).rowsBetween(W.unboundedPreceding, 0)
    running = elements.select("key", F.sum("value").over(along).alias("w"))
    return running.groupBy("key").agg(F.max("w").alias("w"))


def histogram(freq: DataFrame) -> DataFrame:
    """(w, m): how many keys have each frequency. Overheads depend on nothing else."""
    return freq.groupBy("w").agg(F.count("*").alias("m"))


def f_statistic(freq: DataFrame, f: FrequencyFunction) -> DataFrame:
    return freq.agg(F.sum(f("w")).alias("value"))


def linear_statistic(freq: DataFrame, f: FrequencyFunction, coefficients: DataFrame, name: str = "coef") -> DataFrame:
    """Sum of coefficient times f(w); ``coefficients`` (key, coef); keys without one count 0."""
    return freq.join(coefficients, "key").agg(F.sum(F.col(name) * f("w")).alias("value"))


def domain_statistic(freq: DataFrame, f: FrequencyFunction, domain: Column | None = None, by: Sequence[str] = ()) -> DataFrame:
    rows = freq if domain is None else freq.where(domain)
    return (rows.groupBy(*by) if by else rows).agg(F.sum(f("w")).alias("value"))


def pps(freq: DataFrame, f: FrequencyFunction) -> DataFrame:
    """``freq`` with p, each key's share of the statistic."""
    total = freq.agg(F.sum(f("w")).alias("_total"))
    return freq.crossJoin(F.broadcast(total)).withColumn("p", f("w") / F.col("_total")).drop("_total")


def norms(hist: DataFrame, exponents: Sequence[float]) -> DataFrame:
    """(p, norm_p, scaled): sums of w^p, and of (w/w_1)^p, for each exponent, in one pass."""
    top = hist.agg(F.max("w").alias("_top"))
    sums = [F.sum(F.col("m") * power(F.col("w") / F.col("_top"), p)).alias(f"s{i}") for i, p in enumerate(exponents)]
    one = hist.crossJoin(F.broadcast(top)).groupBy().agg(F.max("_top").alias("top"), *sums)
    rows = F.array(*[F.struct(F.lit(float(p)).alias("p"), F.col(f"s{i}").alias("scaled")) for i, p in enumerate(exponents)])
    return one.select("top", F.inline(rows))


def ranked(hist: DataFrame, one_task: int = ONE_TASK) -> DataFrame:
    """(w, m, first_rank, last_rank, prefix, tail), from the most frequent down.

    prefix and tail are the sums of frequencies up to and behind the block of equal
    frequencies. A histogram of many rows is range-partitioned; each partition is summed
    by itself and shifted by the totals of those before it.
    """
    order = F.col("w").desc()
    small = hist.limit(one_task + 1).count() <= one_task
    if small:
        upto, behind = W.orderBy(order).rowsBetween(W.unboundedPreceding, 0), W.orderBy(order).rowsBetween(1, W.unboundedFollowing)
        return hist.select(
            "w", "m",
            (F.sum("m").over(upto) - F.col("m") + 1).alias("first_rank"), F.sum("m").over(upto).alias("last_rank"),
            F.sum(F.col("m") * F.col("w")).over(upto).alias("prefix"), F.coalesce(F.sum(F.col("m") * F.col("w")).over(behind), F.lit(0.0)).alias("tail"),
        )
    return ranked_by_parts(hist)


def ranked_by_parts(hist: DataFrame, parts: int | None = None) -> DataFrame:
    """As ``ranked``, without a task that sees all rows."""
    from ..plans.lineage import cut

    order = F.col("w").desc()
    spread = hist.repartitionByRange(*([parts] if parts else []), order)
    spread = cut(spread.withColumn("part", F.spark_partition_id()))
    totals = spread.groupBy("part").agg(F.sum("m").alias("tm"), F.sum(F.col("m") * F.col("w")).alias("tw"), F.max("w").alias("top"))
    along = W.orderBy(F.col("top").desc())
    before = along.rowsBetween(W.unboundedPreceding, -1)
    shift = totals.select(
        "part", F.coalesce(F.sum("tm").over(before), F.lit(0)).alias("sm"), F.coalesce(F.sum("tw").over(before), F.lit(0.0)).alias("sw"),
        F.sum("tw").over(along.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("all_w"),
    )
    inside = W.partitionBy("part").orderBy(order).rowsBetween(W.unboundedPreceding, 0)
    m, s = F.sum("m").over(inside), F.sum(F.col("m") * F.col("w")).over(inside)
    run = spread.withColumn("im", m).withColumn("iw", s).join(F.broadcast(shift), "part")
    return run.select(
        "w", "m", (F.col("sm") + F.col("im") - F.col("m") + 1).alias("first_rank"), (F.col("sm") + F.col("im")).alias("last_rank"),
        (F.col("sw") + F.col("iw")).alias("prefix"), (F.col("all_w") - F.col("sw") - F.col("iw")).alias("tail"),
    )


def global_rank(freq: DataFrame, parts: int | None = None) -> DataFrame:
    """``freq`` with rank: keys in order of falling frequency, then of key.

    Keys are dealt by ranges of (frequency, key), so that the many keys of one frequency
    spread over tasks too; each part is numbered by itself and shifted by the counts of the
    parts before it.
    """
    from ..plans.lineage import cut

    order = [F.col("w").desc(), F.col("key")]
    spread = cut(freq.repartitionByRange(*([parts] if parts else []), *order).withColumn("_part", F.spark_partition_id()))
    counts = spread.groupBy("_part").agg(F.count("*").alias("_n"))
    shift = counts.select("_part", F.coalesce(F.sum("_n").over(W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    numbered = spread.withColumn("_i", F.row_number().over(W.partitionBy("_part").orderBy(*order)))
    return numbered.join(F.broadcast(shift), "_part").withColumn("rank", F.col("_before") + F.col("_i")).drop("_part", "_before", "_i")


def self_join_size(freq: DataFrame, p: int) -> DataFrame:
    """Rows of the p-way self-join on the key: the p-th moment."""
    return freq.agg(F.sum(power(F.col("w"), p)).alias("value"))


def self_join_count(elements: DataFrame, p: int) -> DataFrame:
    """The same by joining, for p of 2 or 3: only for checks on small data."""
    rows = elements.select("key")
    out = rows
    for _ in range(p - 1):
        out = out.join(rows, "key")
    return out.agg(F.count("*").cast("double").alias("value"))
