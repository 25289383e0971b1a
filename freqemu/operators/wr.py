"""With-replacement samples of aggregated keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window as W, functions as F

from ..functions.frequency import FrequencyFunction
from ..functions.seeds import exp_of, unit_seed, wr_inclusion
from ..plans.lineage import cut

#: Cells of the lookup that turns the range join of draws with intervals into an equality.
CELLS = 4096


def cumulated(freq: DataFrame, f: FrequencyFunction, digits: int = 3) -> DataFrame:
    """(key, w, lo, hi): each key's interval of the unit line, of length f(w) / ||f||.

    Keys are dealt into parts by the first ``digits`` hexadecimal digits of their md5 and
    summed inside; the parts' totals (16^digits rows) shift them. No task orders all keys.
    """
    rows = freq.withColumn("v", f("w")).where("v > 0")
    rows = rows.withColumn("part", F.substring(F.md5(F.col("key").cast("binary")), 1, digits))
    totals = rows.groupBy("part").agg(F.sum("v").alias("t"))
    before = W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    shift = totals.select("part", F.coalesce(F.sum("t").over(before), F.lit(0.0)).alias("s"), F.sum("t").over(W.partitionBy()).alias("all"))
    inside = W.partitionBy("part").orderBy("key").rowsBetween(W.unboundedPreceding, 0)
    run = rows.withColumn("c", F.sum("v").over(inside)).join(F.broadcast(shift), "part")
    return run.select("key", "w", "v", ((F.col("s") + F.col("c") - F.col("v")) / F.col("all")).alias("lo"), ((F.col("s") + F.col("c")) / F.col("all")).alias("hi"), (F.col("v") / F.col("all")).alias("q"))


def pps_wr(freq: DataFrame, f: FrequencyFunction, k: int, salt: str = "s") -> DataFrame:
    """(key, w, q, draws, p_incl): k independent draws by f(w), found by a range join.

    The k points go into cells of the unit line; an interval that lies in few cells meets
    only their points by equality, and a longer one (at most CELLS / 2 of them) all points.
    """
    spark = freq.sparkSession
    points = spark.range(k).select(unit_seed(F.col("id").cast("string"), f"wr|{salt}").alias("x")).withColumn("cell", F.floor(F.col("x") * CELLS))
    spans = cut(cumulated(freq, f))
    first, last = F.floor(F.col("lo") * CELLS), F.floor(F.col("hi") * CELLS)
    short = spans.where(last - first <= 2).withColumn("cell", F.explode(F.sequence(first, last)))
    inside = (F.col("x") >= F.col("lo")) & (F.col("x") < F.col("hi"))
    near = short.join(F.broadcast(points), "cell").where(inside).select("key", "w", "q")
    far = spans.where(last - first > 2).join(F.broadcast(points), inside).select("key", "w", "q")
    drawn = near.unionByName(far).groupBy("key").agg(F.max("w").alias("w"), F.max("q").alias("q"), F.count("*").alias("draws"))
    return drawn.withColumn("p_incl", wr_inclusion(F.col("q"), k))


def pps_wr_min(freq: DataFrame, f: FrequencyFunction, k: int, salt: str = "s") -> DataFrame:
    """The same kind of sample as the winners of k independent bottom-1 contests: mergeable, O(n k)."""
    rows = freq.withColumn("v", f("w")).where("v > 0")
    total = rows.agg(F.sum("v").alias("all"))
    contests = F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    seeded = rows.select("key", "w", "v", contests.alias("j"))
    seed = exp_of(unit_seed(F.concat(F.col("j").cast("string"), F.lit("|"), F.col("key")), salt)) / F.col("v")
    wins = seeded.withColumn("seed", seed).groupBy("j").agg(F.min_by(F.struct("key", "w", "v"), F.struct("seed", "key")).alias("x"))
    drawn = wins.groupBy("x.key").agg(F.max("x.w").alias("w"), F.max("x.v").alias("v"), F.count("*").alias("draws"))
    out = drawn.crossJoin(F.broadcast(total)).withColumn("q", F.col("v") / F.col("all"))
    return out.select("key", "w", "q", "draws", wr_inclusion(F.col("q"), k).alias("p_incl"))
