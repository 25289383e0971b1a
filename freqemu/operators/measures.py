"""Accuracy and cost measures of sampling schemes.

NRMSE is the standard deviation of the estimate of sum f(w) over its true value. With
replacement it has a closed bound over the histogram. Without replacement it is averaged
over runs: in each run, every key's chance of being included is computed given the seeds
of all other keys, and f^2 (1/p - 1) is summed over all keys, sampled or not.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from ..functions.frequency import FrequencyFunction, moment, power
from ..functions.seeds import draw, inclusion, wr_inclusion
from . import advice as A
from .bottomk import threshold_of
from .overhead import Scheme, benchmark_key_variance, chances, scaled


def nrmse(variance, truth):
    return F.sqrt(variance) / truth


def benchmark_curve(spark: SparkSession, ks: Sequence[int]) -> DataFrame:
    """(k, nrmse) = 1 / sqrt(k): ideal sampling."""
    return spark.createDataFrame([(int(k),) for k in ks], "k bigint").select("k", (1 / F.sqrt("k")).alias("nrmse"))


def benchmark_errors(hist: DataFrame, f: FrequencyFunction, ks: Sequence[int]) -> DataFrame:
    """(k, nrmse): the curve of ``benchmark_curve``, from the variances that ideal sampling allows the keys of a vector."""
    sizes = F.explode(F.array(*[F.lit(int(k)).cast("bigint") for k in ks])).alias("k")
    one = benchmark_key_variance(hist, f, 1).agg(F.sum(F.col("m") * F.col("variance")).alias("v"), F.sum(F.col("m") * f("w")).alias("s"))
    return one.select(sizes, "v", "s").select("k", (F.sqrt(F.col("v") / F.col("k")) / F.col("s")).alias("nrmse"))


def wr_nrmse(hist: DataFrame, f: FrequencyFunction, scheme: Scheme, ks: Sequence[int]) -> DataFrame:
    """(k, nrmse) of samples with replacement: an upper bound, exact key by key."""
    rows = chances(hist, [f], scheme)  # p0 = f / ||f||
    aggs = [F.sum(F.col("m") * F.col("p0") * F.col("p0") * (1 / wr_inclusion(F.col("q"), k) - 1)).alias(f"v{k}") for k in ks]
    each = F.array(*[F.struct(F.lit(int(k)).cast("bigint").alias("k"), F.sqrt(f"v{k}").alias("nrmse")) for k in ks])
    return rows.agg(*aggs).select(F.inline(each))


def wr_nrmse_by(hist: DataFrame, qs: Sequence[float], ks: Sequence[int], powers: Sequence[float]) -> DataFrame:
    """(q, k, f, nrmse) of samples with replacement by w^q for moments: all of them from two aggregations."""
    rows = scaled(hist)
    used = sorted({float(x) for x in (*qs, *powers)})
    sums = rows.agg(*[F.sum(F.col("m") * power(F.col("u"), x)).alias(f"t{i}") for i, x in enumerate(used)])
    share = lambda x: power(F.col("u"), x) / F.col(f"t{used.index(float(x))}")
    cells = [(q, k, p) for q in qs for k in ks for p in powers]
    aggs = [F.sum(F.col("m") * share(p) * share(p) * (1 / wr_inclusion(share(q), k) - 1)).alias(f"v{i}") for i, (q, k, p) in enumerate(cells)]
    each = [F.struct(F.lit(float(q)).alias("q"), F.lit(int(k)).cast("bigint").alias("k"), F.lit(moment(p).name).alias("f"), F.sqrt(f"v{i}").alias("nrmse")) for i, (q, k, p) in enumerate(cells)]
    return rows.crossJoin(F.broadcast(sums)).agg(*aggs).select(F.inline(F.array(*each)))


def runs_of(freq: DataFrame, runs: int) -> DataFrame:
    """Every key once for each run, with the run's number: draws are hashes of both."""
    return freq.withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))


def conditional_nrmse(freq: DataFrame, q: float, ks: Sequence[int], functions: Sequence[FrequencyFunction], runs: int = 50, scheme: str = "ppswor") -> DataFrame:
    """(k, f, nrmse) of bottom-k samples by w^q."""
    return conditional_nrmse_by(freq, [q], ks, functions, runs, scheme).select("k", "f", "nrmse")


def conditional_nrmse_by(freq: DataFrame, qs: Sequence[float], ks: Sequence[int], functions: Sequence[FrequencyFunction], runs: int = 50, scheme: str = "ppswor") -> DataFrame:
    """(q, k, f, nrmse) of bottom-k samples by w^q for each q; they share their draws.

    Runs times keys are made twice, in flight: once to find each run's two thresholds for
    every k (a per-group limit of max(k) rows before the shuffle), once to add up.
    """
    powers = list(enumerate(qs))
    rows = runs_of(freq, runs).withColumn("h", draw(F.col("key"), F.col("run"), scheme))
    seeds = F.inline(F.array(*[F.struct(F.lit(i).alias("i"), (F.col("h") / moment(q)("w")).alias("seed")) for i, q in powers]))
    window = W.partitionBy("run", "i").orderBy("seed", "key")
    low = rows.select("run", "key", seeds).withColumn("at", F.row_number().over(window)).where(F.col("at") <= max(ks))
    at = lambda i, n: F.min(F.when((F.col("i") == i) & (F.col("at") == n), F.col("seed")))
    marks = low.groupBy("run").agg(*[c for i, _ in powers for k in ks for c in (at(i, k).alias(f"a{i}_{k}"), at(i, k - 1).alias(f"b{i}_{k}"))])
    truths = freq.agg(*[F.sum(f("w")).alias(f"t{j}") for j, f in enumerate(functions)])
    both = rows.join(F.broadcast(marks), "run").crossJoin(F.broadcast(truths))
    both = both.select("*", *[moment(q)("w").alias(f"x{i}") for i, q in powers], *[(f("w") / F.col(f"t{j}")).alias(f"s{j}") for j, f in enumerate(functions)])

    def chance(i, k):
        return inclusion(scheme, F.col(f"x{i}"), threshold_of(F.col("h") / F.col(f"x{i}"), F.col(f"a{i}_{k}"), F.col(f"b{i}_{k}"), k))

    both = both.select(*[f"s{j}" for j in range(len(functions))], *[(1 / chance(i, k) - 1).alias(f"e{i}_{k}") for i, _ in powers for k in ks])
    cells = [(i, q, k, j, f) for i, q in powers for k in ks for j, f in enumerate(functions)]
    sums = both.agg(*[F.sum(F.col(f"s{j}") * F.col(f"s{j}") * F.col(f"e{i}_{k}")).alias(f"v{i}_{k}_{j}") for i, _, k, j, _ in cells])
    each = [F.struct(F.lit(float(q)).alias("q"), F.lit(int(k)).cast("bigint").alias("k"), F.lit(f.name).alias("f"), F.sqrt(F.col(f"v{i}_{k}_{j}") / runs).alias("nrmse")) for i, q, k, j, f in cells]
    return sums.select(F.inline(F.array(*each)))


def conditional_nrmse_advice(rows: DataFrame, f: FrequencyFunction, sizes: Sequence[tuple[int, int, int]], runs: int = 50, scheme: str = "ppswor", functions: Sequence[FrequencyFunction] | None = None) -> DataFrame:
    """(k, k_uniform, f, nrmse) of sampling by advice for ``rows`` (key, w, advice): k = k_p + k_u for each of ``sizes`` (k_h, k_p, k_u).

    Keys of the top part have no error. The two thresholds of each part follow from the
    smallest seeds of the run among the other keys.
    """
    functions = list(functions or [f])
    kh = sizes[0][0]
    if any(s[0] != kh for s in sizes):
        raise ValueError("one k_h at a time")
    all_rows = A.seeded(runs_of(rows, runs), f, scheme, F.col("run"))
    if kh:
        place = F.row_number().over(W.partitionBy("run").orderBy(F.col("advice").desc(), "h", "key"))
        top = all_rows.select("run", "key", "advice", "h").withColumn("at", place).where(F.col("at") <= kh).select("run", "key")
        all_rows = all_rows.join(F.broadcast(top), ["run", "key"], "left_anti")
    p_marks, u_marks = {s[1] for s in sizes}, {s[2] for s in sizes}
    at = lambda c, i, n: F.min(F.when(F.col("at") == i, F.col(c))).alias(n)
    by_r = all_rows.where("r is not null").select("run", "key", "r").withColumn("at", F.row_number().over(W.partitionBy("run").orderBy("r", "key"))).where(F.col("at") <= max(1, *p_marks))
    by_h = all_rows.select("run", "key", "h").withColumn("at", F.row_number().over(W.partitionBy("run").orderBy("h", "key"))).where(F.col("at") <= max(1, *u_marks))
    a = by_r.groupBy("run").agg(*[c for k in sorted(p_marks) for c in (at("r", k - 1, f"p1_{k}"), at("r", k, f"p2_{k}"))])
    b = by_h.groupBy("run").agg(*[c for k in sorted(u_marks) for c in (at("h", k - 1, f"u1_{k}"), at("h", k, f"u2_{k}"))])
    both = all_rows.join(F.broadcast(b.join(a, "run", "left")), "run")
    truths = rows.agg(*[F.sum(g("w")).alias(f"t{j}") for j, g in enumerate(functions)])
    both = both.crossJoin(F.broadcast(truths))

    def loo(x, first, second, k):
        if k <= 1:
            return F.lit(0.0)
        return F.when(F.col(x).isNotNull() & (F.col(first).isNull() | (F.col(x) <= F.col(first))), F.col(second)).otherwise(F.col(first))

    aggs, cells = [], []
    for i, (_, kp, ku) in enumerate(sizes):
        tp, tu = loo("r", f"p1_{kp}", f"p2_{kp}", kp), loo("h", f"u1_{ku}", f"u2_{ku}", ku)
        reach = F.when(F.col("fa") <= 0, 0.0).when(tp.isNull(), F.lit(None).cast("double")).otherwise(F.col("fa") * tp)
        limit = F.when(reach.isNull() | tu.isNull(), F.lit(None).cast("double")).otherwise(F.greatest(reach, tu))
        p = A.chance(limit, scheme)
        for j, g in enumerate(functions):
            share = g("w") / F.col(f"t{j}")
            aggs.append(F.sum(share * share * (1 / p - 1)).alias(f"v{i}_{j}"))
            cells.append(F.struct(F.lit(kp + ku).cast("bigint").alias("k"), F.lit(ku).cast("bigint").alias("k_uniform"), F.lit(g.name).alias("f"), F.sqrt(F.col(f"v{i}_{j}") / runs).alias("nrmse")))
    return both.agg(*aggs).select(F.inline(F.array(*cells)))


def empirical_errors(freq: DataFrame, q: float, k: int, f: FrequencyFunction, runs: int = 50, scheme: str = "ppswor") -> DataFrame:
    """(run, error): the relative error of the estimate in each run."""
    rows = runs_of(freq, runs).withColumn("weight", moment(q)("w"))
    rows = rows.withColumn("seed", draw(F.col("key"), F.col("run"), scheme) / F.col("weight"))
    place = F.row_number().over(W.partitionBy("run").orderBy("seed", "key"))
    low = rows.withColumn("at", place).where(F.col("at") <= k)
    tau = low.groupBy("run").agg(F.max(F.when(F.col("at") == k, F.col("seed"))).alias("tau"))
    inside = low.join(tau, "run").where(F.col("tau").isNull() | (F.col("at") < k))
    totals = inside.groupBy("run").agg(F.sum(f("w") / inclusion(scheme, F.col("weight"), F.col("tau"))).alias("x"))
    truth = freq.agg(F.sum(f("w")).alias("t"))
    return totals.crossJoin(F.broadcast(truth)).select("run", (F.col("x") / F.col("t") - 1).alias("error"))


def empirical_nrmse(errors: DataFrame) -> DataFrame:
    return errors.agg(F.sqrt(F.avg(F.col("error") * F.col("error"))).alias("nrmse"), F.avg("error").alias("bias"))


def error_quantiles(errors: DataFrame, at: Sequence[float] = (0.5, 0.9, 0.95)) -> DataFrame:
    """Quantiles of the absolute relative error over runs, and the share within 1 and 2 root mean squares."""
    rms = errors.agg(F.sqrt(F.avg(F.col("error") * F.col("error"))).alias("rms"))
    e = F.abs("error")
    within = [F.avg((e <= z * F.col("rms")).cast("double")).alias(f"within_{z}") for z in (1, 2)]
    return errors.crossJoin(F.broadcast(rms)).agg(*[F.percentile(e, x).alias(f"q{int(100 * x)}") for x in at], *within)


def sketch_size(sketch: DataFrame, kh: int, kp: int, ku: int) -> DataFrame:
    return sketch.agg(F.count("*").alias("held")).select("held", F.lit(kh + kp + ku).cast("bigint").alias("most"))


def practicality(overhead: float, epsilon: float, n: int) -> dict:
    """Whether a sample of overhead / epsilon^2 keys is far smaller than n."""
    size = -int(-(overhead / epsilon**2) // 1)
    return {"size": size, "share": size / n, "practical": size < 0.1 * n}


def space_bounds(hist: DataFrame, exponents: Sequence[float]) -> DataFrame:
    """(p, n, worst, with_oracle, concave): orders of growth known for moments above 2, at n keys; constants left out."""
    n = hist.agg(F.sum("m").cast("double").alias("n"))
    each = F.array(*[F.struct(F.lit(float(p)).alias("p"), F.pow("n", F.lit(1 - 2 / p)).alias("worst"), F.pow("n", F.lit(0.5 - 1 / p)).alias("with_oracle"), F.log("n").alias("concave")) for p in exponents])
    return n.select(F.col("n").cast("bigint").alias("n"), F.inline(each))
