"""Linear sketches: l_p samples (p up to 2) of elements that need no aggregation by key.

Every element adds value * sign / e(key)^(1/p) to one cell in each row of a small table;
the cells of parts add up, so Spark's own partial aggregation is the merge. The keys of
largest scaled estimates are the bottom-k sample by w^p.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..functions.seeds import exp_of, fast_unit_seed, seed_bits, unit_seed
from ..plans.lineage import cut


def _scale(key: Column, p: float, salt: str, fast: bool = False) -> Column:
    return F.pow(exp_of(fast_unit_seed(key, salt) if fast else unit_seed(key, salt)), F.lit(-1.0 / p))


def _cell_of(row: Column, width: int, salt: str, fast: bool = False) -> tuple[Column, Column]:
    """Bucket and sign of ``key`` in a table row."""
    name = f"cell|{salt}"
    bits = F.shiftrightunsigned(F.xxhash64(F.lit(name), row, F.col("key")), 12) if fast else seed_bits(F.concat(row, F.lit("|"), F.col("key")), name)
    return F.pmod(F.shiftright(bits, 1), F.lit(width)), (bits % 2 * 2 - 1).cast("double")


def _cells(rows: DataFrame, depth: int, width: int, salt: str, fast: bool = False) -> DataFrame:
    """For every row of ``rows`` (key, ...): its bucket and sign in each of ``depth`` table rows."""
    spread = rows.withColumn("row", F.explode(F.sequence(F.lit(0), F.lit(depth - 1))))
    bucket, sign = _cell_of(F.col("row").cast("string"), width, salt, fast)
    return spread.withColumn("bucket", bucket).withColumn("sign", sign)


def sketch_cells(elements: DataFrame, p: float, depth: int = 7, width: int = 2048, salt: str = "s", fast: bool = False) -> DataFrame:
    """(row, bucket, total): at most depth * width rows, whatever the number of keys.

    Elements are first summed by key on the map side only where that is free: the sum is
    linear, so any order of adding gives the same cells.
    """
    scaled = elements.select("key", (F.col("value") * _scale(F.col("key"), p, salt, fast)).alias("x"))
    return _cells(scaled, depth, width, salt, fast).groupBy("row", "bucket").agg(F.sum(F.col("x") * F.col("sign")).alias("total"))


def recover(cells: DataFrame, candidates: DataFrame, p: float, k: int, depth: int = 7, width: int = 2048, salt: str = "s", fast: bool = False) -> DataFrame:
    """(key, scaled, seed): the k candidates of largest scaled estimate; seed = scaled^-p is e / w^p.

    ``cells`` has a fixed number of rows and is broadcast; candidates are distinct keys.
    """
    each = _cells(candidates.select("key"), depth, width, salt, fast).join(F.broadcast(cells), ["row", "bucket"], "left")
    x = F.coalesce("total", F.lit(0.0)) * F.col("sign")
    guess = each.groupBy("key").agg(F.abs(F.median(x)).alias("scaled"))
    top = guess.orderBy(F.col("scaled").desc(), "key").limit(k)
    return top.withColumn("seed", F.pow("scaled", F.lit(-float(p))))


def linear_sample(elements: DataFrame, p: float, k: int, depth: int = 7, width: int = 2048, salt: str = "s", fast: bool = True) -> DataFrame:
    """(key, w, seed, tau, p_incl): k - 1 recovered keys with exact frequencies from a second pass.

    ``fast`` hashes with xxhash64; without it the seeds are those of the other samples.
    """
    cells = cut(sketch_cells(elements, p, depth, width, salt, fast))  # at most depth * width rows
    top = recover(cells, elements.select("key").distinct(), p, k, depth, width, salt, fast)
    tau = F.when(F.count("*").over(W.partitionBy()) >= k, F.max("seed").over(W.partitionBy()))
    kept = cut(top.withColumn("tau", tau).where("tau is null or seed < tau"))
    w = elements.join(F.broadcast(kept.select("key")), "key", "left_semi").groupBy("key").agg(F.sum("value").alias("w"))
    rows = w.join(F.broadcast(kept), "key")
    p_incl = F.when(F.col("tau").isNull(), 1.0).otherwise(-F.expm1(-F.pow("w", F.lit(float(p))) * F.col("tau")))
    return rows.select("key", "w", "seed", "tau", p_incl.alias("p_incl"))


def second_moment_cells(elements: DataFrame, depth: int = 5, width: int = 1024, salt: str = "f2") -> DataFrame:
    """(row, bucket, total) of unscaled values: the sum of squares of a row estimates the second moment."""
    return _cells(elements.select("key", F.col("value").alias("x")), depth, width, salt).groupBy("row", "bucket").agg(F.sum(F.col("x") * F.col("sign")).alias("total"))


def second_moment(cells: DataFrame) -> DataFrame:
    """The median over rows of their sums of squares."""
    return cells.groupBy("row").agg(F.sum(F.col("total") * F.col("total")).alias("x")).agg(F.median("x").alias("estimate"))
