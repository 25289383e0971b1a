"""Operators around the samples: as-of joins, sketch storage, SQL functions, per-group sketches, generators."""

from __future__ import annotations

from collections.abc import Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window as W, functions as F, types as T

from ..functions.seeds import unit_seed
from ..sources.tables import read, write


def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, values: Sequence[str]) -> DataFrame:
    """``left`` with the values of the latest row of ``right`` at or before its time, per key.

    Both sides are put in one order, right rows first at equal times, and the last known
    values carried on: one shuffle by key, no pairs.
    """
    a = left.withColumn("_side", F.lit(1)).withColumns({v: F.lit(None).cast(right.schema[v].dataType) for v in values})
    b = right.select(key, time, *values).withColumn("_side", F.lit(0))
    order = W.partitionBy(key).orderBy(time, "_side").rowsBetween(W.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True)
    return both.withColumns({v: F.last(v, ignorenulls=True).over(order) for v in values}).where("_side = 1").drop("_side")


def count_near(rows: DataFrame, by: str, at: Column, reach: int) -> DataFrame:
    """``rows`` with near: how many rows of the same group stand at most ``reach`` from the whole number ``at``.

    A place's rows enter at ``reach`` before it and leave behind ``reach`` after it, so near is
    a running sum over places. One task sums a group's distinct places, never its rows. Rows
    at no place (null) are near each other.
    """
    placed = rows.withColumn("_p", at)
    m = placed.groupBy(by, "_p").agg(F.count("*").alias("_m"))
    leave = F.when(F.col("_p").isNull(), 0).otherwise(-F.col("_m"))
    steps = [(F.col("_p") - reach, F.col("_m")), (F.col("_p"), F.lit(0)), (F.col("_p") + reach + 1, leave)]
    points = m.select(F.col(by).alias("_by"), F.inline(F.array(*[F.struct(x.alias("_at"), d.cast("bigint").alias("_d")) for x, d in steps])))
    along = W.partitionBy("_by", F.col("_at").isNull()).orderBy("_at").rowsBetween(W.unboundedPreceding, 0)
    run = points.groupBy("_by", "_at").agg(F.sum("_d").alias("_d")).select("_by", "_at", F.sum("_d").over(along).alias("near"))
    return placed.join(run, F.col(by).eqNullSafe(F.col("_by")) & F.col("_p").eqNullSafe(F.col("_at"))).drop("_p", "_by", "_at")


def store_sketch(sketch: DataFrame, sketch_id: str, path: str, parameters: dict, mode: str = "append") -> str:
    """Adds a sketch's rows to a store of sketches, partitioned by id, so that one is read alone and many are merged."""
    tagged = sketch.withColumn("sketch_id", F.lit(sketch_id))
    for name, value in parameters.items():
        tagged = tagged.withColumn(f"param_{name}", F.lit(value))
    return write(tagged, path, by=["sketch_id"], mode=mode)


def stored_rows(spark: SparkSession, path: str, sketch_id: str) -> DataFrame:
    return read(spark, path).where(F.col("sketch_id") == sketch_id)


def pack_sketch(sketch: DataFrame) -> DataFrame:
    """A sketch (bounded rows) as one row with an array of structs."""
    return sketch.agg(F.array_sort(F.collect_list(F.struct(*sketch.columns))).alias("rows"))


def unpack_sketch(packed: DataFrame) -> DataFrame:
    return packed.select(F.inline("rows"))


def register_functions(spark: SparkSession) -> None:
    """SQL functions of this session: unit_seed(key, salt), and chance_ppswor(weight, tau), chance_priority(weight, tau)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION unit_seed(k STRING, salt STRING) RETURNS DOUBLE RETURN (CAST(conv(substring(md5(concat(salt, '|', k)), 1, 13), 16, 10) AS BIGINT) + 0.5D) / 4503599627370496D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION chance_ppswor(weight DOUBLE, tau DOUBLE) RETURNS DOUBLE RETURN coalesce(-expm1(-weight * tau), 1D)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION chance_priority(weight DOUBLE, tau DOUBLE) RETURNS DOUBLE RETURN coalesce(least(1D, weight * tau), 1D)")


@F.pandas_udf(T.LongType())
def code_points(x: pd.Series) -> pd.Series:
    return x.str.len()


def bottom_k_by_group(rows: DataFrame, by: str, k: int, salt: str = "s") -> DataFrame:
    """(by, keys): the k keys of smallest seed in each group, comma-joined; each task keeps k rows a group."""
    order = W.partitionBy(by).orderBy("u", "key")
    low = rows.withColumn("u", unit_seed(F.col("key"), salt)).withColumn("_at", F.row_number().over(order)).where(F.col("_at") <= k)
    listed = low.groupBy(by).agg(F.array_sort(F.collect_list(F.struct("u", "key"))).alias("x"))
    return listed.select(by, F.array_join(F.transform("x", lambda r: r["key"]), ",").alias("keys"))


def bottom_k_by_group_pandas(rows: DataFrame, by: str, k: int, salt: str = "s") -> DataFrame:
    """The same with a grouped pandas function, for groups that fit in a task."""

    def smallest(pdf: pd.DataFrame) -> pd.DataFrame:
        low = pdf.sort_values(["u", "key"]).head(k)
        return pd.DataFrame({by: [pdf[by].iloc[0]], "keys": [",".join(low["key"])]})

    seeded = rows.select(by, "key", unit_seed(F.col("key"), salt).alias("u"))
    return seeded.groupBy(by).applyInPandas(smallest, f"{by} string, keys string")


@F.udtf(returnType=T.StructType([T.StructField("key", T.StringType()), T.StructField("w", T.DoubleType())]))
class _Zipf:
    def eval(self, n: int, alpha: float, w1: float):
        for i in range(1, n + 1):
            yield str(i), w1 * i**-alpha


def zipf_rows(rows: DataFrame, n: str, alpha: float, w1: str) -> DataFrame:
    """Beside each of ``rows``, by a table function, a small vector (key, w) of ``n`` keys, the first with ``w1``;
    ``combos.zipf_frequencies`` makes large ones."""
    return rows.lateralJoin(_Zipf(F.col(n).cast("int").outer(), F.lit(float(alpha)), F.col(w1).outer()))
