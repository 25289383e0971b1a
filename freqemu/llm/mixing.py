"""Mixing sources to target weights by systematic sampling, with DataFrame functions only.

Targets: all sources share the total size by weight; a target stops at a multiple of its
source's size and the excess goes to the others by weight. Sorted by cap over weight, the
capped sources are a prefix, so one running sum finds the level.

Sampling: every document of a source expects target / source size copies. Documents stand
in order of size; the running sum of expected copies, plus one offset for the source,
emits a copy at each integer that it crosses. As sizes rise slowly along the order, the
words taken stay near the target. The running sum is a count of the documents before,
times the expectation: counts of small buckets (source, size class, hash) are summed
first and rows are numbered only inside their bucket, so no task sees a whole source. The
buckets' own running counts are those of a size class's buckets and of a source's classes.

Sources may be many: running sums over all of them go by ranges of their order, each range
summed by itself and shifted by the totals of the ranges before it.

Edge cases: a null text has size 0 and is taken 0 times; a null source is a source of its
own, behind all others; rows with a null id count and are kept; repeated rows are
separate documents; no documents give no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..plans.lineage import cut
from .common import SPACED_SET, free_names

CAP = 3
WEIGHTS = (1, 2, 3)
#: Sources up to this number are broadcast to the documents.
BROADCAST_SOURCES = 20_000


def offset(source: Column) -> Column:
    """A number in [0, 1) that depends on the source's name only."""
    digits = F.substring(F.md5(F.concat(F.lit("mix|"), F.coalesce(source, F.lit("")))), 1, 12)
    return F.conv(digits, 16, 10).cast("bigint") / float(1 << 48)


def running(rows: DataFrame, order: list[Column], sums: dict[str, Column], parts: int | None = None) -> DataFrame:
    """``rows`` with, for each of ``sums``, its running sum up to the row along ``order`` (a total order of ``rows``).

    The rows are dealt by ranges of the order; only one row a range is summed in one task.
    """
    before, parts = [f"_before_{c}" for c in sums], [parts] if parts else []
    spread = cut(rows.repartitionByRange(*parts, *order).withColumn("_part", F.spark_partition_id()))
    total = spread.groupBy("_part").agg(*[F.sum(v).alias(c) for c, v in sums.items()])
    ahead = W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)
    shift = total.select("_part", *[F.coalesce(F.sum(c).over(ahead), F.lit(0)).alias(b) for c, b in zip(sums, before)])
    inside = W.partitionBy("_part").orderBy(*order).rowsBetween(W.unboundedPreceding, 0)
    summed = spread.withColumns({c: F.sum(v).over(inside) for c, v in sums.items()})
    return summed.join(F.broadcast(shift), "_part").withColumns({c: F.col(c) + F.col(b) for c, b in zip(sums, before)}).drop("_part", *before)


def targets(sizes: DataFrame, weights=WEIGHTS, cap: int = CAP, parts: int | None = None) -> DataFrame:
    """(source, source_size, n, target) from (source, source_size, n): one row a source."""
    name = F.col("source").asc_nulls_last()
    turned = running(sizes, [name], {"turn": F.lit(1)}, parts)
    turn = F.pmod(F.col("turn") - 1, F.lit(len(weights))) + 1
    w = turned.withColumn("w", F.element_at(F.array(*[F.lit(x) for x in weights]), turn.cast("int")).cast("bigint")).drop("turn")
    w = w.withColumn("top", F.col("source_size") * cap)
    summed = cut(running(w, [(F.col("top") / F.col("w")).asc(), name], {"tops": F.col("top"), "ws": F.col("w")}, parts))
    whole = summed.agg(F.sum("source_size").alias("total"), F.sum("w").alias("all_w"))
    level = (
        summed.crossJoin(F.broadcast(whole))
        .withColumn("left", F.col("total") - F.col("tops") + F.col("top"))
        .withColumn("rest", F.col("all_w") - F.col("ws") + F.col("w"))
    )
    free = (F.col("left") / F.col("rest")) <= (F.col("top") / F.col("w"))
    first = level.where(free).agg(F.max_by(F.struct("left", "rest"), "rest").alias("first"))
    target = F.when(F.col("rest") <= F.col("first.rest"), (F.col("w") * F.col("first.left")) / F.col("first.rest")).otherwise(F.col("top").cast("double"))
    return level.crossJoin(F.broadcast(first)).select("source", "source_size", "n", target.alias("target"))


def size_class(size: Column) -> Column:
    """Grows with the size: its bit length and the four bits behind the leading one."""
    bits = F.bin(size)
    return F.concat(F.lpad(F.length(bits).cast("string"), 2, "0"), F.rpad(F.substring(bits, 2, 4), 4, "0"))


def mix(docs: DataFrame, id_col: str = "doc_id", text: str = "text", source: str = "source", weights=WEIGHTS, cap: int = CAP) -> DataFrame:
    """(id_col, size, source_size, target, taken, copies), a row for each of ``docs``."""
    size = F.coalesce(F.regexp_count(F.col(text), F.lit(SPACED_SET)), F.lit(0)).cast("bigint")
    mark = F.md5(F.coalesce(F.col(id_col).cast("string"), F.lit("")))
    rows = cut(docs.select(F.col(id_col).alias("id"), F.col(source).alias("source"), size.alias("size"), mark.alias("mark")))
    rows = rows.withColumn("class", size_class(F.col("size"))).withColumn("slot", F.substring("mark", 1, 2))
    buckets = cut(rows.groupBy("source", "class", "slot").agg(F.count("*").alias("m"), F.sum("size").alias("words")))
    shares = targets(buckets.groupBy("source").agg(F.sum("words").alias("source_size"), F.sum("m").alias("n")), weights, cap)
    # a class has at most 256 slots, a source at most some hundreds of classes: no window grows with the data
    along = W.partitionBy("source", "class").orderBy("slot").rowsBetween(W.unboundedPreceding, -1)
    over = W.partitionBy("owner").orderBy("sort").rowsBetween(W.unboundedPreceding, -1)
    below = buckets.groupBy(F.col("source").alias("owner"), F.col("class").alias("sort")).agg(F.sum("m").alias("many"))
    below = below.withColumn("lower", F.coalesce(F.sum("many").over(over), F.lit(0))).drop("many")
    ahead = buckets.withColumn("in_class", F.coalesce(F.sum("m").over(along), F.lit(0)))
    ahead = ahead.join(below, F.col("source").eqNullSafe(F.col("owner")) & (F.col("class") == F.col("sort")))
    ahead = ahead.select("source", "class", "slot", (F.col("in_class") + F.col("lower")).alias("ahead"))
    inside = W.partitionBy("source", "class", "slot").orderBy("size", "mark", "id")
    numbered = rows.withColumn("k", F.row_number().over(inside))
    a, b = numbered.alias("a"), ahead.alias("b")
    placed = a.join(b, F.col("a.source").eqNullSafe(F.col("b.source")) & (F.col("a.class") == F.col("b.class")) & (F.col("a.slot") == F.col("b.slot"))).select(
        "a.id", "a.source", "a.size", (F.col("a.k") + F.col("b.ahead")).alias("k")
    )
    few = shares.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    dims = shares.withColumn("u", offset(F.col("source"))).withColumn("e", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0)))
    dims = dims.withColumnRenamed("source", "owner")
    joined = placed.join(F.broadcast(dims) if few else dims, F.col("source").eqNullSafe(F.col("owner")))
    copies = F.floor(F.col("u") + F.col("k") * F.col("e")) - F.floor(F.col("u") + (F.col("k") - 1) * F.col("e"))
    return joined.select(F.col("id").alias(id_col), "size", "source_size", "target", (copies * F.col("size")).cast("bigint").alias("taken"), copies.cast("bigint").alias("copies"))


def emitted(docs: DataFrame, mixed: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The mix itself: each document as many times as it was taken; ids must not repeat."""
    own, times, copy = free_names(["own", "times", "copy"], docs.columns)
    taken = mixed.where("copies > 0").select(F.col(id_col).alias(own), F.col("copies").cast("int").alias(times))
    rows = docs.join(taken, F.col(id_col) == F.col(own))
    return rows.withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(times)))).select(*[F.col(f"`{c}`") for c in docs.columns])


def op5_mixing(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", "text")
    return mix(docs).select("doc_id", "size", "source_size", "target", "taken")


OP5_SQL = r"""
WITH d AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
    md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS mark
  FROM documents
), s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source
), w AS (
  SELECT source, source_size, 3 * source_size AS top, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS w FROM s
), l AS (
  SELECT source, source_size, top, w,
    CAST(sum(source_size) OVER () AS BIGINT) - CAST(coalesce(sum(top) OVER (ORDER BY top / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS lft,
    CAST(sum(w) OVER (ORDER BY top / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS BIGINT) AS rest
  FROM w
), f AS (
  SELECT lft AS flft, rest AS frest FROM l WHERE lft / rest <= top / w ORDER BY rest DESC LIMIT 1
), t AS (
  SELECT source, source_size, CASE WHEN rest <= frest THEN (w * flft) / frest ELSE CAST(top AS DOUBLE) END AS target,
    CAST('0x' || substr(md5('mix|' || coalesce(source, '')), 1, 12) AS BIGINT) / 281474976710656.0 AS u
  FROM l, f
), c AS (
  SELECT doc_id, source, size, mark, lpad(CAST(length(bin(size)) AS VARCHAR), 2, '0') || rpad(substr(bin(size), 2, 4), 4, '0') AS class FROM d
), k AS (
  SELECT doc_id, source, size, row_number() OVER (PARTITION BY source ORDER BY class, substr(mark, 1, 2), size, mark, doc_id) AS k FROM c
), e AS (
  SELECT k.doc_id, k.size, t.source_size, t.target, k.k, t.u, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0.0 END AS e
  FROM k JOIN t ON k.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, size, source_size, CAST(target AS DOUBLE) AS target, CAST((floor(u + k * e) - floor(u + (k - 1) * e)) * size AS BIGINT) AS taken FROM e
"""
