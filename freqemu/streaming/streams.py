"""Samples and frequencies over streams: every operator keeps bounded state or a watermark.

Sketches merge, and seeds are hashes of keys, so a batch that runs twice changes nothing:
each micro-batch writes the version of the stored sketch that carries its number, made
from the version before it.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from ..functions.frequency import FrequencyFunction
from ..operators import advice as A
from ..operators.kernel import unit_seed_of
from ..operators.linear import second_moment, second_moment_cells
from ..plans.lineage import checkpoint_folder, cut


def folder(spark: SparkSession, name: str) -> str:
    return f"{checkpoint_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def replay(rows: DataFrame, time: str, path: str, files: int = 10) -> str:
    """Writes ``rows`` as files in order of time, one file each, for a file stream."""
    at = F.col(time).cast("timestamp").cast("double")
    marks = rows.agg(F.percentile_approx(at, [i / files for i in range(1, files)], 1000)).first()[0] or []
    marks = [float("-inf"), *marks, float("inf")]
    for low, high in zip(marks, marks[1:]):
        rows.where((at > low) & (at <= high)).coalesce(1).write.mode("append").parquet(path)
    return path


def stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def drain(rows: DataFrame, each: Callable[[DataFrame, int], None], mode: str = "append", log: str | None = None) -> None:
    """Runs a stream over all that its source has now, handing every micro-batch to ``each``.

    With the same ``log`` folder a later call goes on where the last one stopped.
    """
    log = log or folder(rows.sparkSession, "stream")
    query = rows.writeStream.outputMode(mode).foreachBatch(each).option("checkpointLocation", log).trigger(availableNow=True).start()
    query.awaitTermination()


def newest(spark: SparkSession, path: str) -> DataFrame | None:
    """The version with the largest number below ``path``; None if no batch has run yet."""
    try:
        rows = spark.read.parquet(path)
    except AnalysisException:
        return None
    last = rows.agg(F.max("n")).first()[0]
    return rows.where(F.col("n").eqNullSafe(F.lit(last))).drop("n")


def collected(rows: DataFrame, mode: str = "append") -> DataFrame:
    """Everything that a stream emits, from Parquet: appended rows, or the last complete result."""
    spark, path = rows.sparkSession, folder(rows.sparkSession, "emitted")
    schema = rows.schema

    def each(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number if mode == 'append' else 0}")

    drain(rows, each, mode)
    return spark.read.schema(schema).parquet(f"{path}/*")


# -- sketches over streams -----------------------------------------------------------------------


def running_sketch(elements: DataFrame, advice: DataFrame, f: FrequencyFunction, kh: int, kp: int, ku: int, path: str | None = None) -> DataFrame:
    """The sketch by advice of a whole stream of (key, value): the stored version after its last batch.

    ``path`` holds the stream's log and the versions; called again with it, the stream goes
    on with what is new. The advice is computed once.
    """
    spark, path = elements.sparkSession, path or folder(elements.sparkSession, "sketch")
    advice = cut(advice)

    def each(batch: DataFrame, number: int) -> None:
        part = A.advice_sketch(batch, advice, f, kh, kp, ku).select("key", "w", "advice", "h", "fa", "r")
        if number > 0:
            part = A.merge_advice([spark.read.parquet(f"{path}/versions/n={number - 1}"), part], kh, kp, ku)
        part.select("key", "w", "advice", "h", "fa", "r").coalesce(1).write.mode("overwrite").parquet(f"{path}/versions/n={number}")

    drain(elements, each, log=f"{path}/log")
    last = newest(spark, f"{path}/versions")
    if last is None:
        raise ValueError("the stream is empty")
    return A.cut_sketch(last, kh, kp, ku)


def windowed_frequencies(events: DataFrame, time: str, key: str, length: str, slide: str | None = None, late: str = "1 day") -> DataFrame:
    """(start, key, w) for tumbling or sliding windows of a stream."""
    span = F.window(time, length, slide) if slide else F.window(time, length)
    rows = events.withWatermark(time, late).groupBy(span.alias("span"), key).agg(F.count("*").alias("w"))
    return rows.select(F.col("span.start").alias("start"), key, "w")


def session_frequencies(events: DataFrame, time: str, key: str, gap: str, late: str = "1 day") -> DataFrame:
    rows = events.withWatermark(time, late).groupBy(F.session_window(time, gap).alias("span"), key).agg(F.count("*").alias("w"))
    return rows.select(F.col("span.start").alias("start"), F.col("span.end").alias("end"), key, "w")


def keyed_sketches(events: DataFrame, by: str, key: str, k: int, salt: str = "s", time: str | None = None, idle: int | None = None, late: str = "1 hour") -> DataFrame:
    """(by, keys): a stream's bottom-k sample of distinct keys for each group, in bounded state.

    With ``time`` and ``idle`` (milliseconds) a group is forgotten once the watermark is that
    far beyond its last event, which a last row with null keys says.
    """

    def update(group: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({by: [group[0]], "keys": [None]})
            return
        kept, last = state.get if state.exists else ("[]", 0)
        held = dict(json.loads(kept))
        for frame in frames:
            last = max(last, int(frame["_ms"].max()))
            for x in frame[key].dropna().unique():
                held[str(x)] = unit_seed_of(str(x), salt)
            held = dict(sorted(held.items(), key=lambda p: (p[1], p[0]))[:k])
        state.update((json.dumps(list(held.items())), last))
        if idle is not None:
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs() + 1, last + idle))
        yield pd.DataFrame({by: [group[0]], "keys": [",".join(held)]})

    columns = [by, F.col(key).cast("string").alias(key)]
    if idle is None:
        rows = events.select(*columns, F.lit(0).cast("long").alias("_ms"))
    else:
        rows = events.withWatermark(time, late).select(*columns, time, F.unix_millis(time).alias("_ms"))
    return rows.groupBy(by).applyInPandasWithState(update, f"{by} string, keys string", "held string, last long", "update", "NoTimeout" if idle is None else "EventTimeTimeout")


def latest(rows: DataFrame, by: str) -> DataFrame:
    """The last row that an updating stream emitted for each ``by``."""
    spark, path = rows.sparkSession, folder(rows.sparkSession, "updates")

    def each(batch: DataFrame, number: int) -> None:
        batch.withColumn("_n", F.lit(number)).write.mode("overwrite").parquet(f"{path}/{number}")

    drain(rows, each, "update")
    found = spark.read.parquet(f"{path}/*")
    values = [c for c in found.columns if c not in (by, "_n")]
    return found.groupBy(by).agg(*[F.max_by(c, "_n").alias(c) for c in values])


def with_snapshot(events: DataFrame, advice: DataFrame, key: str) -> DataFrame:
    """A stream joined with a static table of advice; keys without a prediction have 0."""
    return events.join(advice, key, "left").withColumn("advice", F.coalesce("advice", F.lit(0.0)))


def pairs_within(events: DataFrame, time: str, key: str, first: str, second: str, limit: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """(first_id, second_id): events of kind ``second`` at most ``limit`` after one of kind ``first`` with the same key."""
    a = events.where(F.col("event_type") == first).select(F.col("event_id").alias("first_id"), F.col(key).alias("ka"), F.col(time).alias("ta"))
    b = events.where(F.col("event_type") == second).select(F.col("event_id").alias("second_id"), F.col(key).alias("kb"), F.col(time).alias("tb"))
    if events.isStreaming:
        a, b = a.withWatermark("ta", late), b.withWatermark("tb", late)
    return a.join(b, F.expr(f"ka = kb AND tb >= ta AND tb <= ta + INTERVAL {limit}")).select("first_id", "second_id")


def without_repeats(events: DataFrame, time: str, columns: list[str], late: str = "2 hours") -> DataFrame:
    return events.withWatermark(time, late).dropDuplicatesWithinWatermark(columns)


def pane_sketches(events: DataFrame, time: str, key: str, length: str, k: int, salt: str = "s") -> DataFrame:
    """(start, key, w, h): the bottom-k sample of keys of each tumbling pane, with exact counts in the pane."""

    from ..functions.seeds import draw

    counts = events.groupBy(F.window(time, length).alias("span"), F.col(key).cast("string").alias("key")).agg(F.count("*").cast("double").alias("w"))
    rows = counts.select(F.col("span.start").alias("start"), "key", "w", draw(F.col("key"), salt).alias("h"))
    return rows.withColumn("_at", F.row_number().over(W.partitionBy("start").orderBy("h", "key"))).where(F.col("_at") <= k).drop("_at")


def sliding_from_panes(panes: DataFrame, length: str, count: int, k: int) -> DataFrame:
    """(start, key, w): uniform bottom-k samples of windows of ``count`` panes, merged from the panes' sketches.

    A key of a window's sample is in the sample of every pane that holds it, so merging
    loses none, and its counts in the panes add up to that in the window.
    """

    starts = F.explode(F.transform(F.sequence(F.lit(0), F.lit(count - 1)), lambda i: F.col("start") - i * F.expr(f"INTERVAL {length}")))
    spread = panes.select(starts.alias("begin"), "key", "w", "h").groupBy("begin", "key").agg(F.sum("w").alias("w"), F.min("h").alias("h"))
    low = spread.withColumn("_at", F.row_number().over(W.partitionBy("begin").orderBy("h", "key"))).where(F.col("_at") <= k)
    return low.select(F.col("begin").alias("start"), "key", "w")


def running_totals(elements: DataFrame, path: str | None = None) -> tuple[float, float]:
    """(sum of values, estimate of the second moment) of a stream: what certificates for q = 1 and q = 2 need.

    ``path`` as in ``running_sketch``; a stream without a batch has totals of 0.
    """
    spark, path = elements.sparkSession, path or folder(elements.sparkSession, "totals")

    def each(batch: DataFrame, number: int) -> None:
        cells = second_moment_cells(batch)
        mass = batch.agg(F.lit(-1).alias("row"), F.lit(0).cast("bigint").alias("bucket"), F.coalesce(F.sum("value"), F.lit(0.0)).alias("total"))
        part = cells.unionByName(mass)
        if number > 0:
            part = part.unionByName(spark.read.parquet(f"{path}/versions/n={number - 1}")).groupBy("row", "bucket").agg(F.sum("total").alias("total"))
        part.coalesce(1).write.mode("overwrite").parquet(f"{path}/versions/n={number}")

    drain(elements, each, log=f"{path}/log")
    rows = newest(spark, f"{path}/versions")
    if rows is None:
        return 0.0, 0.0
    return rows.where("row = -1").first()["total"], second_moment(rows.where("row >= 0")).first()["estimate"]
