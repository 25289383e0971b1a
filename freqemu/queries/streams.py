"""Queries over replayed event streams: each equals its batch form, which is its oracle."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.frequency import moment
from ..operators import advice_models as AM
from ..operators.combos import certify
from ..plans.registry import query
from ..sources.tables import load
from ..streaming import streams as ST
from .advice import ROWS, SHOWN, between, event_parts, shown, sketch_ctes
from .sql import u_sql


def instant(c):
    """The instant of a zone-less time read as UTC, whatever the session's zone."""
    return F.convert_timezone(F.lit("UTC"), F.current_timezone(), c).cast("timestamp")


def zoneless(c):
    return F.convert_timezone(F.current_timezone(), F.lit("UTC"), c.cast("timestamp_ntz"))


def _events(spark, d, *columns):
    """The events as a stream of ten files in order of time; ts as a timestamp."""
    rows = load(spark, d, "events").select(*(columns or ("event_id", "ts", "user_id", "event_type", "value"))).withColumn("ts", instant(F.col("ts")))
    return ST.stream(spark, ST.replay(rows, "ts", ST.folder(spark, "events")))


def _user_elements(rows):
    return rows.select(F.col("user_id").cast("string").alias("key"), F.lit(1.0).alias("value"))


@query("st_running_sketch", f"WITH {sketch_ctes(ROWS['events'], 'advice*advice*advice', 2, 16, 16, 'ppswor')} SELECT {SHOWN} FROM sk")
def st_running_sketch(spark, d):
    past, _ = event_parts(spark, d)
    e = load(spark, d, "events").where(between("ts", "2024-01-16", "2024-01-31")).select("ts", "user_id")
    live = _user_elements(ST.stream(spark, ST.replay(e, "ts", ST.folder(spark, "now"))))
    return shown(ST.running_sketch(live, AM.past_frequency(past), moment(3), 2, 16, 16))


@query("st_tumbling", "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type, CAST(count(*) AS BIGINT) AS w FROM events GROUP BY 1, 2")
def st_tumbling(spark, d):
    rows = ST.collected(ST.windowed_frequencies(_events(spark, d), "ts", "event_type", "1 day"), "complete")
    return rows.withColumn("start", zoneless(F.col("start")))


@query("st_sliding", "SELECT CAST(date_trunc('hour', ts) - INTERVAL 1 HOUR * i AS TIMESTAMP) AS start, CAST(count(*) AS BIGINT) AS w FROM events, (SELECT unnest(range(0, 3)) AS i) x GROUP BY 1")
def st_sliding(spark, d):
    live = _events(spark, d).withColumn("all", F.lit(1))
    rows = ST.collected(ST.windowed_frequencies(live, "ts", "all", "3 hours", "1 hour"), "complete")
    return rows.select(zoneless(F.col("start")).alias("start"), "w")


@query(
    "st_session",
    """SELECT user_id, min(ts) AS start, CAST(count(*) AS BIGINT) AS w FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (
    SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR > ts THEN 0 ELSE 1 END AS fresh FROM events) a) b GROUP BY user_id, g""",
)
def st_session(spark, d):
    rows = ST.collected(ST.session_frequencies(_events(spark, d), "ts", "user_id", "6 hours"), "complete")
    return rows.select("user_id", zoneless(F.col("start")).alias("start"), "w")


@query(
    "st_watermark",
    """SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type, CAST(count(*) AS BIGINT) AS w FROM events
    WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 2 HOUR GROUP BY 1, 2""",
)
def st_watermark(spark, d):
    """Days closed by the watermark, each once: append mode holds back what may still change.

    The first day's events come once more at the end, too late to count.
    """
    rows = load(spark, d, "events").select("ts", "event_type").withColumn("ts", instant(F.col("ts")))
    path = ST.replay(rows, "ts", ST.folder(spark, "events"))
    first = rows.agg(F.min("ts").alias("first"))
    rows.crossJoin(F.broadcast(first)).where("ts < first + INTERVAL 1 DAY").drop("first").coalesce(1).write.mode("append").parquet(path)
    rows = ST.collected(ST.windowed_frequencies(ST.stream(spark, path), "ts", "event_type", "1 day", late="2 hours"), "append")
    return rows.withColumn("start", zoneless(F.col("start")))


@query("st_keyed_sketch", f"SELECT event_type, string_agg(key, ',' ORDER BY u, key) AS keys FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY u, key) AS rn FROM (SELECT DISTINCT event_type, CAST(user_id AS VARCHAR) AS key, {u_sql(key='CAST(user_id AS VARCHAR)')} AS u FROM events) a) b WHERE rn <= 12 GROUP BY 1")
def st_keyed_sketch(spark, d):
    return ST.latest(ST.keyed_sketches(_events(spark, d), "event_type", "user_id", 12), "event_type")


@query("st_static_join", "SELECT CAST(e.user_id AS BIGINT) AS user_id, CAST(count(*) AS BIGINT) AS n, CAST(max(a.n) AS BIGINT) AS advice FROM events e LEFT JOIN (SELECT user_id, count(*) AS n FROM events WHERE ts < TIMESTAMP '2024-01-16 00:00:00' GROUP BY 1) a ON a.user_id = e.user_id GROUP BY 1")
def st_static_join(spark, d):
    advice = load(spark, d, "events").where(between("ts", "2024-01-01", "2024-01-16")).groupBy("user_id").agg(F.count("*").cast("double").alias("advice"))
    rows = ST.collected(ST.with_snapshot(_events(spark, d), advice, "user_id").select("user_id", "event_id", "advice"))
    return rows.groupBy("user_id").agg(F.count("*").alias("n"), F.max("advice").cast("bigint").alias("advice"))


_KINDS = "(SELECT event_type AS k, row_number() OVER (ORDER BY event_type) AS i FROM (SELECT DISTINCT event_type FROM events) x)"


@query("st_stream_join", f"SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 3 HOUR WHERE a.event_type = (SELECT k FROM {_KINDS} q WHERE i = 1) AND b.event_type = (SELECT k FROM {_KINDS} q WHERE i = 2)")
def st_stream_join(spark, d):
    kinds = sorted(r[0] for r in load(spark, d, "events").select("event_type").distinct().collect())
    return ST.collected(ST.pairs_within(_events(spark, d), "ts", "user_id", kinds[0], kinds[1], "3 hours", "1 hour"))


@query("st_dedupe", "SELECT CAST(count(*) AS BIGINT) AS n FROM (SELECT DISTINCT event_id FROM events) x")
def st_dedupe(spark, d):
    rows = load(spark, d, "events").select("event_id", "ts").withColumn("ts", instant(F.col("ts")))
    twice = rows.unionByName(rows.where("event_id % 3 = 0"))
    live = ST.stream(spark, ST.replay(twice, "ts", ST.folder(spark, "twice")))
    return ST.collected(ST.without_repeats(live, "ts", ["event_id"]).select("event_id")).agg(F.count("*").alias("n"))


_PANE = "INTERVAL 1 DAY"


@query(
    "st_pane_merge",
    f"""SELECT start, key, CAST(w AS BIGINT) AS w FROM (SELECT *, row_number() OVER (PARTITION BY start ORDER BY h, key) AS rn FROM (
    SELECT CAST(date_trunc('day', ts) - {_PANE} * i AS TIMESTAMP) AS start, CAST(user_id AS VARCHAR) AS key, count(*) AS w, min(-ln(1 - {u_sql(key='CAST(user_id AS VARCHAR)')})) AS h
    FROM events, (SELECT unnest(range(0, 3)) AS i) x GROUP BY 1, 2) a) b WHERE rn <= 10""",
)
def st_pane_merge(spark, d):
    e = load(spark, d, "events").select("user_id", instant(F.col("ts")).alias("ts"))
    panes = ST.pane_sketches(e, "ts", "user_id", "1 day", 10)
    rows = ST.sliding_from_panes(panes, "1 day", 3, 10)
    return rows.select(zoneless(F.col("start")).alias("start"), "key", F.col("w").cast("bigint").alias("w"))


@query("st_certificate")
def st_certificate(spark, d):
    """Certificates of samples of a stream: q = 1 with the running total, q = 2 with the running sketch of squares."""
    from ..operators.bottomk import ppswor

    mass, squares = ST.running_totals(_user_elements(_events(spark, d)))
    w = load(spark, d, "events").groupBy(F.col("user_id").cast("string").alias("key")).agg(F.count("*").cast("double").alias("w"))
    rows = [certify(ppswor(w, 32, q), q, norm, 32).withColumn("q", F.lit(q)) for q, norm in ((1, mass), (2, squares))]
    return rows[0].unionByName(rows[1])
