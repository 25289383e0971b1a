"""Streams that stop and go on, and state that is forgotten."""

from pyspark.sql import functions as F

from freqemu.functions.frequency import moment
from freqemu.operators import advice as A
from freqemu.streaming import streams as ST


def part(spark, keys):
    return spark.createDataFrame([(k, 1.0) for k in keys], "key string, value double").coalesce(1)


def test_a_sketch_goes_on_where_the_last_run_stopped(spark, tmp_path):
    source, path = str(tmp_path / "in"), str(tmp_path / "state")
    first, second = ["a"] * 5 + ["b", "c"], ["a"] * 3 + ["d"] * 4
    advice = spark.createDataFrame([("a", 5.0), ("d", 2.0)], "key string, advice double")
    part(spark, first).write.mode("append").parquet(source)
    once = ST.running_sketch(ST.stream(spark, source), advice, moment(3), 1, 2, 2, path)
    assert {r.key: r.w for r in once.collect()}["a"] == 5
    part(spark, second).write.mode("append").parquet(source)
    again = ST.running_sketch(ST.stream(spark, source), advice, moment(3), 1, 2, 2, path)
    whole = A.advice_sketch(part(spark, first + second), advice, moment(3), 1, 2, 2)
    shown = lambda df: sorted((r.key, r.w) for r in df.collect())
    assert shown(again) == shown(whole)
    third = ST.running_sketch(ST.stream(spark, source), advice, moment(3), 1, 2, 2, path)
    assert shown(third) == shown(whole)  # nothing new, nothing counted twice


def test_totals_go_on_and_an_empty_stream_has_none(spark, tmp_path):
    source, path = str(tmp_path / "in"), str(tmp_path / "state")
    part(spark, ["a", "a", "b"]).write.parquet(source)
    assert ST.running_totals(ST.stream(spark, source), path)[0] == 3
    part(spark, ["a"]).write.mode("append").parquet(source)
    assert ST.running_totals(ST.stream(spark, source), path)[0] == 4
    hollow = str(tmp_path / "none")
    part(spark, []).where("false").write.parquet(hollow)
    assert ST.running_totals(ST.stream(spark, hollow))[0] == 0


def test_idle_groups_are_forgotten(spark, tmp_path):
    source = str(tmp_path / "in")
    for day, kind in ((1, "old"), (5, "new"), (9, "new"), (12, "new")):
        rows = spark.createDataFrame([(f"2024-01-{day:02d} 00:00:00", kind, "u%d" % day)], "ts string, kind string, user string")
        rows.withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(source)
    found = ST.keyed_sketches(ST.stream(spark, source), "kind", "user", 4, time="ts", idle=24 * 3600 * 1000)
    last = {r.kind: r["keys"] for r in ST.latest(found, "kind").collect()}
    assert set(last) == {"old", "new"} and last["old"] is None and last["new"]
