"""Streams give what their batch twins give."""

import time

import pytest
from pyspark.sql import functions as F

from clipforge.operators import scene as S
from clipforge.queries import streams as Q
from clipforge.sources import tables as T
from clipforge.streaming import telemetry as St


@pytest.fixture(scope="module")
def replay(spark, sf, tmp_path_factory):
    """Events in four files, by time."""
    folder = str(tmp_path_factory.mktemp("replay"))
    e = T.load(spark, sf, "events").filter("event_id < 2000")
    for k in range(4):
        e.filter((F.col("event_id") >= k * 500) & (F.col("event_id") < (k + 1) * 500)).coalesce(1).write.mode("append").parquet(folder)
    return folder


def rows(df):
    return sorted(map(tuple, df.collect()))


def batch(spark, sf):
    return T.load(spark, sf, "events").filter("event_id < 2000").withColumn("ts", F.col("ts").cast("timestamp"))


@pytest.mark.parametrize(("size", "slide"), [("1 day", None), ("2 hours", "1 hour")])
def test_windows(spark, sf, replay, size, slide):
    out, _ = St.run_stream(St.stream_phase(St.with_lateness(St.event_stream(spark, replay)), size, slide), f"w{size[0]}", "complete")
    assert rows(out) == rows(St.stream_phase(batch(spark, sf), size, slide))


def test_dedup(spark, sf, replay, tmp_path):
    twice = batch(spark, sf).withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    folder = str(tmp_path / "twice")
    twice.filter("event_id < 300").unionByName(twice.filter("event_id < 300")).coalesce(1).write.parquet(folder)
    out, _ = St.run_stream(St.stream_dedup(St.event_stream(spark, folder)), "once")
    assert out.count() == 300


def test_cuts(spark, sf, replay):
    out, _ = St.run_stream(St.stream_cuts(St.event_stream(spark, replay), 150.0), "cuts")
    f = T.frames(spark, sf).filter("event_id < 2000")
    want = {r["event_id"] for r in S.split_by_delta(f, 150.0).filter("cut").collect()}
    assert {r["event_id"] for r in out.filter("cut").collect()} == want and out.count() == 2000


def test_handoff(spark, sf, replay):
    a = St.event_stream(spark, replay, 4).filter("event_type = 'view'")
    b = St.event_stream(spark, replay, 4).filter("event_type = 'click'")
    out, _ = St.run_stream(St.stream_handoff(a, b), "handoff")
    want = [r for r in rows(Q.QUERIES["handoff_batch"](spark, sf)) if max(r) < 2000]
    assert rows(out) == want


def test_restart_repeats_nothing(spark, replay, tmp_path):
    path, mark = str(tmp_path / "out"), str(tmp_path / "mark")
    for _ in range(2):
        St.run_to_parquet(St.event_stream(spark, replay).select("event_id"), path, mark)
    assert spark.read.parquet(path).count() == 2000


def test_late_rows_are_dropped(spark, tmp_path):
    folder = str(tmp_path / "late")
    for k, rows_ in enumerate(([(1, "2024-01-01 00:00:00"), (2, "2024-01-03 00:00:00")], [(4, "2024-01-03 01:00:00")], [(3, "2024-01-01 00:10:00")])):
        df = spark.createDataFrame(rows_, "event_id bigint, t string").select("event_id", F.col("t").cast("timestamp_ntz").alias("ts"), F.lit(1).cast("bigint").alias("user_id"), F.lit("view").alias("event_type"), F.lit(1.0).alias("value"), F.lit("{}").alias("props"))
        df.coalesce(1).write.mode("append").parquet(folder)
        time.sleep(1.2)  # files are taken in the order of their times
    out, q = St.run_stream(St.stream_phase(St.with_lateness(St.event_stream(spark, folder)), "1 hour"), "late", "update")
    dropped = sum(int(s["numRowsDroppedByWatermark"]) for p in q.recentProgress for s in p["stateOperators"])
    assert dropped == 1 and out.agg(F.sum("n")).collect()[0][0] == 3


@pytest.fixture(scope="module")
def media_files(spark, sf, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("media"))
    T.media_meta(spark, sf).repartition(3).write.mode("append").parquet(folder)
    return folder


def test_gate_and_buckets_of_a_stream(spark, sf, media_files):
    batch_ = T.media_meta(spark, sf)
    stream = lambda: spark.readStream.schema(batch_.schema).option("maxFilesPerTrigger", 1).parquet(media_files)
    gate, _ = St.run_stream(St.stream_gate(stream()), "gate")
    assert rows(gate) == rows(St.stream_gate(batch_)) and 0 < gate.count() < batch_.count()
    pick = lambda df: df.select("media_id", F.col("bucket.id").alias("bucket"))
    bucket, _ = St.run_stream(pick(St.stream_bucket(stream())), "bucket")
    key = lambda r: (r[0], -1 if r[1] is None else r[1])
    assert sorted(map(key, bucket.collect())) == sorted(map(key, pick(St.stream_bucket(batch_)).collect()))


def test_silent_users_are_forgotten(spark, tmp_path):
    folder = str(tmp_path / "silent")
    for k, (user, hour) in enumerate(((1, 0), (2, 1), (2, 40), (2, 80), (1, 81))):
        df = spark.range(1).select(F.lit(k).cast("bigint").alias("event_id"), (F.lit("2024-01-01 00:00:00").cast("timestamp") + F.make_dt_interval(hours=F.lit(hour))).cast("timestamp_ntz").alias("ts"), F.lit(user).cast("bigint").alias("user_id"), F.lit("view").alias("event_type"), F.lit(1000.0 * (k + 1)).alias("value"), F.lit("{}").alias("props"))
        df.coalesce(1).write.mode("append").parquet(folder)
        time.sleep(1.1)
    out, _ = St.run_stream(St.stream_cuts(St.event_stream(spark, folder), 10.0, keep_hours=12), "silent")
    assert [r["cut"] for r in out.orderBy("event_id").collect()] == [False, False, True, True, False]  # the state of user 1 went when the watermark passed it
    long, _ = St.run_stream(St.stream_cuts(St.event_stream(spark, folder), 10.0, keep_hours=1000), "talkative")
    assert [r["cut"] for r in long.orderBy("event_id").collect()] == [False, False, True, True, True]
