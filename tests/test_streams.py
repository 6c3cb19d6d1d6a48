"""Streams give what a batch over the same events gives; late rows are dropped and counted."""

import os
import time

import pytest
from pyspark.sql import functions as F

from shoal.streaming import edges as streaming

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string"


@pytest.fixture
def folder(spark, tmp_path):
    """Three files, read one a micro-batch in this order; the last holds two events behind the watermark of the batch before its own."""
    rows = [
        [(1, "2024-01-01 10:00:00", 1, "a"), (2, "2024-01-01 10:05:00", 1, "b"), (3, "2024-01-01 10:01:00", 2, "a")],
        [(4, "2024-01-02 10:00:00", 1, "c"), (5, "2024-01-02 10:00:00", 2, "c"), (6, "2024-01-02 10:00:00", 2, "d")],
        [(7, "2024-01-01 08:00:00", 1, "z"), (8, "2024-01-01 08:00:30", 2, "z"), (9, "2024-01-03 10:00:00", 3, "a")],
    ]
    out = tmp_path / "events"
    out.mkdir()
    for i, part in enumerate(rows):
        df = spark.createDataFrame(part, "event_id long, ts string, user_id long, event_type string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
        df.toPandas().astype({"ts": "datetime64[us]"}).to_parquet(out / f"{i}.parquet", index=False)
        os.utime(out / f"{i}.parquet", (time.time() - 100 + 10 * i,) * 2)
    return str(out)


def test_user_state_over_batches(spark, folder):
    states = streaming.drain(streaming.user_state(streaming.read_stream(spark, folder)), "users")
    assert states.count() > 3  # one row for each user of each micro-batch
    got = {tuple(r) for r in streaming.latest(states).collect()}
    assert got == {(1, 4, 4, "c"), (2, 4, 6, "d"), (3, 1, 9, "a")}


def test_sessions_and_late_rows(spark, folder):
    log = {}
    sessions = streaming.drain(streaming.stream_sessions(streaming.read_stream(spark, folder)), "sessions", log)
    assert log == {"late_rows": 2}
    # the last session of user 3 is still open when the stream ends
    got = {(r["user_id"], str(r["start"]), r["n"]) for r in sessions.collect()}
    assert got == {(1, "2024-01-01 10:00:00", 2), (2, "2024-01-01 10:01:00", 1), (1, "2024-01-02 10:00:00", 1), (2, "2024-01-02 10:00:00", 2)}


def test_activity_equals_batch_without_late_rows(spark, folder):
    log = {}
    got = streaming.drain(streaming.stream_activity(streaming.read_stream(spark, folder)), "activity", log)
    events = spark.read.parquet(folder).where("ts >= '2024-01-01 10:00:00' AND ts < '2024-01-03'")
    want = streaming.stream_activity(events)
    assert log == {"late_rows": 2}
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
