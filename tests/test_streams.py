from __future__ import annotations

import pytest

from coverjoin.streaming import streams


@pytest.fixture(scope="module")
def events(spark, tmp_path_factory):
    at = tmp_path_factory.mktemp("events")
    spark.sql("SELECT id AS event_id, timestamp_seconds(id * 720) AS ts, id % 3 AS user_id, 'x' AS event_type FROM range(40)").coalesce(1).write.parquet(f"{at}/events.parquet")
    return str(at)


def _stream(spark, at):
    s = spark.readStream.schema("event_id long, ts timestamp, user_id long, event_type string").parquet(f"{at}/events.parquet")
    return s


def test_drained_rows_stay_out_of_the_driver(spark, events):
    got = streams.drain(_stream(spark, events).select("event_id", "user_id"), "drained")
    assert "parquet" in got._jdf.queryExecution().toString().lower() and "drained" not in {t.name for t in spark.catalog.listTables()}
    assert sorted(map(tuple, got.collect())) == [(i, i % 3) for i in range(40)]


def test_sessions_and_complete_mode(spark, events):
    got = streams.drain(streams.sessions(_stream(spark, events)), "sessions")  # one event in 30 minutes: a session each
    assert all(r["n_events"] == 1 for r in got.collect()) and got.count() > 20
    n = streams.drain(streams.tumbling(_stream(spark, events), "1 hour"), "hours", "complete").collect()
    assert sum(r["n_events"] for r in n) == 40 and len(n) == 8


def test_a_stream_without_rows(spark, events):
    s = _stream(spark, events).filter("event_id < 0")
    assert streams.drain(s.select("event_id"), "none").count() == 0
    assert streams.drain(streams.tumbling(s), "nothing", "complete").count() == 0
