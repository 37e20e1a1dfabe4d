"""Profiles, stream joins and output modes, and the file formats."""

import datetime as dt
import random

import pytest

from quorumlab.operators import clock, profile
from quorumlab.sources import tables
from quorumlab.streaming import clock as live


def test_recent_steps_against_all_pairs(spark):
    r = random.Random(3)
    at = [dt.datetime(2024, 1, 1) + dt.timedelta(seconds=r.choice([0, 599, 600, 601, 1200, 1800, r.randrange(5000)])) for _ in range(120)]
    rows = [(k, 0 if k % 3 else 1, t) for k, t in enumerate(at)] + [(500, 0, None)]
    got = profile.recent_steps(spark.createDataFrame(rows, "event_id int, worker int, ts timestamp_ntz"), 600).collect()
    want = {k: sum(v == w and b is not None and dt.timedelta(0) <= t - b <= dt.timedelta(seconds=600) for _, v, b in rows) for k, w, t in rows if t}
    assert {g.event_id: g.recent for g in got} == want


def test_placings_without_a_quorum(spark):
    lines = clock.timelines(tables.hashed_durations(spark, 1, 4, 3))
    assert {r.kth_ack for r in profile.placings(lines, 2, 9).collect()} == {None}


def test_cogrouped_chains_skip_idle_workers(spark):
    s = spark.createDataFrame([(0, 0, 1, 1.0, 4.0), (0, 0, 0, 1.0, 2.0), (0, 1, 0, 1.0, 2.0), (0, 2, 0, 1.0, 2.0)], "round_no int, worker int, step_no int, x double, y double")
    plan = spark.createDataFrame([(0, 0, 2), (0, 1, 0)], "round_no int, worker int, steps int")
    assert [tuple(r) for r in profile.cogrouped_chains(s, plan, 0.5).collect()] == [(0, 0, 2, 2.5)]


def test_main_labels_of_empty_and_null(spark):
    rows = spark.createDataFrame([("a", "x")] * 9 + [("a", "y"), ("a", None), (None, "z")], "g string, l string")
    assert {r.g: r.main for r in profile.main_labels(rows, "g", "l", 2).collect()} == {"a": {"x": 9}, None: {"z": 1}}
    assert profile.main_labels(rows.limit(0), "g", "l", 2).count() == 0


@pytest.mark.parametrize("fmt", tables.FORMATS)
def test_formats_round_trip(spark, tmp_path, fmt):
    log = spark.createDataFrame([("r", 0, 1.5), ("r", 1, None)], "run_id string, round_no int, time double")
    tables.write_log(log, str(tmp_path / fmt), fmt)
    assert sorted(tables.load(spark, fmt, str(tmp_path / fmt), log.schema).select(log.columns).collect(), key=str) == sorted(log.collect(), key=str)


def test_stream_joins(spark, tmp_path):
    t0 = dt.datetime(2024, 1, 1)
    acks = spark.createDataFrame([(0, 1, t0 + dt.timedelta(minutes=5)), (0, 2, t0 + dt.timedelta(hours=3)), (1, 1, t0)], "round_no int, worker int, ts timestamp")
    starts = spark.createDataFrame([(0, t0)], "round_no int, ts timestamp")
    acks.write.parquet(str(tmp_path / "acks"))
    starts.write.parquet(str(tmp_path / "starts"))
    read = lambda n, s: spark.readStream.schema(s.schema).parquet(str(tmp_path / n)).withWatermark("ts", "1 hour")
    names = spark.createDataFrame([(1, "fast")], "worker int, name string")

    def run(df, name):
        q = df.writeStream.format("memory").queryName(name).option("checkpointLocation", str(tmp_path / f"state-{name}")).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.table(name).collect()

    assert [r.worker for r in run(live.pair(read("starts", starts), read("acks", acks)), "paired")] == [1]
    assert {r.name for r in run(live.enrich(read("acks", acks), names), "enriched")} == {"fast"}


def test_unknown_output_mode(spark, small):
    with pytest.raises(ValueError):
        live.hourly_to_end(spark, f"{small}/events.parquet*", 20, "append")
