"""Round clocks: a hand-made timeline, invariants over random settings, schemes against each other."""

import random

import pytest
from pyspark.sql import functions as F

from quorumlab.operators import clock, metrics
from quorumlab.sources import tables

#: Four workers, quorum 3, quota 3: worker 0 is fast, 3 is slow and never finishes a step in time.
HAND = {0: [1, 1, 1, 1, 1, 1], 1: [2, 1, 2, 2, 2, 2], 2: [2, 2, 2, 1, 3, 3], 3: [7, 1, 1, 1, 1, 1]}


def hand(spark):
    rows = [(0, w, k, float(d)) for w, ds in HAND.items() for k, d in enumerate(ds)]
    return clock.timelines(spark.createDataFrame(rows, tables.DURATIONS))


def by_worker(schedule):
    return {r["worker"]: r for r in schedule.collect()}


def test_hand_timeline(spark):
    s = by_worker(clock.quorum_schedule(hand(spark), 3, 3))
    # Quota times: 3, 5, 6 and 9; the third is 6.
    assert {w: r["steps"] for w, r in s.items()} == {0: 6, 1: 3, 2: 3, 3: 0}
    assert {w for w, r in s.items() if r["uploads"]} == {0, 1, 2} and s[0]["round_time"] == 6.0
    assert s[0]["capped"] and not s[1]["capped"]


def test_stragglers_and_ablations(spark):
    lines = hand(spark)
    s = by_worker(clock.quorum_schedule(lines, 2, 3))  # stop at 5
    assert {w: r["steps"] for w, r in s.items()} == {0: 5, 1: 3, 2: 2, 3: 0}
    fast = by_worker(clock.quorum_schedule(lines, 2, 3, keep_partial=False))
    assert {w for w, r in fast.items() if r["uploads"]} == {0, 1} and fast[0]["steps"] == 5
    partial = by_worker(clock.quorum_schedule(lines, 2, 3, keep_surplus=False))
    assert {w: r["steps"] for w, r in partial.items()} == {0: 3, 1: 3, 2: 2, 3: 0}
    assert {w for w, r in partial.items() if r["uploads"]} == {0, 1, 2}
    waits = metrics.work_accounting(clock.quorum_schedule(lines, 2, 3), lines, 3).first()
    assert (waits["surplus"], waits["partial"], waits["cancelled"]) == (2, 2, 2)


def test_acknowledgement_delay_moves_the_stop(spark):
    s = by_worker(clock.quorum_schedule(hand(spark), 3, 3, ack_cost=1.5))
    assert s[0]["round_time"] == 7.5 and s[3]["steps"] == 1


@pytest.mark.parametrize("seed", range(4))
def test_invariants(spark, seed):
    rnd = random.Random(seed)
    m = rnd.randint(2, 12)
    k, u = rnd.randint(1, m), rnd.randint(1, 6)
    lines = clock.timelines(tables.hashed_durations(spark, 5, m, clock.step_cap(4 * u), 1.0, seed)).persist()
    rows = clock.quorum_schedule(lines, k, u).collect()
    assert len(rows) == 5 * m and not any(r["capped"] for r in rows)
    for j in range(5):
        mine = [r for r in rows if r["round_no"] == j]
        acked = [r for r in mine if r["steps"] >= u]
        assert len(acked) == k and min(r["steps"] for r in acked) == u
        assert max(r["ack_time"] for r in acked) == mine[0]["round_time"]
        assert k <= sum(r["uploads"] for r in mine) <= m
        if k == m:
            assert all(r["uploads"] for r in mine)
        if u == 1:
            assert sum(r["uploads"] for r in mine) == k
    schedule = clock.quorum_schedule(lines, k, u)
    assert all(r["by_order"] == r["counted"] for r in metrics.uploads_from_first_steps(lines, schedule).collect())
    times = {r["round_no"]: r["round_time"] for r in metrics.round_summary(schedule).collect()}
    own = {r["round_no"]: r["upload_time"] for r in metrics.upload_time(lines, schedule).collect()}
    assert times == pytest.approx(own)
    wait = {r["round_no"]: r["round_time"] for r in metrics.round_summary(clock.periodic_schedule(lines, u)).collect()}
    assert all(times[j] <= wait[j] for j in times)
    alone = clock.quorum_schedule(lines, k, u, keep_partial=False)
    assert {r["uploads"] for r in metrics.round_summary(alone).collect()} == {k}
    assert all(r["steps"] <= u for r in clock.quorum_schedule(lines, k, u, keep_surplus=False).collect())


def test_stop_grows_with_quorum_and_quota(spark):
    lines = clock.timelines(tables.hashed_durations(spark, 3, 8, 80)).persist()
    stop = lambda k, u: [r["round_time"] for r in metrics.round_summary(clock.quorum_schedule(lines, k, u)).orderBy("round_no").collect()]
    assert all(a <= b for a, b in zip(stop(2, 3), stop(5, 3), strict=True)) and all(a <= b for a, b in zip(stop(2, 3), stop(2, 6), strict=True))


def test_baselines(spark):
    lines = clock.timelines(tables.hashed_durations(spark, 4, 6, 80)).persist()
    s = metrics.round_summary(clock.sampled_schedule(lines, 6, 3, run_id="x")).drop("run_id").collect()
    assert sorted(s) == sorted(metrics.round_summary(clock.periodic_schedule(lines, 3)).drop("run_id").collect())
    sampled = metrics.round_summary(clock.sampled_schedule(lines, 2, 3)).collect()
    assert {(r["uploads"], r["messages"]) for r in sampled} == {(2, 4)}
    random_steps = clock.random_steps_schedule(lines, 4.0).collect()
    assert all(r["steps"] >= 1 and r["weight"] == pytest.approx(1 / r["steps"]) for r in random_steps)
    complete = clock.deadline_schedule(lines, 3.0, 3, True).collect()
    partial = clock.deadline_schedule(lines, 3.0, 3, False).collect()
    assert all(r["steps"] == 3 for r in complete if r["uploads"]) and sum(r["uploads"] for r in partial) >= sum(r["uploads"] for r in complete)
    batches = clock.quorum_batches_schedule(lines, 5)
    assert {r["n"] for r in batches.groupBy("round_no").agg(F.sum("steps").alias("n")).collect()} == {5}
    redundant = clock.redundant_schedule(lines, 6, 2)
    one = metrics.round_summary(clock.periodic_schedule(lines, 1)).agg(F.sum("round_time")).first()[0]
    assert {r["n"] for r in redundant.groupBy("round_no").agg(F.sum("weight").alias("n")).collect()} == {6.0}
    assert metrics.round_summary(clock.redundant_schedule(lines, 6, 1)).agg(F.sum("round_time")).first()[0] == pytest.approx(one)
    slow = clock.timelines(tables.hashed_durations(spark, 12, 4, 80, dist="constant", slow={1: 4.0}))
    shifted = clock.reassign_schedule(slow, 8).groupBy("round_no").agg(F.sum("steps").alias("n")).collect()
    assert {r["n"] for r in shifted} == {32}
    assert clock.reassign_schedule(slow, 8).where("round_no = 11 and worker = 1").first()["steps"] == 2


def test_plans(spark):
    rows = clock.stagewise_rows(3, 0.4, 2, 4)
    assert rows == [(0, 0, 3, 2, 0.4), (1, 4, 11, 4, 0.2), (2, 12, 27, 8, 0.1)]
    assert clock.next_period(10, 10, 0.25, 1.0) == 5 and clock.next_period(5, 10, 0.25, 1.0) == 2 and clock.next_period(1, 10, 1.0, 1.0) == 1
    assert clock.next_period(10, 10, 0.25, 1.0, direction="grow") == 20


def test_async_staleness(spark):
    d = tables.hashed_durations(spark, 1, 3, 20, dist="exponential")
    e = clock.async_events(d).orderBy("version").collect()
    assert [r["version"] for r in e] == list(range(60)) and all(r["staleness"] >= 0 for r in e)
    assert sum(r["staleness"] for r in e[:10]) <= 2 * 10 + 3


def test_ties_rank_by_worker(spark):
    rows = [(0, w, k, 1.0) for w in range(4) for k in range(5)]
    s = by_worker(clock.quorum_schedule(clock.timelines(spark.createDataFrame(rows, tables.DURATIONS)), 2, 2))
    assert s[0]["round_time"] == 2.0 and all(r["steps"] == 2 for r in s.values())


def test_empty_and_missing(spark):
    none = clock.timelines(spark.createDataFrame([], tables.DURATIONS))
    assert clock.quorum_schedule(none, 2, 2).count() == 0 and metrics.round_summary(clock.periodic_schedule(none, 3)).count() == 0
    with pytest.raises(ValueError):
        tables.require(none, tables.DURATIONS)


def test_other_distributions_have_mean_one(spark):
    for dist in ("exponential", "constant", "uniform", "shifted", "erlang2", "pareto"):
        assert tables.hashed_durations(spark, 10, 20, 50, dist=dist).agg(F.avg("dur")).first()[0] == pytest.approx(1, abs=0.05), dist
