"""Closed forms against published values and simulation."""

import pytest

from quorumlab.operators import clock, metrics, theory, training
from quorumlab.sources import tables


def test_expected_counts(spark):
    rows = theory.expected_counts(theory.settings(spark, [(40, 30, 2), (20, 5, 10), (20, 5, 1), (20, 20, 10)])).collect()
    at = {(r["workers"], r["quorum"], r["quota"]): r for r in rows}
    assert at[40, 30, 2]["expected_steps"] == pytest.approx(2.6352, abs=1e-4) and at[40, 30, 2]["uploads_approx"] == pytest.approx(37.132, abs=1e-3)
    assert at[40, 30, 2]["uploads_exact"] == pytest.approx(37.2215, abs=2e-3)
    assert at[20, 5, 10]["expected_steps"] == pytest.approx(7.56773, abs=1e-4) and at[20, 20, 10]["expected_steps"] == pytest.approx(16.77605, abs=1e-4)
    assert at[20, 5, 1]["uploads_approx"] < 5 == at[20, 5, 1]["uploads_clamped"] and at[20, 5, 1]["uploads_exact"] == pytest.approx(5, abs=2e-3)
    assert training.expected_steps(20, 5, 10) == pytest.approx(7.56773, abs=1e-4)


def test_two_hundred_rounds(spark):
    lines = clock.timelines(tables.hashed_durations(spark, 200, 40, 60))
    m = metrics.empirical_means(clock.quorum_schedule(lines, 30, 2)).first()
    assert m["capped"] == 0 and m["mean_steps"] == pytest.approx(2.6352, abs=0.08) and m["mean_uploads"] == pytest.approx(37.22, abs=0.4)


def test_first_step_and_monotone(spark):
    f = theory.expected_first_step(spark, 20).orderBy("s").collect()
    assert f[-1]["logarithm"] is None and f[0]["harmonic"] == pytest.approx(0.05) and all(r["harmonic"] <= r["logarithm"] for r in f[:-1])
    g = theory.monotone_grid(theory.settings(spark, [(20, k, u) for k in (1, 5, 20) for u in (1, 5)])).collect()
    assert all(r[c] is None or r[c] > -1e-9 for r in g for c in r.asDict() if "rise" in c)


def test_bound():
    k = dict(f_start=1.0, f_low=0.0, alpha=0.01, mean_steps=7.5, most_steps=20, smooth=1.0, quorum=5, batch=100, local_var=1.0, global_var=0.5)
    assert theory.gradient_bound(**k, rounds=100) > theory.gradient_bound(**k, rounds=1000)
    assert theory.gradient_bound(**(k | {"global_var": 2.0}), rounds=100) > theory.gradient_bound(**(k | {"global_var": 0.0}), rounds=100)
    assert theory.min_rounds(5, 20, 7.56773, 10) >= 9687
    j = theory.min_rounds(5, 20, 7.56773, 20)
    assert theory.rate_step_size(5, 7.56773, j, 1.0) <= theory.max_step_size(7.56773, 20, 1.0, 5, 20) * (1 + 1e-9)
    assert theory.bound_gap(7.5, **k, rounds=100) < 0
