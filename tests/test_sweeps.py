"""Sweeps over many samples: all runs share a round's passes, and give the log of the small path."""

import time

import numpy as np
import pytest

from quorumlab.functions import rng
from quorumlab.operators import lockstep, models, training
from quorumlab.plans.runspec import RunSpec
from tests.test_training import SCHEMES, task

BASE = RunSpec(workers=4, quorum=2, quota=3, batch=4, mean=1.0, rounds=3, target=2.0)
COLUMNS = ("round_no", "period", "round_time", "cum_time", "cum_messages", "uploads", "mean_steps", "max_steps", "step_size", "loss", "accuracy", "grad_sq", "smooth")


def by_run(log):
    return {(r["run_id"], r["round_no"]): r for r in log.collect()}


def agree(a, b, columns=COLUMNS):
    assert a.keys() == b.keys()
    for k in a:
        for c in columns:
            assert a[k][c] == (b[k][c] if b[k][c] is None else pytest.approx(b[k][c], rel=1e-7)), (k, c)


def test_all_runs_together_agree_with_runs_alone(spark, monkeypatch):
    """Every scheme, the asynchronous ones too, both splits and several numbers of workers, in blocks much smaller than a piece."""
    specs = [BASE.but(scheme=s, options=o) for s, o in [*SCHEMES, ("asynchronous", {}), ("lock_free", {"blocks": 3})]]
    specs += [BASE.but(split="even_by_label", workers=w, quorum=1, seed=w, eval_every=2, rounds=4) for w in (1, 3)]
    t = task(spark, 60)
    want = by_run(training.sweep(spark, specs, t, 4))
    monkeypatch.setattr(training, "SWEEP_BYTES", 0)
    monkeypatch.setattr(training, "collect_shards", None)  # nothing comes to the driver
    monkeypatch.setattr(lockstep, "BLOCK_ROWS", 5)
    agree(by_run(training.sweep(spark, specs, t, 4)), want)


def test_only_measures_that_are_read(spark, monkeypatch):
    t, specs = task(spark, 40), [BASE, BASE.but(scheme="adaptive_period", options={"direction": "grow"}), BASE.but(target=0.0)]
    want = by_run(training.sweep(spark, specs, t, 4))
    monkeypatch.setattr(training, "SWEEP_BYTES", 0)
    got = by_run(training.sweep(spark, specs, t, 4, ()))
    agree(got, want, [c for c in COLUMNS if c not in ("loss", "grad_sq", "smooth")])
    assert len(got) == 3 + 3 + 1  # a run that is at its target ends; the others go on
    agree(by_run(training.sweep(spark, specs, t, 4, ("loss",))), want, [c for c in COLUMNS if c not in ("grad_sq", "smooth")])


@pytest.mark.parametrize("model", [models.least_squares(5), models.logistic(5), models.softmax(5, 3), models.mlp(5, 4, 3), models.small_cnn(3)])
def test_loss_alone(model):
    rng = np.random.default_rng(0)
    x = rng.standard_normal((6, model.dims))
    y = rng.standard_normal(6) if model.kind == "least_squares" else rng.integers(0, 2 if model.kind == "logistic" else 3, 6)
    w = model.init(1) + 0.05 * rng.standard_normal(model.size)
    assert model.loss(w, x, y) == pytest.approx(model.loss_grad(w, x, y)[0], rel=1e-12)


def test_a_round_is_one_pass(spark, monkeypatch):
    """All of a round's chains and the scores of the round before share a job: one more than rounds, where it was two a round."""
    monkeypatch.setattr(training, "SWEEP_BYTES", 0)
    passes = []
    monkeypatch.setattr(spark.sparkContext, "union", lambda rdds, union=spark.sparkContext.union: passes.append(len(rdds)) or union(rdds))
    training.sweep(spark, [BASE.but(rounds=5), BASE.but(rounds=3, seed=1)], task(spark, 40), 4, ("loss",))
    assert len(passes) == 5 + 1


def test_models_side_by_side():
    """Chains of different lengths, and scores with equal ones and an unknown label, as for each model alone."""
    rng = np.random.default_rng(0)
    model, steps, rates = models.softmax(5, 3), [2, 0, 4, 1], [0.1, 0.2, 0.3, 0.4]
    ws = [rng.standard_normal(model.size) for _ in range(3)] + [np.zeros(model.size)]
    xs, ys, begins = rng.standard_normal((7, 6, 5)), rng.integers(-1, 3, (7, 6)), [0, 2, 2, 6]
    got = models.softmax_chains(ws, xs, ys, begins, steps, rates, 5, 3)
    for w, b, n, rate, g in zip(ws, begins, steps, rates, got, strict=True):
        np.testing.assert_allclose(g, models.local_chain(model, w, [(xs[k], ys[k]) for k in range(b, b + n)], rate), rtol=1e-12)
    x, y = xs.reshape(-1, 5), ys.ravel()
    runs, wide, classes, rest = lockstep.widen([(k, model, w, False) for k, w in enumerate(ws)] + [(9, model, ws[0], True)])
    assert runs == [0, 1, 2, 3] and [e[0] for e in rest] == [9]
    for held in (True, False):
        total = {}
        lockstep.add_scores(total, (runs, wide, classes, rest), held, x, y)
        for k, w in enumerate(ws):
            n, v = total[k, held]
            assert n == len(y) and v[0] == pytest.approx((model.predict(w, x) == y).sum() if held else model.loss(w, x, y) * len(y), rel=1e-12)


def test_a_round_has_no_more_tasks_than_cores_for_each_split(spark, monkeypatch):
    """Several pieces share a task where there are more of them than cores; blocks stay of one piece each."""
    monkeypatch.setattr(training, "SWEEP_BYTES", 0)
    specs, t, cores = [BASE.but(workers=3 * spark.sparkContext.defaultParallelism)], task(spark, 120), spark.sparkContext.defaultParallelism
    tasks = []
    monkeypatch.setattr(spark.sparkContext, "union", lambda rdds, union=spark.sparkContext.union: tasks.append([r.getNumPartitions() for r in rdds]) or union(rdds))
    got = by_run(training.sweep(spark, specs, t, 4))
    assert all(n <= cores for ns in tasks for n in ns)
    monkeypatch.setattr(training, "SWEEP_BYTES", 1 << 20)
    agree(got, by_run(training.sweep(spark, specs, t, 4)))


def test_runs_share_the_durations_of_a_seed(spark, monkeypatch):
    """A duration is hashed once for all runs of its seed, though they ask for timelines of different lengths; the values are those of each alone."""
    monkeypatch.setattr(training, "SWEEP_BYTES", 0)
    monkeypatch.setattr(training, "UNIT_DURATIONS", {}, raising=False)
    asked = []
    monkeypatch.setattr(rng, "hash48_py", lambda *key, hash48=rng.hash48_py: asked.append(key) or hash48(*key))
    specs = [BASE.but(quorum=k, quota=u, seed=seed) for k, u in ((1, 3), (4, 3), (2, 40)) for seed in (0, 1)]
    training.sweep(spark, specs, task(spark, 40), 4, ()).count()
    durations = [key for key in asked if key[1] == "dur"]
    assert len(durations) == len(set(durations)) > 0
    monkeypatch.setattr(training, "UNIT_DURATIONS", {})
    monkeypatch.setattr(training, "KEPT_ROUNDS", 1)
    for cap in (7, 3, 50):
        for seed in (0, 1):
            h = np.array([[rng.hash48_py(seed, "dur", 2, m, u) for u in range(cap)] for m in range(BASE.workers)], float)
            assert (training.durations_py(BASE.but(seed=seed, mean=0.3), 2, cap) == -np.log((h + 0.5) / rng.SPACE) * 0.3).all()
    assert len(training.UNIT_DURATIONS) == 1


def test_runs_share_the_mini_batches_of_a_seed(monkeypatch):
    """Runs of one seed and batch size draw a step's rows once; the results are those of each run alone."""
    asked = []
    monkeypatch.setattr(lockstep.tasks, "draws_py", lambda *a, draws=lockstep.tasks.draws_py: asked.append(a[:5]) or draws(*a))
    gen = np.random.default_rng(0)
    blocks = [(0, 1, 0, gen.standard_normal((7, 5)), gen.integers(0, 3, 7)), (0, 1, 7, gen.standard_normal((4, 5)), gen.integers(0, 3, 4))]
    softmax, mlp = models.softmax(5, 3), models.mlp(5, 4, 3)
    steps = lambda n: {1: [(2, 1, s) for s in range(n)]}
    kinds = [(BASE, softmax, 3), (BASE, softmax, 5), (BASE.but(seed=1), softmax, 2), (BASE.but(batch=6), softmax, 2), (BASE, mlp, 4), (BASE.but(scheme="large_batch"), softmax, 1), (BASE, softmax, 0)]
    runs = [(nth, spec, model, gen.standard_normal(model.size), 0.1, steps(n)) for nth, (spec, model, n) in enumerate(kinds)]
    found = lambda own: {nth: (n, w) for nth, _, n, w in lockstep.chains({"sizes": {0: {1: 11}}, "runs": {0: own}}, blocks)}
    together = found(runs)
    assert len(asked) == len(set(asked)) == 5 + 2 + 2
    assert together.keys() == {0, 1, 2, 3, 4, 5}
    for run in runs[:-1]:
        n, w = found([run])[run[0]]
        assert together[run[0]][0] == n
        np.testing.assert_allclose(together[run[0]][1], w, rtol=1e-12)


def test_groups_are_packed_side_by_side(spark, monkeypatch):
    """A group with few pieces doesn't hold up the others: each waits here until the other one has begun."""
    monkeypatch.setattr(training, "SWEEP_BYTES", 0)
    begun, split = [], lockstep.tasks.SPLITS["even_random"]

    def wait(samples, workers):
        begun.append(workers)
        until = time.time() + 20
        while len(begun) < 2 and time.time() < until:
            time.sleep(0.01)
        assert len(begun) == 2
        return split(samples, workers)

    monkeypatch.setitem(lockstep.tasks.SPLITS, "even_random", wait)
    specs, t = [BASE, BASE.but(workers=1, quorum=1)], task(spark, 40)
    got = by_run(training.sweep(spark, specs, t, 4))
    monkeypatch.setitem(lockstep.tasks.SPLITS, "even_random", split)
    monkeypatch.setattr(training, "SWEEP_BYTES", 1 << 20)
    agree(got, by_run(training.sweep(spark, specs, t, 4)))
