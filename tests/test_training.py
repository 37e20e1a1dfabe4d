"""Models, averaging rules, splits, draws, and both training paths."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from quorumlab.operators import averaging, models, samples, training
from quorumlab.plans.runspec import RunSpec, should_stop
from quorumlab.sources import tables


@pytest.mark.parametrize("model", [models.least_squares(5), models.logistic(5), models.softmax(5, 3), models.mlp(5, 4, 3), models.small_cnn(3)])
def test_gradients_by_finite_differences(model):
    rng = np.random.default_rng(0)
    x = rng.standard_normal((6, model.dims))
    y = rng.standard_normal(6) if model.kind == "least_squares" else rng.integers(0, 2 if model.kind == "logistic" else 3, 6)
    w = model.init(1) + 0.05 * rng.standard_normal(model.size)
    _, g = model.loss_grad(w, x, y)
    assert len(g) == model.size
    for k in rng.choice(model.size, min(model.size, 25), replace=False):
        e = np.zeros(model.size)
        e[k] = 1e-6
        assert g[k] == pytest.approx((model.loss_grad(w + e, x, y)[0] - model.loss_grad(w - e, x, y)[0]) / 2e-6, abs=1e-5)


@pytest.mark.parametrize("model", [models.least_squares(5), models.logistic(5), models.softmax(5, 3), models.mlp(5, 4, 3), models.small_cnn(3)])
def test_squared_gradients_of_samples(model):
    rng = np.random.default_rng(0)
    x, y = rng.standard_normal((6, model.dims)), rng.integers(0, 2, 6)
    w = model.init(1) + 0.05 * rng.standard_normal(model.size)
    want = [(model.loss_grad(w, x[k : k + 1], y[k : k + 1])[1] ** 2).sum() for k in range(6)]
    assert model.sample_grad_sq(w, x, y) == pytest.approx(want)


def test_averaging_rules(spark):
    rows = [(0, 2, [1.0, 4.0]), (1, 4, [3.0, 0.0]), (2, 0, [9.0, 9.0])]
    df = spark.createDataFrame(rows, averaging.LOCALS)
    got = lambda rule, start=None: [r["w"] for r in averaging.average_models(df, rule, start).orderBy("pos").collect()]
    assert got("uniform") == [2.0, 2.0]
    assert got("inverse_model") == pytest.approx([(1 / 2 + 3 / 4) / 0.75, 2 / 0.75])
    start = spark.createDataFrame([(0, 0.0), (1, 0.0)], "pos int, w double")
    local = [[1.0, 4.0], [3.0, 0.0]]
    want = models.average(np.zeros(2), local, [1, 1], [2, 4], "normalised_direction")
    assert got("normalised_direction", start) == pytest.approx(want.tolist())
    for rule in ("uniform", "inverse_model", "normalised_direction"):
        assert models.average(np.ones(2), local, [1, 1], [3, 3], rule) == pytest.approx([2.0, 2.0])
    assert averaging.to_vector(averaging.average_models(df)).first()["w"] == [2.0, 2.0]
    assert {r["block"]: r["w"] for r in averaging.to_blocks(averaging.average_models(df), 1).collect()} == {0: [2.0], 1: [2.0]}


def task(spark, n=101):
    rows = [(i, [float(i % 7), float(i % 3), 1.0], i % 4) for i in range(n)]
    return spark.createDataFrame(rows, "row_id bigint, x array<double>, y int")


@pytest.mark.parametrize("split", ["even_random", "even_by_label"])
def test_splits_are_even_and_complete(spark, split):
    s = samples.SPLITS[split](task(spark), 8).collect()
    assert sorted(r["row_id"] for r in s) == list(range(101))
    sizes = {}
    for r in s:
        sizes.setdefault(r["worker"], []).append(r["pos"])
    assert len(sizes) == 8 and all(sorted(p) == list(range(len(p))) for p in sizes.values())
    assert max(map(len, sizes.values())) - min(map(len, sizes.values())) <= 1
    if split == "even_by_label":
        assert all(len({r["y"] for r in s if r["worker"] == w}) <= 2 for w in sizes)


def test_stored_shards_and_skew(spark, tmp_path):
    s = samples.even_random(task(spark), 4)
    tables.write_shards(s, str(tmp_path / "shards"), 3)
    back = spark.read.parquet(str(tmp_path / "shards"))
    assert sorted(map(str, back.collect())) == sorted(map(str, s.collect()))
    even, skewed = (samples.shard_label_stats(samples.label_skew(task(spark, 400), 8, b)).agg(F.avg("distance")).first()[0] for b in (1.0, 0.05))
    assert even < skewed
    assert samples.fetch(samples.draw_batches(spark.createDataFrame([(0, 0, 2)], "round_no int, worker int, steps int"), s.groupBy("worker").agg(F.count("*").alias("n")), 6, 1), s, 0).count() == 12


def test_split_ignores_partitioning(spark):
    a = samples.even_random(task(spark).repartition(1), 5).collect()
    b = samples.even_random(task(spark).repartition(7), 5).collect()
    assert sorted(a) == sorted(b)


def test_draws_agree_with_numpy(spark):
    schedule = spark.createDataFrame([(0, 0, 2), (0, 1, 1), (3, 1, 0)], "round_no int, worker int, steps int")
    sizes = spark.createDataFrame([(0, 10), (1, 7)], "worker int, n bigint")
    got = {}
    for r in samples.draw_batches(schedule, sizes, 5, 9).collect():
        got.setdefault((r["round_no"], r["worker"], r["step_no"]), {})[r["slot"]] = r["pos"]
    assert set(got) == {(0, 0, 0), (0, 0, 1), (0, 1, 0)}
    for (j, m, u), pos in got.items():
        want = samples.draws_py(9, j, m, u, 5, {0: 10, 1: 7}[m], samples.draw_powers(5))
        assert [pos[k] for k in range(5)] == want.tolist()
    apart = samples.draw_batches(schedule, sizes, 7, 9, "distinct").where("worker = 1").collect()
    assert sorted(r["pos"] for r in apart) == list(range(7))
    ten = samples.draw_batches(schedule, sizes, 10, 9, "distinct").where("worker = 0 and step_no = 1").collect()
    assert sorted(r["pos"] for r in ten) == list(range(10))
    block = samples.draw_batches(schedule, sizes, 5, 9, "block").where("worker = 1").orderBy("slot").collect()
    assert all((b["pos"] - a["pos"]) % 7 == 1 for a, b in zip(block, block[1:], strict=False))


def test_batch_gradients_are_unbiased():
    model, rng = models.softmax(3, 2), np.random.default_rng(2)
    x, y = rng.standard_normal((20, 3)), rng.integers(0, 2, 20)
    w, p = rng.standard_normal(6), samples.draw_powers(50)
    mean = np.mean([model.loss_grad(w, x[d], y[d])[1] for d in (samples.draws_py(1, j, 0, 0, 50, 20, p) for j in range(800))], axis=0)
    assert mean == pytest.approx(model.loss_grad(w, x, y)[1], abs=0.01)


SCHEMES = [
    ("quorum_stop", {}), ("fast_surplus_only", {}), ("straggler_partial_only", {}), ("plain_quorum", {}), ("periodic_average", {}), ("adaptive_period", {"direction": "grow"}),
    ("adaptive_period", {"shrink": 0.5, "interval": 2.0, "halve_every": 1}), ("sampled_average", {"sample": 2}), ("step_normalised", {"mean": 3}), ("random_uniform", {"mean": 3}), ("stagewise", {"length": 1}),
    ("large_batch", {}), ("complete_only", {}), ("complete_and_incomplete", {}), ("quorum_gradient", {}), ("quorum_batches", {}), ("redundant", {}), ("reassign", {}), ("fixed_steps", {}),
]


@pytest.mark.parametrize("scheme, options", SCHEMES)
def test_both_paths_agree(spark, scheme, options):
    t = task(spark, 40)
    spec = RunSpec(scheme=scheme, workers=4, quorum=2, quota=3, batch=4, mean=1.0, rounds=3, target=2.0, options=options)
    a = training.sweep(spark, [spec], t, 4).collect()
    log, w = training.train(spark, spec, t, 4)
    b = log.collect()
    assert len(w) == 3 * 4 and len(a) == len(b) == 3
    for x, y in zip(a, b, strict=True):
        for c in ("period", "round_time", "cum_messages", "uploads", "mean_steps", "max_steps", "step_size", "loss", "accuracy", "grad_sq", "smooth"):
            assert x[c] == (y[c] if y[c] is None else pytest.approx(y[c], rel=1e-7)), (scheme, c)


def test_periods_beyond_the_first_timeline(spark):
    """A growing period ends beyond the steps that were planned at first; the timelines are made longer."""
    spec = RunSpec(scheme="adaptive_period", workers=2, quota=1, batch=4, mean=1.0, rounds=2, target=2.0, options={"mean": 1})
    assert training.cap_of(spec) < 100
    _, planned = training.planned_block(spark, spec.but(scheme="fixed_steps", options={"spread": 1, "least": 150}), 0, 1, 1)
    assert [(r["steps"], r["capped"]) for r in planned[0]] == [(150, False)] * 2


def test_unknown_schemes_raise(spark):
    spec = RunSpec(scheme="no_such")
    with pytest.raises(ValueError, match="unknown scheme"):
        training.sweep(spark, [spec], task(spark, 20), 4)
    with pytest.raises(ValueError, match="unknown scheme"):
        training.train(spark, spec, task(spark, 20), 4)


def test_large_sweeps_take_the_distributed_path(spark, monkeypatch):
    spec = RunSpec(workers=3, quorum=2, quota=2, batch=4, mean=1.0, rounds=2, target=2.0)
    want = training.sweep(spark, [spec], task(spark, 40), 4).collect()
    monkeypatch.setattr(training, "SWEEP_BYTES", 0)
    monkeypatch.setattr(training, "collect_shards", None)  # nothing comes to the driver
    got = training.sweep(spark, [spec], task(spark, 40), 4).collect()
    assert [r["loss"] for r in got] == pytest.approx([r["loss"] for r in want])


def test_stored_runs_go_on(spark, tmp_path):
    store = str(tmp_path / "store")
    spec = RunSpec(scheme="adaptive_period", workers=3, quota=2, batch=4, mean=1.0, rounds=3, target=2.0)
    whole, w = training.train(spark, spec, task(spark, 40), 4)
    training.train(spark, spec, task(spark, 40), 4, store=store)
    # A driver that was lost after round 1: its last state is gone.
    last = spark.read.schema(training.STATE).parquet(store + "/state").where("round_no < 2")
    last.write.parquet(store + "/kept")
    import shutil

    shutil.rmtree(store + "/state")
    shutil.move(store + "/kept", store + "/state")
    log, again = training.train(spark, spec, task(spark, 40), 4, store=store)
    assert again == pytest.approx(w, abs=1e-12)
    assert [(r["round_no"], r["cum_time"]) for r in log.orderBy("round_no").collect()] == [(r["round_no"], pytest.approx(r["cum_time"])) for r in whole.orderBy("round_no").collect()]
    assert training.train(spark, spec, task(spark, 40), 4, store=store)[0].count() == 3


def test_asynchronous_runs():
    rng = np.random.default_rng(5)
    x, y = rng.standard_normal((40, 3)), rng.integers(0, 3, 40)
    shards = [(x[:20], y[:20]), (x[20:], y[20:])]
    spec = RunSpec(scheme="asynchronous", workers=2, batch=5, mean=1.0, rounds=4, target=2.0)
    log = list(training.async_py(spec, shards, (x, y), 3, 3))
    assert [r["cum_messages"] for r in log] == [4, 8, 12, 16] and all(a["cum_time"] < b["cum_time"] for a, b in zip(log, log[1:], strict=False))
    # One worker alone is serial descent, and reads whole models whether it locks or not.
    alone = [list(training.async_py(spec.but(workers=1, scheme=s), [(x, y)], (x, y), 3, 3))[-1]["loss"] for s in training.ASYNCHRONOUS]
    w, model = np.zeros(9), models.softmax(3, 3)
    for n in range(4):
        p = samples.draws_py(0, n, 0, 0, 5, 40, samples.draw_powers(5))
        w = w - 0.1 * model.loss_grad(w, x[p], y[p])[1]
    assert alone == pytest.approx([model.loss_grad(w, x, y)[0]] * 2)
    assert list(training.async_py(spec.but(scheme="lock_free"), shards, (x, y), 3, 3))[-1]["loss"] != log[-1]["loss"]


def test_degenerate_settings(spark):
    rng = np.random.default_rng(5)
    x, y = rng.standard_normal((30, 3)), rng.integers(0, 3, 30)
    model = models.softmax(3, 3)
    one = RunSpec(workers=1, quorum=1, quota=4, batch=6, mean=1.0, rounds=1, target=2.0)
    plan = training.round_py(one, 0, 4)
    assert plan["steps"].tolist() == [4]
    # One worker: the round is a serial chain with the same draws.
    w = model.init()
    for s in range(4):
        p = samples.draws_py(0, 0, 0, s, 6, 30, samples.draw_powers(6))
        w = w - 0.1 * model.loss_grad(w, x[p], y[p])[1]
    log = list(training.run_py(one, [(x, y)], (x, y), 3, 3))
    assert log[0]["loss"] == model.loss_grad(w, x, y)[0]
    # Synchronous single steps average to one step with all batches.
    shards = [(x[:15], y[:15]), (x[15:], y[15:])]
    batches = [(a[p], b[p]) for m, (a, b) in enumerate(shards) for p in [samples.draws_py(0, 0, m, 0, 6, 15, samples.draw_powers(6))]]
    locals_ = [models.local_chain(model, model.init(), [b], 0.1) for b in batches]
    both = (np.concatenate([b[0] for b in batches]), np.concatenate([b[1] for b in batches]))
    assert models.average(None, locals_, [1, 1], [1, 1]) == pytest.approx(-0.1 * model.loss_grad(model.init(), *both)[1])
    full, losses = training.serial_run(model, x, y, 0, 0.5, 20)
    assert losses[-1] < losses[0] and len(full) == 9
    assert len(training.one_shot_run(model, shards, 6, 0.1, 5)) == 9
    events = [(0, 0, 0, 0), (1, 0, 1, 0), (0, 1, 2, 1)]
    for kind in ("whole", "coordinate", "disjoint_blocks"):
        w, worst = training.async_run(model, events, shards, 6, 0.1, consistency=kind, blocks=3)
        assert worst == 1 and np.isfinite(w).all()


def test_resume_gives_the_same_run(spark, small):
    t = samples.language_task(spark, small)
    spec = RunSpec(workers=3, quorum=2, quota=2, batch=8, mean=1.0, rounds=2, target=2.0)
    log, w = training.train(spark, spec, t, 4)
    first = log.where("round_no = 0").first()
    _, half = training.train(spark, spec.but(rounds=1), t, 4)
    _, again = training.train(spark, spec, t, 4, resume=(1, np.array(half), first["cum_time"], first["cum_messages"]))
    assert again == pytest.approx(w, abs=1e-12)


def test_runspec():
    s = RunSpec(seed=3, options={"mean": 4.0})
    assert RunSpec.from_json(s.to_json()) == s and s.run_id != s.but(seed=4).run_id
    row = {"accuracy": 0.5, "round_no": 2, "cum_time": 3.0, "cum_messages": 40}
    assert not should_stop(s, row) and should_stop(s.but(max_time=3.0), row) and should_stop(s.but(max_messages=40), row) and should_stop(s.but(target=0.5), row) and should_stop(s.but(rounds=3), row)


def test_letters(spark):
    df = spark.createDataFrame([("AaBö",), (None,), ("",)], "t string").select(samples.letters(F.col("t")).alias("x"))
    a, b, c = (r["x"] for r in df.collect())
    assert a[0] == 5.0 and a[1] == 2.5 and a[samples.LETTERS.index("ö")] == 2.5 and a[-1] == 1.0
    assert b == c and sum(b) == 1.0 and math.isclose(len(b), 40)
