"""Training runs: one Spark job for each round, or whole runs as tasks of a sweep.

Both paths use the same hashed durations, draws and samples, so they give the same log. The distributed
path fetches only the rows that finished steps draw; a round is one job that sends the model out as a broadcast and
brings back one local model (or gradient) for each uploader. The sweep path suits small models: data up to a checked
size is broadcast once, and every (setting, seed) is a task of its own; over larger data all runs share each round's passes (``lockstep.py``).
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quorumlab.functions import rng
from quorumlab.operators import clock, models, samples as tasks
from quorumlab.plans.runspec import RunSpec, should_stop
from quorumlab.sources import tables

LOG = (
    "run_id string, scheme string, split string, seed int, quorum int, quota int, workers int, round_no int, period int, round_time double, cum_time double, messages bigint, cum_messages bigint, "
    "uploads int, mean_steps double, max_steps int, step_size double, loss double, accuracy double, grad_sq double, smooth double"
)
#: The measures of a log that an evaluation makes.
MEASURES = ("loss", "accuracy", "grad_sq", "smooth")
#: Bytes of samples up to which a sweep broadcasts them. Each Python worker holds a copy, and each run passes over it alone.
SWEEP_BYTES = 16 << 20
#: Rounds planned and fetched at a time.
BLOCK = 10

QUORUM = {"quorum_stop": (True, True), "fast_surplus_only": (False, True), "straggler_partial_only": (True, False), "plain_quorum": (False, False), "quorum_gradient": (False, False)}
RANDOM = ("step_normalised", "random_uniform")
#: Schemes whose uploads are gradients at the round's model; the others upload models.
GRADIENTS = ("large_batch", "quorum_batches", "redundant")


def quota_of(spec: RunSpec) -> int:
    return 1 if spec.scheme == "quorum_gradient" else spec.quota


def stages_of(spec: RunSpec) -> list[tuple]:
    """The stages of a stage-wise run: each halves the step and multiplies period and length; the last has no end."""
    o = spec.options
    return clock.stagewise_rows(int(o.get("stages", 5)), spec.step_size, spec.quota, int(o.get("length", 4)), int(o.get("growth", 2)))


def stage_at(spec: RunSpec, round_no: int) -> tuple:
    return next((s for s in stages_of(spec) if round_no <= s[2]), stages_of(spec)[-1])


def step_size_at(spec: RunSpec, round_no: int) -> float:
    """Stage-wise runs shrink the step by stage; any other run halves it every ``halve_every`` rounds, if that is given."""
    if spec.scheme == "stagewise":
        return stage_at(spec, round_no)[4]
    every = int(spec.options.get("halve_every", 0))
    return spec.step_size / 2 ** (round_no // every) if every else spec.step_size


class Period:
    """The number of local steps of a round: fixed, by stage, or adapted to the loss. The adaptive rule acts at evaluations at least
    ``interval`` of simulated time apart; ``shrink``, ``direction`` and ``step_power`` are those of ``clock.next_period``."""

    def __init__(self, spec: RunSpec, state: tuple | None = None):
        self.spec = spec
        self.value, self.loss0, self.since = state or (spec.quota, None, 0.0)

    @property
    def state(self) -> tuple:
        return self.value, self.loss0, self.since

    def of(self, round_no: int) -> int:
        return stage_at(self.spec, round_no)[3] if self.spec.scheme == "stagewise" else self.value

    def learn(self, loss: float, time: float, round_no: int) -> None:
        o = self.spec.options
        if self.spec.scheme != "adaptive_period":
            return
        self.loss0 = self.loss0 or loss
        if time - self.since >= float(o.get("interval", 0.0)):
            ratio = self.spec.step_size / step_size_at(self.spec, round_no + 1)
            scaled = loss * ratio ** float(o.get("step_power", 1.0))
            self.value, self.since = clock.next_period(self.value, self.spec.quota, scaled, self.loss0, float(o.get("shrink", 1.0)), str(o.get("direction", "shrink"))), time


def make_model(spec: RunSpec, dims: int, classes: int) -> models.Model:
    return models.Model(spec.model, dims, classes, int(spec.options.get("hidden", 16)))


@cache
def expected_steps(workers: int, quorum: int, quota: int) -> float:
    """Expected stop time in mean durations, by quadrature; for choosing caps and for measures."""
    import numpy as np

    t_max = quota + 14 * math.sqrt(quota) + 40
    t = (np.arange(20_000) + 0.5) * t_max / 20_000
    term, tail = np.exp(-t), np.zeros_like(t)
    for i in range(quota):
        tail += term
        term = term * t / (i + 1)
    q = np.clip(1 - tail, 0, 1)
    late = np.zeros_like(t)
    for i in range(quorum):  # fewer than `quorum` have finished
        late += math.comb(workers, i) * q**i * np.clip(tail, 0, 1) ** (workers - i)
    return float(late.sum() * t_max / 20_000)


def cap_of(spec: RunSpec, period: int | None = None) -> int:
    """Steps of a timeline that are practically enough; where they are not, timelines are planned again at twice the length."""
    longest = float(spec.options.get("mean", 10)) * 12 if spec.scheme in RANDOM else 0
    base = expected_steps(spec.workers, spec.workers, max(quota_of(spec), 1)) if spec.scheme in QUORUM else float(max(period or 1, spec.quota))
    return int(max(clock.step_cap(base), longest))


# --- the clock outside Spark, for sweeps ----------------------------------------------------------------------------


#: Durations of unit mean by (seed, round, workers), for the runs of a sweep that share them: the last of them, as far as a run has asked.
UNIT_DURATIONS: dict[tuple[int, int, int], object] = {}
KEPT_ROUNDS = 256


def durations_py(spec: RunSpec, round_no: int, cap: int):
    """The same hashed durations as ``hashed_durations``: workers x cap."""
    import numpy as np

    key = spec.seed, round_no, spec.workers
    unit = UNIT_DURATIONS.get(key, np.empty((spec.workers, 0)))
    if (have := unit.shape[1]) < cap:
        h = np.array([[rng.hash48_py(spec.seed, "dur", round_no, m, u) for u in range(have, cap)] for m in range(spec.workers)], float)
        unit = UNIT_DURATIONS[key] = np.concatenate([unit, -np.log((h + 0.5) / rng.SPACE)], axis=1)
        if len(UNIT_DURATIONS) > KEPT_ROUNDS:
            UNIT_DURATIONS.pop(next(iter(UNIT_DURATIONS)))
    return unit[:, :cap] * spec.mean


def round_py(spec: RunSpec, round_no: int, period: int) -> dict:
    """steps, up (mask of uploads), draw (mini-batches used of each piece), time, down; the semantics of the DataFrame clocks."""
    import numpy as np

    m, k, u, s = spec.workers, spec.quorum, quota_of(spec), spec.scheme
    every = np.ones(m, bool)

    def grown(enough, cap: int):
        """Completion times, long enough for a condition on them."""
        while not enough(done := durations_py(spec, round_no, cap).cumsum(axis=1)):
            cap *= 2
        return done

    def plan(steps, up, time, draw=None, down=m) -> dict:
        return {"steps": steps, "up": up, "draw": np.where(up, steps, 0) if draw is None else draw, "time": float(time), "down": down}

    if s in QUORUM:
        partial, surplus = QUORUM[s]
        at = lambda done: done[np.lexsort((np.arange(m), done[:, u - 1]))[k - 1], u - 1]
        done = grown(lambda d: (d[:, -1] > at(d)).all(), clock.step_cap(float(u)) if k < m else cap_of(spec))
        stop = at(done)
        steps = (done <= stop).sum(axis=1)
        steps = steps if surplus else np.minimum(steps, u)
        return plan(steps, steps >= 1 if partial else done[:, u - 1] <= stop, stop)
    if s in ("complete_only", "complete_and_incomplete"):
        deadline = deadline_of(spec)
        steps = (durations_py(spec, round_no, u).cumsum(axis=1) <= deadline).sum(axis=1)
        return plan(steps, steps == u if s == "complete_only" else steps >= 1, deadline)
    if s == "quorum_batches":
        done = durations_py(spec, round_no, k).cumsum(axis=1)  # only a worker's first K batches can be among the first K
        order = np.lexsort((np.tile(np.arange(k), m), np.repeat(np.arange(m), k), done.ravel()))[:k]
        steps = np.bincount(order // k, minlength=m)
        return plan(steps, steps >= 1, done.ravel()[order[-1]])
    if s == "redundant":
        r = int(spec.options.get("replication", 2))
        done = durations_py(spec, round_no, r).cumsum(axis=1)
        held = np.stack([[done[(p + j) % m, j] for j in range(r)] for p in range(m)])  # piece p is step j of worker p + j
        owner = np.array([min(((p + j) % m for j in range(r)), key=lambda w, p=p: (held[p, (w - p) % m], w)) for p in range(m)])
        stop = held.min(axis=1).max()
        return plan((done <= stop).sum(axis=1), np.isin(np.arange(m), owner), stop, np.ones(m, int))
    if s in RANDOM:
        mean = float(spec.options.get("mean", 10))
        h = np.array([rng.hash48_py(spec.seed, "steps", round_no, w) for w in range(m)], float)
        steps = np.maximum(1, np.ceil(-np.log((h + 0.5) / rng.SPACE) * mean)).astype(int)
    elif s == "sampled_average":
        size = int(spec.options.get("sample", m))
        order = sorted(range(m), key=lambda w: (rng.hash48_py(spec.seed, "sample", round_no, w), w))
        every = np.isin(np.arange(m), order[:size])
        steps = np.where(every, u, 0)
    elif s == "reassign":
        steps = reassigned_py(spec, round_no)
    elif s == "fixed_steps":
        steps = np.array([pattern_of(spec, w) for w in range(m)])
    elif s in PERIODIC:
        steps = np.full(m, period)
    else:
        raise ValueError(f"unknown scheme {s!r}")
    done = durations_py(spec, round_no, int(steps.max())).cumsum(axis=1)
    return plan(steps, every & (steps >= 1), max(done[w, steps[w] - 1] for w in range(m) if steps[w]), down=int(every.sum()))


PERIODIC = ("periodic_average", "adaptive_period", "stagewise", "large_batch")
SCHEMES = (*QUORUM, *PERIODIC, *RANDOM, "sampled_average", "complete_only", "complete_and_incomplete", "quorum_batches", "redundant", "reassign", "fixed_steps")


def check_scheme(spec: RunSpec, known: tuple) -> None:
    if spec.scheme not in known:
        raise ValueError(f"unknown scheme {spec.scheme!r}; known are {', '.join(known)}")


def deadline_of(spec: RunSpec) -> float:
    """The length of a round with a deadline; by default the mean duration of a quota."""
    return float(spec.options.get("deadline", spec.quota * spec.mean))


def pattern_of(spec: RunSpec, worker):
    """A hand-set unequal pattern: ``least`` steps and up to ``spread`` - 1 more, by worker. Works on numbers and columns."""
    return worker % int(spec.options.get("spread", 4)) + int(spec.options.get("least", 2))


def reassigned_py(spec: RunSpec, round_no: int):
    """Steps of a round after reassignment, from the first steps of the rounds before it."""
    import numpy as np

    m, window, factor = spec.workers, int(spec.options.get("window", 5)), float(spec.options.get("factor", 1.5))
    if round_no == 0:
        return np.full(m, spec.quota)
    own = np.mean([durations_py(spec, j, 1)[:, 0] for j in range(max(0, round_no - window), round_no)], axis=0)
    middle = np.median(own)
    cut = np.where(own > factor * middle, np.maximum(1, np.floor(spec.quota * middle / own)), spec.quota).astype(int)
    cut[np.lexsort((np.arange(m), own))[0]] += int((spec.quota - cut).sum())
    return cut


def rule_of(spec: RunSpec) -> str:
    return str(spec.options.get("rule", "inverse_model" if spec.scheme == "step_normalised" else "uniform"))


def log_row(spec: RunSpec, round_no: int, period: int, time: float, cum_time: float, messages: int, cum_messages: int, uploads: int, steps, measures: dict) -> dict:
    return {
        "run_id": spec.run_id, "scheme": spec.scheme, "split": spec.split, "seed": spec.seed, "quorum": spec.quorum, "quota": spec.quota, "workers": spec.workers, "round_no": round_no, "period": period,
        "round_time": time, "cum_time": cum_time, "messages": messages, "cum_messages": cum_messages, "uploads": uploads, "mean_steps": sum(steps) / len(steps), "max_steps": int(max(steps)),
        "step_size": step_size_at(spec, round_no), **{c: measures.get(c) for c in ("loss", "accuracy", "grad_sq", "smooth")},
    }


class Curvature:
    """Smoothness along a run: how far the gradient moved for each unit that the model moved since the last evaluation."""

    def __init__(self):
        self.last = None

    def see(self, w, gradient) -> float | None:
        import numpy as np

        before, self.last = self.last, (w, gradient)
        if before is None or not (moved := float(np.linalg.norm(w - before[0]))):
            return None
        return float(np.linalg.norm(gradient - before[1])) / moved


def run_py(spec: RunSpec, shards: list, test: tuple, dims: int, classes: int) -> Iterator[dict]:
    """A whole run in one process. ``shards``: (x, y) of each worker in order of pos."""
    import numpy as np

    model = make_model(spec, dims, classes)
    w, powers = model.init(spec.seed), tasks.draw_powers(spec.batch)
    every_x, every_y = np.concatenate([s[0] for s in shards]), np.concatenate([s[1] for s in shards])
    time, messages, period, curve = 0.0, 0, Period(spec), Curvature()
    for j in range(spec.rounds):
        now = period.of(j)
        plan, alpha = round_py(spec, j, now), step_size_at(spec, j)
        results, counts = [], []
        for m in np.flatnonzero(plan["draw"]):
            x, y = shards[m]
            n = int(plan["draw"][m])
            batches = [(x[p], y[p]) for p in (tasks.draws_py(spec.seed, j, m, s, spec.batch, len(y), powers) for s in range(n))]
            results.append(models.gradients_at(model, w, batches) if spec.scheme in GRADIENTS else models.local_chain(model, w, batches, alpha))
            counts.append(n)
        w = next_model(spec, w, results, counts, alpha)
        up = int(plan["up"].sum())
        time, messages = time + plan["time"], messages + plan["down"] + up
        measures = {}
        if (j + 1) % spec.eval_every == 0:
            loss, grad = model.loss_grad(w, every_x, every_y)
            measures = {"loss": loss, "accuracy": model.evaluate(w, *test)[1], "grad_sq": float(grad @ grad), "smooth": curve.see(w, grad)}
            period.learn(loss, time, j)
        row = log_row(spec, j, now, plan["time"], time, plan["down"] + up, messages, up, plan["steps"].tolist(), measures)
        yield row
        if should_stop(spec, row):
            return


def next_model(spec: RunSpec, w, results: list, counts: list, alpha: float):
    """The model after a round, from local models or gradients of the round's contributors and their numbers of mini-batches."""
    import numpy as np

    if not results:
        return w
    if spec.scheme in GRADIENTS:
        return w - alpha * np.average(np.asarray(results), axis=0, weights=counts)
    return models.average(w, results, [1.0] * len(results), counts, rule_of(spec))


#: Schemes without rounds: every gradient is applied as it arrives. Their logs have a row for every M updates.
ASYNCHRONOUS = ("asynchronous", "lock_free")


class Arrivals:
    """The order of an asynchronous run's updates, which durations alone decide, and its models, kept only as far back as some worker's read."""

    def __init__(self, spec: RunSpec, model: models.Model):
        import heapq

        import numpy as np

        self.spec, self.model, self.w = spec, model, model.init(spec.seed)
        self.parts = np.array_split(np.arange(len(self.w)), int(spec.options.get("blocks", 8)))
        self.heap = [(self.lasts(0, k), k, 0) for k in range(spec.workers)]
        heapq.heapify(self.heap)
        self.read, self.history, self.version = [0] * spec.workers, {0: self.w}, 0

    def lasts(self, n: int, k: int) -> float:
        return -math.log((rng.hash48_py(self.spec.seed, "dur", n, k, 0) + 0.5) / rng.SPACE) * self.spec.mean

    def due(self) -> list[tuple[float, int, int]]:
        """The next M updates: (time, worker, the worker's how-manieth)."""
        import heapq

        out = []
        for _ in range(self.spec.workers):
            t, k, n = heapq.heappop(self.heap)
            out.append((t, k, n))
            heapq.heappush(self.heap, (t + self.lasts(n + 1, k), k, n + 1))
        return out

    def apply(self, events: list, batch, alpha: float) -> None:
        """Apply updates in order; ``batch`` gives (x, y) of a worker's n-th update."""
        for _, k, n in events:
            at = self.history[self.read[k]]
            if self.spec.scheme == "lock_free":
                at = at.copy()
                for b, part in enumerate(self.parts):
                    at[part] = self.history[self.read[k] + rng.hash48_py(self.spec.seed, "block", k, n, b) % (self.version - self.read[k] + 1)][part]
            self.w = self.w - alpha * self.model.loss_grad(at, *batch(k, n))[1]
            self.version += 1
            self.history[self.version], self.read[k] = self.w, self.version
            for old in range(min(self.history), min(self.read)):
                self.history.pop(old, None)


def async_py(spec: RunSpec, shards: list, test: tuple, dims: int, classes: int) -> Iterator[dict]:
    """Asynchronous descent in one process, as the order of events is the meaning. ``asynchronous`` reads a consistent model;
    ``lock_free`` reads each block of it at a version of its own, between the worker's read and the update."""
    import numpy as np

    model, m = make_model(spec, dims, classes), spec.workers
    powers = tasks.draw_powers(spec.batch)
    every_x, every_y = np.concatenate([s[0] for s in shards]), np.concatenate([s[1] for s in shards])
    run, before, curve = Arrivals(spec, model), 0.0, Curvature()

    def batch(k, n):
        x, y = shards[k]
        p = tasks.draws_py(spec.seed, n, k, 0, spec.batch, len(y), powers)
        return x[p], y[p]

    for j in range(spec.rounds):
        events = run.due()
        run.apply(events, batch, step_size_at(spec, j))
        t, w = events[-1][0], run.w
        measures = {}
        if (j + 1) % spec.eval_every == 0:
            loss, grad = model.loss_grad(w, every_x, every_y)
            measures = {"loss": loss, "accuracy": model.evaluate(w, *test)[1], "grad_sq": float(grad @ grad), "smooth": curve.see(w, grad)}
        row = log_row(spec, j, 1, t - before, t, 2 * m, 2 * m * (j + 1), m, [1] * m, measures)
        before = t
        yield row
        if should_stop(spec, row):
            return


def as_arrays(samples: DataFrame) -> tuple:
    import numpy as np

    table = samples.select("x", "y").toArrow().to_pandas()
    return np.stack(table.x.to_list()), table.y.to_numpy()


def collect_shards(shards: DataFrame, workers: int) -> list:
    """Samples of each worker as arrays on the driver; the caller has checked their size."""
    import numpy as np

    table = shards.select("worker", "pos", "x", "y").toArrow().to_pandas().sort_values(["worker", "pos"])
    out = []
    for m in range(workers):
        mine = table[table.worker == m]
        out.append((np.stack(mine.x.to_list()), mine.y.to_numpy()))
    return out


def sweep(spark: SparkSession, specs: list[RunSpec], samples: DataFrame, classes: int, measures: tuple[str, ...] = MEASURES) -> DataFrame:
    """The logs of all runs. Samples: (row_id, x, y); a fifth of them is held out for accuracy.

    Up to ``SWEEP_BYTES`` of samples (all splits' copies and the held-out fold) are broadcast and each run is a task; beyond,
    :func:`lockstep.sweep` takes all runs through their rounds together, with the same log, and never brings samples to the driver.
    ``measures`` are those that the caller reads, besides accuracy: others may be null.
    """
    for spec in specs:
        check_scheme(spec, SCHEMES + ASYNCHRONOUS)
    pieces = {(s.split, s.workers) for s in specs}
    samples = samples.select("row_id", "x", "y").persist()
    rows, dims = samples.count(), samples.select(F.size("x")).first()[0]
    if rows * (dims + 2) * 8 * (len(pieces) + 1) > SWEEP_BYTES:
        from quorumlab.operators import lockstep

        return spark.createDataFrame([tuple(r.values()) for r in lockstep.sweep(spark, specs, samples, dims, classes, measures)], LOG)
    train_rows = tasks.train_test(samples, False).persist()
    test = as_arrays(tasks.train_test(samples, True))
    data = {(split, workers): collect_shards(tasks.SPLITS[split](train_rows, workers), workers) for split, workers in pieces}
    train_rows.unpersist()
    samples.unpersist()
    shared = spark.sparkContext.broadcast((data, test))
    jobs = spark.createDataFrame([(k, s.to_json()) for k, s in enumerate(specs)], "nth int, spec string").repartition(len(specs), "nth")

    def work(frames: Iterator) -> Iterator:
        import pandas as pd

        data, test = shared.value
        for frame in frames:
            for text in frame["spec"]:
                spec = RunSpec.from_json(text)
                run = async_py if spec.scheme in ASYNCHRONOUS else run_py
                yield pd.DataFrame(list(run(spec, data[spec.split, spec.workers], test, dims, classes)))

    return jobs.mapInPandas(work, LOG)


# --- the distributed path -------------------------------------------------------------------------------------------


def plan_rounds(spark: SparkSession, spec: RunSpec, lines: DataFrame, period: int | None = None) -> DataFrame:
    """The schedule of a scheme for the rounds of the lines."""
    s, o = spec.scheme, spec.options
    if s in QUORUM:
        return clock.quorum_schedule(lines, spec.quorum, quota_of(spec), *QUORUM[s], run_id=spec.run_id)
    if s == "stagewise":
        return clock.planned_schedule(lines, spark.createDataFrame(stages_of(spec), clock.PLAN), spec.run_id, open_end=True)
    if s in PERIODIC:
        return clock.periodic_schedule(lines, period or spec.quota, run_id=spec.run_id)
    if s == "sampled_average":
        return clock.sampled_schedule(lines, int(o.get("sample", spec.workers)), spec.quota, spec.seed, spec.run_id)
    if s in RANDOM:
        return clock.random_steps_schedule(lines, float(o.get("mean", 10)), "ceil", spec.seed, "uniform" if s == "random_uniform" else "inverse_model", spec.run_id)
    if s in ("complete_only", "complete_and_incomplete"):
        return clock.deadline_schedule(lines, deadline_of(spec), spec.quota, s == "complete_only", spec.run_id)
    if s == "quorum_batches":
        return clock.quorum_batches_schedule(lines, spec.quorum, spec.run_id)
    if s == "redundant":
        return clock.redundant_schedule(lines, spec.workers, int(o.get("replication", 2)), spec.run_id)
    if s == "reassign":
        return clock.reassign_schedule(lines, spec.quota, float(o.get("factor", 1.5)), int(o.get("window", 5)), spec.run_id)
    if s == "fixed_steps":
        return clock.fixed_steps_schedule(lines, pattern_of(spec, F.col("worker")), run_id=spec.run_id)
    raise ValueError(f"unknown scheme {s!r}")


def planned_block(spark: SparkSession, spec: RunSpec, start: int, end: int, period: int) -> tuple[DataFrame, dict[int, list]]:
    """The persisted schedule of rounds start .. end-1 and its rows by round. Timelines too short for a plan are made again, twice as long."""
    cap, before = cap_of(spec, period), int(spec.options.get("window", 5)) if spec.scheme == "reassign" else 0
    while True:
        lines = clock.timelines(tables.hashed_durations(spark, end, spec.workers, cap, spec.mean, spec.seed).where(F.col("round_no") >= start - before))
        schedule = plan_rounds(spark, spec, lines, period).where(F.col("round_no") >= start).persist()
        planned: dict[int, list] = {}
        for r in schedule.collect():  # one small row for each round and worker
            planned.setdefault(r["round_no"], []).append(r)
        if not any(r["capped"] for rows in planned.values() for r in rows):
            return schedule, planned
        schedule.unpersist()
        cap *= 2


def drawn_steps(spec: RunSpec, schedule: DataFrame) -> DataFrame:
    """(round_no, worker, steps) whose mini-batches a round uses: those of uploaders, or, with redundancy, one of each piece."""
    if spec.scheme == "redundant":
        return schedule.select("round_no", "worker", F.lit(1).alias("steps"))
    return schedule.where("uploads").select("round_no", "worker", "steps")


def local_results(fetched: DataFrame, round_no: int, model: models.Model, w, step_size: float, gradients: bool) -> DataFrame:
    """(worker, steps, w) of a round: each worker's batches, in order of step and slot, run through its local chain, or their mean
    gradient at the round's model."""
    shared = fetched.sparkSession.sparkContext.broadcast(w)

    def chain(frame):
        import numpy as np
        import pandas as pd

        frame = frame.sort_values(["step_no", "slot"])
        x, y, step = np.stack(frame.x.to_list()), frame.y.to_numpy(), frame.step_no.to_numpy()
        cuts = np.flatnonzero(np.diff(step)) + 1
        batches = list(zip(np.split(x, cuts), np.split(y, cuts), strict=True))
        out = models.gradients_at(model, shared.value, batches) if gradients else models.local_chain(model, shared.value, batches, step_size)
        return pd.DataFrame({"worker": [int(frame.worker.iloc[0])], "steps": [len(batches)], "w": [out.tolist()]})

    return fetched.where(F.col("round_no") == round_no).groupBy("worker").applyInPandas(chain, "worker int, steps int, w array<double>")


def evaluate(samples: DataFrame, model: models.Model, w) -> tuple[float, float]:
    """(mean loss, share correct) over a table, as partial sums of Arrow batches."""
    shared = samples.sparkSession.sparkContext.broadcast(w)

    def score(frames: Iterator) -> Iterator:
        import numpy as np
        import pandas as pd

        for frame in frames:
            if len(frame):
                loss, share = model.evaluate(shared.value, np.stack(frame.x.to_list()), frame.y.to_numpy())
                yield pd.DataFrame({"n": [len(frame)], "loss": [loss * len(frame)], "right": [share * len(frame)]})

    r = samples.select("x", "y").mapInPandas(score, "n bigint, loss double, right double").groupBy().sum().first()
    return (r[1] / r[0], r[2] / r[0]) if r and r[0] else (float("nan"), float("nan"))


def mean_gradient(samples: DataFrame, model: models.Model, w, by: str | None = None):
    """Full-pass mean gradient, or one for each value of a column: {key: gradient}."""
    import numpy as np

    shared = samples.sparkSession.sparkContext.broadcast(w)
    key = F.col(by).cast("int") if by else F.lit(0)

    def part(frames: Iterator) -> Iterator:
        import pandas as pd

        for frame in frames:
            for k, mine in frame.groupby("k"):
                g = model.loss_grad(shared.value, np.stack(mine.x.to_list()), mine.y.to_numpy())[1] * len(mine)
                yield pd.DataFrame({"k": k, "n": len(mine), "pos": range(len(g)), "g": g})

    sums = samples.select(key.alias("k"), "x", "y").mapInPandas(part, "k int, n bigint, pos int, g double").groupBy("k", "pos").agg((F.sum("g") / F.sum("n")).alias("g")).collect()
    out: dict = {}
    for r in sorted(sums, key=lambda r: (r["k"], r["pos"])):
        out.setdefault(r["k"], []).append(r["g"])
    return {k: np.array(v) for k, v in out.items()} if by else np.array(out[0])


def loss_and_gradient(samples: DataFrame, model: models.Model, w) -> tuple:
    """(mean loss, mean gradient) over a table, in one pass: each task sums its batches, and the sums meet by position."""
    import numpy as np

    shared = samples.sparkSession.sparkContext.broadcast(w)

    def part(frames: Iterator) -> Iterator:
        import pandas as pd

        total = None
        for frame in frames:
            if n := len(frame):
                loss, g = model.loss_grad(shared.value, np.stack(frame.x.to_list()), frame.y.to_numpy())
                mine = np.concatenate([[n, loss * n], g * n])
                total = mine if total is None else total + mine
        if total is not None:
            yield pd.DataFrame({"pos": np.arange(len(total)), "v": total})

    sums = samples.select("x", "y").mapInPandas(part, "pos bigint, v double").groupBy("pos").agg(F.sum("v").alias("v")).collect()
    v = np.array([r["v"] for r in sorted(sums, key=lambda r: r["pos"])])
    return float(v[1] / v[0]), v[2:] / v[0]


STATE = "run_id string, round_no int, w array<double>, cum_time double, cum_messages bigint, period int, loss0 double, since double"


def stored_state(spark: SparkSession, store: str, spec: RunSpec) -> tuple | None:
    """(next round, model, cum_time, cum_messages, period state) after the last round of a run in a store, or None."""
    import numpy as np

    path = spark._jvm.org.apache.hadoop.fs.Path(f"{store}/state")
    if not path.getFileSystem(spark._jsc.hadoopConfiguration()).exists(path):
        return None
    r = spark.read.schema(STATE).parquet(f"{store}/state").where(F.col("run_id") == spec.run_id).orderBy(F.col("round_no").desc()).first()
    return r and (r["round_no"] + 1, np.array(r["w"]), r["cum_time"], r["cum_messages"], (r["period"], r["loss0"], r["since"]))


def train(spark: SparkSession, spec: RunSpec, samples: DataFrame, classes: int, resume: tuple | None = None, draw: str = "independent", store: str | None = None) -> tuple[DataFrame, list[float]]:
    """(log, model). ``resume`` = (next round, model, cum_time, cum_messages) continues a run from a given state.

    With ``store``, a folder that driver and executors share, the state and log of each evaluated round are written there, and a run that finds
    its own state goes on after it, so a lost driver costs the rounds since the last evaluation; the log then holds all rounds.
    """
    check_scheme(spec, SCHEMES)
    train_rows, test = tasks.train_test(samples, False), tasks.train_test(samples, True).persist()
    shards = tasks.SPLITS[spec.split](train_rows, spec.workers).persist()
    sizes = shards.groupBy("worker").agg(F.count("*").alias("n")).persist()
    dims = shards.select(F.size("x")).first()[0]
    model = make_model(spec, dims, classes)
    found_state = stored_state(spark, store, spec) if store else None
    first, w, time, messages, *rest = resume or found_state or (0, model.init(spec.seed), 0.0, 0)
    period, curve, log = Period(spec, rest[0] if rest else None), Curvature(), []
    old = spark.read.schema(LOG).parquet(f"{store}/log").where((F.col("run_id") == spec.run_id) & (F.col("round_no") < first)).dropDuplicates(["round_no"]).collect() if found_state else []
    done = bool(old) and should_stop(spec, max(old, key=lambda r: r["round_no"]).asDict())
    # A scheme that re-plans from the loss plans a round at a time.
    block = 1 if spec.scheme == "adaptive_period" else BLOCK
    start, unsaved = first, 0
    while start < spec.rounds and not done:
        end = min(start + block, spec.rounds)
        schedule, planned = planned_block(spark, spec, start, end, period.of(start))
        draws = tasks.draw_batches(drawn_steps(spec, schedule), sizes, spec.batch, spec.seed, draw)
        fetched = tasks.fetch(draws, shards).repartition(spec.workers, "worker").persist()
        for j in sorted(planned):
            rows, now, alpha = planned[j], period.of(j), step_size_at(spec, j)
            found = sorted(local_results(fetched, j, model, w, alpha, spec.scheme in GRADIENTS).collect(), key=lambda r: r["worker"])
            w = next_model(spec, w, [r["w"] for r in found], [r["steps"] for r in found], alpha)
            up, down = sum(r["uploads"] for r in rows), sum(r["downloads"] for r in rows)
            time, messages = time + rows[0]["round_time"], messages + up + down
            measures = {}
            if (j + 1) % spec.eval_every == 0:
                loss, grad = loss_and_gradient(shards, model, w)
                measures = {"loss": loss, "accuracy": evaluate(test, model, w)[1], "grad_sq": float(grad @ grad), "smooth": curve.see(w, grad)}
                period.learn(loss, time, j)
            row = log_row(spec, j, now, rows[0]["round_time"], time, up + down, messages, up, [r["steps"] for r in rows], measures)
            log.append(row)
            done = should_stop(spec, row)
            if store and (measures or done):
                state = (spec.run_id, j, [float(v) for v in w], time, messages, *period.state)
                spark.createDataFrame(log[unsaved:], LOG).coalesce(1).write.mode("append").parquet(f"{store}/log")
                spark.createDataFrame([state], STATE).coalesce(1).write.mode("append").parquet(f"{store}/state")  # last: a state's log is complete
                unsaved = len(log)
            if done:
                break
        fetched.unpersist()
        schedule.unpersist()
        start = end
    for kept in (test, shards, sizes):
        kept.unpersist()
    return spark.createDataFrame([*old, *(tuple(r.values()) for r in log)], LOG), [float(v) for v in w]


# --- single-machine and one-shot baselines ---------------------------------------------------------------------------


def serial_run(model: models.Model, x, y, batch: int, step_size: float, steps: int, seed: int = 0):
    """Serial mini-batch descent; with ``batch`` = 0 full gradient descent. Returns (model, losses)."""
    w, losses = model.init(seed), []
    powers = tasks.draw_powers(max(batch, 1))
    for s in range(steps):
        p = slice(None) if not batch else tasks.draws_py(seed, s, 0, 0, batch, len(y), powers)
        loss, g = model.loss_grad(w, x[p], y[p])
        w = w - step_size * g
        losses.append(loss)
    return w, losses


def one_shot_run(model: models.Model, shards: list, batch: int, step_size: float, steps: int, seed: int = 0):
    """Long local runs from one start and a single average at the end."""
    powers, w0, out = tasks.draw_powers(batch), model.init(seed), []
    for m, (x, y) in enumerate(shards):
        draws = (tasks.draws_py(seed, 0, m, s, batch, len(y), powers) for s in range(steps))
        out.append(models.local_chain(model, w0, ((x[p], y[p]) for p in draws), step_size))
    return models.average(w0, out, [1.0] * len(out), [steps] * len(out))


def async_run(model: models.Model, events: list, shards: list, batch: int, step_size: float, seed: int = 0, consistency: str = "whole", blocks: int = 8):
    """Asynchronous descent over events (worker, nth, version, read_version) in order of time.

    ``whole`` reads a consistent model; ``coordinate`` reads each block at a version of its own between the worker's read and
    the update (lock-free sharing); ``disjoint_blocks`` lets an update touch only the block that its number names, so
    concurrent updates never meet. Returns (model, largest staleness).
    """
    import numpy as np

    powers, w = tasks.draw_powers(batch), model.init(seed)
    history, worst = {0: w}, 0
    parts = np.array_split(np.arange(len(w)), blocks)
    needed = np.minimum.accumulate([e[3] for e in events][::-1])[::-1].tolist() if events else []  # the oldest version that any later event reads
    for at_event, (worker, nth, version, read) in enumerate(events):
        for old in range(min(history), needed[at_event]):
            history.pop(old, None)
        worst = max(worst, version - read)
        at = history[read].copy()
        if consistency == "coordinate":
            for b, part in enumerate(parts):
                at[part] = history[read + rng.hash48_py(seed, "block", worker, nth, b) % (version - read + 1)][part]
        x, y = shards[worker]
        p = tasks.draws_py(seed, 0, worker, nth, batch, len(y), powers)
        g = model.loss_grad(at, x[p], y[p])[1]
        if consistency == "disjoint_blocks":
            mask = np.zeros(len(w))
            mask[parts[version % blocks]] = 1
            g = g * mask
        w = w - step_size * g
        history[version + 1] = w
    return w, worst
