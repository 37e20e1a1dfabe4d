"""The experiments: step histograms, ablation, accuracy against time and messages, sweeps, bound, scale.

Each query trains with the same hashed durations and draws for all its schemes and reports logs or summaries; simulated time
is in units of the mean step duration's clock and never mixed with machine time.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quorumlab.operators import metrics, samples, theory, training
from quorumlab.plans.runspec import RunSpec

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SEEDS = (0, 1, 2, 3, 4)
SUMMARY = ["scheme", "split", "quorum", "quota", "workers"]


def workload(f):
    QUERIES[f.__name__] = f
    return f


def summarise(log: DataFrame, target: float) -> DataFrame:
    """Mean and deviation over seeds of what a setting needs to reach the target."""
    settings = log.select("run_id", "seed", *SUMMARY).distinct()
    per = metrics.to_target(log, target).join(settings, "run_id")
    out = per.groupBy(*SUMMARY).agg(
        F.count("*").alias("runs"), F.count("rounds").alias("reached"), F.avg("rounds").alias("rounds"), F.stddev("rounds").alias("rounds_sd"),
        F.avg("time").alias("sim_time"), F.stddev("time").alias("sim_time_sd"), F.avg("messages").alias("messages"), F.stddev("messages").alias("messages_sd"), F.max("best").alias("best"),
    )
    return out


def grid(base: RunSpec, changes: list[dict], splits=("even_random", "even_by_label"), seeds=SEEDS) -> list[RunSpec]:
    return [base.but(split=split, seed=seed, **c) for c in changes for split in splits for seed in seeds]


#: The language task stops at 90 % held-out accuracy, with unit mean durations.
LANGUAGE = RunSpec(model="softmax", mean=1.0, target=0.9, rounds=60)
#: The three-layer network on the planted task. Its 500 or 2,000 vectors are too few for 70 % held out, and a run costs much more than a
#: linear one: a lower target, few rounds, small mini-batches, three seeds.
PLANTED, NETWORK_SEEDS = RunSpec(model="small_cnn", mean=1.0, target=0.25, rounds=12, batch=20), (0, 1, 2)
SCHEMES = [{"scheme": "quorum_stop"}, {"scheme": "periodic_average"}, {"scheme": "adaptive_period"}, {"scheme": "step_normalised", "options": {"mean": 10}}]


def language_runs(spark: SparkSession, sf_dir: str, specs: list[RunSpec], *measures: str) -> DataFrame:
    return training.sweep(spark, specs, samples.language_task(spark, sf_dir), 4, measures)


@workload
def ablation(spark, sf_dir):
    """The method, its two halves and periodic averaging: rounds to the target, quorum 10, quota 5."""
    kinds = [{"scheme": s, "quorum": 10, "quota": 5} for s in ("quorum_stop", "fast_surplus_only", "straggler_partial_only", "periodic_average")]
    return summarise(language_runs(spark, sf_dir, grid(LANGUAGE, kinds)), LANGUAGE.target)


def planted_runs(spark: SparkSession, sf_dir: str, specs: list[RunSpec], *measures: str) -> DataFrame:
    return training.sweep(spark, specs, samples.planted_task(spark, sf_dir), 10, measures)


@workload
def ablation_network(spark, sf_dir):
    """The same with the three-layer network on the ten-class vectors."""
    kinds = [{"scheme": s, "quorum": 10, "quota": 5} for s in ("quorum_stop", "fast_surplus_only", "straggler_partial_only", "periodic_average")]
    return summarise(planted_runs(spark, sf_dir, grid(PLANTED, kinds, seeds=NETWORK_SEEDS)), PLANTED.target)


@workload
def network_curves(spark, sf_dir):
    """Accuracy against simulated time and messages of the four schemes with the three-layer network, both splits: a row for each round and seed."""
    log = planted_runs(spark, sf_dir, grid(PLANTED, SCHEMES, seeds=NETWORK_SEEDS), "loss")
    return log.select("scheme", "split", "seed", "round_no", "cum_time", "cum_messages", "loss", "accuracy", "mean_steps", "uploads")


@workload
def network_quorum_sweep(spark, sf_dir):
    """Time and messages to the target as the quorum grows, quota 10, with the three-layer network."""
    return summarise(planted_runs(spark, sf_dir, grid(PLANTED, [{"quorum": k} for k in (1, 5, 10, 15, 20)], seeds=NETWORK_SEEDS)), PLANTED.target)


@workload
def network_quota_sweep(spark, sf_dir):
    """Time and messages to the target as the quota grows, quorum 5, with the three-layer network."""
    return summarise(planted_runs(spark, sf_dir, grid(PLANTED, [{"quota": u} for u in (5, 10, 20)], seeds=NETWORK_SEEDS)), PLANTED.target)


#: Prior art as training schemes: (name, settings), all with the same step size and mini-batches.
PRIOR_ART = [
    ("main method", {"scheme": "quorum_stop"}), ("plain quorum", {"scheme": "plain_quorum"}), ("periodic", {"scheme": "periodic_average"}), ("sampled, 8 of 20", {"scheme": "sampled_average", "options": {"sample": 8}}),
    ("adaptive by interval", {"scheme": "adaptive_period", "options": {"interval": 20.0, "shrink": 0.5}}), ("adaptive, growing", {"scheme": "adaptive_period", "quota": 5, "options": {"direction": "grow"}}),
    ("stage-wise", {"scheme": "stagewise", "quota": 5}), ("random steps, equal weights", {"scheme": "random_uniform", "options": {"mean": 10}}), ("hand-set steps", {"scheme": "fixed_steps"}),
    ("deadline, complete only", {"scheme": "complete_only"}), ("deadline, all", {"scheme": "complete_and_incomplete"}), ("quorum gradients", {"scheme": "quorum_gradient"}),
    ("quorum mini-batches", {"scheme": "quorum_batches"}), ("synchronous single steps", {"scheme": "periodic_average", "quota": 1}), ("large mini-batch", {"scheme": "large_batch"}),
    ("redundant pieces", {"scheme": "redundant", "options": {"replication": 3}}), ("reassigned work", {"scheme": "reassign"}), ("asynchronous", {"scheme": "asynchronous"}), ("lock-free", {"scheme": "lock_free"}),
    ("one-shot average", {"scheme": "periodic_average", "quota": 100, "rounds": 1}), ("serial", {"scheme": "periodic_average", "workers": 1}),
]


@workload
def prior_art_to_target(spark, sf_dir):
    """Rounds, time and messages to the target of every prior scheme, even pieces; 200 rounds at most, null where the target isn't reached."""
    base = LANGUAGE.but(rounds=200)
    specs = {base.but(**c).run_id: (name, base.but(**c)) for name, c in PRIOR_ART}
    log = language_runs(spark, sf_dir, [s for _, s in specs.values()])
    names = spark.createDataFrame([(k, name) for k, (name, _) in specs.items()], "run_id string, scheme string")
    return metrics.to_target(log, base.target).join(F.broadcast(names), "run_id").select("scheme", "rounds", F.col("time").alias("sim_time"), "messages", "best")


@workload
def accuracy_curves(spark, sf_dir):
    """Accuracy against simulated time and messages of the four schemes, both splits: a row for each round."""
    log = language_runs(spark, sf_dir, grid(LANGUAGE, SCHEMES), "loss")
    return log.select("scheme", "split", "seed", "round_no", "cum_time", "cum_messages", "loss", "accuracy", "mean_steps", "uploads")


@workload
def schemes_to_target(spark, sf_dir):
    """Rounds, time and messages to the target of the four schemes, both splits."""
    return summarise(language_runs(spark, sf_dir, grid(LANGUAGE, SCHEMES)), LANGUAGE.target)


@workload
def schemes_at_large_steps(spark, sf_dir):
    """The same at a named, larger step size, for which the ordering of messages differs."""
    base = LANGUAGE.but(step_size=0.5, target=0.95)
    return summarise(language_runs(spark, sf_dir, grid(base, SCHEMES)), base.target)


@workload
def quorum_sweep(spark, sf_dir):
    """Time and messages to the target as the quorum grows, quota 10."""
    return summarise(language_runs(spark, sf_dir, grid(LANGUAGE, [{"quorum": k} for k in (1, 5, 10, 15, 20)])), LANGUAGE.target)


@workload
def quota_sweep(spark, sf_dir):
    """Time and messages to the target as the quota grows, quorum 5."""
    return summarise(language_runs(spark, sf_dir, grid(LANGUAGE.but(rounds=120), [{"quota": u} for u in (1, 5, 10, 20)])), LANGUAGE.target)


@workload
def worker_scaling(spark, sf_dir):
    """Speed-up with the number of workers, and local steps against one large mini-batch of the same samples."""
    kinds = [{"scheme": "periodic_average", "workers": m} for m in (1, 5, 10, 20, 40)]
    kinds += [{"scheme": "large_batch", "workers": m} for m in (5, 20)]
    return summarise(language_runs(spark, sf_dir, grid(LANGUAGE, kinds, splits=("even_random",))), LANGUAGE.target)


@workload
def bound_along_runs(spark, sf_dir):
    """Mean squared gradient so far, and the bound with measured constants, along runs of the main method with the convex and the
    one-hidden-layer model. Largest steps and smoothness are the largest of the run so far; the latter between consecutive models."""
    import numpy as np

    task = samples.language_task(spark, sf_dir)
    shards = samples.even_random(samples.train_test(task, False), LANGUAGE.workers).persist()
    rows = []
    for kind in ("softmax", "mlp"):
        spec = LANGUAGE.but(model=kind, target=2.0, rounds=20, quorum=5, quota=10, step_size=0.01)
        log = sorted(training.sweep(spark, [spec], task, 4).collect(), key=lambda r: r["round_no"])
        model = training.make_model(spec, 40, 4)
        w0 = model.init(spec.seed)
        loss0, full = training.loss_and_gradient(shards, model, w0)
        own = training.mean_gradient(shards, model, w0, "worker")
        apart = float(np.mean([((g - full) ** 2).sum() for g in own.values()]))
        inside = local_variance(shards, model, w0, own)
        steps, most, smooth, total = training.expected_steps(spec.workers, spec.quorum, spec.quota), 0, 0.0, 0.0
        for j, r in enumerate(log, 1):
            total, most, smooth = total + r["grad_sq"], max(most, r["max_steps"]), max(smooth, r["smooth"] or 0.0)
            if smooth:
                bound = theory.gradient_bound(loss0, 0.0, spec.step_size, steps, most, smooth, spec.quorum, spec.batch, inside, apart, j)
                rows.append((kind, j, total / j, most, smooth, bound))
    shards.unpersist()
    return spark.createDataFrame(rows, "model string, rounds int, mean_grad_sq double, max_steps int, smooth double, bound double")


def local_variance(shards: DataFrame, model, w, own: dict) -> float:
    """Mean squared distance of a sample's gradient from its worker's mean gradient: mean square less the square of the mean, by worker."""
    shared = shards.sparkSession.sparkContext.broadcast(w)

    def part(frames):
        import numpy as np
        import pandas as pd

        for frame in frames:
            if len(frame):
                square = model.sample_grad_sq(shared.value, np.stack(frame.x.to_list()), frame.y.to_numpy())
                yield pd.DataFrame({"worker": frame.worker, "n": 1, "s": square}).groupby("worker", as_index=False).sum()

    rows = shards.select("worker", "x", "y").mapInPandas(part, "worker int, n bigint, s double").groupBy("worker").agg(F.sum("n").alias("n"), F.sum("s").alias("s")).collect()
    return sum(r["s"] - r["n"] * float(own[r["worker"]] @ own[r["worker"]]) for r in rows) / sum(r["n"] for r in rows)


@workload
def distributed_training(spark, sf_dir):
    """The main method on the distributed path, one job a round, on the language task, to its target."""
    log, _ = training.train(spark, LANGUAGE, samples.language_task(spark, sf_dir), 4)
    return log.select("scheme", "round_no", "round_time", "cum_time", "messages", "uploads", "mean_steps", "accuracy")


@workload
def scale_training(spark, sf_dir):
    """Ten rounds of the main method on the scale table: only drawn rows are fetched; evaluated at the end."""
    spec = LANGUAGE.but(model="logistic", rounds=10, eval_every=10, target=2.0)
    log, _ = training.train(spark, spec, samples.revenue_task(spark, sf_dir), 2)
    drawn = F.round(F.col("mean_steps") * spec.workers * spec.batch).cast("bigint")
    return log.select("scheme", "round_no", "round_time", "uploads", "mean_steps", drawn.alias("samples"), "loss", "accuracy")
