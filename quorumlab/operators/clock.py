"""Round clocks: which worker does how many steps in a round, who uploads, and how long the round takes.

All schemes work on timelines, one row for each (round, worker) with the completion times of its steps in
order. A timeline is short (the step cap), rounds are independent, and every scheme is a choice of a stop time, a
cap and an upload rule, so a whole grid of settings shares one shuffle of the durations.

A schedule has one row for each (round, worker), workers without a step included:
run_id, round_no, worker, steps, uploads, downloads, weight, ack_time, round_time, capped.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from quorumlab.functions import rng
from quorumlab.operators.samples import dense_rank_distributed

COLUMNS = ["run_id", "round_no", "worker", "steps", "uploads", "downloads", "weight", "ack_time", "round_time", "capped"]


def timelines(durations: DataFrame) -> DataFrame:
    """(round_no, worker, done): done[u] is when the worker finishes step u + 1, if nobody stops it."""
    steps = durations.groupBy("round_no", "worker").agg(F.array_sort(F.collect_list(F.struct("step_no", "dur"))).alias("s"))
    start = F.struct(F.lit(0.0).alias("t"), F.array().cast("array<double>").alias("done"))
    run = F.aggregate("s", start, lambda a, x: F.struct((a["t"] + x["dur"]).alias("t"), F.concat(a["done"], F.array(a["t"] + x["dur"])).alias("done")))
    return steps.select("round_no", "worker", run["done"].alias("done"))


def finished(done: Column, stop: Column) -> Column:
    """Steps finished at or before a time."""
    return F.size(F.filter(done, lambda t: t <= stop))


def at_step(done: Column, step: Column) -> Column:
    """When a step (1-based) is finished; null beyond the timeline or for step 0."""
    return F.when((step >= 1) & (step <= F.size(done)), F.element_at(done, F.greatest(step, F.lit(1)).cast("int")))


def go_on(rows: DataFrame, steps: DataFrame, cap: int) -> DataFrame:
    """Lines with ``planned`` steps beyond their timeline go on into the worker's trace (worker, seq, dur); round r starts at
    seq r * cap. A line for which the trace is too short keeps its timeline, and its schedule is capped."""
    k = F.explode(F.sequence(F.size("done"), F.col("planned") - 1))
    missing = rows.where(F.col("planned") > F.size("done")).select("round_no", "worker", k.alias("k"))
    missing = missing.withColumn("seq", F.col("round_no").cast("bigint") * cap + F.col("k"))
    more = missing.join(steps.select("worker", "seq", "dur"), ["worker", "seq"]).groupBy("round_no", "worker").agg(F.array_sort(F.collect_list(F.struct("k", "dur"))).alias("more"))
    add = lambda done, x: F.concat(done, F.array(F.element_at(done, -1) + x["dur"]))
    whole = F.size("more") == F.col("planned") - F.size("done")
    return rows.join(more, ["round_no", "worker"], "left").withColumn("done", F.when(whole, F.aggregate("more", F.col("done"), add)).otherwise(F.col("done"))).drop("more")


def assemble(rows: DataFrame, run_id: str, steps: Column, uploads: Column, ack: Column, stop: Column, downloads: Column | None = None, weight: Column | None = None, capped: Column | None = None) -> DataFrame:
    """A schedule from per-(round, worker) columns. ``weight`` defaults to 1 for uploaders, 0 for others."""
    up = F.coalesce(uploads, F.lit(False))
    return rows.select(
        F.lit(run_id).alias("run_id"), "round_no", "worker", steps.cast("int").alias("steps"), up.alias("uploads"),
        (F.lit(True) if downloads is None else downloads).alias("downloads"),
        F.when(up, F.lit(1.0) if weight is None else weight).otherwise(0.0).alias("weight"),
        ack.alias("ack_time"), stop.alias("round_time"), F.coalesce(F.lit(False) if capped is None else capped, F.lit(False)).alias("capped"),
    )


def _stop_after(rows: DataFrame, time: str, k: int | Column) -> DataFrame:
    """Add ``stop``, the k-th smallest of a per-worker time in each round. Ties rank by worker; a round has M rows."""
    k = F.lit(k) if isinstance(k, int) else k
    ranked = rows.withColumn("rank", F.row_number().over(W.partitionBy("round_no").orderBy(F.col(time).asc_nulls_last(), "worker")))
    return ranked.withColumn("stop", F.max(F.when(F.col("rank") == k, F.col(time))).over(W.partitionBy("round_no")))


def quorum_schedule(lines: DataFrame, quorum: int, quota: int | Column, keep_partial: bool = True, keep_surplus: bool = True, ack_cost: float = 0.0, link: Column | None = None, run_id: str = "quorum_stop") -> DataFrame:
    """The main method: a round ends when the quorum-th worker finishes its quota; all keep stepping until then, and
    everybody with a finished step uploads.

    ``keep_partial=False`` (fast_surplus_only) lets only workers that made their quota upload;
    ``keep_surplus=False`` (straggler_partial_only) caps steps at the quota; both off is the plain quorum. ``ack_cost`` and
    ``link`` (a column, say a random link time of a worker) delay the acknowledgement, during which work goes on.
    """
    quota_column = F.lit(quota) if isinstance(quota, int) else quota
    delay = F.lit(float(ack_cost)) + (F.lit(0.0) if link is None else link)
    rows = lines.withColumn("quota", quota_column.cast("int")).withColumn("ack", at_step(F.col("done"), F.col("quota")) + delay)
    rows = _stop_after(rows, "ack", quorum)
    stop, acked = F.col("stop"), F.col("ack") <= F.col("stop")
    steps = finished(F.col("done"), stop)
    capped = (F.size("done") == 0) | (F.element_at("done", -1) <= stop)
    if not keep_surplus:
        steps, capped = F.least(steps, F.col("quota")), F.lit(False)
    uploads = (steps >= 1) if keep_partial else acked
    return assemble(rows, run_id, steps, uploads, F.col("ack"), stop, capped=capped)


def fixed_steps_schedule(lines: DataFrame, steps: Column, downloads: Column | None = None, run_id: str = "fixed_steps", weight: Column | None = None) -> DataFrame:
    """Every participating worker does its own number of steps, and the round waits for the slowest of them. If a worker's
    steps exceed its timeline, it is capped and the round's time is null, as nobody knows it."""
    part = F.lit(True) if downloads is None else downloads
    rows = lines.withColumn("part", part).withColumn("n", F.when(F.col("part"), steps).otherwise(0).cast("int"))
    rows = rows.withColumn("ack", at_step(F.col("done"), F.col("n")))
    each_round = W.partitionBy("round_no")
    known = F.count_if((F.col("n") >= 1) & F.col("ack").isNull()).over(each_round) == 0
    stop = F.when(known, F.max("ack").over(each_round))
    return assemble(rows.withColumn("stop", stop), run_id, F.col("n"), F.col("part") & (F.col("n") >= 1), F.col("ack"), F.col("stop"), F.col("part"), weight, F.col("n") > F.size("done"))


def periodic_schedule(lines: DataFrame, quota: int, run_id: str = "periodic_average") -> DataFrame:
    """All workers, ``quota`` steps each; with quota 1 it is fully synchronous parallel descent."""
    return fixed_steps_schedule(lines, F.lit(quota), run_id=run_id)


def sampled_schedule(lines: DataFrame, sample: int, quota: int, seed: int = 0, run_id: str = "sampled_average") -> DataFrame:
    """Federated averaging: the ``sample`` workers with the smallest hash of the round take part."""
    order = W.partitionBy("round_no").orderBy(rng.hash48(seed, "sample", F.col("round_no"), F.col("worker")), "worker")
    rows = lines.withColumn("chosen", F.row_number().over(order) <= sample)
    return fixed_steps_schedule(rows, F.lit(quota), F.col("chosen"), run_id)


def planned_schedule(lines: DataFrame, plan: DataFrame, run_id: str = "adaptive_period", open_end: bool = False) -> DataFrame:
    """Steps of a round from a plan (first_round, last_round, period): adaptive and stage-wise schemes. The plan is a few rows;
    with ``open_end`` its last row holds for all later rounds."""
    stages = plan.select("first_round", "last_round", "period")
    end = F.col("last_round")
    if open_end:
        stages = stages.crossJoin(F.broadcast(plan.agg(F.max("last_round").alias("end"))))
        end = F.when(F.col("last_round") < F.col("end"), end).otherwise(2**31 - 1)
    rows = lines.join(F.broadcast(stages.select("first_round", end.alias("last_round"), "period")), F.col("round_no").between(F.col("first_round"), F.col("last_round")))
    return fixed_steps_schedule(rows, F.col("period"), run_id=run_id)


def random_step_count(mean: float, rounding: str, seed: int) -> Column:
    draw = rng.exponential(mean, seed, "steps", F.col("round_no"), F.col("worker"))
    if rounding == "ceil":
        return F.greatest(F.lit(1), F.ceil(draw)).cast("int")
    if rounding == "round":
        return F.greatest(F.lit(1), F.round(draw)).cast("int")
    if rounding == "floor0":
        return F.floor(draw).cast("int")
    raise ValueError(f"unknown rounding {rounding!r}")


def random_steps_schedule(lines: DataFrame, mean: float = 10.0, rounding: str = "ceil", seed: int = 0, rule: str = "inverse_model", run_id: str = "step_normalised", steps: DataFrame | None = None, cap: int = 0) -> DataFrame:
    """Random step counts, all workers, wait for all; weights inverse to the steps (``uniform`` is the control). With the
    ``steps`` of a trace cut into rounds of ``cap``, plans longer than a timeline go on into it."""
    rows = lines.withColumn("planned", random_step_count(mean, rounding, seed))
    rows = rows if steps is None else go_on(rows, steps, cap)
    weight = F.lit(1.0) if rule == "uniform" else 1.0 / F.greatest(F.col("planned"), F.lit(1))
    return fixed_steps_schedule(rows, F.col("planned"), run_id=run_id, weight=weight)


def deadline_schedule(lines: DataFrame, deadline: float, quota: int, complete_only: bool, run_id: str | None = None) -> DataFrame:
    """A round lasts a fixed time, nobody goes beyond the quota; complete workers upload, or all with a finished step."""
    steps = F.least(finished(F.col("done"), F.lit(deadline)), F.lit(quota))
    rows = lines.withColumn("n", steps)
    uploads = F.col("n") == quota if complete_only else F.col("n") >= 1
    name = run_id or ("complete_only" if complete_only else "complete_and_incomplete")
    return assemble(rows, name, F.col("n"), uploads, at_step(F.col("done"), F.lit(quota)), F.lit(float(deadline)))


def quorum_gradient_schedule(lines: DataFrame, quorum: int, run_id: str = "quorum_gradient") -> DataFrame:
    """The first ``quorum`` workers' single gradients."""
    return quorum_schedule(lines, quorum, 1, keep_partial=False, keep_surplus=False, run_id=run_id)


def quorum_batches_schedule(lines: DataFrame, quorum: int, run_id: str = "quorum_batches") -> DataFrame:
    """The first ``quorum`` mini-batches from anybody, all at the round's model; the weight is the number supplied."""
    events = lines.select("round_no", "worker", F.posexplode("done").alias("step", "t"))
    # Only a worker's first `quorum` batches can be among the first `quorum` of all.
    events = events.where(F.col("step") < quorum)
    order = W.partitionBy("round_no").orderBy("t", "worker", "step")
    used = events.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= quorum)
    per = used.groupBy("round_no", "worker").agg(F.count("*").cast("int").alias("n"), F.max("t").alias("ack"))
    stop = used.groupBy("round_no").agg(F.max("t").alias("stop"))
    rows = lines.join(per, ["round_no", "worker"], "left").join(stop, "round_no").withColumn("n", F.coalesce("n", F.lit(0)))
    return assemble(rows, run_id, F.col("n"), F.col("n") >= 1, F.col("ack"), F.col("stop"), weight=F.col("n").cast("double"), capped=F.col("n") == F.size("done"))


def redundant_schedule(lines: DataFrame, workers: int, replication: int, run_id: str = "redundant") -> DataFrame:
    """Cyclic replication: piece p is held by workers p .. p+r-1 (mod M), each does a step for each piece it holds in that
    order; the round ends when every piece has a finisher."""
    pieces = lines.select("round_no", "worker", F.explode(F.sequence(F.lit(0), F.lit(replication - 1))).alias("k"), "done")
    pieces = pieces.select("round_no", "worker", F.pmod(F.col("worker") - F.col("k"), F.lit(workers)).alias("piece"), F.element_at("done", F.col("k") + 1).alias("t"))
    first = pieces.groupBy("round_no", "piece").agg(F.min(F.struct("t", "worker")).alias("f")).select("round_no", "piece", F.col("f.t").alias("t"), F.col("f.worker").alias("worker"))
    used = first.groupBy("round_no", "worker").agg(F.count("*").alias("n"), F.max("t").alias("ack"))
    stop = first.groupBy("round_no").agg(F.max("t").alias("stop"))
    rows = lines.join(used, ["round_no", "worker"], "left").join(stop, "round_no")
    rows = rows.withColumn("steps", F.least(finished(F.col("done"), F.col("stop")), F.lit(replication)))
    return assemble(rows, run_id, F.col("steps"), F.col("n").isNotNull(), F.col("ack"), F.col("stop"), weight=F.col("n").cast("double"))


def reassigned_quota(lines: DataFrame, quota: int, factor: float, window: int) -> DataFrame:
    """Lines with ``planned`` steps: a worker whose trailing mean step time exceeds factor x the round's median is given
    floor(quota * median / own) steps, at least 1; the fastest gets the surplus."""
    own = F.avg(F.element_at("done", 1)).over(W.partitionBy("worker").orderBy("round_no").rowsBetween(-window, -1))
    rows = lines.withColumn("own", own)
    rows = rows.withColumn("median", F.expr("percentile(own, 0.5)").over(W.partitionBy("round_no")))
    cut = F.when(F.col("own") > factor * F.col("median"), F.greatest(F.lit(1), F.floor(quota * F.col("median") / F.col("own")))).otherwise(quota)
    rows = rows.withColumn("cut", cut.cast("int"))
    surplus = F.sum(F.lit(quota) - F.col("cut")).over(W.partitionBy("round_no"))
    fastest = F.row_number().over(W.partitionBy("round_no").orderBy(F.col("own").asc_nulls_last(), "worker")) == 1
    return rows.withColumn("surplus", surplus).withColumn("first", fastest).withColumn("planned", (F.col("cut") + F.when(F.col("first"), F.col("surplus")).otherwise(0)).cast("int"))


def reassign_schedule(lines: DataFrame, quota: int, factor: float = 1.5, window: int = 5, run_id: str = "reassign", steps: DataFrame | None = None, cap: int = 0) -> DataFrame:
    """Straggler detection with work shifted to the fastest worker; total steps of a round stay the same. ``steps`` and
    ``cap`` as in random_steps_schedule."""
    rows = reassigned_quota(lines, quota, factor, window)
    return fixed_steps_schedule(rows if steps is None else go_on(rows, steps, cap), F.col("planned"), run_id=run_id)


def async_events(durations: DataFrame, horizon: float | None = None) -> DataFrame:
    """Asynchronous descent: every finished step is applied at once to the server's model, in order of time.

    One row for each event: version (updates before it), read_version (when its worker last read), staleness. Works on the
    concatenation of a worker's steps over all rounds of the trace.
    """
    own = W.partitionBy("worker").orderBy("round_no", "step_no")
    done = durations.withColumn("t", F.sum("dur").over(own.rowsBetween(W.unboundedPreceding, 0))).withColumn("nth", F.row_number().over(own))
    if horizon is not None:
        done = done.where(F.col("t") <= horizon)
    # One sequence over all workers, numbered by range partitions rather than in one task.
    events = dense_rank_distributed(done.select("worker", "nth", "t"), ["t", "worker", "nth"], "version")
    read = F.coalesce(F.lag("version").over(W.partitionBy("worker").orderBy("nth")) + 1, F.lit(0))
    return events.withColumn("read_version", read.cast("bigint")).withColumn("staleness", F.col("version") - F.col("read_version"))


def async_multi_step(durations: DataFrame, quota: int, horizon: float | None = None) -> DataFrame:
    """Asynchronous arrival of workers that make ``quota`` local steps before each upload."""
    chunk = durations.withColumn("nth", F.row_number().over(W.partitionBy("worker").orderBy("round_no", "step_no")) - 1)
    chunk = chunk.groupBy("worker", F.floor(F.col("nth") / quota).cast("int").alias("step_no")).agg(F.sum("dur").alias("dur"), F.count("*").alias("n")).where(F.col("n") == quota)
    return async_events(chunk.select(F.lit(0).alias("round_no"), "worker", "step_no", "dur"), horizon)


def stagewise_rows(stages: int, step_size: float, period: int, length: int, growth: int = 2) -> list[tuple]:
    """(stage, first_round, last_round, period, step_size): each stage halves the step, and multiplies period and length."""
    rows, first = [], 0
    for s in range(stages):
        n = length * growth**s
        rows.append((s, first, first + n - 1, period * growth**s, step_size / growth**s))
        first += n
    return rows


PLAN = "stage int, first_round int, last_round int, period int, step_size double"


def next_period(period: int, period0: int, loss: float, loss0: float, shrink: float = 0.5, direction: str = "shrink") -> int:
    """The adaptive rule: ceil(period0 * sqrt(loss / loss0)); if that isn't smaller than before, the old one times ``shrink``;
    at least 1. ``grow`` communicates less often as training goes on instead."""
    import math

    if direction == "grow":
        return max(period, math.ceil(period0 * math.sqrt(loss0 / max(loss, 1e-12))))
    to = math.ceil(period0 * math.sqrt(max(loss, 0.0) / loss0))
    return max(1, to if to < period else math.floor(period * shrink))


def step_cap(mean_steps: float) -> int:
    """A cap that a round with this many expected steps practically never reaches."""
    import math

    return math.ceil(mean_steps + 12 * math.sqrt(mean_steps) + 20)
