"""Measures of schedules and of training logs: time, messages, work, accuracy against cost."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def round_summary(schedule: DataFrame) -> DataFrame:
    """Per run and round: realised time, uploads, messages (downloads plus uploads), steps."""
    return schedule.groupBy("run_id", "round_no").agg(
        F.max("round_time").alias("round_time"), F.count_if("uploads").alias("uploads"), (F.count_if("downloads") + F.count_if("uploads")).alias("messages"),
        F.sum("steps").alias("steps"), F.max("steps").alias("max_steps"), F.count_if("capped").alias("capped"),
    )


def upload_time(lines: DataFrame, schedule: DataFrame) -> DataFrame:
    """The realised round time from its definition: the longest sum of finished durations among uploaders."""
    own = schedule.join(lines, ["round_no", "worker"]).where("uploads").withColumn("t", F.element_at("done", F.col("steps")))
    return own.groupBy("run_id", "round_no").agg(F.max("t").alias("upload_time"))


def accumulate(rounds: DataFrame, time: str = "round_time", messages: str = "messages") -> DataFrame:
    """Running time and messages of each run."""
    so_far = W.partitionBy("run_id").orderBy("round_no").rowsBetween(W.unboundedPreceding, 0)
    return rounds.withColumn("cum_time", F.sum(time).over(so_far)).withColumn("cum_messages", F.sum(messages).over(so_far))


def empirical_means(schedule: DataFrame) -> DataFrame:
    """Per run: mean steps of a worker in a round, mean uploads and time of a round, capped rows."""
    rounds = round_summary(schedule)
    workers = schedule.groupBy("run_id").agg(F.avg("steps").alias("mean_steps"))
    per = rounds.groupBy("run_id").agg(F.count("*").alias("rounds"), F.avg("uploads").alias("mean_uploads"), F.avg("round_time").alias("mean_time"), F.sum("capped").alias("capped"))
    return per.join(workers, "run_id")


def step_classes(schedule: DataFrame, quota: int) -> Column:
    return F.when(F.col("steps") > quota, "surplus").when(F.col("steps") == quota, "exact").when(F.col("steps") >= 1, "partial").otherwise("none")


def step_histogram(schedule: DataFrame, quota: int, round_no: int | None = None) -> DataFrame:
    rows = schedule if round_no is None else schedule.where(F.col("round_no") == round_no)
    return rows.groupBy("run_id", "steps", step_classes(rows, quota).alias("class")).agg(F.count("*").alias("workers"))


def work_accounting(schedule: DataFrame, lines: DataFrame, quota: int) -> DataFrame:
    """Per run and round: steps beyond the quota, steps of stragglers that count, steps cut off, and time spent waiting."""
    both = schedule.join(lines, ["round_no", "worker"])
    last = F.when(F.col("steps") >= 1, F.element_at("done", F.greatest(F.col("steps"), F.lit(1)))).otherwise(0.0)
    cut = F.col("downloads") & (F.col("steps") < F.size("done")) & (last < F.col("round_time"))
    return both.groupBy("run_id", "round_no").agg(
        F.sum(F.greatest(F.col("steps") - quota, F.lit(0))).alias("surplus"),
        F.sum(F.when(F.col("uploads") & (F.col("steps") < quota), F.col("steps")).otherwise(0)).alias("partial"),
        F.count_if(cut).alias("cancelled"),
        F.sum(F.when(F.col("downloads"), F.col("round_time") - last).otherwise(0.0)).alias("waiting"),
    )


def idle_time(schedule: DataFrame) -> DataFrame:
    """Per run: how long workers of a wait-for-all scheme stand idle."""
    return schedule.where("downloads").groupBy("run_id").agg(F.sum(F.col("round_time") - F.coalesce("ack_time", F.lit(0.0))).alias("idle"), F.sum("round_time").alias("total"))


def uploads_from_first_steps(lines: DataFrame, schedule: DataFrame) -> DataFrame:
    """Uploads of a round by order statistics: the largest s whose s-th first completion is not after the stop."""
    first = lines.select("round_no", "worker", F.element_at("done", 1).alias("first"))
    ranked = first.withColumn("s", F.row_number().over(W.partitionBy("round_no").orderBy("first", "worker")))
    stop = schedule.groupBy("run_id", "round_no").agg(F.max("round_time").alias("stop"), F.count_if(F.col("steps") >= 1).alias("counted"))
    both = ranked.join(stop, "round_no").groupBy("run_id", "round_no").agg(F.max(F.when(F.col("first") <= F.col("stop"), F.col("s"))).alias("by_order"), F.max("counted").alias("counted"))
    return both.select("run_id", "round_no", F.coalesce("by_order", F.lit(0)).alias("by_order"), "counted")


def to_target(log: DataFrame, target: float) -> DataFrame:
    """Per run: rounds, time and messages until the accuracy first reaches the target; null if it never does."""
    hit = F.when(F.col("accuracy") >= target, F.col("round_no"))
    when = F.when(F.col("accuracy") >= target, F.struct("round_no", "cum_time", "cum_messages"))
    per = log.groupBy("run_id").agg(F.min(when).alias("at"), F.max("accuracy").alias("best"), F.count(hit).alias("rounds_at_target"))
    return per.select("run_id", (F.col("at.round_no") + 1).alias("rounds"), F.col("at.cum_time").alias("time"), F.col("at.cum_messages").alias("messages"), "best")


def accuracy_at(log: DataFrame, grid: DataFrame, axis: str = "cum_time") -> DataFrame:
    """As-of join: the last accuracy of each run within each budget of a small grid (column ``budget``)."""
    both = log.join(F.broadcast(grid), F.col(axis) <= F.col("budget"))
    return both.groupBy("run_id", "budget").agg(F.max_by("accuracy", axis).alias("accuracy"), F.max("round_no").alias("round_no"))


def curve_roughness(log: DataFrame) -> DataFrame:
    """Standard deviation of the accuracy's first difference."""
    step = F.col("accuracy") - F.lag("accuracy").over(W.partitionBy("run_id").orderBy("round_no"))
    return log.withColumn("step", step).groupBy("run_id").agg(F.stddev("step").alias("roughness"))


def frontier(results: DataFrame) -> DataFrame:
    """Results that no other beats on time and messages at once. Results are a few rows a sweep."""
    other = results.select(F.col("time").alias("_t"), F.col("messages").alias("_m"))
    better = (F.col("_t") <= F.col("time")) & (F.col("_m") <= F.col("messages")) & ((F.col("_t") < F.col("time")) | (F.col("_m") < F.col("messages")))
    return results.where(F.col("time").isNotNull()).join(F.broadcast(other.where(F.col("_t").isNotNull())), better, "left_anti")


def side_by_side(results: DataFrame, key: str, schemes: list[str], value: str) -> DataFrame:
    return results.groupBy(key).pivot("run_id", schemes).agg(F.first(value))


def summary_cube(results: DataFrame, keys: list[str], value: str) -> DataFrame:
    return results.cube(*keys).agg(F.avg(value).alias(value), F.count("*").alias("n"), F.grouping_id().cast("bigint").alias("level"))


def bytes_moved(rounds: DataFrame, size: int) -> DataFrame:
    return rounds.withColumn("bytes", F.col("messages") * F.lit(size * 8).cast("bigint"))


def assign_round(events: DataFrame, bounds: DataFrame, time: str = "t") -> DataFrame:
    """Interval join of events with rounds [start, stop) of a run (a short list, which the driver collects). Both sides are dealt into
    slices of a mean round's length, so an event meets the few rounds that share its slice."""
    rounds = bounds.select("round_no", "start", "stop").where("start < stop").collect()
    width = sum(r["stop"] - r["start"] for r in rounds) / len(rounds) if rounds else 1.0
    slice_of = lambda t: F.floor(F.col(t) / width)
    short = events.sparkSession.createDataFrame(rounds, "round_no int, start double, stop double")
    dealt = short.withColumn("_slice", F.explode(F.sequence(slice_of("start"), slice_of("stop"))))
    inside = (F.col(time) >= F.col("start")) & (F.col(time) < F.col("stop"))
    return events.withColumn("_slice", slice_of(time)).join(F.broadcast(dealt), "_slice").where(inside).drop("_slice")


def client_drift(locals_: DataFrame) -> DataFrame:
    """Mean squared distance of local models (worker, w) from their mean, by coordinate blocks."""
    parts = locals_.select("worker", F.posexplode("w").alias("pos", "v"))
    per = parts.groupBy("pos").agg(F.var_pop("v").alias("var"))
    return per.agg(F.sum("var").alias("drift"))
