"""Profiles of traces and shards: placings inside a round, moving counts, approximate sketches, histograms as maps, cogrouped chains."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def placings(lines: DataFrame, quorum: int, quota: int) -> DataFrame:
    """Per round and worker: relative places by the first step's time, and the quorum-th quota time of the round.

    Windows are over the workers of one round. ``kth_ack`` is null where fewer than ``quorum`` timelines reach the quota.
    """
    acks = lines.select("round_no", "worker", F.try_element_at("done", F.lit(1)).alias("first"), F.try_element_at("done", F.lit(quota)).alias("ack"))
    by_first = W.partitionBy("round_no").orderBy("first")
    by_ack = W.partitionBy("round_no").orderBy(F.col("ack").asc_nulls_last(), "worker").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return acks.select(
        "round_no", "worker", F.percent_rank().over(by_first).alias("share_faster"), F.cume_dist().over(by_first).alias("share_not_slower"),
        F.nth_value("ack", quorum).over(by_ack).alias("kth_ack"),
    )


def recent_steps(completions: DataFrame, seconds: int) -> DataFrame:
    """For each completion (event_id, worker, ts): how many of its worker's lie in the last ``seconds``, itself included.

    A row enters the span of time it lies in and, as context, the next one; the range frame then runs inside
    (worker, span), so no task holds a worker's whole trace. Completions without a time are left out.
    """
    span = seconds * 1_000_000
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    timed = completions.where(F.col("ts").isNotNull()).select("event_id", "worker", at.alias("at"))
    spread = timed.withColumn("late", F.explode(F.array(F.lit(0), F.lit(1)))).withColumn("span", F.floor(F.col("at") / span) + F.col("late"))
    frame = W.partitionBy("worker", "span").orderBy("at").rangeBetween(-span, 0)
    return spread.withColumn("recent", F.count("*").over(frame)).where("late = 0").select("event_id", "worker", "recent")


def trace_profile(events: DataFrame) -> DataFrame:
    """Per event type: rows, exact and sketched distinct users, exact and sketched median value, and the correlation of the
    value with the number in the JSON properties. The sketches alone need one pass and bounded memory."""
    k = F.get_json_object("props", "$.k").cast("double")
    return events.groupBy("event_type").agg(
        F.count("*").alias("n"), F.countDistinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("users_sketched"),
        F.percentile("value", F.lit(0.5)).alias("median"), F.percentile_approx("value", 0.5, 10_000).alias("median_sketched"), F.corr("value", k).alias("correlation"),
    )


def main_labels(rows: DataFrame, group: str, label: str, one_in: int) -> DataFrame:
    """Per group: the histogram of its labels as a map, and the part of it that holds at least one in ``one_in`` of its labelled rows.

    Rows are counted by (group, label) first, so a map has one entry a label whatever the group's size.
    """
    counts = rows.where(F.col(label).isNotNull()).groupBy(group, label).agg(F.count("*").alias("n"))
    hist = counts.groupBy(group).agg(F.map_from_entries(F.collect_list(F.struct(label, "n"))).alias("hist"), F.sum("n").alias("total"))
    return hist.withColumn("main", F.map_filter("hist", lambda _, n: n * one_in >= F.col("total")))


def cogrouped_chains(samples: DataFrame, schedule: DataFrame, step_size: float) -> DataFrame:
    """Local least-squares chains from zero: samples (round_no, worker, step_no, x, y) cogrouped with a schedule's steps.

    A chain takes the samples of the steps that its worker finished, in their order. A group is one worker's draws of one
    round, at most a timeline long. Workers without a finished step have no chain.
    """

    def chain(key: tuple, mine, plan):
        import pandas as pd

        steps = int(plan["steps"].max()) if len(plan) else 0
        w = 0.0
        done = mine[mine["step_no"] < steps].sort_values("step_no")
        for x, y in zip(done["x"], done["y"], strict=True):
            w -= step_size * (w * x - y) * x
        return pd.DataFrame([(*key, steps, w)] if len(done) else [], columns=["round_no", "worker", "steps", "w"])

    keys = ["round_no", "worker"]
    return samples.groupBy(*keys).cogroup(schedule.select(*keys, "steps").groupBy(*keys)).applyInPandas(chain, "round_no int, worker int, steps int, w double")
