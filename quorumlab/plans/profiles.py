"""Queries over profiles of traces and shards, join strategies, and the output modes of the stream."""

from __future__ import annotations

from pyspark.sql import functions as F

from quorumlab.operators import clock, profile
from quorumlab.plans.queries import completions, lines_of, quorum_sql, r6, steps_of_trace, trace_sql
from quorumlab.sources import tables

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str):
    def add(f):
        QUERIES[f.__name__] = f
        ORACLES[f.__name__] = sql
        return f

    return add


@query(trace_sql() + """,
a as (select round_no, worker, max(case when u = 1 then t end) first, max(case when u = 10 then t end) ack from c group by 1, 2)
select round_no, worker, round(percent_rank() over (partition by round_no order by first), 6) share_faster, round(cume_dist() over (partition by round_no order by first), 6) share_not_slower,
  round(nth_value(ack, 5) over (partition by round_no order by ack nulls last, worker rows between unbounded preceding and unbounded following), 6) kth_ack from a""")
def worker_placings(spark, sf_dir):
    out = profile.placings(lines_of(spark, sf_dir), 5, 10)
    return out.select("round_no", "worker", *[r6(c).alias(c) for c in ("share_faster", "share_not_slower", "kth_ack")])


@query("""select event_id, cast(user_id % 20 as int) worker, count(*) over (partition by user_id % 20 order by epoch_us(ts) range between 3600000000 preceding and current row) recent
from events where ts is not null""")
def steps_in_last_hour(spark, sf_dir):
    return profile.recent_steps(completions(spark, sf_dir), 3600)


@query("""select event_type, count(*) n, count(distinct user_id) users, true users_close, round(quantile_cont(value, 0.5), 6) median, true median_close,
  round(corr(value, cast(regexp_extract(props, '[0-9]+') as double)), 6) correlation from events group by 1""")
def event_profile(spark, sf_dir):
    """Sketched values are held against exact ones: both within a twentieth."""
    p = profile.trace_profile(tables.table(spark, sf_dir, "events"))
    close = lambda c: F.abs(F.col(f"{c}_sketched") - F.col(c)) * 20 <= F.col(c)
    return p.select("event_type", "n", "users", close("users").alias("users_close"), r6("median").alias("median"), close("median").alias("median_close"), r6("correlation").alias("correlation"))


@query("""with h as (select source, lang, count(*) n from documents where lang is not null group by 1, 2), t as (select *, sum(n) over (partition by source) total from h)
select source, count(*) labels, coalesce(string_agg(lang, ',' order by lang) filter (n * 5 >= total), '') main from t group by 1""")
def main_languages(spark, sf_dir):
    """Languages that hold at least a fifth of a source."""
    m = profile.main_labels(tables.table(spark, sf_dir, "documents"), "source", "lang", 5)
    return m.select("source", F.size("hist").cast("bigint").alias("labels"), F.concat_ws(",", F.array_sort(F.map_keys("main"))).alias("main"))


@query("""select h strategy, c_nationkey nation, count(*) steps from orders join customer on o_custkey = c_custkey, (values ('merge'), ('shuffle_hash')) v(h) group by 1, 2""")
def join_strategies(spark, sf_dir):
    """Work by nation through either shuffled join; orders are counted by customer before they move."""
    per = tables.table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"))
    out = None
    for hint in ("merge", "shuffle_hash"):
        both = per.join(tables.table(spark, sf_dir, "customer").hint(hint), F.col("o_custkey") == F.col("c_custkey"))
        one = both.groupBy(F.col("c_nationkey").alias("nation")).agg(F.sum("n").alias("steps")).select(F.lit(hint).alias("strategy"), "nation", "steps")
        out = one if out is None else out.unionByName(one)
    return out


@query(trace_sql() + quorum_sql(5, 10) + """
select q.round_no, q.worker, cast(steps as int) steps, round(sum(0.1 * pow(0.9, steps - 1 - step_no) * dur), 6) w from q join d on d.round_no = q.round_no and d.worker = q.worker and d.step_no < q.steps group by 1, 2, 3""")
def chains_of_workers(spark, sf_dir):
    """Each worker's running estimate of its own step time by local steps of size 0.1, over the steps it finished in a round."""
    draws = steps_of_trace(spark, sf_dir).select("round_no", "worker", "step_no", F.lit(1.0).alias("x"), F.col("dur").alias("y"))
    out = profile.cogrouped_chains(draws, clock.quorum_schedule(lines_of(spark, sf_dir), 5, 10), 0.1)
    return out.select("round_no", "worker", "steps", r6("w").alias("w"))


HOURLY = "select date_trunc('hour', ts) \"hour\", cast(user_id % 20 as int) worker, count(*) steps from events where ts is not null group by 1, 2"


def _streamed(spark, sf_dir, mode: str):
    from quorumlab.streaming import clock as live

    out = live.hourly_to_end(spark, f"{sf_dir}/events.parquet*", 20, mode)
    return out.select(F.col("hour").cast("timestamp_ntz").alias("hour"), "worker", "steps")


@query(HOURLY)
def hourly_stream_update(spark, sf_dir):
    return _streamed(spark, sf_dir, "update")


@query(HOURLY)
def hourly_stream_complete(spark, sf_dir):
    return _streamed(spark, sf_dir, "complete")
