"""The engine's registered queries and their DuckDB counterparts.

Schedules run on the duration trace in ``events`` (20 workers, 50 steps a round) unless a query says otherwise. Doubles
are rounded to six places, since the two systems' logarithms and sums may differ in the last bits.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from quorumlab.functions import rng, vec
from quorumlab.operators import averaging, clock, metrics, running, samples, theory
from quorumlab.sources import tables

M, CAP = 20, 50
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    from quorumlab.plans import profiles, workloads

    return QUERIES | workloads.QUERIES | profiles.QUERIES


def oracle_sql() -> dict[str, str]:
    from quorumlab.plans import profiles

    return ORACLES | profiles.ORACLES


def r6(c: Column | str) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, 6) + F.lit(0.0)


def steps_of_trace(spark: SparkSession, sf_dir: str, workers: int = M, cap: int = CAP) -> DataFrame:
    return tables.durations_from_trace(tables.table(spark, sf_dir, "events"), workers, cap)


def lines_of(spark: SparkSession, sf_dir: str, workers: int = M, cap: int = CAP) -> DataFrame:
    return clock.timelines(steps_of_trace(spark, sf_dir, workers, cap))


def uncut(spark: SparkSession, sf_dir: str) -> dict:
    """For plans longer than a timeline: the trace of all steps, and the cut of its rounds."""
    return {"steps": tables.uncut_steps(tables.table(spark, sf_dir, "events"), M), "cap": CAP}


def trace_sql(workers: int = M, cap: int = CAP) -> str:
    """CTEs d (durations of full rounds) and c (with completion times t and step numbers u from 1)."""
    return f"""
with e as (select cast(event_id % {workers} as int) worker, event_id // {workers} seq, value / 50.0 dur from events),
d0 as (select cast(seq // {cap} as int) round_no, worker, cast(seq % {cap} as int) step_no, dur from e),
d as (select d0.* from d0 where round_no in (select round_no from d0 group by 1 having count(*) = {workers * cap})),
c as (select *, step_no + 1 u, sum(dur) over (partition by round_no, worker order by step_no rows unbounded preceding) t from d)"""


def quorum_sql(quorum: int, quota: int, prefix: str = "") -> str:
    """CTE q: round_no, worker, steps, ack, stop, last (time of the last step of the timeline)."""
    return f""",
{prefix}a as (select round_no, worker, max(case when u = {quota} then t end) ack, max(t) last from c group by 1, 2),
{prefix}k as (select round_no, ack stop from (select *, row_number() over (partition by round_no order by ack nulls last, worker) r from {prefix}a) where r = {quorum}),
{prefix}q as (select a.round_no, a.worker, a.ack, k.stop, a.last, count(c.t) filter (c.t <= k.stop) steps
  from {prefix}a a join {prefix}k k using (round_no) join c on c.round_no = a.round_no and c.worker = a.worker group by 1, 2, 3, 4, 5)"""


def fixed_sql(steps: str, part: str = "true", prefix: str = "", extra: str = "") -> str:
    """CTE f: round_no, worker, n, part, ack, stop for schemes that wait for all; ``steps`` and ``part`` may use round_no and worker."""
    return f""",
{prefix}w as (select distinct round_no, worker from d),
{prefix}p as (select round_no, worker, {part} part, {steps} n0 from {prefix}w {extra}),
{prefix}g as (select p.round_no, p.worker, p.part, cast(case when p.part then p.n0 else 0 end as int) n, max(case when c.u = p.n0 and p.part then c.t end) ack
  from {prefix}p p join c on c.round_no = p.round_no and c.worker = p.worker group by 1, 2, 3, 4),
{prefix}f as (select *, max(ack) over (partition by round_no) stop from {prefix}g)"""


def summary_columns(schedule: DataFrame) -> DataFrame:
    s = metrics.round_summary(schedule)
    return s.select("round_no", r6("round_time").alias("round_time"), F.col("uploads").cast("bigint").alias("uploads"), F.col("messages").cast("bigint").alias("messages"), F.col("steps").cast("bigint").alias("steps"))


FIXED_SUMMARY = """
select round_no, round(max(stop), 6) round_time, count(*) filter (part and n >= 1) uploads, count(*) filter (part) + count(*) filter (part and n >= 1) messages, cast(sum(n) as bigint) steps from f group by 1"""


#: Plans (CTE z: round_no, worker, planned) that may go on beyond a round's cut into the trace; unknown where the trace ends.
UNCUT_SUMMARY = f""",
x as (select z.round_no, z.worker, z.planned, case when count(e.dur) = z.planned then sum(e.dur) end ack from z join e on e.worker = z.worker and e.seq >= z.round_no * {CAP} and e.seq < z.round_no * {CAP} + z.planned group by 1, 2, 3)
select round_no, case when count(ack) = count(*) then round(max(ack), 6) end round_time, count(*) uploads, 2 * count(*) messages, cast(sum(planned) as bigint) steps from x group by 1"""


# --- schedules ---------------------------------------------------------------------------------------------------


@query(trace_sql() + quorum_sql(5, 10) + """
select round_no, worker, cast(steps as int) steps, steps >= 1 uploads, round(ack, 6) ack_time, round(stop, 6) round_time, last <= stop capped from q""")
def quorum_schedule(spark, sf_dir):
    s = clock.quorum_schedule(lines_of(spark, sf_dir), 5, 10)
    return s.select("round_no", "worker", "steps", "uploads", r6("ack_time").alias("ack_time"), r6("round_time").alias("round_time"), "capped")


@query(trace_sql() + quorum_sql(5, 10) + """
select round_no, round(max(stop), 6) round_time, count(*) filter (steps >= 1) uploads, 20 + count(*) filter (steps >= 1) messages, cast(sum(steps) as bigint) steps from q group by 1""")
def quorum_round_summary(spark, sf_dir):
    return summary_columns(clock.quorum_schedule(lines_of(spark, sf_dir), 5, 10))


@query(trace_sql() + fixed_sql("10") + FIXED_SUMMARY)
def periodic_round_summary(spark, sf_dir):
    return summary_columns(clock.periodic_schedule(lines_of(spark, sf_dir), 10))


@query(trace_sql() + fixed_sql("1") + FIXED_SUMMARY)
def synchronous_round_summary(spark, sf_dir):
    return summary_columns(clock.periodic_schedule(lines_of(spark, sf_dir), 1, "synchronous"))


@query(trace_sql() + fixed_sql("10", f"row_number() over (partition by round_no order by {rng.hash48_sql(0, 'sample', 'round_no', 'worker')}, worker) <= 8") + FIXED_SUMMARY)
def sampled_round_summary(spark, sf_dir):
    return summary_columns(clock.sampled_schedule(lines_of(spark, sf_dir), 8, 10))


PLAN_ROWS = [(0, 0, 3, 10, 0.1), (1, 4, 6, 5, 0.1), (2, 7, 9999, 2, 0.1)]


@query(trace_sql() + fixed_sql("case when round_no <= 3 then 10 when round_no <= 6 then 5 else 2 end") + FIXED_SUMMARY)
def adaptive_fixed_plan(spark, sf_dir):
    return summary_columns(clock.planned_schedule(lines_of(spark, sf_dir), spark.createDataFrame(PLAN_ROWS, clock.PLAN)))


RANDOM_STEPS_SQL = f"greatest(1, cast(ceil(-ln((cast({rng.hash48_sql(0, 'steps', 'round_no', 'worker')} as double) + 0.5) / 281474976710656.0) * 10.0) as int))"


@query(trace_sql() + f", z as (select round_no, worker, {RANDOM_STEPS_SQL} planned from (select distinct round_no, worker from d))" + UNCUT_SUMMARY)
def random_steps_summary(spark, sf_dir):
    return summary_columns(clock.random_steps_schedule(lines_of(spark, sf_dir), 10.0, **uncut(spark, sf_dir)))


@query(trace_sql() + fixed_sql(RANDOM_STEPS_SQL) + " select round_no, worker, n steps, round(1.0 / n, 6) weight from f")
def random_steps_weights(spark, sf_dir):
    return clock.random_steps_schedule(lines_of(spark, sf_dir), 10.0).select("round_no", "worker", "steps", r6("weight").alias("weight"))


@query(trace_sql() + quorum_sql(10, 5) + """
select round_no, worker, cast(steps as int) steps, ack <= stop uploads, round(stop, 6) round_time from q""")
def ablation_fast_only(spark, sf_dir):
    return clock.quorum_schedule(lines_of(spark, sf_dir), 10, 5, keep_partial=False).select("round_no", "worker", "steps", "uploads", r6("round_time").alias("round_time"))


@query(trace_sql() + quorum_sql(10, 5) + """
select round_no, worker, cast(least(steps, 5) as int) steps, steps >= 1 uploads, round(stop, 6) round_time from q""")
def ablation_straggler_only(spark, sf_dir):
    return clock.quorum_schedule(lines_of(spark, sf_dir), 10, 5, keep_surplus=False).select("round_no", "worker", "steps", "uploads", r6("round_time").alias("round_time"))


@query(trace_sql() + quorum_sql(10, 5) + """
select round_no, round(max(stop), 6) round_time, count(*) filter (ack <= stop) uploads, 20 + count(*) filter (ack <= stop) messages, cast(sum(least(steps, 5)) as bigint) steps from q group by 1""")
def plain_quorum_summary(spark, sf_dir):
    return summary_columns(clock.quorum_schedule(lines_of(spark, sf_dir), 10, 5, False, False))


DEADLINE_SQL = trace_sql() + """,
n as (select round_no, worker, least(count(*) filter (t <= 8.0), 10) n from c group by 1, 2)
select round_no, 8.0::double round_time, count(*) filter ({up}) uploads, 20 + count(*) filter ({up}) messages, cast(sum(n) as bigint) steps from n group by 1"""


@query(DEADLINE_SQL.format(up="n = 10"))
def complete_only_summary(spark, sf_dir):
    return summary_columns(clock.deadline_schedule(lines_of(spark, sf_dir), 8.0, 10, True))


@query(DEADLINE_SQL.format(up="n >= 1"))
def complete_and_incomplete_summary(spark, sf_dir):
    return summary_columns(clock.deadline_schedule(lines_of(spark, sf_dir), 8.0, 10, False))


@query(trace_sql() + quorum_sql(5, 1) + """
select round_no, round(max(stop), 6) round_time, count(*) filter (ack <= stop) uploads, 20 + count(*) filter (ack <= stop) messages, cast(sum(least(steps, 1)) as bigint) steps from q group by 1""")
def quorum_gradient_summary(spark, sf_dir):
    return summary_columns(clock.quorum_gradient_schedule(lines_of(spark, sf_dir), 5))


@query(trace_sql() + """,
u as (select * from (select round_no, worker, t, row_number() over (partition by round_no order by t, worker, u) r from c) where r <= 5)
select round_no, round(max(t), 6) round_time, count(distinct worker) uploads, 20 + count(distinct worker) messages, count(*) steps from u group by 1""")
def quorum_batches_summary(spark, sf_dir):
    return summary_columns(clock.quorum_batches_schedule(lines_of(spark, sf_dir), 5))


ASYNC_SQL = trace_sql() + """,
o as (select worker, row_number() over (partition by worker order by round_no, step_no) nth, sum(dur) over (partition by worker order by round_no, step_no rows unbounded preceding) t from d),
v as (select *, row_number() over (order by t, worker, nth) - 1 v from o),
s as (select *, v - coalesce(lag(v) over (partition by worker order by nth) + 1, 0) staleness from v)
"""


@query(ASYNC_SQL + "select worker, count(*) updates, max(staleness) max_staleness, round(avg(staleness), 6) mean_staleness from s group by 1")
def async_staleness(spark, sf_dir):
    e = clock.async_events(steps_of_trace(spark, sf_dir))
    return e.groupBy("worker").agg(F.count("*").alias("updates"), F.max("staleness").alias("max_staleness"), r6(F.avg("staleness")).alias("mean_staleness"))


@query(trace_sql() + """,
o as (select worker, row_number() over (partition by worker order by round_no, step_no) - 1 n, dur from d),
g as (select worker, n // 5 nth, sum(dur) dur from o group by 1, 2 having count(*) = 5),
h as (select worker, nth, sum(dur) over (partition by worker order by nth rows unbounded preceding) t from g),
v as (select *, row_number() over (order by t, worker, nth) - 1 v from h),
s as (select *, v - coalesce(lag(v) over (partition by worker order by nth) + 1, 0) staleness from v)
select worker, count(*) updates, max(staleness) max_staleness, round(avg(staleness), 6) mean_staleness from s group by 1""")
def async_multi_step_staleness(spark, sf_dir):
    e = clock.async_multi_step(steps_of_trace(spark, sf_dir), 5)
    return e.groupBy("worker").agg(F.count("*").alias("updates"), F.max("staleness").alias("max_staleness"), r6(F.avg("staleness")).alias("mean_staleness"))


@query(trace_sql() + """,
p as (select round_no, worker, (worker - (u - 1) + 20) % 20 piece, t from c where u <= 3),
f as (select round_no, piece, min(t) t, arg_min(worker, struct_pack(t := t, w := worker)) worker from p group by 1, 2)
select round_no, round(max(t), 6) round_time, count(distinct worker) uploads, count(*) pieces from f group by 1""")
def redundant_summary(spark, sf_dir):
    s = clock.redundant_schedule(lines_of(spark, sf_dir), M, 3)
    return s.groupBy("round_no").agg(r6(F.max("round_time")).alias("round_time"), F.count_if("uploads").alias("uploads"), F.sum("weight").cast("bigint").alias("pieces"))


@query(trace_sql() + fixed_sql("worker % 4 + 2") + FIXED_SUMMARY)
def fixed_steps_summary(spark, sf_dir):
    return summary_columns(clock.fixed_steps_schedule(lines_of(spark, sf_dir), F.col("worker") % 4 + 2))


REASSIGN_SQL = trace_sql() + """,
o as (select round_no, worker, avg(case when u = 1 then t end) t1 from c group by 1, 2),
p as (select *, avg(t1) over (partition by worker order by round_no rows between 5 preceding and 1 preceding) own from o),
m as (select round_no, quantile_cont(own, 0.5) med from p group by 1),
q as (select p.*, med, case when own > 1.5 * med then greatest(1, floor(10 * med / own)) else 10 end cut from p join m using (round_no)),
y as (select *, sum(10 - cut) over (partition by round_no) surplus, row_number() over (partition by round_no order by own nulls last, worker) rk from q),
z as (select round_no, worker, cast(cut + case when rk = 1 then surplus else 0 end as int) planned from y)"""


@query(REASSIGN_SQL + " select * from z")
def reassigned_steps(spark, sf_dir):
    return clock.reassigned_quota(lines_of(spark, sf_dir), 10, 1.5, 5).select("round_no", "worker", "planned")


@query(REASSIGN_SQL + UNCUT_SUMMARY)
def reassign_summary(spark, sf_dir):
    return summary_columns(clock.reassign_schedule(lines_of(spark, sf_dir), 10, **uncut(spark, sf_dir)))


@query(trace_sql() + """,
p as (select s stage, cast(4 * (power(2, s) - 1) as int) first_round, cast(4 * (power(2, s + 1) - 1) - 1 as int) last_round, cast(2 * power(2, s) as int) period, 0.1 / power(2, s) step_size from (select unnest(range(5))::int s)),
r as (select round_no, count(*) steps from d group by 1)
select stage, first_round, last_round, period, step_size, count(round_no) rounds, coalesce(cast(sum(steps) as bigint), 0) steps
from p left join r on round_no >= first_round and (round_no <= last_round or stage = 4) group by 1, 2, 3, 4, 5""")
def stage_plan(spark, sf_dir):
    """The stages, with the rounds and steps of the trace that fall into each; the last stage has no end."""
    plan = spark.createDataFrame(clock.stagewise_rows(5, 0.1, 2, 4), clock.PLAN)
    rounds = steps_of_trace(spark, sf_dir).groupBy("round_no").agg(F.count("*").alias("steps"))
    inside = (F.col("round_no") >= F.col("first_round")) & ((F.col("round_no") <= F.col("last_round")) | (F.col("stage") == 4))
    own = rounds.join(F.broadcast(plan.select("stage", "first_round", "last_round")), inside).groupBy("stage").agg(F.count("*").alias("rounds"), F.sum("steps").alias("steps"))
    return plan.join(F.broadcast(own), "stage", "left").select(*plan.columns, F.coalesce("rounds", F.lit(0)).alias("rounds"), F.coalesce("steps", F.lit(0)).alias("steps"))


@query(trace_sql() + fixed_sql("case when round_no <= 3 then 2 when round_no <= 11 then 4 when round_no <= 27 then 8 when round_no <= 59 then 16 else 32 end") + FIXED_SUMMARY)
def stagewise_summary(spark, sf_dir):
    plan = spark.createDataFrame(clock.stagewise_rows(5, 0.1, 2, 4), clock.PLAN)
    return summary_columns(clock.planned_schedule(lines_of(spark, sf_dir), plan, "stagewise", open_end=True))


@query(trace_sql() + """,
a as (select round_no, worker, max(case when u = 10 - 2 * least(round_no, 4) then t end) ack from c group by 1, 2),
k as (select round_no, ack stop from (select *, row_number() over (partition by round_no order by ack nulls last, worker) r from a) where r = 5),
q as (select c.round_no, c.worker, k.stop, count(*) filter (c.t <= k.stop) steps from c join k using (round_no) group by 1, 2, 3)
select round_no, round(max(stop), 6) round_time, count(*) filter (steps >= 1) uploads, 20 + count(*) filter (steps >= 1) messages, cast(sum(steps) as bigint) steps from q group by 1""")
def quorum_adaptive_summary(spark, sf_dir):
    """The main method with a quota that shrinks over rounds."""
    quota = 10 - 2 * F.least(F.col("round_no"), F.lit(4))
    return summary_columns(clock.quorum_schedule(lines_of(spark, sf_dir), 5, quota, run_id="quorum_adaptive"))


LINK_SQL = f"(-ln((cast({rng.hash48_sql(0, 'link', 'a.round_no', 'a.worker')} as double) + 0.5) / 281474976710656.0) * 0.5)"


@query(trace_sql() + f""",
a0 as (select round_no, worker, max(case when u = 10 then t end) ack from c group by 1, 2),
a as (select a.round_no, a.worker, a.ack + {LINK_SQL} ack from a0 a),
k as (select round_no, ack stop from (select *, row_number() over (partition by round_no order by ack nulls last, worker) r from a) where r = 5),
q as (select c.round_no, c.worker, k.stop, count(*) filter (c.t <= k.stop) steps from c join k using (round_no) group by 1, 2, 3)
select round_no, round(max(stop), 6) round_time, count(*) filter (steps >= 1) uploads, 20 + count(*) filter (steps >= 1) messages, cast(sum(steps) as bigint) steps from q group by 1""")
def quorum_link_summary(spark, sf_dir):
    """The main method over a medium with a random link time for each acknowledgement."""
    link = rng.exponential(0.5, 0, "link", F.col("round_no"), F.col("worker"))
    return summary_columns(clock.quorum_schedule(lines_of(spark, sf_dir), 5, 10, link=link))


@query(trace_sql() + """,
h as (select worker, u, t from c where round_no = 0 and worker < 4),
a as (select worker, max(t) filter (u = 3) ack from h group by 1), k as (select ack stop from a order by ack, worker limit 1 offset 2)
select 'quorum of 3' shape, worker, cast(count(*) filter (t <= stop) as int) steps, count(*) filter (t <= stop) >= 1 uploads, round(max(stop), 6) round_time from h, k group by 2
union all select 'two of the first three', worker, case when worker < 2 then 3 else 0 end, worker < 2, (select round(max(ack), 6) from a where worker < 2) from a""")
def two_shapes(spark, sf_dir):
    """Two shapes of the trace's first round for four of its workers: it ends with the third worker's third step, or two chosen workers make
    three steps each."""
    lines = lines_of(spark, sf_dir).where("round_no = 0 and worker < 4")
    chosen = clock.fixed_steps_schedule(lines, F.lit(3), F.col("worker") < 2)
    said = lambda s, name: s.select(F.lit(name).alias("shape"), "worker", "steps", "uploads", r6("round_time").alias("round_time"))
    return said(clock.quorum_schedule(lines, 3, 3), "quorum of 3").unionByName(said(chosen, "two of the first three"))


@query(trace_sql(40, 25) + quorum_sql(30, 2) + """
select cast(steps as int) steps, case when steps > 2 then 'surplus' when steps = 2 then 'exact' when steps >= 1 then 'partial' else 'none' end class, count(*) workers from q where round_no = (select max(round_no) from q) group by 1, 2""")
def histogram_of_one_round(spark, sf_dir):
    """Steps of 40 workers in the last full round of the trace, quorum 30, quota 2."""
    steps = steps_of_trace(spark, sf_dir, 40, 25)
    last = steps.join(F.broadcast(steps.agg(F.max("round_no").alias("round_no"))), "round_no")
    return metrics.step_histogram(clock.quorum_schedule(clock.timelines(last), 30, 2), 2).select("steps", "class", "workers")


# --- measures ----------------------------------------------------------------------------------------------------


@query(trace_sql() + quorum_sql(5, 10) + """,
x as (select q.round_no, max(c.t) t from q join c on c.round_no = q.round_no and c.worker = q.worker and c.u = q.steps where q.steps >= 1 group by 1)
select round_no, round(t, 6) upload_time from x""")
def realised_round_time(spark, sf_dir):
    lines = lines_of(spark, sf_dir)
    return metrics.upload_time(lines, clock.quorum_schedule(lines, 5, 10)).select("round_no", r6("upload_time").alias("upload_time"))


@query(trace_sql() + quorum_sql(5, 10) + """,
b as (select round_no, min(t) t1, worker from c group by 1, 3), s as (select round_no, max(stop) stop, count(*) filter (steps >= 1) counted from q group by 1)
select s.round_no, count(*) filter (b.t1 <= s.stop) by_order, counted from s join b using (round_no) group by 1, 3""")
def uploads_order_stat(spark, sf_dir):
    lines = lines_of(spark, sf_dir)
    u = metrics.uploads_from_first_steps(lines, clock.quorum_schedule(lines, 5, 10))
    return u.select("round_no", F.col("by_order").cast("bigint").alias("by_order"), "counted")


@query(trace_sql(40, 12) + quorum_sql(30, 2) + """
select cast(steps as int) steps, case when steps > 2 then 'surplus' when steps = 2 then 'exact' when steps >= 1 then 'partial' else 'none' end class, count(*) workers from q where round_no = 0 group by 1, 2""")
def step_histogram(spark, sf_dir):
    s = clock.quorum_schedule(lines_of(spark, sf_dir, 40, 12), 30, 2)
    return metrics.step_histogram(s, 2, 0).select("steps", "class", "workers")


@query(trace_sql(40, 12) + quorum_sql(30, 2) + """,
r as (select round_no, max(stop) stop, count(*) filter (steps >= 1) uploads, count(*) filter (last <= stop) capped from q group by 1)
select count(*) rounds, round(avg(uploads), 6) mean_uploads, round(avg(stop), 6) mean_time, cast(sum(capped) as bigint) capped, (select round(avg(steps), 6) from q) mean_steps from r""")
def empirical_means(spark, sf_dir):
    m = metrics.empirical_means(clock.quorum_schedule(lines_of(spark, sf_dir, 40, 12), 30, 2))
    return m.select("rounds", r6("mean_uploads").alias("mean_uploads"), r6("mean_time").alias("mean_time"), "capped", r6("mean_steps").alias("mean_steps"))


@query(trace_sql() + quorum_sql(5, 10) + """,
x as (select q.*, coalesce(max(c.t) filter (c.u = q.steps), 0) last_done, max(c.u) n from q join c on c.round_no = q.round_no and c.worker = q.worker group by all)
select round_no, cast(sum(greatest(steps - 10, 0)) as bigint) surplus, cast(sum(case when steps >= 1 and steps < 10 then steps else 0 end) as bigint) partial, count(*) filter (steps < n and last_done < stop) cancelled,
  round(sum(stop - last_done), 6) waiting from x group by 1""")
def work_accounting(spark, sf_dir):
    lines = lines_of(spark, sf_dir)
    a = metrics.work_accounting(clock.quorum_schedule(lines, 5, 10), lines, 10)
    return a.select("round_no", "surplus", "partial", "cancelled", r6("waiting").alias("waiting"))


@query(trace_sql() + fixed_sql("10") + " select round(sum(stop - coalesce(ack, 0)), 6) idle, round(sum(stop), 6) total from f")
def idle_time(spark, sf_dir):
    return metrics.idle_time(clock.periodic_schedule(lines_of(spark, sf_dir), 10)).select(r6("idle").alias("idle"), r6("total").alias("total"))


@query(trace_sql() + quorum_sql(5, 10) + """,
r as (select round_no, max(stop) t, 20 + count(*) filter (steps >= 1) m from q group by 1)
select round_no, round(sum(t) over (order by round_no rows unbounded preceding), 6) cum_time, cast(sum(m) over (order by round_no rows unbounded preceding) as bigint) cum_messages from r""")
def cumulative_costs(spark, sf_dir):
    a = metrics.accumulate(metrics.round_summary(clock.quorum_schedule(lines_of(spark, sf_dir), 5, 10)))
    return a.select("round_no", r6("cum_time").alias("cum_time"), F.col("cum_messages").cast("bigint").alias("cum_messages"))


def all_schemes(spark, sf_dir) -> DataFrame:
    lines = lines_of(spark, sf_dir)
    runs = [clock.quorum_schedule(lines, 5, 10), clock.quorum_schedule(lines, 5, 10, keep_partial=False, run_id="fast_surplus_only"), clock.periodic_schedule(lines, 10), clock.sampled_schedule(lines, 8, 10)]
    out = runs[0]
    for r in runs[1:]:
        out = out.unionByName(r)
    return out


ALL_SQL = trace_sql() + quorum_sql(5, 10) + fixed_sql("10") + fixed_sql("10", f"row_number() over (partition by round_no order by {rng.hash48_sql(0, 'sample', 'round_no', 'worker')}, worker) <= 8", "s") + """,
al as (select 'quorum_stop' run_id, round_no, worker, steps >= 1 up, true down, stop from q union all
  select 'fast_surplus_only', round_no, worker, ack <= stop, true, stop from q union all
  select 'periodic_average', round_no, worker, part and n >= 1, part, stop from f union all
  select 'sampled_average', round_no, worker, part and n >= 1, part, stop from sf)"""


@query(ALL_SQL + """
select run_id, round_no, count(*) filter (up) + count(*) filter (down) messages, round(max(stop), 6) round_time from al group by 1, 2""")
def messages_by_scheme(spark, sf_dir):
    s = metrics.round_summary(all_schemes(spark, sf_dir))
    return s.select("run_id", "round_no", F.col("messages").cast("bigint").alias("messages"), r6("round_time").alias("round_time"))


@query(ALL_SQL + """,
r as (select run_id, round_no, count(*) filter (up) + count(*) filter (down) messages, max(stop) round_time from al group by 1, 2)
select run_id, round_no % 2 parity, round(avg(round_time), 6) round_time, count(*) n, cast(grouping(run_id) * 2 + grouping(round_no % 2) as bigint) level from r group by cube (run_id, round_no % 2)""")
def cube_summary(spark, sf_dir):
    s = metrics.round_summary(all_schemes(spark, sf_dir)).withColumn("parity", F.col("round_no") % 2)
    out = metrics.summary_cube(s, ["run_id", "parity"], "round_time")
    return out.select("run_id", "parity", r6("round_time").alias("round_time"), "n", "level")


@query(ALL_SQL + """,
r as (select run_id, round_no, max(stop) t from al group by 1, 2)
select round_no, round(max(t) filter (run_id = 'quorum_stop'), 6) quorum_stop, round(max(t) filter (run_id = 'periodic_average'), 6) periodic_average from r group by 1""")
def schemes_side_by_side(spark, sf_dir):
    s = metrics.round_summary(all_schemes(spark, sf_dir))
    out = metrics.side_by_side(s, "round_no", ["quorum_stop", "periodic_average"], "round_time")
    return out.select("round_no", r6("quorum_stop").alias("quorum_stop"), r6("periodic_average").alias("periodic_average"))


@query(trace_sql() + quorum_sql(5, 10) + ", z as (select distinct worker from q where round_no = 0 and steps >= 10) select worker, true acked from z union all select distinct worker, false from q where worker not in (select worker from z)")
def semi_anti_workers(spark, sf_dir):
    s = clock.quorum_schedule(lines_of(spark, sf_dir), 5, 10)
    acked = s.where("round_no = 0 and steps >= 10").select("worker").distinct()
    every = s.select("worker").distinct()
    return every.join(acked, "worker", "left_semi").withColumn("acked", F.lit(True)).unionByName(every.join(acked, "worker", "left_anti").withColumn("acked", F.lit(False)))


@query(trace_sql() + quorum_sql(5, 10) + """,
m as (select round_no, worker from q where steps >= 1), f as (select round_no, worker from q where ack <= stop)
select 'lost' kind, * from (select * from m except select * from f) union all select 'both', * from (select * from m intersect select * from f)""")
def setop_uploaders(spark, sf_dir):
    """Uploaders that the fast-only ablation loses, and those that both have."""
    lines = lines_of(spark, sf_dir)
    up = lambda s: s.where("uploads").select("round_no", "worker")
    main, fast = up(clock.quorum_schedule(lines, 5, 10)), up(clock.quorum_schedule(lines, 5, 10, keep_partial=False))
    lost, both = main.exceptAll(fast).withColumn("kind", F.lit("lost")), main.intersect(fast).withColumn("kind", F.lit("both"))
    return lost.unionByName(both).select("kind", "round_no", "worker")


@query(trace_sql() + quorum_sql(5, 10) + """,
b as (select round_no, sum(t) over (order by round_no rows unbounded preceding) - t "start", sum(t) over (order by round_no rows unbounded preceding) stop from (select round_no, max(stop) t from q group by 1)),
ev as (select worker, sum(dur) over (partition by worker order by round_no, step_no rows unbounded preceding) t from d)
select b.round_no, count(*) events, count(distinct worker) workers from ev join b on ev.t >= b."start" and ev.t < b.stop group by 1""")
def round_of_event(spark, sf_dir):
    """Interval join: which round of the main method each step of the uninterrupted trace falls into. Steps may end exactly when a round
    does, so both sums add in the SQL's order."""
    s = metrics.round_summary(clock.quorum_schedule(lines_of(spark, sf_dir), 5, 10)).select(F.lit(0).alias("run"), "round_no", "round_time")
    a = running.running_sums(s, "run", ["round_no"], "round_time", "stop")
    bounds = a.select("round_no", (F.col("stop") - F.col("round_time")).alias("start"), "stop")
    events = running.running_sums(steps_of_trace(spark, sf_dir), "worker", ["round_no", "step_no"], "dur", "t").select("worker", "t")
    return metrics.assign_round(events, bounds).groupBy("round_no").agg(F.count("*").alias("events"), F.countDistinct("worker").alias("workers"))


# --- theory ------------------------------------------------------------------------------------------------------

GRID = [(40, 30, 2), (20, 10, 5), (20, 5, 10), (20, 10, 10), (20, 15, 10), (20, 20, 10), (20, 5, 5), (20, 5, 1), (20, 5, 20)]


def counts_sql(cells: list[tuple[int, int, int]]) -> str:
    """CTEs up to x: expected steps and uploads of settings, by midpoint sums."""
    return f"""with s(workers, quorum, quota) as (values {", ".join(f"({m}, {k}, {u})" for m, k, u in cells)}),
g as (select *, (quota + 14 * sqrt(quota) + 40) / 4000 dt, unnest(range(4000)) i from s),
h as (select *, (i + 0.5) * dt t, lgamma(workers + 1) - lgamma(quorum) - lgamma(workers - quorum + 1) lw, lgamma(quota) lq from g),
j as (select *, exp(-t) * list_sum(list_transform(range(quota), lambda x: exp(x * ln(t) - lgamma(x + 1)))) tail from h),
fd as (select *, exp(lw + (quorum - 1) * ln(greatest(1 - tail, 1e-300)) + (workers - quorum) * ln(greatest(tail, 1e-300)) + (quota - 1) * ln(t) - t - lq) f from j),
ei as (select workers, quorum, quota, sum(t * f * dt) e, sum(case when tail > 1e-290 then f * (1 - exp(-t) / tail) * dt else 0 end) p from fd group by 1, 2, 3),
x as (select workers, quorum, quota, e expected_steps, workers * (1 - exp(-e)) uploads_approx, greatest(quorum, workers * (1 - exp(-e))) uploads_clamped, quorum + (workers - quorum) * p uploads_exact from ei)"""


#: CTE mu: the mean step duration of the trace, in which the closed forms' times are given.
MEAN_SQL = ", mu as (select avg(value / 50.0) mu from events)"


def mean_duration(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row (mu), for a broadcast."""
    return F.broadcast(tables.table(spark, sf_dir, "events").agg(F.avg(F.col("value") / 50.0).alias("mu")))


COUNTS = ("expected_steps", "uploads_approx", "uploads_clamped", "uploads_exact")


def r5(c: str) -> Column:
    return (F.round(c, 5) + F.lit(0.0)).alias(c)


@query(counts_sql(GRID) + MEAN_SQL + " select workers, quorum, quota, " + ", ".join(f"round({c}, 5) {c}" for c in COUNTS) + ", round(expected_steps * mu, 5) round_time from x, mu")
def expected_counts_grid(spark, sf_dir):
    """Expected steps and uploads, and the expected round time at the trace's mean step duration."""
    e = theory.expected_counts(theory.settings(spark, GRID)).crossJoin(mean_duration(spark, sf_dir)).withColumn("round_time", F.col("expected_steps") * F.col("mu"))
    return e.select("workers", "quorum", "quota", *map(r5, COUNTS), r5("round_time"))


@query("with" + MEAN_SQL[1:] + """
select s, round(list_sum(list_transform(range(20 - s + 1, 21), lambda x: 1.0 / x)) * mu, 6) harmonic, case when s < 20 then round(ln(20.0 / (20 - s)) * mu, 6) end logarithm from (select unnest(range(1, 21))::int s), mu""")
def expected_first_step(spark, sf_dir):
    """Expected time until s of 20 workers have a step, at the trace's mean step duration."""
    e = theory.expected_first_step(spark, M).crossJoin(mean_duration(spark, sf_dir))
    return e.select("s", *[r6(F.col(c) * F.col("mu")).alias(c) for c in ("harmonic", "logarithm")])


MONOTONE = [(20, k, u) for k in (1, 5, 10, 15, 20) for u in (1, 5, 10, 20)]
RISES = [(f"{name}_rise_in_{by}", c, over) for by, over in (("quorum", "quota"), ("quota", "quorum")) for name, c in (("steps", "expected_steps"), ("uploads", "uploads_exact"))]


@query(counts_sql(MONOTONE) + MEAN_SQL + " select workers, quorum, quota, " + ", ".join(f"round({c}, 5) {c}" for c in COUNTS) + ", " + ", ".join(f"round({c} - lag({c}) over (partition by workers, {over} order by {name.split('_in_')[1]}), 5) {name}" for name, c, over in RISES) + ", round(expected_steps * mu, 5) round_time from x, mu")
def monotone_grid(spark, sf_dir):
    """Expected steps, uploads and round time (at the trace's mean step duration) over the quorum and quota grid, with the rise to the next setting."""
    e = theory.monotone_grid(theory.settings(spark, MONOTONE)).crossJoin(mean_duration(spark, sf_dir)).withColumn("round_time", F.col("expected_steps") * F.col("mu"))
    return e.select("workers", "quorum", "quota", *map(r5, COUNTS), *[r5(name) for name, _, _ in RISES], r5("round_time"))


@query(trace_sql(40, 25) + quorum_sql(30, 2) + ", r as (select round_no, max(stop) stop, count(*) filter (steps >= 1) uploads, count(*) filter (last <= stop) capped from q group by 1)," + counts_sql([(40, 30, 2)]).removeprefix("with ") + """
select (select count(*) from r) rounds, (select round(avg(steps), 6) from q) mean_steps, (select round(avg(uploads), 6) from r) mean_uploads, (select round(avg(stop), 6) from r) mean_time, (select cast(sum(capped) as bigint) from r) capped,
  round(expected_steps, 5) expected_steps, round(uploads_approx, 5) uploads_approx, round(uploads_exact, 5) uploads_exact from x""")
def means_against_formulas(spark, sf_dir):
    """The trace's rounds at quorum 30 of 40, quota 2: measured means of steps and uploads beside the closed forms."""
    lines = lines_of(spark, sf_dir, 40, 25)
    e = metrics.empirical_means(clock.quorum_schedule(lines, 30, 2))
    t = theory.expected_counts(theory.settings(spark, [(40, 30, 2)]))
    both = e.crossJoin(F.broadcast(t))
    return both.select("rounds", r6("mean_steps").alias("mean_steps"), r6("mean_uploads").alias("mean_uploads"), r6("mean_time").alias("mean_time"), "capped", *[r5(c) for c in COUNTS if c != "uploads_clamped"])


CELLS = [(20, k, u) for k in (1, 5, 10, 15) for u in (1, 5, 10)]


@query(trace_sql() + f""",
st(quorum, quota) as (values {", ".join(f"({k}, {u})" for _, k, u in CELLS)}),
a as (select quorum, quota, round_no, worker, max(t) filter (u = quota) ack, max(t) last from st, c group by 1, 2, 3, 4),
kk as (select quorum, quota, round_no, ack stop from (select *, row_number() over (partition by quorum, quota, round_no order by ack nulls last, worker) r from a) where r = quorum),
n as (select kk.quorum, kk.quota, round_no, worker, count(*) filter (t <= stop) steps, max(t) <= max(stop) capped from kk join c using (round_no) group by 1, 2, 3, 4),
r as (select quorum, quota, round_no, count(*) filter (steps >= 1) uploads, count(*) filter (capped) capped from n group by 1, 2, 3),
mu as (select quorum, quota, round(avg(uploads), 6) mean_uploads, cast(sum(capped) as bigint) capped from r group by 1, 2), ms as (select quorum, quota, round(avg(steps), 6) mean_steps from n group by 1, 2),""" + counts_sql(CELLS).removeprefix("with ") + """
select quorum, quota, mean_steps, mean_uploads, capped, """ + ", ".join(f"round({c}, 5) {c}" for c in COUNTS) + " from mu join ms using (quorum, quota) join x using (quorum, quota)")
def uploads_over_settings(spark, sf_dir):
    """Expected and measured uploads as quorum and quota grow."""
    lines = lines_of(spark, sf_dir)
    out = None
    for _, k, u in CELLS:
        m = metrics.empirical_means(clock.quorum_schedule(lines, k, u, run_id=f"{k},{u}"))
        m = m.select(F.lit(k).alias("quorum"), F.lit(u).alias("quota"), r6("mean_steps").alias("mean_steps"), r6("mean_uploads").alias("mean_uploads"), "capped")
        out = m if out is None else out.unionByName(m)
    return out.join(F.broadcast(theory.expected_counts(theory.settings(spark, CELLS)).select("quorum", "quota", *map(r5, COUNTS))), ["quorum", "quota"])


BOUND_SETTINGS = [(5, 10), (10, 5), (20, 10)]


def bound_sql(mean: str, most: str, apart: float) -> str:
    """The bound at step size 0.01, batch 100, smoothness 2, noise 4, c = 1/2, with expressions for mean and largest steps."""
    return f"((1.0 / (0.01 * {mean} * rounds)) + 0.01 * {most} * 2.0 * 4.0 / (2.0 * quorum * 100 * {mean}) + 5.0 * 0.0001 * power({most}, 3) * 4.0 * (4.0 + 6.0 * {most} * {apart}) / (2.0 * {mean} * {mean})) / 0.5"


#: CTE s: mean and largest steps of the trace's rounds in each setting.
MEASURED = trace_sql() + "".join(quorum_sql(k, q, f"b{k}_{q}") for k, q in BOUND_SETTINGS) + ", s as (" + " union all ".join(f"select {k} quorum, {q} quota, avg(steps)::double e, max(steps)::double u from b{k}_{q}q" for k, q in BOUND_SETTINGS) + ")"
BOUND_CTE = MEASURED + ", x as (select *, quota::double q from s, (values (100), (1000), (10000)) j(rounds))"


def measured_steps(spark, sf_dir) -> DataFrame:
    """(quorum, quota, e, u): mean and largest steps of a worker in the rounds of the trace."""
    lines, out = lines_of(spark, sf_dir), None
    for k, q in BOUND_SETTINGS:
        steps = clock.quorum_schedule(lines, k, q).agg(F.avg("steps").alias("e"), F.max("steps").cast("double").alias("u"))
        own = steps.select(F.lit(k).alias("quorum"), F.lit(q).alias("quota"), "e", "u")
        out = own if out is None else out.unionByName(own)
    return out


def bound_cells(spark, sf_dir) -> DataFrame:
    return measured_steps(spark, sf_dir).crossJoin(F.broadcast(spark.createDataFrame([(100,), (1000,), (10000,)], "rounds int")))


def bound_of(mean: Column, most: Column, apart: float) -> Column:
    return theory.bound_column(F.lit(0.01), mean, most, F.col("quorum"), F.col("rounds"), 2.0, 100, 4.0, apart, 1.0)


@query(BOUND_CTE + f" select quorum, quota, rounds, round({bound_sql('e', 'u', 0.5)}, 6) bound from x")
def bound_table(spark, sf_dir):
    return bound_cells(spark, sf_dir).select("quorum", "quota", "rounds", r6(bound_of(F.col("e"), F.col("u"), 0.5)).alias("bound"))


@query(BOUND_CTE + f" select quorum, quota, rounds, round({bound_sql('e', 'u', 0.0)}, 6) bound, round({bound_sql('e', 'u', 0.5)} - {bound_sql('e', 'u', 0.0)}, 6) saved from x")
def bound_homogeneous(spark, sf_dir):
    """The bound where all workers draw from one distribution, and what that takes off the general one."""
    same, apart = (bound_of(F.col("e"), F.col("u"), v) for v in (0.0, 0.5))
    return bound_cells(spark, sf_dir).select("quorum", "quota", "rounds", r6(same).alias("bound"), r6(apart - same).alias("saved"))


@query(BOUND_CTE + f" select quorum, quota, rounds, round({bound_sql('q', 'q', 0.5)}, 6) equal_steps, round({bound_sql('q', 'q', 0.5)} - {bound_sql('e', 'u', 0.5)}, 6) gap from x")
def bound_equal_steps(spark, sf_dir):
    """The bound of equal steps for all workers, and how far it lies above that of the main method."""
    equal = bound_of(F.col("quota").cast("double"), F.col("quota").cast("double"), 0.5)
    return bound_cells(spark, sf_dir).select("quorum", "quota", "rounds", r6(equal).alias("equal_steps"), r6(equal - bound_of(F.col("e"), F.col("u"), 0.5)).alias("gap"))


@query(MEASURED + """
select quorum, quota, round(least(e / (sqrt(30) * 2.0 * u * u), quorum * quorum / (2.0 * e * 400)), 9) max_step, round(sqrt(quorum) / (sqrt(e * 1000) * 2.0), 9) rate_step,
  cast(ceil(greatest(30 * quorum * power(u, 4) / power(e, 3), e * 160000 / power(quorum, 3))) as bigint) min_rounds, round(1 / sqrt(quorum * quota * 1000) + 0.001, 9) rate_term from s""")
def step_size_table(spark, sf_dir):
    rows = [(k, q, round(theory.max_step_size(e, u, 2.0, k, 20), 9), round(theory.rate_step_size(k, e, 1000, 2.0), 9), theory.min_rounds(k, 20, e, u), round(theory.rate_term(k, q, 1000), 9)) for k, q, e, u in measured_steps(spark, sf_dir).collect()]  # three rows
    return spark.createDataFrame(rows, "quorum int, quota int, max_step double, rate_step double, min_rounds bigint, rate_term double")


# --- samples, splits, models ----------------------------------------------------------------------------------------


@query("select worker, count(*) n from (select (row_number() over (order by " + rng.hash48_sql(0, "split", "doc_id") + ", doc_id) - 1) % 20 worker from documents) group by 1")
def split_random_sizes(spark, sf_dir):
    s = samples.even_random(samples.language_task(spark, sf_dir).select("row_id", "y"), M)
    return s.groupBy(F.col("worker").cast("bigint").alias("worker")).agg(F.count("*").alias("n"))


@query("""select cast((r * 20) // n as int) worker, y, count(*) rows from (select row_number() over (order by y, doc_id) - 1 r, y, count(*) over () n
from (select doc_id, cast(list_position(['de', 'en', 'es', 'fr'], lang) - 1 as int) y from documents)) group by 1, 2""")
def split_label_histogram(spark, sf_dir):
    s = samples.even_by_label(samples.language_task(spark, sf_dir).select("row_id", "y"), M)
    return s.groupBy("worker", "y").agg(F.count("*").alias("rows"))


@query("select source, cast(dense_rank() over (order by source) - 1 as int) worker, n from (select source, count(*) n from documents group by 1)")
def split_by_source(spark, sf_dir):
    s = samples.by_key(samples.language_task(spark, sf_dir).select("row_id", "y", "source"), "source")
    return s.groupBy("source", "worker").agg(F.count("*").alias("n"))


@query("""with k as (select l_suppkey, count(*) n from lineitem group by 1)
select n_name nation, count(*) shards, cast(sum(n) as bigint) rows, max(n) largest from k join supplier on s_suppkey = l_suppkey join nation on n_nationkey = s_nationkey group by 1""")
def natural_shards(spark, sf_dir):
    """Supplier-owned shards of the scale table, by nation."""
    t = lambda n: tables.table(spark, sf_dir, n)
    k = t("lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n"))
    both = k.join(t("supplier"), F.col("s_suppkey") == F.col("l_suppkey")).join(t("nation"), F.col("n_nationkey") == F.col("s_nationkey"))
    return both.groupBy(F.col("n_name").alias("nation")).agg(F.count("*").alias("shards"), F.sum("n").alias("rows"), F.max("n").alias("largest"))


@query("""with s as (select dense_rank() over (order by source) - 1 worker, list_position(['de', 'en', 'es', 'fr'], lang) - 1 y from documents),
c as (select worker, y, count(*) n from s group by 1, 2), t as (select y, sum(n) a from c group by 1), w as (select worker, sum(n) r, count(*) labels from c group by 1)
select cast(w.worker as int) worker, cast(r as bigint) rows, labels, round(sum(abs(coalesce(c.n, 0) / r - a / (select sum(a) from t))) / 2, 6) distance from w cross join t left join c on c.worker = w.worker and c.y = t.y group by 1, 2, 3""")
def shard_skew(spark, sf_dir):
    s = samples.shard_label_stats(samples.by_key(samples.language_task(spark, sf_dir).select("row_id", "y", "source"), "source"))
    return s.select("worker", "rows", "labels", r6("distance").alias("distance"))


@query("""with s as (select doc_id, lower(text) t from documents)
select doc_id row_id, round(10.0 * (length(t) - length(replace(t, 'e', ''))) / greatest(length(t), 1), 6) e_share, round(10.0 * (length(t) - length(replace(t, 'ö', ''))) / greatest(length(t), 1), 6) o_share, 40::int dims from s""")
def letters_features(spark, sf_dir):
    t = samples.language_task(spark, sf_dir)
    return t.select("row_id", r6(F.col("x")[4]).alias("e_share"), r6(F.col("x")[samples.LETTERS.index("ö")]).alias("o_share"), F.size("x").alias("dims"))


@query("select vec_id row_id, cast(list_position(embedding[1:10], list_max(embedding[1:10])) - 1 as int) y, round(8 * embedding[1]::double, 6) x0 from embeddings")
def planted_labels(spark, sf_dir):
    return samples.planted_task(spark, sf_dir).select("row_id", "y", r6(F.col("x")[0]).alias("x0"))


LOCAL_SQL = "with l as (select cast(l_suppkey as int) worker, cast(1 + l_suppkey % 5 as int) steps, avg(l_quantity) w0, avg(l_extendedprice) w1 from lineitem group by 1, 2)"


def local_rows(spark, sf_dir) -> DataFrame:
    """Local models for the averaging rules: each supplier's mean quantity and price, after 1 to 5 steps."""
    li = tables.table(spark, sf_dir, "lineitem")
    g = li.groupBy(F.col("l_suppkey").cast("int").alias("worker")).agg(F.avg("l_quantity").alias("a"), F.avg("l_extendedprice").alias("b"))
    return g.select("worker", (1 + F.col("worker") % 5).cast("int").alias("steps"), F.array("a", "b").alias("w"))


@query(LOCAL_SQL + " select 0::int pos, round(avg(w0), 6) w from l union all select 1, round(avg(w1), 6) from l")
def average_uniform(spark, sf_dir):
    return averaging.average_models(local_rows(spark, sf_dir), "uniform").select("pos", r6("w").alias("w"))


@query(LOCAL_SQL + " select 0::int pos, round(sum(w0 / steps) / sum(1.0 / steps), 6) w from l union all select 1, round(sum(w1 / steps) / sum(1.0 / steps), 6) from l")
def average_inverse_steps(spark, sf_dir):
    return averaging.average_models(local_rows(spark, sf_dir), "inverse_model").select("pos", r6("w").alias("w"))


@query(LOCAL_SQL + " select 0::int pos, round(20.0 - avg(steps) * avg((20.0 - w0) / steps), 6) w from l union all select 1, round(1000.0 - avg(steps) * avg((1000.0 - w1) / steps), 6) from l")
def average_normalised_direction(spark, sf_dir):
    start = spark.createDataFrame([(0, 20.0), (1, 1000.0)], "pos int, w double")
    return averaging.average_models(local_rows(spark, sf_dir), "normalised_direction", start).select("pos", r6("w").alias("w"))


@query(LOCAL_SQL + " select round(var_pop(w0) + var_pop(w1), 4) drift from l")
def client_drift(spark, sf_dir):
    return metrics.client_drift(local_rows(spark, sf_dir)).select((F.round("drift", 4) + 0.0).alias("drift"))


TRAIN_M, TRAIN_U, TRAIN_B, TRAIN_J = 4, 3, 8, 6


def line_batches(spark, sf_dir) -> DataFrame:
    """Mini-batches for the one-variable regression, drawn by hash from pieces dealt by key: (round_no, worker, step_no, batch)."""
    rows = samples.line_task(spark, sf_dir)
    dealt = rows.withColumn("worker", F.pmod("row_id", F.lit(TRAIN_M)).cast("int"))
    shards = dealt.withColumn("pos", F.row_number().over(W.partitionBy("worker").orderBy("row_id")) - 1)
    n = spark.range(TRAIN_J * TRAIN_M * TRAIN_U * TRAIN_B)
    i = F.col("id")
    keys = n.select(F.floor(i / (TRAIN_M * TRAIN_U * TRAIN_B)).cast("int").alias("round_no"), (F.floor(i / (TRAIN_U * TRAIN_B)) % TRAIN_M).cast("int").alias("worker"), (F.floor(i / TRAIN_B) % TRAIN_U).cast("int").alias("step_no"), (i % TRAIN_B).cast("int").alias("slot"))
    sizes = shards.groupBy("worker").agg(F.count("*").alias("n"))
    draws = keys.join(F.broadcast(sizes), "worker").withColumn("pos", rng.randint(F.col("n"), 0, "draw", F.col("round_no"), F.col("worker"), F.col("step_no"), F.col("slot")))
    hit = shards.join(F.broadcast(draws), ["worker", "pos"])
    return hit.groupBy("round_no", "worker", "step_no").agg(F.array_sort(F.collect_list(F.struct("slot", "x", "y"))).alias("batch"))


def line_rounds(spark, sf_dir) -> DataFrame:
    """All rounds of the chain as one expression: rounds fold over an array of rounds, steps fold over a worker's batches.

    The model of a run is two numbers, so the whole run is an aggregate over its (small) batches.
    """
    b = line_batches(spark, sf_dir)
    chains = b.groupBy("round_no", "worker").agg(F.array_sort(F.collect_list(F.struct("step_no", "batch"))).alias("steps"))
    rounds = chains.groupBy("round_no").agg(F.array_sort(F.collect_list(F.struct("worker", "steps"))).alias("workers"))
    run = rounds.groupBy().agg(F.array_sort(F.collect_list(F.struct("round_no", "workers"))).alias("rounds"))

    def step(w, s):
        err = lambda t: w["a"] + w["b"] * t["x"] - t["y"]
        ga = vec.total(F.transform(s["batch"], err)) / TRAIN_B
        gb = vec.total(F.transform(s["batch"], lambda t: err(t) * t["x"])) / TRAIN_B
        return F.struct((w["a"] - 0.1 * ga).alias("a"), (w["b"] - 0.1 * gb).alias("b"))

    def one_round(log, r):
        now = F.element_at(log, -1)
        ends = F.transform(r["workers"], lambda m: F.aggregate(m["steps"], now, step))
        mean = lambda f: vec.total(F.transform(ends, lambda e: e[f])) / F.size(ends)
        return F.concat(log, F.array(F.struct(mean("a").alias("a"), mean("b").alias("b"))))

    start = F.array(F.struct(F.lit(0.0).alias("a"), F.lit(0.0).alias("b")))
    return run.select(F.posexplode(F.aggregate("rounds", start, one_round)).alias("round_no", "w")).select("round_no", "w.a", "w.b")


LINE_SQL = f"""with recursive p as (select p_partkey id, (p_partkey % 1000) / 1000.0::double x, (p_retailprice - 900.0) / 100.0 y, cast(p_partkey % 4 as int) worker from part),
sh as (select *, row_number() over (partition by worker order by id) - 1 pos from p),
sz as (select worker, count(*) n from sh group by 1),
dr as (select j round_no, sz.worker, s step_no, k slot, {rng.hash48_sql(0, 'draw', 'j', 'sz.worker', 's', 'k')} % n pos from (select unnest(range(6)) j), sz, (select unnest(range(3)) s), (select unnest(range(8)) k)),
bt as (select round_no, worker, step_no, list({{'x': x, 'y': y}} order by slot) b from dr join sh using (worker, pos) group by 1, 2, 3),
ch as (
  select 0 r, 0 s, worker, 0.0::double a, 0.0::double b from sz
  union all
  select case when s = 2 then r + 1 else r end, (s + 1) % 3, worker, case when s = 2 then avg(na) over () else na end, case when s = 2 then avg(nb) over () else nb end
  from (select ch.r, ch.s, ch.worker, ch.a - 0.1 * list_sum(list_transform(bt.b, lambda t: ch.a + ch.b * t.x - t.y)) / 8 na, ch.b - 0.1 * list_sum(list_transform(bt.b, lambda t: (ch.a + ch.b * t.x - t.y) * t.x)) / 8 nb
    from ch join bt on bt.round_no = ch.r and bt.worker = ch.worker and bt.step_no = ch.s where ch.r < 6)
)"""


@query(LINE_SQL + " select r::int round_no, round(max(a), 6) a, round(max(b), 6) b from ch where s = 0 group by 1")
def line_training_rounds(spark, sf_dir):
    return line_rounds(spark, sf_dir).select("round_no", r6("a").alias("a"), r6("b").alias("b"))


@query(LINE_SQL + ", w as (select r::int round_no, max(a) a, max(b) b from ch where s = 0 group by 1) select round_no, round(avg((a + b * x - y) * (a + b * x - y)) / 2, 6) loss from w, p group by 1")
def loss_by_round(spark, sf_dir):
    w, p = line_rounds(spark, sf_dir), samples.line_task(spark, sf_dir)
    err = F.col("a") + F.col("b") * F.col("x") - F.col("y")
    return p.crossJoin(F.broadcast(w)).groupBy("round_no").agg(r6(F.avg(err * err) / 2).alias("loss"))


@query("""with s as (select doc_id, lower(text) t, list_position(['de', 'en', 'es', 'fr'], lang) - 1 y from documents),
z as (select y, [10.0 * (length(t) - length(replace(t, 'ö', ''))) / greatest(length(t), 1) * 10 + 0.05, 0.1, 10.0 * (length(t) - length(replace(t, 'ñ', ''))) / greatest(length(t), 1) * 10 + 0.02, 10.0 * (length(t) - length(replace(t, 'è', ''))) / greatest(length(t), 1) * 10] v from s)
select cast(y as int) y, count(*) n, count(*) filter (list_position(v, list_max(v)) - 1 = y) correct from z group by 1""")
def softmax_accuracy(spark, sf_dir):
    """Accuracy of a fixed linear scorer over letter features, classes by largest score."""
    at = lambda c: F.col("x")[samples.LETTERS.index(c)]
    t = samples.language_task(spark, sf_dir).withColumn("v", F.array(at("ö") * 10 + 0.05, F.lit(0.1), at("ñ") * 10 + 0.02, at("è") * 10))
    return t.groupBy("y").agg(F.count("*").alias("n"), F.count_if(vec.argmax(F.col("v")) == F.col("y")).alias("correct"))


@query("select quality y, count(*) n, count(*) filter (doc_id % 5 = 0) held_out from documents join labels using (doc_id) group by 1")
def quality_join(spark, sf_dir):
    t = samples.quality_task(spark, sf_dir)
    return t.groupBy("y").agg(F.count("*").alias("n"), F.count_if(F.col("row_id") % 5 == 0).alias("held_out"))


# --- logs ---------------------------------------------------------------------------------------------------------

LOG_SQL = trace_sql() + quorum_sql(5, 10) + fixed_sql("10") + """,
r as (select 'quorum_stop' run_id, round_no, max(stop) t, 20 + count(*) filter (steps >= 1) m, sum(steps) s from q group by 2 union all select 'periodic_average', round_no, max(stop), 40, sum(n) from f group by 2),
lg as (select run_id, round_no, sum(t) over w cum_time, cast(sum(m) over w as bigint) cum_messages, 1 - exp(-sum(s) over w / 600.0) accuracy from r window w as (partition by run_id order by round_no rows unbounded preceding))"""


def surrogate_log(spark, sf_dir) -> DataFrame:
    """Logs of two schemes whose accuracy is a fixed function of the steps done so far, for testing the log measures in SQL."""
    lines = lines_of(spark, sf_dir)
    s = clock.quorum_schedule(lines, 5, 10).unionByName(clock.periodic_schedule(lines, 10))
    a = metrics.accumulate(metrics.round_summary(s))
    done = F.sum("steps").over(W.partitionBy("run_id").orderBy("round_no").rowsBetween(W.unboundedPreceding, 0))
    return a.withColumn("accuracy", 1 - F.exp(-done / 600.0))


@query(LOG_SQL + """, b as (select unnest([5.0, 20.0, 60.0, 100.0])::double budget)
select run_id, budget, round(arg_max(accuracy, cum_time), 6) accuracy, max(round_no) round_no from lg join b on cum_time <= budget group by 1, 2""")
def accuracy_at_budget(spark, sf_dir):
    grid = spark.createDataFrame([(5.0,), (20.0,), (60.0,), (100.0,)], "budget double")
    return metrics.accuracy_at(surrogate_log(spark, sf_dir), grid).select("run_id", "budget", r6("accuracy").alias("accuracy"), "round_no")


@query(LOG_SQL + """
select run_id, cast(min(round_no) filter (accuracy >= 0.6) + 1 as int) rounds, round(min(cum_time) filter (accuracy >= 0.6), 6) "time", min(cum_messages) filter (accuracy >= 0.6) messages, round(max(accuracy), 6) best from lg group by 1""")
def to_target_summary(spark, sf_dir):
    t = metrics.to_target(surrogate_log(spark, sf_dir), 0.6)
    return t.select("run_id", "rounds", r6("time").alias("time"), F.col("messages").cast("bigint").alias("messages"), r6("best").alias("best"))


@query(LOG_SQL + ", s as (select run_id, accuracy - lag(accuracy) over (partition by run_id order by round_no) d from lg) select run_id, round(stddev(d), 6) roughness from s group by 1")
def curve_roughness(spark, sf_dir):
    return metrics.curve_roughness(surrogate_log(spark, sf_dir)).select("run_id", r6("roughness").alias("roughness"))


@query(trace_sql() + "".join(quorum_sql(k, 10, f"k{k}") for k in (1, 5, 10, 15, 20)) + ", z as (" + " union all ".join(f"select {k} quorum, sum(t) time, sum(m) messages from (select round_no, max(stop) t, 20 + count(*) filter (steps >= 1) m from k{k}q group by 1)" for k in (1, 5, 10, 15, 20)) + """)
select quorum::int quorum, round(time, 6) "time", messages::bigint messages from z where not exists (select 1 from z o where o.time <= z.time and o.messages <= z.messages and (o.time < z.time or o.messages < z.messages))""")
def frontier(spark, sf_dir):
    lines, out = lines_of(spark, sf_dir), None
    for k in (1, 5, 10, 15, 20):
        s = metrics.round_summary(clock.quorum_schedule(lines, k, 10, run_id=str(k)))
        g = s.groupBy(F.col("run_id").cast("int").alias("quorum")).agg(F.sum("round_time").alias("time"), F.sum("messages").cast("bigint").alias("messages"))
        out = g if out is None else out.unionByName(g)
    return metrics.frontier(out).select("quorum", r6("time").alias("time"), "messages")


@query("""with o as (select o_custkey, count(*) steps from orders group by 1)
select r_name region, n_name nation, cast(sum(steps) as bigint) steps, count(*) workers, cast(grouping(r_name) * 2 + grouping(n_name) as bigint) level
from o join customer on c_custkey = o_custkey join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey group by rollup (r_name, n_name)""")
def rollup_geography(spark, sf_dir):
    """Work of customer-owned shards rolled up to nations and regions."""
    t = lambda n: tables.table(spark, sf_dir, n)
    steps = t("orders").groupBy("o_custkey").agg(F.count("*").alias("steps"))
    geo = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    both = steps.join(t("customer"), F.col("c_custkey") == F.col("o_custkey")).join(geo, F.col("c_nationkey") == F.col("n_nationkey"))
    out = both.rollup(F.col("r_name").alias("region"), F.col("n_name").alias("nation"))
    return out.agg(F.sum("steps").alias("steps"), F.count("*").alias("workers"), F.grouping_id().cast("bigint").alias("level"))


# --- windows over the completion trace, batch form ------------------------------------------------------------------


def completions(spark, sf_dir) -> DataFrame:
    e = tables.table(spark, sf_dir, "events")
    return e.select("event_id", "ts", (F.col("user_id") % M).cast("int").alias("worker"))


@query("select date_trunc('hour', ts) \"hour\", cast(user_id % 20 as int) worker, count(*) steps from events group by 1, 2")
def hourly_throughput(spark, sf_dir):
    c = completions(spark, sf_dir)
    return c.groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour"), "worker").agg(F.count("*").alias("steps"))


@query("""select time_bucket(interval 15 minute, ts) - interval 15 minute * k "start", count(*) steps, count(distinct user_id % 20) workers from events, (select unnest(range(4)) k) group by 1""")
def sliding_throughput(spark, sf_dir):
    c = completions(spark, sf_dir).groupBy(F.window("ts", "1 hour", "15 minutes"))
    return c.agg(F.count("*").alias("steps"), F.countDistinct("worker").alias("workers")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "steps", "workers")


@query("""with g as (select user_id % 20 worker, ts, case when ts - lag(ts) over (partition by user_id % 20 order by ts) < interval 30 minute then 0 else 1 end n from events),
s as (select *, sum(n) over (partition by worker order by ts rows unbounded preceding) k from g)
select worker::int worker, count(distinct k) bursts, max(c) longest from (select worker, k, count(*) over (partition by worker, k) c from s) group by 1""")
def session_bursts(spark, sf_dir):
    c = completions(spark, sf_dir).groupBy("worker", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("n"))
    return c.groupBy("worker").agg(F.count("*").alias("bursts"), F.max("n").alias("longest"))


#: Where a round goes that starts after event s: the quorum-th smallest, over workers, of the places of their next quota-th events.
STREAM_SQL = """with recursive ev as (select ts, cast(user_id % 20 as int) worker, row_number() over (order by ts, event_id) g, row_number() over (partition by user_id % 20 order by ts, event_id) k from events),
pl as (select 0 s, i worker, 0 n from range(20) w(i) union all select g, i, sum((ev.worker = i)::int) over (partition by i order by g) from ev, range(20) w(i)),
nx as (select s, g, row_number() over (partition by s order by g) r from pl join ev on ev.worker = pl.worker and ev.k = pl.n + 10),
nt as (select s, g from nx where r = 5),
rd as (select 0 j, s, g from nt where s = 0 union all select j + 1, nt.s, nt.g from rd join nt on nt.s = rd.g),
per as (select j, worker, count(*) n from rd join ev on ev.g > rd.s and ev.g <= rd.g group by 1, 2)
select j::int round_no, a.ts "start", b.ts stop, cast(rd.g - rd.s as bigint) events, cast((select count(*) from per where per.j = rd.j) as int) uploads, cast((select max(n) from per where per.j = rd.j) as int) max_steps
from rd join ev a on a.g = greatest(rd.s, 1) join ev b on b.g = rd.g"""


@query(STREAM_SQL)
def stream_clock(spark, sf_dir):
    """The streaming round clock over the completion trace, run to its end: one row for each closed round."""
    from quorumlab.streaming import clock as live

    rounds = live.run_to_end(spark, f"{sf_dir}/events.parquet*", workers=20, quorum=5, quota=10)
    return rounds.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "stop")})
