"""Queries do the whole job: whole texts, every event, long plans, every round."""

import duckdb
import pytest
from pyspark.sql import functions as F

from quorumlab.operators import clock, samples
from quorumlab.plans import queries
from quorumlab.sources import tables
from quorumlab.streaming import clock as live


def test_letters_of_the_whole_text(spark):
    df = spark.createDataFrame([("a" * 2000 + "b" * 6000,)], "t string").select(samples.letters(F.col("t")).alias("x"))
    assert df.first()["x"][:2] == [2.5, 7.5]


def test_features_of_every_document_in_full(spark, small):
    docs = duckdb.connect().execute(f"select doc_id, lower(text) from '{small}/documents.parquet'").fetchall()
    assert any(len(t) > 2000 for _, t in docs)
    got = {r["row_id"]: [r["e_share"], r["o_share"]] for r in queries.queries()["letters_features"](spark, small).collect()}
    assert len(got) == len(docs)
    assert all(got[k] == pytest.approx([10.0 * t.count(c) / max(len(t), 1) for c in "eö"], abs=1e-6) for k, t in docs)


def test_stream_of_unsorted_files_equals_batch(spark, small, tmp_path):
    events = tables.table(spark, small, "events")
    events.withColumn("part", F.pmod(F.xxhash64("event_id"), F.lit(4))).repartition(4, "part").drop("part").write.parquet(str(tmp_path / "events.parquet"))
    assert len(list((tmp_path / "events.parquet").glob("part-*"))) > 1
    got = queries.queries()["stream_clock"](spark, str(tmp_path)).orderBy("round_no").collect()
    want = live.batch_clock(events, 20, 5, 10).orderBy("round_no").drop("run_id").collect()
    assert len(want) > 3 and got == want
    dense = live.run_to_end(spark, str(tmp_path / "events.parquet"), 20, 1, 1).orderBy("round_no").collect()
    assert dense == live.batch_clock(events, 20, 1, 1).orderBy("round_no").drop("run_id").collect()


def test_plans_beyond_the_timeline(spark):
    """Rounds of 2 steps; worker 0 is planned 3 steps, and its third is the first of the next round."""
    steps = spark.createDataFrame([(w, i, float(1 + w + i)) for w in (0, 1) for i in range(4)], "worker int, seq bigint, dur double")
    lines = clock.timelines(steps.selectExpr("cast(seq div 2 as int) round_no", "worker", "cast(seq % 2 as int) step_no", "dur"))
    plan = lines.withColumn("planned", F.when(F.col("worker") == 0, 3).otherwise(1))
    got = {(r["round_no"], r["worker"]): (r["round_time"], r["capped"]) for r in clock.fixed_steps_schedule(clock.go_on(plan, steps, 2), F.col("planned")).collect()}
    assert got[0, 0] == (6.0, False) and got[0, 1] == (6.0, False)
    assert got[1, 0] == (None, True) and got[1, 1] == (None, False)  # the trace ends
    short = clock.fixed_steps_schedule(plan, F.col("planned")).collect()
    assert all(r["round_time"] is None for r in short) and [r["worker"] for r in short if r["capped"]] == [0, 0]


def test_random_steps_wait_for_long_plans(spark):
    sf = "/root/testdata/sf0.01"
    durations = {(r[0], r[1]): r[2] for r in tables.uncut_steps(tables.table(spark, sf, "events"), 20).collect()}
    plans = queries.queries()["random_steps_weights"](spark, sf).collect()
    assert max(r["steps"] for r in plans) > 50
    want = {}
    for r in plans:
        t = sum(durations[r["worker"], r["round_no"] * 50 + k] for k in range(r["steps"]))
        want[r["round_no"]] = max(want.get(r["round_no"], 0.0), t)
    got = {r["round_no"]: r["round_time"] for r in queries.queries()["random_steps_summary"](spark, sf).collect()}
    assert got == pytest.approx(want, abs=1e-5)


def test_stagewise_covers_every_round(spark, tmp_path):
    """130 rounds, more than the plan's 124, with equal steps: a round lasts as long as its stage's period."""
    spark.range(130 * 1000).select(F.col("id").alias("event_id"), F.lit(50.0).alias("value")).write.parquet(str(tmp_path / "events.parquet"))
    rows = queries.queries()["stagewise_summary"](spark, str(tmp_path)).collect()
    period = lambda j: next((2 << s for s, last in enumerate((3, 11, 27, 59)) if j <= last), 32)
    assert {r["round_no"]: (r["round_time"], r["steps"]) for r in rows} == {j: (float(period(j)), 20 * period(j)) for j in range(130)}


def test_letters_of_every_character(spark):
    """Letters are counted as in lowered texts, without lowering them first: every character of two planes, capitals of other blocks too."""
    df = spark.createDataFrame([(f"É{chr(i)}b",) for i in range(0x20000) if not 0xD800 <= i < 0xE000], "t string")
    both = df.select("t", samples.letters(F.col("t")).alias("x"), samples.letters(F.lower("t")).alias("want"), F.lower("t").alias("low"))
    assert both.where("x != want").count() == 0
    odd = both.where(F.length("low") > 3).collect()
    assert [(r["t"][1], r["x"][samples.LETTERS.index("i")]) for r in odd] == [("İ", 2.5)]
