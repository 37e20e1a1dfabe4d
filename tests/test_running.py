"""Running sums in DuckDB's order of additions, and what follows from it where sums tie."""

import duckdb
import numpy as np
import pandas as pd
import pytest

from quorumlab.operators import metrics, running
from quorumlab.plans import queries


@pytest.fixture(scope="module")
def con():
    return duckdb.connect()


@pytest.mark.parametrize("rows", [3, 16, 257, 4999])
def test_running_sums_have_the_bits_of_sql(spark, con, rows):
    """Keys of several sizes, some behind others in their hash partition; nulls, also first ones."""
    rng = np.random.default_rng(rows)
    df = pd.DataFrame({"k": np.repeat(np.arange(20), rows + np.arange(20) * 3), "v": 0.0})
    df["i"], df["v"] = rng.permutation(len(df)), rng.exponential(1.0, len(df)).round(4) / 50
    df.loc[df.groupby("k").i.idxmin()[::3], "v"] = np.nan
    df.loc[::11, "v"] = np.nan
    con.register("df", df)
    want = con.execute("select k, i, sum(case when not isnan(v) then v end) over (partition by k order by i rows unbounded preceding) t from df").fetchall()
    rows = spark.createDataFrame(df.astype(object).where(df.notna(), None).values.tolist(), "k int, v double, i int")
    got = running.running_sums(rows, "k", ["i"], "v", "t").select("k", "i", "t").collect()
    assert sorted(map(tuple, got)) == sorted(want)
    assert len({b for b in running.begins(dict.fromkeys(range(20), 5)).values()}) > 1


def test_hash_partitions_grow_with_rows():
    """Offsets seen on DuckDB 2.0.0: 20 workers of 300,000 rows are in 64 partitions."""
    found = running.begins(dict.fromkeys(range(20), 300_000))
    assert {k: b // 300_000 for k, b in found.items() if b} == {9: 1, 13: 1, 17: 2}


def test_rounds_of_steps_that_end_with_a_round(spark, con, tmp_path):
    """Durations of few values, so that many steps end exactly when a round does."""
    rng = np.random.default_rng(0)
    n = 20_000
    pd.DataFrame({"event_id": np.arange(n), "value": rng.integers(1, 40, n) * 1.1}).to_parquet(tmp_path / "events.parquet")
    con.execute(f"create or replace view events as select * from '{tmp_path}/events.parquet'")
    want = con.execute(queries.oracle_sql()["round_of_event"]).fetchall()
    assert sorted(map(tuple, queries.round_of_event(spark, str(tmp_path)).select("round_no", "events", "workers").collect())) == sorted(want)


def test_assign_round_meets_all_rounds(spark):
    """Rounds of very different lengths, with a gap, an overlap, an empty one and unknown ones."""
    rounds = [(0, 0.0, 0.5), (1, 0.5, 100.0), (2, 99.0, 101.0), (3, 102.0, 102.0), (4, None, None), (5, 103.0, 103.25)]
    bounds = spark.createDataFrame(rounds, "round_no int, start double, stop double")
    times = [0.0, 0.5, 50.0, 99.5, 100.0, 101.5, 102.0, 103.2, 103.25, None]
    got = metrics.assign_round(spark.createDataFrame([(t,) for t in times], "t double"), bounds).select("t", "round_no").collect()
    assert sorted(map(tuple, got)) == sorted((t, r) for t in times if t is not None for r, a, b in rounds if a is not None and a <= t < b)
