"""Every engine query against its DuckDB counterpart on the smallest tables, sinks, and the stream."""

import math
import os

import duckdb
import pytest

from quorumlab.operators import clock
from quorumlab.plans import queries
from quorumlab.sources import tables
from quorumlab.streaming import clock as live


def norm(v):
    if isinstance(v, float):
        return str(v) if math.isnan(v) or math.isinf(v) else round(v, 5) + 0.0
    return v


@pytest.fixture(scope="module")
def con(small):
    c = duckdb.connect()
    for f in os.listdir(small):
        c.execute(f"create view {f[:-8]} as select * from '{small}/{f}'")
    return c


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_against_duckdb(spark, small, con, name):
    df = queries.queries()[name](spark, small)
    cols = sorted(df.columns)
    got = sorted((tuple(map(norm, r)) for r in df.select(cols).collect()), key=str)
    r = con.execute(queries.oracle_sql()[name])
    names = [d[0] for d in r.description]
    assert sorted(names) == cols
    want = sorted((tuple(norm(row[names.index(c)]) for c in cols) for row in r.fetchall()), key=str)
    assert got == want


def test_flagship(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0


def test_stream_equals_batch(spark, small, tmp_path):
    import time

    events = tables.table(spark, small, "events").orderBy("ts").toPandas()
    for k in range(4):  # files in order of time, as a stream brings them
        events[k * 250 : (k + 1) * 250].to_parquet(tmp_path / f"{k}.parquet", coerce_timestamps="us")
        time.sleep(0.05)
    got = live.run_to_end(spark, str(tmp_path), 20, 5, 3).orderBy("round_no").collect()
    want = live.batch_clock(tables.table(spark, small, "events"), 20, 5, 3).orderBy("round_no").drop("run_id").collect()
    assert len(want) > 30 and got == want


def test_sinks(spark, tmp_path):
    s = clock.periodic_schedule(clock.timelines(tables.hashed_durations(spark, 2, 3, 5)), 2)
    tables.write_log(s, str(tmp_path / "log"))
    tables.write_log(s, str(tmp_path / "json"), "json")
    assert tables.load(spark, "parquet", str(tmp_path / "log"), s.schema).count() == 6 == tables.load(spark, "json", str(tmp_path / "json"), s.schema).count()
    m = spark.createDataFrame([("a", 0, 0, [1.0]), ("a", 1, 0, [2.0])], "run_id string, round_no int, block int, w array<double>")
    tables.write_model(m, str(tmp_path / "m"))
    tables.write_model(m.where("round_no = 1"), str(tmp_path / "m"))
    assert spark.read.parquet(str(tmp_path / "m")).count() == 2
