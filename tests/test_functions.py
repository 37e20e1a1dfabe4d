"""Hash numbers, vectors and the functions registered for SQL."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from quorumlab.functions import registry, rng, vec
from quorumlab.operators import clock, models, samples
from quorumlab.sources import tables


def test_hash_numbers(spark):
    df = spark.range(500).select("id", rng.hash48(7, "t", F.col("id")).alias("h"), rng.uniform(7, "t", F.col("id")).alias("u"), rng.exponential(2.0, 7, "t", F.col("id")).alias("e"), rng.randint(10, 7, "t", F.col("id")).alias("k"))
    rows = df.collect()
    assert [r["h"] for r in rows] == [rng.hash48_py(7, "t", r["id"]) for r in rows]
    assert all(0 < r["u"] < 1 and 0 <= r["k"] < 10 for r in rows)
    assert np.mean([r["u"] for r in rows]) == pytest.approx(0.5, abs=0.05) and np.mean([r["e"] for r in rows]) == pytest.approx(2, abs=0.3)


def test_vectors(spark):
    x, y = F.col("x"), F.col("y")
    r = spark.createDataFrame([([1.0, 2.0], [3.0, 5.0])], "x array<double>, y array<double>").select(
        vec.dot(x, y).alias("dot"), vec.axpy(2, x, y).alias("axpy"), vec.scale(3.0, x).alias("scale"), vec.norm2(x).alias("n"), vec.argmax(y).alias("m"), vec.softmax(x).alias("s")
    )
    r = r.first()
    assert (r["dot"], r["axpy"], r["scale"], r["n"], r["m"]) == (13.0, [5.0, 9.0], [3.0, 6.0], 5.0, 1) and r["s"] == pytest.approx([1 / (1 + math.e), math.e / (1 + math.e)])


def test_sql_surface(spark, small):
    registry.register(spark, small)
    assert spark.sql("select count(*) from region").first()[0] == 5
    w = spark.sql("select avg_vector(w) a, weighted_avg_vector(w, k) b from values (array(1d, 2d), 1d), (array(3d, 4d), 3d) t(w, k)").first()
    assert w["a"] == [2.0, 3.0] and w["b"] == [2.5, 3.5]
    got = [r["pos"] for r in spark.sql("select * from draw_positions(1, 2, 3, 4, 5, 100) order by slot").collect()]
    assert got == samples.draws_py(1, 2, 3, 4, 5, 100, samples.draw_powers(5)).tolist()
    assert spark.sql("select * from plan_rounds(40, 30, 2, 3)").first()["steps"] == pytest.approx(2.6352, abs=1e-4)
    lines = clock.timelines(tables.hashed_durations(spark, 3, 6, 60))
    lines.createOrReplaceTempView("lines")
    a = registry.sql_quorum_schedule(spark, 3, 2).collect()
    b = clock.quorum_schedule(lines, 3, 2).select("round_no", "worker", "steps", "round_time").collect()
    assert sorted(map(tuple, a)) == sorted(map(tuple, b))
    model = models.softmax(2, 2)
    predict = registry.predict_column(spark, model, np.array([1.0, 0.0, 0.0, 1.0]))
    df = spark.createDataFrame([([2.0, 1.0],), ([1.0, 2.0],)], "x array<double>")
    assert [r[0] for r in df.select(predict("x")).collect()] == [0, 1]
    o = spark.createDataFrame([('{"mean": "4"}',)], "o string").select(registry.run_options(F.col("o")).alias("m")).first()
    assert o["m"] == {"mean": "4"}
