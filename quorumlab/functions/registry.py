"""Functions for SQL: scalar, aggregate and table functions, and views, under names of a session."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import PandasUDFType, pandas_udf, udtf

#: The tables that are registered as views.
TABLES = ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"]


@pandas_udf(T.ArrayType(T.DoubleType()), PandasUDFType.GROUPED_AGG)
def avg_vector(w: pd.Series) -> list:
    """Grouped mean of vectors, for groups that fit a task; posexplode and avg serve larger ones."""
    import numpy as np

    return np.mean(np.stack(w.to_list()), axis=0).tolist()


@pandas_udf(T.ArrayType(T.DoubleType()), PandasUDFType.GROUPED_AGG)
def weighted_avg_vector(w: pd.Series, weight: pd.Series) -> list:
    import numpy as np

    return np.average(np.stack(w.to_list()), axis=0, weights=weight.to_numpy()).tolist()


@udtf(returnType=T.StructType([T.StructField("slot", T.IntegerType()), T.StructField("pos", T.LongType())]))
class DrawPositions:
    """The positions of a mini-batch: draw_positions(seed, round, worker, step, batch, n)."""

    def eval(self, seed: int, round_no: int, worker: int, step_no: int, batch: int, n: int):
        from quorumlab.operators.samples import draw_powers, draws_py

        for slot, pos in enumerate(draws_py(seed, round_no, worker, step_no, batch, n, draw_powers(batch))):
            yield slot, int(pos)


@udtf(returnType=T.StructType([T.StructField("round_no", T.IntegerType()), T.StructField("steps", T.DoubleType()), T.StructField("uploads", T.DoubleType())]))
class PlanRounds:
    """Expected steps and uploads of each of the next rounds: plan_rounds(workers, quorum, quota, rounds)."""

    def eval(self, workers: int, quorum: int, quota: int, rounds: int):
        import math

        from quorumlab.operators.training import expected_steps

        e = expected_steps(workers, quorum, quota)
        for j in range(rounds):
            yield j, e, max(float(quorum), workers * (1 - math.exp(-e)))


def predict_column(spark: SparkSession, model, w) -> "Column":
    """A function of a feature array that gives a model's class for it; the weights travel as a broadcast."""
    shared = spark.sparkContext.broadcast(w)

    @pandas_udf("int")
    def predict(x: pd.Series) -> pd.Series:
        import numpy as np

        return pd.Series(model.predict(shared.value, np.stack(x.to_list())).astype("int32"))

    return predict


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Make the functions, and with a folder the tables, known to SQL."""
    spark.udf.register("avg_vector", avg_vector)
    spark.udf.register("weighted_avg_vector", weighted_avg_vector)
    spark.udtf.register("draw_positions", DrawPositions)
    spark.udtf.register("plan_rounds", PlanRounds)
    for name in TABLES if sf_dir else ():
        spark.read.parquet(f"{sf_dir}/{name}.parquet").createOrReplaceTempView(name)


def sql_quorum_schedule(spark: SparkSession, quorum: int, quota: int, view: str = "lines") -> DataFrame:
    """The main schedule as one SQL statement over a view of timelines, with parameters."""
    return spark.sql(
        f"""
        with acks as (select *, try_element_at(done, :quota) as ack_time from {view}),
        stops as (select round_no, ack_time as stop from (select round_no, ack_time, row_number() over (partition by round_no order by ack_time nulls last, worker) as place from acks) where place = :quorum)
        select round_no, worker, size(filter(done, t -> t <= stop)) as steps, stop as round_time from acks join stops using (round_no)
        """,
        args={"quota": quota, "quorum": quorum},
    )


def run_options(options: Column) -> Column:
    """Scheme options kept as JSON text, as a map."""
    return F.from_json(options, "map<string,string>")
