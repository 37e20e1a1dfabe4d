"""Closed forms of the main method: expected time, steps and uploads of a round, and the convergence bound.

Step durations are exponential with a given mean; all integrals are taken in units of that mean. The quota-th
completion of a worker is Erlang distributed with cdf Q and density q, and the stop time is the K-th of M such
times. Integrals are midpoint sums over an exploded grid, so a whole table of settings is one aggregate.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

POINTS = 4000

SETTINGS = "workers int, quorum int, quota int"


def settings(spark: SparkSession, rows: list[tuple[int, int, int]]) -> DataFrame:
    return spark.createDataFrame(rows, SETTINGS)


def _log_factorial(n: Column) -> Column:
    return F.aggregate(F.sequence(F.lit(0), n), F.lit(0.0), lambda a, i: a + F.when(i > 0, F.log(F.greatest(i, F.lit(1)).cast("double"))).otherwise(0.0))


def reach(quota: Column) -> Column:
    """An upper end beyond which nothing of the integrals is left."""
    return quota + 14 * F.sqrt(quota) + 40


def _grid(rows: DataFrame, points: int) -> DataFrame:
    """Add t and, at t: tail = 1 - Q, density f of the stop time, and the step width dt."""
    rows = rows.withColumn("dt", reach(F.col("quota").cast("double")) / points)
    log_weight = _log_factorial(F.col("workers")) - _log_factorial(F.col("quorum") - 1) - _log_factorial(F.col("workers") - F.col("quorum"))
    rows = rows.withColumn("_lw", log_weight).withColumn("_lq", _log_factorial(F.col("quota") - 1))
    rows = rows.withColumn("_i", F.explode(F.sequence(F.lit(0), F.lit(points - 1)))).withColumn("t", (F.col("_i") + 0.5) * F.col("dt"))
    # sum of t^i / i! for i < quota, by its recurrence
    zero = F.struct(F.lit(0.0).alias("s"), F.lit(1.0).alias("term"))
    series = F.aggregate(F.sequence(F.lit(1), F.col("quota")), zero, lambda a, i: F.struct((a["s"] + a["term"]).alias("s"), (a["term"] * F.col("t") / i).alias("term")), lambda a: a["s"])
    rows = rows.withColumn("tail", F.exp(-F.col("t")) * series)
    log_density = (F.col("quota") - 1) * F.log("t") - F.col("t") - F.col("_lq")
    cdf = F.greatest(1 - F.col("tail"), F.lit(1e-300))
    log_f = F.col("_lw") + (F.col("quorum") - 1) * F.log(cdf) + (F.col("workers") - F.col("quorum")) * F.log(F.greatest("tail", F.lit(1e-300))) + log_density
    return rows.withColumn("f", F.exp(log_f))


def expected_counts(rows: DataFrame, points: int = POINTS) -> DataFrame:
    """Per setting: expected_time in mean durations (it equals the expected steps of a worker), and expected uploads:
    ``approx`` M (1 - e^-E), ``clamped`` at least K, ``exact`` K + (M - K) integral of f (1 - e^-t / (1 - Q))."""
    keys = ["workers", "quorum", "quota"]
    at = _grid(rows.select(*keys), points)
    stragglers = F.col("f") * (1 - F.exp(-F.col("t")) / F.greatest("tail", F.lit(1e-300))) * F.col("dt")
    out = at.groupBy(*keys).agg(F.sum(F.col("t") * F.col("f") * F.col("dt")).alias("expected_steps"), F.sum(F.when(F.col("tail") > 1e-290, stragglers).otherwise(0.0)).alias("_p"))
    approx = F.col("workers") * (1 - F.exp(-F.col("expected_steps")))
    return out.select(
        *keys, "expected_steps", approx.alias("uploads_approx"), F.greatest(F.col("quorum").cast("double"), approx).alias("uploads_clamped"),
        (F.col("quorum") + (F.col("workers") - F.col("quorum")) * F.col("_p")).alias("uploads_exact"),
    )


def expected_round_time(rows: DataFrame, mean: float) -> DataFrame:
    return expected_counts(rows).withColumn("round_time", F.col("expected_steps") * mean)


def expected_first_step(spark: SparkSession, workers: int, mean: float = 1.0) -> DataFrame:
    """Per s: mean time until s workers have a step, by harmonic sum and by the logarithm (null where it is infinite)."""
    rows = spark.range(1, workers + 1).select(F.col("id").cast("int").alias("s"))
    harmonic = F.aggregate(F.sequence(F.lit(workers) - F.col("s") + 1, F.lit(workers)), F.lit(0.0), lambda a, i: a + 1.0 / i)
    log_form = F.when(F.col("s") < workers, F.log(workers / (F.lit(workers) - F.col("s"))))
    return rows.select("s", (harmonic * mean).alias("harmonic"), (log_form * mean).alias("logarithm"))


def monotone_grid(rows: DataFrame) -> DataFrame:
    """Do expected steps and uploads rise along the quorum and along the quota? One row for each setting and neighbour."""
    counts = expected_counts(rows)
    by_k, by_u = W.partitionBy("workers", "quota").orderBy("quorum"), W.partitionBy("workers", "quorum").orderBy("quota")
    out = counts
    for name, w in (("quorum", by_k), ("quota", by_u)):
        out = out.withColumn(f"steps_rise_in_{name}", F.col("expected_steps") - F.lag("expected_steps").over(w)).withColumn(f"uploads_rise_in_{name}", F.col("uploads_exact") - F.lag("uploads_exact").over(w))
    return out


def gradient_bound(f_start: float, f_low: float, alpha: float, mean_steps: float, most_steps: float, smooth: float, quorum: int, batch: int, local_var: float, global_var: float, rounds: int, c: float = 0.5) -> float:
    """The bound on the mean squared gradient norm. ``f_start`` is the initial objective; ``c`` is illustrative, as no value is known."""
    drop = (f_start - f_low) / (alpha * mean_steps * rounds)
    noise = alpha * most_steps * smooth * local_var / (2 * quorum * batch * mean_steps)
    drift = 5 * alpha**2 * most_steps**3 * smooth**2 * (local_var + 6 * most_steps * global_var) / (2 * mean_steps**2)
    return (drop + noise + drift) / c


def bound_column(alpha: Column, mean_steps: Column, most_steps: Column, quorum: Column, rounds: Column, smooth: float, batch: int, local_var: float, global_var: float, gap: float, c: float = 0.5) -> Column:
    """The same as a column over a table of settings."""
    drop = F.lit(gap) / (alpha * mean_steps * rounds)
    noise = alpha * most_steps * smooth * local_var / (2.0 * quorum * batch * mean_steps)
    drift = 5.0 * alpha * alpha * F.pow(most_steps, F.lit(3.0)) * smooth * smooth * (F.lit(local_var) + 6.0 * most_steps * global_var) / (2.0 * mean_steps * mean_steps)
    return (drop + noise + drift) / c


def max_step_size(mean_steps: float, most_steps: float, smooth: float, quorum: int, workers: int) -> float:
    return min(mean_steps / (math.sqrt(30) * smooth * most_steps**2), quorum**2 / (smooth * mean_steps * workers**2))


def rate_step_size(quorum: int, mean_steps: float, rounds: int, smooth: float) -> float:
    return math.sqrt(quorum) / (math.sqrt(mean_steps * rounds) * smooth)


def min_rounds(quorum: int, workers: int, mean_steps: float, most_steps: float) -> int:
    """Smallest number of rounds for which the rate's step size is admissible."""
    return math.ceil(max(30 * quorum * most_steps**4 / mean_steps**3, mean_steps * workers**4 / quorum**3))


def rate_term(quorum: int, quota: float, rounds: int) -> float:
    return 1 / math.sqrt(quorum * quota * rounds) + 1 / rounds


def bound_gap(equal_steps: float, **kwargs) -> float:
    """How much lower the bound is than that of equal steps for all."""
    return gradient_bound(**(kwargs | {"mean_steps": equal_steps, "most_steps": equal_steps})) - gradient_bound(**kwargs)
