"""Averaging local models as DataFrame operations, for models too large for the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LOCALS = "worker int, steps int, w array<double>"


def average_models(locals_: DataFrame, rule: str = "uniform", start: DataFrame | None = None, by: list[str] | None = None) -> DataFrame:
    """(pos, w) of the next model from rows (worker, steps, w) with at least one step.

    Sums are taken by position (and by the columns ``by``, say a block number), so each task holds a few sums and
    partial sums are combined before the shuffle. ``normalised_direction`` needs the round's start model (pos, w).
    """
    keys = [*(by or []), "pos"]
    rows = locals_.where("steps >= 1").select(*(by or []), "steps", F.posexplode("w").alias("pos", "v"))
    if rule == "uniform":
        return rows.groupBy(*keys).agg(F.avg("v").alias("w"))
    if rule == "inverse_model":
        return rows.groupBy(*keys).agg((F.sum(F.col("v") / F.col("steps")) / F.sum(1.0 / F.col("steps"))).alias("w"))
    if rule == "normalised_direction":
        if start is None:
            raise ValueError("normalised_direction needs the start model")
        both = rows.join(start.select(*keys, F.col("w").alias("w0")), keys)
        return both.groupBy(*keys).agg((F.first("w0") - F.avg("steps") * F.avg((F.col("w0") - F.col("v")) / F.col("steps"))).alias("w"))
    raise ValueError(f"unknown rule {rule!r}")


def to_vector(model: DataFrame) -> DataFrame:
    """One row with the model as an array, for small models."""
    return model.groupBy().agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "w"))), lambda s: s["w"]).alias("w"))


def to_blocks(model: DataFrame, width: int = 65_536) -> DataFrame:
    """(block, w): rows of at most ``width`` weights, the form in which large models are stored and averaged."""
    blocks = model.withColumn("block", F.floor(F.col("pos") / width).cast("int"))
    return blocks.groupBy("block").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "w"))), lambda s: s["w"]).alias("w"))
