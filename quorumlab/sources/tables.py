"""Reading tables and step-duration traces; writing logs and models."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from quorumlab.functions import rng

DURATIONS = "round_no int, worker int, step_no int, dur double"
EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
FORMATS = ("parquet", "orc", "json", "csv")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load(spark: SparkSession, fmt: str, path: str, schema: str | T.StructType) -> DataFrame:
    """Read a sample or duration table with a given schema; nothing is inferred."""
    if fmt not in FORMATS:
        raise ValueError(f"unknown format {fmt!r}")
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def require(df: DataFrame, schema: str) -> DataFrame:
    """Fail early if a column is missing or has another type."""
    have = dict(df.dtypes)
    want = {f.name: f.dataType.simpleString() for f in T.DataType.fromDDL(schema).fields}
    if wrong := {c: (have.get(c), t) for c, t in want.items() if have.get(c) != t}:
        raise ValueError(f"columns differ from the schema (have, want): {wrong}")
    return df


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a stream of files; ``ts`` becomes a timestamp, which watermarks need."""
    stream = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("props", F.from_json("props", "k int"))


def trace(events: DataFrame, workers: int, mean: float = 1.0) -> DataFrame:
    """(worker, seq, dur): the events of a worker in order of their id are its steps; values have mean 50."""
    from pyspark.sql import Window as W

    worker = F.pmod("event_id", F.lit(workers)).cast("int")
    seq = F.row_number().over(W.partitionBy("worker").orderBy("event_id")) - 1
    dealt = events.select(worker.alias("worker"), "event_id", (F.col("value") / 50.0 * mean).alias("dur"))
    return dealt.select("worker", seq.alias("seq"), "dur")


def uncut_steps(events: DataFrame, workers: int, mean: float = 1.0) -> DataFrame:
    """(worker, seq, dur) of the whole trace, not cut into rounds; ids are dense."""
    return events.select(F.pmod("event_id", F.lit(workers)).cast("int").alias("worker"), F.floor(F.col("event_id") / workers).cast("bigint").alias("seq"), (F.col("value") / 50.0 * mean).alias("dur"))


def durations_from_trace(events: DataFrame, workers: int, cap: int, mean: float = 1.0) -> DataFrame:
    """Cut each worker's trace into rounds of ``cap`` steps; only rounds that are full for every worker remain.

    Ids are dense, so a step's place in its worker's trace is ``event_id div workers`` and needs no sort.
    """
    cut = uncut_steps(events, workers, mean).select((F.floor(F.col("seq") / cap)).cast("int").alias("round_no"), "worker", (F.col("seq") % cap).cast("int").alias("step_no"), "dur")
    full = cut.groupBy("round_no").agg(F.count("*").alias("n")).where(F.col("n") == workers * cap).select("round_no")
    return cut.join(full, "round_no").select("round_no", "worker", "step_no", "dur")


def unit_draw(dist: str, seed: int, *keys: Column) -> Column:
    """A positive draw of mean one."""
    u = rng.uniform(seed, "dur", *keys)
    if dist == "exponential":
        return -F.log(u)
    if dist == "constant":
        return F.lit(1.0)
    if dist == "uniform":
        return 2 * u
    if dist == "shifted":
        return 0.5 - 0.5 * F.log(u)
    if dist == "erlang2":
        return -(F.log(u) + F.log(rng.uniform(seed, "dur2", *keys))) / 2
    if dist == "pareto":
        return F.pow(u, -1 / 3.0) * (2 / 3.0)
    raise ValueError(f"unknown distribution {dist!r}")


def hashed_durations(spark: SparkSession, rounds: int, workers: int, cap: int, mean: float = 1.0, seed: int = 0, dist: str = "exponential", slow: dict[int, float] | None = None) -> DataFrame:
    """Unlimited deterministic durations: keys alone decide. ``slow`` gives factors of single workers."""
    n = rounds * workers * cap
    i = F.col("id")
    keys = spark.range(n).select(F.floor(i / (workers * cap)).cast("int").alias("round_no"), (F.floor(i / cap) % workers).cast("int").alias("worker"), (i % cap).cast("int").alias("step_no"))
    factor = F.lit(1.0)
    for w, f in (slow or {}).items():
        factor = F.when(F.col("worker") == w, F.lit(float(f))).otherwise(factor)
    return keys.withColumn("dur", unit_draw(dist, seed, F.col("round_no"), F.col("worker"), F.col("step_no")) * mean * factor)


def write_log(log: DataFrame, path: str, fmt: str = "parquet", mode: str = "append") -> None:
    """Round logs or schedules, one folder for each run."""
    writer = log.write.mode(mode).partitionBy("run_id").format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)


def write_model(model: DataFrame, path: str) -> None:
    """Model rows (run_id, round_no, block, w); a round that is written again replaces its partition only."""
    model.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run_id", "round_no").parquet(path)


def write_shards(shards: DataFrame, path: str, files: int) -> None:
    """Pieces sorted by (worker, pos), so that row groups of a file cover narrow ranges and a fetch prunes the others."""
    shards.repartitionByRange(files, "worker", "pos").sortWithinPartitions("worker", "pos").write.mode("overwrite").parquet(path)
