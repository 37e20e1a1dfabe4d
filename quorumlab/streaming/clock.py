"""The round clock as a stream: completions in, closed rounds out.

The state of a run is a handful of counters, keyed by run, so many runs scale by key. Inside a micro-batch event
order isn't given, so completions wait in the state until the watermark has passed them and are then taken in
order of (ts, event_id). A completion that comes after its round has closed counts for the next one.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROUNDS = "run_id string, round_no int, start timestamp, stop timestamp, events bigint, uploads int, max_steps int"
STATE = "round_no int, start timestamp, counts array<int>, events bigint, held array<struct<ts:timestamp,event_id:bigint,worker:int>>"

LATENESS = "1 hour"
ALL_FILES = 2**31 - 1


def clean(events: DataFrame, lateness: str = LATENESS, workers: int = 20) -> DataFrame:
    """Completions (run_id, event_id, ts, worker) with a watermark, repeated event ids dropped within it."""
    c = events.select(F.lit("run").alias("run_id"), "event_id", "ts", F.pmod("user_id", F.lit(workers)).cast("int").alias("worker"))
    return c.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"])


class RoundClock:
    """Plain state machine of one run; the same code serves stream and batch."""

    def __init__(self, workers: int, quorum: int, quota: int, round_no: int = 0, counts: list[int] | None = None, events: int = 0, start=None):
        self.workers, self.quorum, self.quota = workers, quorum, quota
        self.round_no, self.counts, self.events, self.start = round_no, counts or [0] * workers, events, start

    def take(self, ts, worker: int) -> tuple | None:
        """Count a completion; the closed round if it was the one that ends it."""
        self.start = self.start or ts
        self.counts[worker] += 1
        self.events += 1
        if self.counts[worker] != self.quota or sum(c >= self.quota for c in self.counts) < self.quorum:
            return None
        row = (self.round_no, self.start, ts, self.events, sum(c > 0 for c in self.counts), max(self.counts))
        self.round_no, self.counts, self.events, self.start = self.round_no + 1, [0] * self.workers, 0, ts
        return row


def quorum_clock(completions: DataFrame, workers: int, quorum: int, quota: int) -> DataFrame:
    """Closed rounds of each run, appended as the watermark passes their last completion."""

    def advance(key: tuple, frames: Iterator, state) -> Iterator:
        import pandas as pd

        round_no, start, counts, events, held = state.get if state.exists else (0, None, None, 0, [])
        machine = RoundClock(workers, quorum, quota, round_no, list(counts) if counts is not None else None, events, start)
        heap = [(pd.Timestamp(h[0]), h[1], h[2]) for h in held or []]
        for frame in frames:
            heap += list(zip(frame.ts, frame.event_id, frame.worker, strict=True))
        heapq.heapify(heap)
        safe = pd.Timestamp(state.getCurrentWatermarkMs(), unit="ms")
        rows = []
        while heap and heap[0][0] <= safe:
            ts, _, worker = heapq.heappop(heap)
            if (row := machine.take(ts, int(worker))) is not None:
                rows.append((key[0], *row))
        kept = [(t.to_pydatetime(), int(e), int(m)) for t, e, m in sorted(heap)]
        first = machine.start.to_pydatetime() if machine.start is not None and hasattr(machine.start, "to_pydatetime") else machine.start
        state.update((machine.round_no, first, machine.counts, machine.events, kept))
        if kept:
            state.setTimeoutTimestamp(int(heap[0][0].timestamp() * 1000) + 1 if int(heap[0][0].timestamp() * 1000) > state.getCurrentWatermarkMs() else state.getCurrentWatermarkMs() + 1)
        if rows:
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in ROUNDS.split(", ")])

    return completions.groupBy("run_id").applyInPandasWithState(advance, ROUNDS, STATE, "append", "EventTimeTimeout")


def batch_clock(events: DataFrame, workers: int, quorum: int, quota: int) -> DataFrame:
    """The same rounds from a finished trace: one ordered pass for each run, as the order is the meaning."""

    def run(key: tuple, frame):
        import pandas as pd

        machine, rows = RoundClock(workers, quorum, quota), []
        for ts, worker in zip(*(frame.sort_values(["ts", "event_id"])[c] for c in ("ts", "worker")), strict=True):
            if (row := machine.take(ts, int(worker))) is not None:
                rows.append((key[0], *row))
        return pd.DataFrame(rows, columns=[c.split()[0] for c in ROUNDS.split(", ")])

    c = events.select(F.lit("run").alias("run_id"), "event_id", F.col("ts").cast("timestamp").alias("ts"), F.pmod("user_id", F.lit(workers)).cast("int").alias("worker"))
    return c.groupBy("run_id").applyInPandas(run, ROUNDS)


def throughput(completions: DataFrame, size: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Steps of each worker in tumbling or sliding windows."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return completions.groupBy(w, "worker").agg(F.count("*").alias("steps"))


def bursts(completions: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Sessions of activity of each worker."""
    return completions.groupBy("worker", F.session_window("ts", gap)).agg(F.count("*").alias("steps"))


def enrich(completions: DataFrame, catalogue: DataFrame) -> DataFrame:
    """Stream with a static, small catalogue of workers."""
    return completions.join(F.broadcast(catalogue), "worker")


def pair(starts: DataFrame, acks: DataFrame, within: str = "2 hours") -> DataFrame:
    """Stream with stream: acknowledgements with their round's start, at most ``within`` apart."""
    s = starts.select(F.col("round_no"), F.col("ts").alias("start_ts"))
    a = acks.select(F.col("round_no").alias("ack_round"), F.col("worker"), F.col("ts").alias("ack_ts"))
    return s.join(a, F.expr(f"round_no = ack_round and ack_ts >= start_ts and ack_ts <= start_ts + interval {within}"))


def _fresh_folder(spark: SparkSession) -> str:
    """A new folder below ``spark.checkpoint.dir``; only a local master may go without that setting."""
    import uuid

    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    return f"{(base or 'file:///tmp/checkpoints').rstrip('/')}/stream-{uuid.uuid4().hex}"


def hourly_to_end(spark: SparkSession, path: str, workers: int, mode: str) -> DataFrame:
    """Hourly steps of each worker (hour, worker, steps) from a stream in ``update`` or ``complete`` output mode.

    Every trigger writes its rows into a folder of its own number, so a trigger that is run again replaces what it wrote. An
    update has the changed counts only and the latest of each key holds; in complete mode the last trigger has all of them.
    """
    from quorumlab.sources.tables import event_stream

    if mode not in ("update", "complete"):
        raise ValueError(f"unknown output mode {mode!r}")
    where = _fresh_folder(spark)
    c = event_stream(spark, path, ALL_FILES).where(F.col("ts").isNotNull()).select("ts", F.pmod("user_id", F.lit(workers)).cast("int").alias("worker"))
    counts = throughput(c.withWatermark("ts", LATENESS)).select(F.col("window.start").alias("hour"), "worker", "steps")

    def write(rows: DataFrame, trigger: int) -> None:
        rows.write.mode("overwrite").parquet(f"{where}/out/trigger={trigger}")

    q = counts.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    out = spark.read.schema("hour timestamp, worker int, steps bigint, trigger bigint").parquet(f"{where}/out")
    if mode == "complete":
        last = out.agg(F.max("trigger").alias("trigger"))
        return out.join(F.broadcast(last), "trigger").select("hour", "worker", "steps")
    return out.groupBy("hour", "worker").agg(F.max_by("steps", "trigger").alias("steps"))


def run_to_end(spark: SparkSession, path: str, workers: int, quorum: int, quota: int, name: str | None = None) -> DataFrame:
    """Run the stream over the files of a finished trace at a path, and return every closed round.

    All files come in one trigger, so no event is late, whatever the order of the files. A mark after the latest event brings
    the watermark past all of them; the mark itself stays held and is never counted.
    """
    from quorumlab.sources.tables import EVENTS, event_stream

    where = _fresh_folder(spark)
    latest = spark.read.schema(EVENTS).parquet(path).agg((F.max("event_id") + 1).alias("event_id"), F.max("ts").alias("ts")).where("ts is not null")
    after = (F.col("ts") + F.expr(f"interval {LATENESS}") + F.expr("interval 1 second")).cast("timestamp_ntz")
    empty = [F.lit(0).cast("bigint").alias("user_id"), *[F.lit(None).cast(t).alias(c) for c, t in (("event_type", "string"), ("value", "double"), ("props", "string"))]]
    latest.select("event_id", after.alias("ts"), *empty).write.parquet(f"{where}/mark")
    events = event_stream(spark, path, ALL_FILES).unionByName(event_stream(spark, f"{where}/mark", ALL_FILES))
    rounds = quorum_clock(clean(events, workers=workers), workers, quorum, quota)
    q = rounds.writeStream.format("parquet").option("path", f"{where}/out").option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(ROUNDS).parquet(f"{where}/out").select("round_no", "start", "stop", "events", "uploads", "max_steps")
