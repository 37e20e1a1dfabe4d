"""Learning tasks on the given tables, their splits over workers, and mini-batch draws."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from quorumlab.functions import rng
from quorumlab.sources.tables import table

#: The letters counted by the language task.
LETTERS = "abcdefghijklmnopqrstuvwxyzäöüßéèêçáíóúñ"
LANGUAGES = ["de", "en", "es", "fr"]


#: Characters of several bytes outside the letters' block that lower to a letter; the last one to a letter and a mark of its own.
LOWERED = {"\u1e9e": "ß", "\u212a": "k", "\u0130": "i"}


def letter_shares(text: pa.Array) -> pa.Array:
    """Arrow strings to their feature rows, from counts of UTF-8 bytes. Capitals count as what they lower to; letters beyond ASCII
    all have the same first byte, and their capitals' second byte is less by 0x20, as ASCII's only one is."""
    import numpy as np

    text = text.cast(pa.large_binary())
    _, offsets, data = text.buffers()
    ends = np.frombuffer(offsets, np.int64)[text.offset : text.offset + len(text) + 1]
    data, ends = np.frombuffer(data or b"", np.uint8)[ends[0] : ends[-1]], ends - ends[0]
    codes = [c.encode() for c in LETTERS]
    lead = codes[-1][0]
    single, double = [c[0] for c in codes if len(c) == 1], [c[1] for c in codes if len(c) == 2 and c[0] == lead]
    counts = np.array([np.bincount(data[begin:end], minlength=256) for begin, end in zip(ends[:-1], ends[1:], strict=True)]).reshape(-1, 256)
    rows = lambda at: np.searchsorted(ends, at, side="right") - 1
    at = np.flatnonzero(data[:-1] == lead)
    after = np.bincount(rows(at) * 256 + data[at + 1], minlength=256 * len(text)).reshape(-1, 256)
    found = np.concatenate([counts[:, single] + counts[:, [c - 0x20 for c in single]], after[:, double] + after[:, [c - 0x20 for c in double]]], axis=1)
    n = counts.sum(axis=1) - counts[:, 0x80:0xC0].sum(axis=1)  # bytes that go on with a character don't count
    for c, letter in LOWERED.items():
        code = c.encode()
        at = np.flatnonzero(data[: len(data) - len(code) + 1] == code[0]) if len(data) >= len(code) else np.zeros(0, np.int64)
        for k in range(1, len(code)):
            at = at[data[at + k] == code[k]]
        own = np.bincount(rows(at), minlength=len(text))
        found[:, LETTERS.index(letter)] += own
        n = n + own * (len(c.lower()) - 1)
    out = np.ones((len(text), len(LETTERS) + 1))
    out[:, :-1] = 10.0 * found / np.maximum(n, 1)[:, None]
    return pa.FixedSizeListArray.from_arrays(pa.array(out.ravel()), out.shape[1]).cast(pa.list_(pa.float64()))


def letters(text: Column) -> Column:
    """Ten times the relative frequency of each letter among the lowered characters of the whole text, and a bias."""
    return F.arrow_udf(letter_shares, "array<double>")(F.coalesce(text, F.lit("")))


def language_task(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return docs.select(F.col("doc_id").alias("row_id"), letters(F.col("text")).alias("x"), (F.array_position(F.array(*map(F.lit, LANGUAGES)), F.col("lang")) - 1).cast("int").alias("y"), "source")


def planted_task(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten classes planted in vectors: the place of the largest of the first ten coordinates."""
    v = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), F.col("embedding").cast("array<double>").alias("e"))
    y = F.array_position(F.slice("e", 1, 10), F.array_max(F.slice("e", 1, 10))) - 1
    return v.select("row_id", F.concat(F.transform("e", lambda a: 8 * a), F.array(F.lit(1.0))).alias("x"), y.cast("int").alias("y"))


def line_task(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "part")
    return p.select(F.col("p_partkey").alias("row_id"), ((F.col("p_partkey") % 1000) / 1000.0).alias("x"), ((F.col("p_retailprice") - 900.0) / 100.0).alias("y"))


def revenue_task(spark: SparkSession, sf_dir: str, median: float = 32_000.0) -> DataFrame:
    """Is the net price above a literal? Keys aren't unique, so the row id is a hash of the row; rows with one id are one sample twice."""
    li = table(spark, sf_dir, "lineitem")
    row = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate"]
    x = F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / 100_000, F.col("l_discount") * 10, F.col("l_tax") * 10, F.lit(1.0))
    return li.select(F.xxhash64(*row).alias("row_id"), x.alias("x"), (F.col("l_extendedprice") * (1 - F.col("l_discount")) > median).cast("int").alias("y"), "l_suppkey")


def quality_task(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return docs.join(labels, "doc_id").select(F.col("doc_id").alias("row_id"), letters(F.col("text")).alias("x"), F.col("quality").alias("y"))


def train_test(samples: DataFrame, test: bool, folds: int = 5) -> DataFrame:
    held = F.pmod(F.col("row_id"), F.lit(folds)) == 0
    return samples.where(held if test else ~held)


# --- splits -----------------------------------------------------------------------------------------------------


def dense_rank_distributed(df: DataFrame, order: list[str], name: str = "rank") -> DataFrame:
    """0, 1, 2 ... in a total order without a single-task window: range partitions, their sizes, ranks inside them.

    The driver sees one small row for each partition.
    """
    parts = max(1, df.sparkSession.sparkContext.defaultParallelism)
    ranged = df.repartitionByRange(parts, *order).withColumn("_part", F.spark_partition_id())
    ranged = ranged.persist()  # the split points must be those of one run
    sizes = sorted((r["_part"], r["count"]) for r in ranged.groupBy("_part").count().collect())
    starts, at = {}, 0
    for p, n in sizes:
        starts[p] = at
        at += n
    begin = F.lit(0).cast("bigint")
    if starts:
        begin = F.element_at(F.create_map(*[F.lit(v) for kv in starts.items() for v in kv]), F.col("_part")).cast("bigint")
    inside = F.row_number().over(W.partitionBy("_part").orderBy(*order)) - 1
    return ranged.withColumn(name, begin + inside).drop("_part")


def even_random(samples: DataFrame, workers: int, seed: int = 0) -> DataFrame:
    """Equal pieces in hash order: adds worker and pos (0 .. n-1 inside the worker)."""
    hashed = samples.withColumn("_h", rng.hash48(seed, "split", F.col("row_id")))
    ranked = dense_rank_distributed(hashed, ["_h", "row_id"])
    return ranked.select(*samples.columns, F.pmod("rank", F.lit(workers)).cast("int").alias("worker"), F.floor(F.col("rank") / workers).cast("bigint").alias("pos"))


def even_by_label(samples: DataFrame, workers: int, seed: int = 0) -> DataFrame:
    """Equal contiguous pieces of the rows sorted by label; sizes differ by one at most."""
    ranked = dense_rank_distributed(samples, ["y", "row_id"])
    n = ranked.count()
    worker = F.floor(F.col("rank") * workers / n)
    start = F.ceil(F.floor(F.col("rank") * workers / n) * n / workers)
    return ranked.select(*samples.columns, worker.cast("int").alias("worker"), (F.col("rank") - start).cast("bigint").alias("pos"))


def by_key(samples: DataFrame, key: str) -> DataFrame:
    """One worker for each key, numbered in order; keys are workers, so few. A hot key is ranked by many tasks."""
    ranked = dense_rank_distributed(samples, [key, "row_id"])
    sizes = samples.groupBy(key).agg(F.count("*").alias("_n"))
    order = W.orderBy(key).rowsBetween(W.unboundedPreceding, -1)
    numbered = sizes.select(key, (F.row_number().over(W.orderBy(key)) - 1).cast("int").alias("worker"), F.coalesce(F.sum("_n").over(order), F.lit(0)).alias("_first"))
    return ranked.join(F.broadcast(numbered), key).withColumn("pos", (F.col("rank") - F.col("_first")).cast("bigint")).drop("rank", "_first")


def label_skew(samples: DataFrame, workers: int, beta: float, seed: int = 0) -> DataFrame:
    """Tunable skew: a row goes to its label's favourite worker block with probability 1 - beta, else anywhere."""
    u = rng.uniform(seed, "skew", F.col("row_id"))
    anywhere = rng.randint(workers, seed, "skew2", F.col("row_id"))
    home = F.pmod(rng.hash48(seed, "home", F.col("y")) + F.pmod(rng.hash48(seed, "skew3", F.col("row_id")), F.lit(2)), F.lit(workers))
    dealt = samples.withColumn("worker", F.when(u < beta, anywhere).otherwise(home).cast("int"))
    first = {w: 0 for w in range(workers)}
    for r in dealt.groupBy("worker").count().orderBy("worker").collect():  # one row for each worker
        first |= {w: first[w] + r["count"] for w in range(r["worker"] + 1, workers)}
    begin = F.element_at(F.create_map(*[F.lit(v) for kv in first.items() for v in kv]), F.col("worker"))
    return dense_rank_distributed(dealt, ["worker", "row_id"]).withColumn("pos", (F.col("rank") - begin).cast("bigint")).drop("rank")


SPLITS = {"even_random": even_random, "even_by_label": even_by_label}


def shard_label_stats(shards: DataFrame) -> DataFrame:
    """Per worker: rows, distinct labels, and the total-variation distance of its labels from all labels'."""
    cells = shards.groupBy("worker", "y").agg(F.count("*").alias("n"))
    total = cells.groupBy("y").agg(F.sum("n").alias("all_n"))
    everything = total.agg(F.sum("all_n").alias("all_rows"))
    sizes = cells.groupBy("worker").agg(F.sum("n").alias("rows"), F.count("*").alias("labels"))
    full = sizes.crossJoin(F.broadcast(total)).crossJoin(F.broadcast(everything)).join(cells, ["worker", "y"], "left")
    distance = F.sum(F.abs(F.coalesce("n", F.lit(0)) / F.col("rows") - F.col("all_n") / F.col("all_rows"))) / 2
    return full.groupBy("worker").agg(F.first("rows").alias("rows"), F.first("labels").alias("labels"), distance.alias("distance"))


# --- draws ------------------------------------------------------------------------------------------------------

#: Fixed values of the multiplicative generator that turns one hash into a batch of draws.
PRIME, MULTIPLIER = (1 << 31) - 1, 48271


def draw_batches(schedule: DataFrame, sizes: DataFrame, batch: int, seed: int, mode: str = "independent") -> DataFrame:
    """(round_no, worker, step_no, slot, pos) for every finished step: only these rows are ever fetched.

    ``independent`` draws with replacement; ``distinct`` without, by steps of a random length that shares no divisor with the piece's size;
    ``block`` takes consecutive positions from a random start, one range read for a batch (for pieces that lie in hashed order). A batch larger
    than the piece goes round it.
    """
    steps = schedule.where("steps > 0").select("round_no", "worker", F.explode(F.sequence(F.lit(0), F.col("steps") - 1)).alias("step_no"))
    steps = steps.join(F.broadcast(sizes), "worker").withColumn("h", 1 + F.pmod(rng.hash48(seed, "draw", F.col("round_no"), F.col("worker"), F.col("step_no")), F.lit(PRIME - 1)))
    slots = steps.select("round_no", "worker", "step_no", "n", "h", F.explode(F.sequence(F.lit(0), F.lit(batch - 1))).alias("slot"))
    if mode == "block":
        pos = F.pmod(F.col("h") + F.col("slot"), F.col("n"))
    elif mode == "distinct":
        # Strides that share no divisor with n visit every position once before any twice.
        start = F.pmod(rng.hash48(seed, "stride", F.col("round_no"), F.col("worker"), F.col("step_no")), F.col("n"))
        shared = lambda a, b: F.aggregate(F.sequence(F.lit(1), F.lit(64)), F.struct(a.alias("a"), b.alias("b")), lambda s, _: F.when(s["b"] == 0, s).otherwise(F.struct(s["b"].alias("a"), F.pmod(s["a"], F.greatest(s["b"], F.lit(1))).alias("b"))), lambda s: s["a"])
        tried = F.filter(F.transform(F.sequence(F.lit(0), F.lit(200)), lambda k: 1 + F.pmod(start + k, F.col("n"))), lambda c: shared(c, F.col("n")) == 1)
        steps = steps.withColumn("stride", tried[0])
        slots = steps.select("round_no", "worker", "step_no", "n", "h", "stride", F.explode(F.sequence(F.lit(0), F.lit(batch - 1))).alias("slot"))
        pos = F.pmod(F.col("h") + F.col("slot") * F.col("stride"), F.col("n"))
    else:
        powers = F.array(*[F.lit(pow(MULTIPLIER, s + 1, PRIME)).cast("bigint") for s in range(batch)])
        pos = F.pmod(F.pmod(F.col("h") * F.element_at(powers, F.col("slot") + 1), F.lit(PRIME)), F.col("n"))
    return slots.select("round_no", "worker", "step_no", "slot", pos.cast("bigint").alias("pos"))


def draws_py(seed: int, round_no: int, worker: int, step: int, batch: int, n: int, powers):
    """The same draws in numpy; ``powers`` as from :func:`draw_powers`."""
    h = 1 + rng.hash48_py(seed, "draw", round_no, worker, step) % (PRIME - 1)
    return h * powers[:batch] % PRIME % n


def draw_powers(batch: int):
    import numpy as np

    return np.array([pow(MULTIPLIER, s + 1, PRIME) for s in range(batch)], np.int64)


def fetch(draws: DataFrame, shards: DataFrame, broadcast_rows: int = 5_000_000) -> DataFrame:
    """Join draws with the rows they name. Draws are few (steps times batch) and broadcast up to a checked count."""
    small = draws.count() <= broadcast_rows
    return shards.join(F.broadcast(draws) if small else draws, ["worker", "pos"]).select("round_no", "worker", "step_no", "slot", "x", "y")
