"""What the training-data operators share: the shared folder, written intermediate tables, text as bytes."""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII capitals and the letters that replace them.
ASCII_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
ASCII_LOWER = "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, from ``spark.checkpoint.dir``.

    Only where the setting is missing and the master is local (tests, a laptop) is a local folder chosen.
    """
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        where = f"file:///tmp/checkpoints/{os.getpid()}"
    return where.rstrip("/")


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends there, and the files
    outlive any executor. The schema is given, so an empty table reads back too."""
    spark = df.sparkSession
    path = fresh_path(spark, label)
    df.write.option("compression", "zstd").parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    vars(back)["_folder"] = path
    return back


def drop_written(*tables: DataFrame) -> None:
    """Delete the files behind tables made by :func:`written` once nothing reads them again."""
    for df in tables:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(vars(df)["_folder"])
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def ascii_lower_bytes(text: Column) -> Column:
    """Text with A-Z lowered and nothing else, for comparing and hashing only.

    The UTF-8 bytes are read as Latin-1 and lowered there. Lead bytes of two-byte characters
    move by 32 as well, but whether a continuation byte follows still tells the cases apart, so
    two texts are equal afterwards exactly if they were equal after lowering A-Z. This stays in
    fast built-in code, where ``translate`` looks up every character.
    """
    return F.lower(F.decode(F.coalesce(text, F.lit("")).cast("binary"), "ISO-8859-1"))


def unit_hash(*parts: Column) -> Column:
    """A double in (0, 1) that depends on the parts alone, never on the partitioning."""
    return (F.shiftrightunsigned(F.xxhash64(*parts), 11).cast("double") + 0.5) / F.lit(float(1 << 53))


def spare(df: DataFrame, *names: str) -> list[str]:
    """Column names like the given ones that the table doesn't have yet, whatever the case."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def key_groups(batches: Iterator, keys: list[str]) -> Iterator:
    """(key values, Arrow table) of each run of equal keys; rows come sorted by the keys, which are never null."""
    import numpy as np
    import pyarrow as pa
    import pyarrow.compute as pc

    held, at = [], None
    for batch in batches:
        n = batch.num_rows
        columns = [batch.column(batch.schema.get_field_index(k)) for k in keys]
        new = np.zeros(n, bool)
        new[:1] = True
        for c in columns:
            if n > 1:
                new[1:] |= pc.not_equal(c.slice(1), c.slice(0, n - 1)).to_numpy(zero_copy_only=False)
        starts = np.flatnonzero(new).tolist()
        for s, e in zip(starts, [*starts[1:], n], strict=True):
            here = tuple(c[s].as_py() for c in columns)
            if held and here != at:
                yield at, pa.Table.from_batches(held)
                held = []
            at = here
            held.append(batch.slice(s, e - s))
    if held:
        yield at, pa.Table.from_batches(held)
