"""Counter-based random numbers: a value depends on (seed, tag, keys) alone, never on the partitioning.

The hash is the first 12 hexadecimal digits of an md5, which DuckDB computes alike.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

SPACE = float(1 << 48)


def hash48(seed: int, tag: str, *keys: Column) -> Column:
    words = F.concat_ws("|", F.lit(str(seed)), F.lit(tag), *[k.cast("string") for k in keys])
    return F.conv(F.substring(F.md5(words.cast("binary")), 1, 12), 16, 10).cast("bigint")


def uniform(seed: int, tag: str, *keys: Column) -> Column:
    """In (0, 1)."""
    return (hash48(seed, tag, *keys).cast("double") + 0.5) / SPACE


def exponential(mean: float, seed: int, tag: str, *keys: Column) -> Column:
    return -F.log(uniform(seed, tag, *keys)) * mean


def randint(n: Column | int, seed: int, tag: str, *keys: Column) -> Column:
    """0 .. n-1."""
    return F.pmod(hash48(seed, tag, *keys), (F.lit(n) if isinstance(n, int) else n).cast("bigint"))


def hash48_py(seed: int, tag: str, *keys) -> int:
    """The same hash outside Spark, for kernels that run a whole experiment in one task."""
    return int(hashlib.md5("|".join([str(seed), tag, *map(str, keys)]).encode()).hexdigest()[:12], 16)


def hash48_sql(seed: int, tag: str, *keys: str) -> str:
    """The same hash as DuckDB SQL over expressions that print as integers or strings."""
    parts = " || '|' || ".join(f"cast({k} as varchar)" for k in keys)
    return f"cast('0x' || substr(md5('{seed}|{tag}|' || {parts}), 1, 12) as bigint)"
