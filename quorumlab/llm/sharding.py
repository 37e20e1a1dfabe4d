"""Sharding by a hierarchical weighted hash tree (region, rack, shard).

A row descends the tree. At each node every child gets a draw ``-ln(u) / weight`` with ``u`` hashed
from the key and the child's name; the smallest draw wins, so a child receives a share in
proportion to its weight. If a weight changes, only keys whose winner changes move, and only
between that subtree and the rest; orders of the other children never change. A shard appended as a
region of its own therefore takes rows only into itself.

Defined cases: a null key is one key (all such rows share a shard); repeated rows share a shard and
take consecutive slots; a null text counts as empty (size 1, CRC 0); an empty table gives an empty
result; further columns of the input are ignored unless they are asked for.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import unit_hash

#: Rows that one ranking task sorts, about.
ROWS_PER_CHUNK = 200_000


@dataclass(frozen=True)
class Topology:
    """Nested weights: ``tree[region][rack] = [(shard, weight), ...]``; a node weighs the sum below it."""

    tree: tuple

    @staticmethod
    def of(shards: int, founding: int = 8, racks: int = 2, per_rack: int = 2) -> "Topology":
        """``founding`` shards of weight 1 in full racks; each later shard is a region of its own."""
        first = min(shards, founding)
        size = racks * per_rack
        regions = []
        for start in range(0, first, size):
            ids = range(start, min(start + size, first))
            regions.append(tuple(tuple((s, 1.0) for s in ids[k : k + per_rack]) for k in range(0, len(ids), per_rack)))
        regions += [(((s, 1.0),),) for s in range(first, shards)]
        return Topology(tuple(regions))


def _sql(values) -> str:
    if isinstance(values, (list, tuple)):
        return "array(" + ", ".join(_sql(v) for v in values) + ")"
    return f"'{values}'" if isinstance(values, str) else f"{values!r}d" if isinstance(values, float) else repr(values)


def _winner(key: Column, names: Column, weights: Column) -> Column:
    """Zero-based index of the child with the smallest draw; a tie goes to the first child."""
    draws = F.zip_with(names, weights, lambda n, w: F.when(w > 0, -F.log(unit_hash(key, n)) / w))
    return F.array_min(F.transform(draws, lambda d, i: F.struct(F.coalesce(d, F.lit(float("inf"))).alias("d"), i.alias("i"))))["i"]


def locate(key: Column, topology: Topology) -> Column:
    """struct(region, rack, shard) for a key column. The tree is data (array literals), so the plan
    does not grow with the number of shards, and a row looks only at the children on its path."""
    tree = topology.tree
    region_names = F.expr(_sql([f"region{r}" for r in range(len(tree))]))
    region_weights = F.expr(_sql([sum(w for rack in region for _, w in rack) for region in tree]))
    rack_names = F.expr(_sql([[f"region{r}/rack{k}" for k in range(len(region))] for r, region in enumerate(tree)]))
    rack_weights = F.expr(_sql([[sum(w for _, w in rack) for rack in region] for region in tree]))
    shard_names = F.expr(_sql([[[f"shard{s}" for s, _ in rack] for rack in region] for region in tree]))
    shard_weights = F.expr(_sql([[[w for _, w in rack] for rack in region] for region in tree]))
    shard_ids = F.expr(_sql([[[s for s, _ in rack] for rack in region] for region in tree]))
    key = F.coalesce(key.cast("string"), F.lit("null key"))
    region = _winner(key, region_names, region_weights)

    def below(values: Column, index: Column) -> Column:
        return F.element_at(values, index + 1)

    # The nested transforms name an index once and use it below, so no draw is computed twice.
    def shard_of(r: Column) -> Column:
        def inner(k: Column) -> Column:
            s = _winner(key, below(below(shard_names, r), k), below(below(shard_weights, r), k))
            return F.struct(r.alias("region"), k.alias("rack"), below(below(below(shard_ids, r), k), s).alias("shard"))

        return F.transform(F.array(_winner(key, below(rack_names, r), below(rack_weights, r))), inner)[0]

    return F.transform(F.array(region), shard_of)[0]


def slots(df: DataFrame, shard: str, order: list[str], rows_per_chunk: int = ROWS_PER_CHUNK) -> DataFrame:
    """Add ``slot``: 0, 1, 2 ... without gaps inside each shard.

    No task sees a whole shard: rows are ranked inside hashed chunks of a shard, and a running sum of
    the chunk sizes (one small row for each chunk) gives where a chunk starts.
    """
    chunks = max(1, df.count() // rows_per_chunk)
    chunk = F.pmod(F.xxhash64(F.lit("slot"), F.col(order[0])), F.lit(chunks))
    rows = df.withColumn("_chunk", chunk)
    starts = rows.groupBy(shard, "_chunk").agg(F.count("*").alias("_n"))
    running = W.partitionBy(shard).orderBy("_chunk").rowsBetween(W.unboundedPreceding, -1)
    starts = starts.select(shard, "_chunk", F.coalesce(F.sum("_n").over(running), F.lit(0)).alias("_start"))
    ranked = rows.withColumn("_rank", F.row_number().over(W.partitionBy(shard, "_chunk").orderBy(*order)))
    out = ranked.join(starts, [shard, "_chunk"])
    return out.withColumn("slot", (F.col("_start") + F.col("_rank") - 1).cast("long")).drop("_chunk", "_rank", "_start")


def shard_documents(docs: DataFrame, shards: int = 8, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, region, rack, shard, slot, grown_shard. The text itself is never shuffled."""
    body = F.coalesce(F.col(text), F.lit("")).cast("binary")
    placed = docs.select(
        F.col(key).alias("doc_id"),
        (F.octet_length(body) + 1).cast("long").alias("size"),
        F.crc32(body).alias("text_crc32"),
        locate(F.col(key), Topology.of(shards)).alias("at"),
        locate(F.col(key), Topology.of(shards + 1)).alias("grown"),
    ).select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "at.region", "at.rack",
        F.col("at.shard").cast("int").alias("shard"), F.col("grown.shard").cast("int").alias("grown_shard"),
    )
    return slots(placed, "shard", ["doc_id", "text_crc32", "size"])
