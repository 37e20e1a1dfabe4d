"""Connected components of an edge table by repeated hooking and contraction.

Each round every node hooks to its smallest neighbour if that is smaller than itself; paths are
shortened by pointer jumping; edges are rewritten to the new labels. Only grouped minima and
equi-joins occur, so a hub with a third of all edges is combined before its shuffle, and joins on it
can be split. Every round ends in a written table, so a lost executor costs one round at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_written, written


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root) for every node of an edge with two different ends; ``root`` is the smallest node of the component
    among those reached, the same for all its members. Nodes without edges do not appear."""
    ends = edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).distinct()
    live = written(ends, "cc-edges")
    maps: list[DataFrame] = []
    while not live.isEmpty():
        hook = live.groupBy("hi").agg(F.min("lo").alias("up")).withColumnRenamed("hi", "node")
        up = hook
        for _ in range(2):
            above = up.select(F.col("node").alias("_n"), F.col("up").alias("_u"))
            up = up.join(above, F.col("up") == F.col("_n"), "left").select("node", F.coalesce("_u", "up").alias("up"))
        maps.append(written(up, "cc-map"))
        to = maps[-1].select(F.col("node").alias("_n"), F.col("up").alias("_u"))
        moved = live.join(to, F.col("hi") == F.col("_n"), "left").select(F.coalesce("_u", "hi").alias("hi"), "lo")
        moved = moved.join(to, F.col("lo") == F.col("_n"), "left").select("hi", F.coalesce("_u", "lo").alias("lo"))
        moved = moved.where("hi != lo").select(F.greatest("hi", "lo").alias("hi"), F.least("hi", "lo").alias("lo")).distinct()
        after = written(moved, "cc-edges")
        drop_written(live)
        live = after
    if not maps:
        return live.select(F.col("hi").alias("node"), F.col("lo").alias("root"))
    # Paths longer than the jumps leave hooked labels in use, so a node may hook again; all its rows end at one root.
    whole = maps[0]
    for later in maps[1:]:
        to = later.select(F.col("node").alias("_n"), F.col("up").alias("_u"))
        whole = whole.join(to, F.col("up") == F.col("_n"), "left").select("node", F.coalesce("_u", "up").alias("up")).unionByName(later)
    whole = written(whole.groupBy("node").agg(F.min("up").alias("up")), "cc-whole")
    drop_written(live, *maps)
    roots = whole.select(F.col("up").alias("node"), F.col("up").alias("root")).distinct()
    return whole.select("node", F.col("up").alias("root")).unionByName(roots)
