"""Near-duplicate vectors by a subspace pigeonhole join.

Vectors are scaled to length one, so cosine >= t means squared distance <= 2 - 2t. A fixed random rotation
spreads the variance; the rotated coordinates are cut into blocks. If two vectors are within the whole budget, then
in some block their squared distance is within the block's share of it (shares in proportion to the
block's dimensions). Each block is a range join on its leading coordinates: cells twice the radius
wide, each vector entering the cells its half-radius box touches, a pair being met in exactly one of them.

1. Place and screen. Only keys and the block's own coordinates, in half precision, go through the join; a tile of a cell
   compares them with a radius widened by the rounding and keeps rows that have a candidate.
2. Confirm. Those rows get their full vector, and their candidates are verified by the exact cosine in double precision.
   A pair found in several blocks counts in the first of them only, so link counts are exact without listing pairs.

* Equal (label, vector) rows are one class; its copies link with each other and share its other links.
* Hot cells are dealt to tiles of at most ``TILE_VALUES`` vector components a side, so memory is bounded for any dimension.
* A tile gives link counts for each vector and a spanning forest of its links, never its pairs.

Defined cases: a null vector or label, a zero vector, and one with null or non-finite components link with
nothing (n_links 0, their own component); vectors of different length under a label link with nothing; repeated
vec_id rows are separate vectors for n_links and one node for components; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import drop_written, key_groups, written
from .components import components

COSINE = 0.93
BLOCK_DIMS = 16
CELL_DIMS = 2
#: Vector components on either side of a tile: 16,384 rows of 64.
TILE_VALUES = 1 << 20
#: Rows of a tile compared with all others at a time, and candidate pairs verified at a time.
CHUNK, PAIRS = 128, 16_384
#: Hot cells up to which their sizes are broadcast; beyond, the join shuffles.
BROADCAST_CELLS = 100_000
#: Widening of every radius against rounding of doubles, and of screens against that of half precision (16 coordinates of at
#: most one, each off by 2**-12 at most, on both sides).
SLACK, SCREEN_SLACK = 1e-9, 2.5e-3


def rotation(dims: int):
    """A random orthogonal matrix, the same everywhere."""
    import numpy as np

    q, r = np.linalg.qr(np.random.Generator(np.random.PCG64(77)).standard_normal((dims, dims)))
    return q * np.sign(np.diag(r))


def blocks_of(dims: int, width: int = BLOCK_DIMS) -> list[tuple[int, int]]:
    return [(a, min(a + width, dims)) for a in range(0, dims, width)]


def _units(x):
    """Rows scaled to length one; rows whose squares leave the safe range of a double are scaled by their largest entry first."""
    import numpy as np

    with np.errstate(over="ignore", under="ignore"):
        square = (x * x).sum(axis=1)
        wild = ~((square > 1e-290) & (square < 1e290))
        if wild.any():
            x = x.copy()
            x[wild] /= np.abs(x[wild]).max(axis=1, keepdims=True)
            square[wild] = (x[wild] * x[wild]).sum(axis=1)
    return x / np.sqrt(square)[:, None]


def _turned(unit, matrix):
    """Rotated rows. Not a matrix product: a row gets the same bits whatever rows are beside it."""
    import numpy as np

    out, step = np.empty_like(unit), max(1, (1 << 20) // matrix.size)
    for at in range(0, len(unit), step):
        out[at : at + step] = (unit[at : at + step, None, :] * matrix).sum(axis=2)
    return out


def _matrix(column, width: int):
    """A list column whose rows all have ``width`` numbers, as doubles."""
    import numpy as np

    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, width)


def _place(batches: Iterator, cosine: float, whole: bool) -> Iterator:
    """Per class (node, label, v): a row for each block and cell it enters. ``area`` names dimension and block; bit c of ``low``
    says that the cell is the lowest that the box touches along c. Without ``whole`` only the cells' keys."""
    import numpy as np
    import pyarrow as pa

    budget, turn = 2 - 2 * cosine, {}
    for batch in batches:
        lists = batch.column(2)
        dims = lists.value_lengths().to_numpy(zero_copy_only=False)
        for d in np.unique(dims).tolist():
            mine = np.flatnonzero(dims == d)
            if d not in turn:
                turn[d] = rotation(d)
            turned = _turned(_units(_matrix(lists.take(pa.array(mine)), d)), turn[d])
            for b, (a, z) in enumerate(blocks_of(d)):
                half = (budget * (z - a) / d) ** 0.5 / 2 * (1 + SLACK) + SLACK
                lead = turned[:, a : min(a + CELL_DIMS, z)]
                low = np.floor((lead - half) / (4 * half)).astype(np.int64)
                high = np.floor((lead + half) / (4 * half)).astype(np.int64)
                axes = lead.shape[1]
                coordinates = turned[:, a:z].astype(np.float16)
                for corner in range(1 << axes):  # a box is half a cell wide, so it touches at most two cells along an axis
                    up = np.array([corner >> c & 1 for c in range(axes)])
                    here = low + up
                    rows = np.flatnonzero((here <= high).all(axis=1))
                    cell = np.zeros(len(rows), np.int64)
                    for c in range(axes):
                        cell = (cell << 32) + here[rows, c]
                    at = pa.array(mine[rows])
                    out = {"label": batch.column(1).take(at), "area": pa.array(np.full(len(rows), d << 16 | b)), "cell": pa.array(cell)}
                    if whole:
                        packed = np.ascontiguousarray(coordinates[rows]).tobytes()
                        ends = pa.array(np.arange(len(rows) + 1, dtype=np.int32) * 2 * (z - a))
                        out["node"] = batch.column(0).take(at)
                        out["low"] = pa.array(np.full(len(rows), ~corner & (1 << axes) - 1, np.int32))
                        out["near"] = pa.Array.from_buffers(pa.binary(), len(rows), [None, ends.buffers()[1], pa.py_buffer(packed)])
                    yield pa.RecordBatch.from_pydict(out)


KEYS = ["label", "area", "cell"]
CELLS = "label string, area bigint, cell bigint"
PLACED = CELLS + ", node binary, low int, near binary"
TILE_KEYS = [*KEYS, "i", "j"]


class _Tile:
    """Rows of one cell, or of two parts of a hot one: which pairs are met here, and are near in the block."""

    def __init__(self, area: int, low, part, crossed: bool, near, cosine: float):
        import numpy as np

        self.dims, self.block = area >> 16, area & 0xFFFF
        self.spans = blocks_of(self.dims)
        budget = 2 - 2 * cosine
        self.limits = [budget * (z - a) / self.dims * (1 + SLACK) + SLACK for a, z in self.spans]
        a, z = self.spans[self.block]
        self.full = (1 << min(CELL_DIMS, z - a)) - 1
        self.screen = np.float32((self.limits[self.block] ** 0.5 + SCREEN_SLACK) ** 2 + 1e-5)
        self.near, self.low, self.part, self.crossed = near.astype(np.float32), low.astype(np.uint8), part, crossed
        self.square = (self.near * self.near).sum(axis=1)

    def candidates(self) -> Iterator:
        """(rows, others) of candidate pairs, a chunk of rows at a time; a pair comes once."""
        import numpy as np

        n = len(self.low)
        left = np.flatnonzero(self.part == self.part.min()) if self.crossed else np.arange(n)
        right = np.flatnonzero(self.part != self.part.min()) if self.crossed else left
        if not len(right):
            return
        for at in range(0, len(left), CHUNK):
            rows = left[at : at + CHUNK]
            others = right if self.crossed else right[at:]
            far = self.square[rows, None] + self.square[others] - 2 * (self.near[rows] @ self.near[others].T)
            hit = (far <= self.screen) & ((self.low[rows, None] | self.low[others]) == self.full)
            if not self.crossed:
                hit &= others > rows[:, None]
            x, y = np.nonzero(hit)
            if len(x):
                yield rows[x], others[y]


def _column(table, name: str):
    return table.column(name).to_numpy()


def _screened(batches: Iterator, cosine: float) -> Iterator:
    """The rows of a tile that have some candidate, without their coordinates."""
    import numpy as np
    import pyarrow as pa

    for (_, area, _, i, j), table in key_groups(batches, TILE_KEYS):
        if table.num_rows < 2:
            continue
        near = np.frombuffer(b"".join(table.column("near").to_pylist()), np.float16).reshape(table.num_rows, -1)
        tile = _Tile(area, _column(table, "low"), _column(table, "part"), i != j, near, cosine)
        marked = np.zeros(table.num_rows, bool)
        for x, y in tile.candidates():
            marked[x] = marked[y] = True
        if marked.any():
            kept = table.drop_columns(["near"]).filter(pa.array(marked))
            yield from kept.combine_chunks().to_batches()


SCREENED = CELLS + ", i int, j int, part int, node binary, low int"


def _confirmed(batches: Iterator, cosine: float) -> Iterator:
    """(a, null, n): a gains n links; (a, b, 0): an edge of the spanning forest of a tile's links."""
    import numpy as np
    import pyarrow as pa

    turn: dict = {}
    for (_, area, _, i, j), table in key_groups(batches, TILE_KEYS):
        n, d = table.num_rows, area >> 16
        if d not in turn:
            turn[d] = rotation(d)
        unit = _units(_matrix(table.column("v").combine_chunks(), d))
        turned = _turned(unit, turn[d])
        a, z = blocks_of(d)[area & 0xFFFF]
        tile = _Tile(area, _column(table, "low"), _column(table, "part"), i != j, turned[:, a:z], cosine)
        copies, links, comp, edges = _column(table, "copies"), np.zeros(n, np.int64), np.arange(n), []

        def apart(x, y, b):
            a, z = tile.spans[b]
            return ((turned[x, a:z] - turned[y, a:z]) ** 2).sum(axis=1)

        for rows, others in tile.candidates():
            for at in range(0, len(rows), PAIRS):
                x, y = rows[at : at + PAIRS], others[at : at + PAIRS]
                for keep in (
                    lambda x, y: (unit[x] * unit[y]).sum(axis=1) >= cosine, lambda x, y: apart(x, y, tile.block) <= tile.limits[tile.block],
                    *(lambda x, y, b=b: apart(x, y, b) > tile.limits[b] for b in range(tile.block)),  # else it was found there
                ):
                    x, y = (v[k] for k in [keep(x, y)] for v in (x, y)) if len(x) else (x, y)
                links += np.bincount(x, copies[y], n).astype(np.int64) + np.bincount(y, copies[x], n).astype(np.int64)
                while len(open_ := np.flatnonzero(comp[x] != comp[y])):  # one edge for each component that joins another
                    p, q = comp[x[open_]], comp[y[open_]]
                    high, first = np.unique(np.maximum(p, q), return_index=True)
                    to = np.arange(n)
                    to[high] = np.minimum(p, q)[first]
                    edges.append(np.stack([x[open_[first]], y[open_[first]]]))
                    while (far := to[to]).tolist() != to.tolist():
                        to = far
                    comp = to[comp]
        some = np.flatnonzero(links)
        if len(some):
            ends = np.concatenate(edges, axis=1)
            nodes = table.column("node").combine_chunks()
            left, right = nodes.take(pa.array(np.concatenate([some, ends[0]]))), nodes.take(pa.array(ends[1]))
            count = np.concatenate([links[some], np.zeros(ends.shape[1], np.int64)])
            yield pa.RecordBatch.from_arrays([left, pa.concat_arrays([pa.nulls(len(some), pa.binary()), right]), pa.array(count)], names=["a", "b", "n"])


def _node(label: Column, v: Column) -> Column:
    """128 bits of hash of a label and a vector."""
    word = lambda *c: F.lpad(F.hex(F.xxhash64(*c)), 16, "0")
    return F.unhex(F.concat(word(label, v), word(F.lit("second"), v, label)))


def near_duplicate_vectors(vectors: DataFrame, cosine: float = COSINE, key: str = "vec_id", vector: str = "embedding", label: str = "label") -> DataFrame:
    """vec_id, n_links, component_id, kept."""
    rows = vectors.select(F.col(key).cast("bigint").alias("vec_id"), F.col(vector).alias("v"), F.col(label).cast("string").alias("label"))
    rows = rows.withColumn("v", F.col("v").cast("array<float>" if dict(rows.dtypes)["v"] == "array<float>" else "array<double>"))
    whole = ~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    usable = F.coalesce(F.col("label").isNotNull() & F.col("v").isNotNull() & whole & F.exists("v", lambda x: x != 0), F.lit(False))
    rows = rows.withColumn("node", F.when(usable, _node(F.col("label"), F.col("v"))))  # the hash takes -0.0 and 0.0 as one value
    classes = rows.where(F.col("node").isNotNull()).groupBy("node").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies"), F.first("label").alias("label"), F.first("v").alias("v"))
    classes = written(classes, "vector-classes")

    bare = classes.select("node", "label", "v")
    dims = F.shiftright("area", 16)
    sizes = bare.mapInArrow(lambda it: _place(it, cosine, False), CELLS).groupBy(*KEYS).agg(F.count("*").alias("size"))
    hot = written(sizes.select(*KEYS, F.ceil(F.col("size") * dims / TILE_VALUES).cast("int").alias("parts")).where("parts > 1"), "hot-cells")
    known = F.broadcast(hot) if hot.count() <= BROADCAST_CELLS else hot
    placed = bare.mapInArrow(lambda it: _place(it, cosine, True), PLACED).join(known, KEYS, "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    part = F.pmod(F.xxhash64(F.lit("part"), "node"), F.col("parts").cast("bigint")).cast("int")
    dealt = placed.withColumn("part", part).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    dealt = dealt.select(*KEYS, F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"), "part", "node", "low", "near")
    tiles = dealt.repartition(*TILE_KEYS).sortWithinPartitions(*TILE_KEYS)
    active = written(tiles.mapInArrow(lambda it: _screened(it, cosine), SCREENED), "near-rows")

    full = active.join(classes.select("node", "copies", "v"), "node").repartition(*TILE_KEYS).sortWithinPartitions(*TILE_KEYS)
    found = written(full.mapInArrow(lambda it: _confirmed(it, cosine), "a binary, b binary, n bigint"), "vector-links")
    links = found.where(F.col("b").isNull()).groupBy(F.col("a").alias("node")).agg(F.sum("n").alias("n"))
    roots = components(found.where(F.col("b").isNotNull()).select("a", "b"))
    every = classes.select("node", "rep", "copies").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node")).join(links, "node", "left")
    least = every.groupBy("root").agg(F.min("rep").alias("component_id"))
    every = every.join(least, "root").select("node", (F.coalesce("n", F.lit(0)) + F.col("copies") - 1).alias("n_links"), "component_id")
    every = written(every, "vector-groups")
    drop_written(classes, hot, active, found)
    out = rows.select("vec_id", "node").join(every, "node", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"), F.when(F.col("node").isNull(), F.col("vec_id")).otherwise(F.col("component_id")).alias("component_id"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


#: DuckDB: every pair of equal labels by its cosine, and who is reachable.
ORACLE = """
with recursive u as (select vec_id, label, embedding::double[] v from embeddings where label is not null and embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0),
e as (select a.vec_id x, b.vec_id y from u a join u b on a.label = b.label and len(a.v) = len(b.v) and a.vec_id <> b.vec_id and list_cosine_similarity(a.v, b.v) >= 0.93),
r as (select vec_id x, vec_id y from embeddings union select r.x, e.y from r join e on r.y = e.x),
c as (select x, min(y) component_id from r group by 1), n as (select x, count(*) n from e group by 1)
select vec_id, cast(coalesce(n.n, 0) as bigint) n_links, component_id, vec_id = component_id kept from embeddings left join c on c.x = vec_id left join n on n.x = vec_id
"""
