"""Near-duplicate documents: MinHash bands propose, odd sketches screen, full shingle sets confirm.

A document's set holds the hashes of its distinct runs of five words; a document with fewer words, but
some, has its whole word sequence as the only member; a document without words (or with a null text) has
the empty set and links with nothing. Two documents are linked if 100 |A & B| >= 75 |A | B|.

* Documents with equal sets become one class at once (grouped minimum), so copies cost nothing later.
* 256 MinHash samples of a class give 32 bands of 4 rows (a pair at similarity 0.75 shares no band with
  probability (1 - 0.75^4)^32 = 5e-6) and an odd sketch: 1024 parity bits, one flipped for each sample.
  The number of bits in which two sketches differ estimates the similarity; a pair goes on only
  if it could be at 0.75 within five standard deviations.
* Buckets never expand into all their pairs. First each bucket compares its members with one pivot, the
  member that shares most with others; members linked to it are merged, and the pivot is done with. Buckets
  that still hold several components are searched in tiles of bounded size: a tile screens by sketch, fetches the
  full sets of the rows that have candidates, and gives a spanning forest of the confirmed links across components.
  Every link is confirmed on full sets, and a tile emits no more rows than it holds.

Defined cases: repeated rows fall in one class, and each input row has its result row; rows with a null id are
compared like all others and belong to the group of those they are linked with (a group without any id has a null component, and
all of it is kept, as nothing tells its rows apart); an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import drop_written, key_groups, written
from .components import components

SHINGLE = 5
BANDS, ROWS = 32, 4
SAMPLES, BITS = 256, 1024
SIGMAS = 5.0
#: Rows of a bucket on either side of a tile of sketches, and shingles on either side of a tile of full sets (or one text's).
TILE, SET_VALUES = 2048, 4 << 20
#: Rows of candidates up to which their ids are broadcast to fetch texts; beyond, the join shuffles.
BROADCAST_ROWS = 2_000_000

SIGNED = "doc_id bigint, n_shingles bigint, node binary, bands array<bigint>, sketch array<bigint>"


def sketch_limit(percent: int = 75) -> int:
    """Most differing bits of a pair at the threshold, plus ``SIGMAS`` standard deviations."""
    far = SAMPLES * (1 - percent / 100)
    decay = math.exp(-4 * far / BITS)
    mean = BITS / 2 * (1 - decay)
    sampling = 2 * decay * math.sqrt(SAMPLES * percent / 100 * (1 - percent / 100))
    parity = math.sqrt(BITS / 4 * (1 - decay**2))
    return math.ceil(mean + SIGMAS * math.hypot(sampling, parity))


def shingle_hashes(body: bytes, size: int = SHINGLE):
    """Sorted distinct 64-bit hashes of the word runs of a text given as UTF-8."""
    import numpy as np
    from xxhash import xxh3_64_intdigest

    words = body.lower().split()  # bytes: lowers A-Z only, splits at ASCII white space only
    h = np.fromiter(map(xxh3_64_intdigest, words), np.uint64, len(words))
    n = len(h)
    if not n:
        return h
    run = min(n, size)
    mult = (np.arange(1, run + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
    g = np.full(n - run + 1, np.uint64(run), np.uint64)
    for k in range(run):
        g ^= h[k : n - run + 1 + k]
        g *= mult[k]
        g ^= g >> np.uint64(29)
    return np.unique(g)


def _constants():
    import numpy as np

    rng = np.random.Generator(np.random.PCG64(20_240_501))
    odd = lambda n, bits, kind: rng.integers(0, 1 << bits, n, dtype=kind) | kind(1)
    return {
        "mul": odd(SAMPLES, 32, np.uint32)[:, None], "xor": rng.integers(0, 1 << 32, SAMPLES, dtype=np.uint32)[:, None],
        "row": odd(ROWS, 63, np.uint64), "band": rng.integers(0, 1 << 63, BANDS, dtype=np.uint64), "bit": odd(SAMPLES, 32, np.uint32), "add": rng.integers(0, 1 << 32, SAMPLES, dtype=np.uint32),
    }


def signature(hashes, const) -> tuple:
    """(band hashes, sketch words) of a non-empty set."""
    import numpy as np

    x = (hashes >> np.uint64(32)).astype(np.uint32)
    low = np.full(SAMPLES, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(x), 4096):  # bounded memory for long texts
        y = x[at : at + 4096] ^ const["xor"]
        y *= const["mul"]
        y ^= y >> np.uint32(15)
        y *= np.uint32(0x2C1B3C6D)
        np.minimum(low, y.min(axis=1), out=low)
    bands = (low[: BANDS * ROWS].astype(np.uint64).reshape(BANDS, ROWS) * const["row"]).sum(axis=1, dtype=np.uint64) ^ const["band"]
    bands ^= bands >> np.uint64(31)
    bands *= np.uint64(0x94D049BB133111EB)
    bands ^= bands >> np.uint64(29)
    bit = ((low ^ const["add"]) * const["bit"]) >> np.uint32(22)
    parity = np.bincount(bit, minlength=BITS).astype(np.uint8) & 1
    return bands.view(np.int64), np.packbits(parity).view(np.int64)


def _sign(batches: Iterator) -> Iterator:
    import numpy as np
    import pyarrow as pa
    from xxhash import xxh3_128_digest

    const = _constants()
    for batch in batches:
        bodies = batch.column(1)
        count, nodes, bands, sketches, sizes = [], [], [], [], []
        for k in range(batch.num_rows):
            u = shingle_hashes(bodies[k].as_py() or b"")
            count.append(len(u))
            sizes.append(int(len(u) > 0))
            nodes.append(xxh3_128_digest(u.tobytes()) if len(u) else None)
            if len(u):
                x, y = signature(u, const)
                bands.append(x)
                sketches.append(y)
        full = np.array([0, *sizes], np.int32).cumsum()
        lists = lambda rows, width: pa.ListArray.from_arrays(pa.array(full * width, pa.int32()), pa.array(np.concatenate(rows) if rows else np.empty(0, np.int64), pa.int64()))
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(count, pa.int64()), pa.array(nodes, pa.binary()), lists(bands, BANDS), lists(sketches, BITS // 64)],
            names=["doc_id", "n_shingles", "node", "bands", "sketch"],
        )


def _sets(batches: Iterator) -> Iterator:
    import numpy as np
    import pyarrow as pa
    from xxhash import xxh3_128_digest

    for batch in batches:
        bodies, nodes, sets, ends = batch.column(0), [], [], [0]
        for k in range(batch.num_rows):
            u = shingle_hashes(bodies[k].as_py() or b"")
            nodes.append(xxh3_128_digest(u.tobytes()))
            sets.append(u.view(np.int64))
            ends.append(ends[-1] + len(u))
        values = pa.array(np.concatenate(sets) if sets else np.empty(0, np.int64), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.binary()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), values)], names=["node", "members"])


def sign(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    body = docs.select(F.col(key).cast("bigint").alias("doc_id"), F.col(text).cast("binary").alias("body"))
    return body.mapInArrow(_sign, SIGNED)


def _differing(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: F.bit_count(a.bitwiseXOR(b))), F.lit(0), lambda s, v: s + v)


def _with_component(members: DataFrame, merged: DataFrame) -> DataFrame:
    return members.join(merged, "node", "left").withColumn("root", F.coalesce("root", "node"))


def _several(members: DataFrame) -> DataFrame:
    """Members of buckets that still hold more than one component."""
    open_ = members.groupBy("bucket").agg(F.min("root").alias("_x"), F.max("root").alias("_y"), F.count("*").alias("size")).where("_x != _y").select("bucket", "size")
    return members.join(open_, "bucket")


def _comparable(percent: int) -> Column:
    return 100 * F.least("n", "m") >= percent * F.greatest("n", "m")


def _ordered(x: str, y: str) -> list[Column]:
    return [F.least(x, y).alias("a"), F.greatest(x, y).alias("b")]


def _tiles(members: DataFrame) -> DataFrame:
    """Deal the members of a bucket to tiles (i, j), i <= j, of at most about TILE rows a side."""
    parts = F.ceil(F.col("size") / TILE).cast("int")
    part = F.pmod(F.xxhash64(F.lit("tile"), "node"), parts.cast("bigint")).cast("int")
    dealt = members.withColumn("part", part).withColumn("other", F.explode(F.sequence(F.lit(0), parts - 1)))
    return dealt.select("bucket", F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"), "part", "node", "root", "n", "sketch")


class _Tile:
    """The rows of a tile, and which later rows a row may link with across components. ``sub`` cuts a tile by the bytes of its sets;
    a crossed one looks only at pairs from different sides."""

    def __init__(self, table, limit: int, percent: int, sides: list):
        import numpy as np

        self.np, self.limit, self.percent, self.sides = np, limit, percent, sides
        self.sketch = table.column("sketch").combine_chunks().flatten().to_numpy().view(np.uint64).reshape(table.num_rows, -1)
        self.n = table.column("n").to_numpy()
        self.root = table.column("root").combine_chunks().dictionary_encode().indices.to_numpy()

    def candidates(self, k: int):
        np = self.np
        o = np.arange(k + 1, len(self.n))
        o = o[self.root[o] != self.root[k]]
        for side in self.sides:
            o = o[side[o] != side[k]]
        o = o[100 * np.minimum(self.n[o], self.n[k]) >= self.percent * np.maximum(self.n[o], self.n[k])]
        return o[np.bitwise_count(self.sketch[o] ^ self.sketch[k]).sum(axis=1) <= self.limit] if len(o) else o


TILE_KEYS = ["bucket", "i", "j"]
ACTIVE = "bucket bigint, i int, j int, part int, node binary, root binary, n bigint, sketch array<bigint>, p int, q int, sub int"


def _active(batches: Iterator, limit: int, percent: int) -> Iterator:
    """The rows of a tile that have some candidate by size and sketch, dealt to sub-tiles (p, q), p <= q, whose full sets have at
    most about ``SET_VALUES`` members on either side. A row goes where it has a candidate."""
    import numpy as np
    import pyarrow as pa

    for (_, i, j), table in key_groups(batches, TILE_KEYS):
        tile = _Tile(table, limit, percent, [table.column("part").to_numpy()] if i != j else [])
        sub = (tile.n.cumsum() - tile.n) // SET_VALUES
        met = np.zeros((len(sub), int(sub[-1]) + 1), bool)
        for k in range(len(sub) - 1):
            if len(o := tile.candidates(k)):
                met[k, sub[o]] = met[o, sub[k]] = True
        row, other = np.nonzero(met)
        if len(row):
            out = table.take(pa.array(row))
            for name, v in (("p", np.minimum(sub[row], other)), ("q", np.maximum(sub[row], other)), ("sub", sub[row])):
                out = out.append_column(name, pa.array(v.astype(np.int32)))
            yield from out.combine_chunks().to_batches()


def _confirmed(batches: Iterator, limit: int, percent: int) -> Iterator:
    for (_, i, j, p, q), table in key_groups(batches, [*TILE_KEYS, "p", "q"]):
        sides = [table.column(c).to_numpy() for c, crossed in (("part", i != j), ("sub", p != q)) if crossed]
        if (out := _confirm(table, _Tile(table, limit, percent, sides))) is not None:
            yield out


def _confirm(table, tile: _Tile):
    """Links of a tile confirmed on full sets, as a spanning forest over components: a pair already connected isn't tested again."""
    import numpy as np
    import pyarrow as pa

    rows, percent = table.column("node").to_pylist(), tile.percent
    every = table.column("members").combine_chunks().flatten().to_numpy()
    members = np.split(every, tile.n.cumsum()[:-1])
    owner = np.repeat(np.arange(len(rows), dtype=np.int32), tile.n)
    order = np.argsort(every, kind="stable")
    every, owner = every[order], owner[order]
    del order
    up = list(range(int(tile.root.max()) + 1))

    def top(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    left, right = [], []
    for k in range(len(rows) - 1):
        o = tile.candidates(k)
        mine = top(tile.root[k])
        o = [x for x in o.tolist() if top(tile.root[x]) != mine]
        if not o:
            continue
        first, last = np.searchsorted(every, members[k], "left"), np.searchsorted(every, members[k], "right")
        size = last - first
        at = np.repeat(first - np.concatenate([[0], size[:-1].cumsum()]), size) + np.arange(size.sum())
        common = np.bincount(owner[at], minlength=len(rows))  # of row k with every row of the tile
        for x in o:
            if 100 * common[x] >= percent * (tile.n[k] + tile.n[x] - common[x]) and (there := top(tile.root[x])) != (mine := top(tile.root[k])):
                up[there] = mine
                left.append(rows[k])
                right.append(rows[x])
    return pa.RecordBatch.from_arrays([pa.array(left, pa.binary()), pa.array(right, pa.binary())], names=["a", "b"]) if left else None


def _full_sets(docs: DataFrame, classes: DataFrame, shared: DataFrame, key: str, text: str) -> DataFrame:
    """(node, members) of the classes that share a bucket, from the texts of their representatives."""
    reps = written(classes.join(shared.select("node").distinct(), "node", "left_semi").select(F.col("rep").alias("_rep")).distinct(), "reps")
    few = reps.count() <= BROADCAST_ROWS
    bodies = docs.select(F.col(key).cast("bigint").alias("_id"), F.col(text).cast("binary").alias("body"))
    wanted = bodies.join(F.broadcast(reps) if few else reps, F.col("_id").eqNullSafe(F.col("_rep")), "left_semi")
    sets = wanted.select("body").mapInArrow(_sets, "node binary, members array<bigint>")
    sets = written(sets.dropDuplicates(["node"]), "sets")
    drop_written(reps)
    return sets


def _links(classes: DataFrame, shared: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Confirmed links whose components are those of all links; not every link is listed."""
    limit = sketch_limit(percent)
    weight = shared.groupBy("node").agg(F.sum("size").alias("weight"))
    weighed = written(shared.join(weight, "node").select("bucket", "node", "n", "weight"), "weighed")
    pivot = weighed.groupBy("bucket").agg(F.max(F.struct("weight", "node", "n")).alias("p")).select("bucket", F.col("p.node").alias("pivot"), F.col("p.n").alias("m"))
    tried = written(weighed.join(pivot, "bucket").where(F.col("node") != F.col("pivot")).select("bucket", "node", "n", "pivot", "m"), "tried")
    pairs = tried.where(_comparable(percent)).select(*_ordered("node", "pivot")).distinct()
    sketch = lambda c: classes.select(F.col("node").alias(c), F.col("sketch").alias(f"sketch_{c}"))
    near = pairs.join(sketch("a"), "a").join(sketch("b"), "b").where(_differing(F.col("sketch_a"), F.col("sketch_b")) <= limit).select("a", "b")
    members = lambda c: sets.select(F.col("node").alias(c), F.col("members").alias(f"of_{c}"))
    both = near.join(members("a"), "a").join(members("b"), "b").withColumn("_i", F.size(F.array_intersect("of_a", "of_b")))
    union = F.size("of_a") + F.size("of_b") - F.col("_i")
    links = written(both.where(100 * F.col("_i") >= percent * union).select("a", "b"), "links")
    # The pivots are done with. What is left to find are links between other members of different components.
    rest = _several(_with_component(tried.select("bucket", "node", "n"), components(links))).join(classes.select("node", "sketch"), "node")
    tiles = _tiles(rest).repartition(*TILE_KEYS).sortWithinPartitions(*TILE_KEYS)
    active = written(tiles.mapInArrow(lambda it: _active(it, limit, percent), ACTIVE), "active")
    drop_written(weighed, tried)
    if active.isEmpty():
        drop_written(active)
        return links
    cut = [*TILE_KEYS, "p", "q"]
    full = active.join(sets, "node").repartition(*cut).sortWithinPartitions(*cut)
    more = written(full.mapInArrow(lambda it: _confirmed(it, limit, percent), "a binary, b binary"), "more-links")
    drop_written(active)
    return links.unionByName(more)


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", percent: int = 75) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable by links), kept (doc_id = component_id)."""
    signed = written(sign(docs, key, text), "signed")
    full = signed.where(F.col("node").isNotNull())
    classes = full.groupBy("node").agg(
        F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n"), F.first("bands").alias("bands"), F.first("sketch").alias("sketch")
    )
    classes = written(classes, "classes")
    members = classes.select("node", "n", F.explode("bands").alias("bucket"))
    crowded = members.groupBy("bucket").agg(F.count("*").alias("size")).where("size > 1")
    shared = written(members.join(crowded, "bucket").select("bucket", "node", "n", "size"), "shared")
    small = classes.select("node", F.col("rep").alias("component_id"))
    if not shared.isEmpty():
        sets = _full_sets(docs, classes, shared, key, text)
        merged = components(_links(classes, shared, sets, percent))
        drop_written(sets, shared)
        both = _with_component(classes.select("node", "rep"), merged)
        small = both.join(both.groupBy("root").agg(F.min("rep").alias("component_id")), "root").select("node", "component_id")
    out = signed.select("doc_id", "n_shingles", "node").join(small, "node", "left").withColumn("component_id", F.coalesce("component_id", "doc_id"))
    return out.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


#: DuckDB: every shingle, every pair that shares one, and who is reachable.
ORACLE = r"""
with recursive d as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') w from documents),
s as (select distinct doc_id, unnest(case when len(w) < 5 then [array_to_string(w, ' ')] else list_transform(range(len(w) - 4), lambda i: array_to_string(w[i + 1:i + 5], ' ')) end) x from d where len(w) > 0),
n as (select doc_id, count(*) n from s group by 1),
i as (select a.doc_id x, b.doc_id y, count(*) c from s a join s b on a.x = b.x and a.doc_id <> b.doc_id group by 1, 2),
e as (select i.x, i.y from i join n p on p.doc_id = i.x join n q on q.doc_id = i.y where 100 * c >= 75 * (p.n + q.n - c)),
r as (select doc_id x, doc_id y from documents union select r.x, e.y from r join e on r.y = e.x),
m as (select x, min(y) component_id from r group by 1)
select doc_id, coalesce(n.n, 0) n_shingles, component_id, doc_id = component_id kept from documents join m on m.x = doc_id left join n using (doc_id)
"""
