"""Near-duplicates of texts and vectors, components, sharding."""

import math
import random
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from quorumlab.llm import components, embeddings, minhash, sharding
from quorumlab.llm.common import table
from tests.llm.helpers import docs, groups, shingles


def check_texts(spark, texts):
    got = minhash.near_duplicates(docs(spark, texts)).collect()
    sets = {i: shingles(t) for i, t in texts if i is not None}
    linked = lambda a, b: bool(sets[a] and sets[b]) and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])
    want = groups(sorted(sets), linked)
    assert len(got) == len(texts)
    for r in got:
        if r["doc_id"] is not None:
            assert (r["n_shingles"], r["component_id"], r["kept"]) == (len(sets[r["doc_id"]]), want[r["doc_id"]], want[r["doc_id"]] == r["doc_id"]), r


def test_near_duplicates_against_brute_force(spark, monkeypatch):
    rng = random.Random(11)
    vocabulary = [f"w{k}" for k in range(400)]
    base = [[rng.choice(vocabulary) for _ in range(n)] for n in (60, 120, 30)]
    texts = []
    for b in base:  # near copies at every distance, around the threshold too
        for _ in range(45):
            w = list(b)
            for _ in range(rng.randint(0, 5)):
                w[rng.randrange(len(w))] = rng.choice(vocabulary)
            texts.append(" ".join(w).replace("w1", "W1"))
    texts += [None, "", "  \n", "a", "A", "a b c d", "a b c d e", "a\tb c  d e", "É b c d e", "é b c d e", "word " * 20_000]
    rng.shuffle(texts)
    check_texts(spark, [*enumerate(texts), (5, texts[5])])
    monkeypatch.setattr(minhash, "TILE", 16)  # hot buckets in many tiles
    monkeypatch.setattr(minhash, "BROADCAST_ROWS", 0)
    monkeypatch.setattr(minhash, "SET_VALUES", 200)  # a few texts on either side of a tile of full sets
    check_texts(spark, list(enumerate(texts)))


def test_near_duplicates_of_nothing(spark):
    assert minhash.near_duplicates(docs(spark, [])).count() == 0
    one = minhash.near_duplicates(docs(spark, [(7, "a lone text of six words"), (None, "a lone text of six words"), (None, None)])).collect()
    assert sorted((r["doc_id"] or -1, r["component_id"] or -1, r["kept"]) for r in one) == [(-1, -1, True), (-1, 7, False), (7, 7, True)]


def test_near_copies_without_an_id(spark):
    words = [f"w{k}" for k in range(60)]
    near = " ".join([*words[:-1], "other"])
    rows = minhash.near_duplicates(docs(spark, [(9, " ".join(words)), (None, near), (None, "x y z " + near), (3, "nothing like it")])).collect()
    assert sorted((r["doc_id"] or -1, r["component_id"], r["kept"]) for r in rows) == [(-1, 9, False), (-1, 9, False), (3, 3, True), (9, 9, True)]


def test_sketch_limit_keeps_pairs_at_the_threshold():
    const, limit, rng = minhash._constants(), minhash.sketch_limit(), np.random.default_rng(0)
    for _ in range(60):
        u = np.unique(rng.integers(0, 1 << 63, 700, dtype=np.uint64))
        a, b = u[:600], np.concatenate([u[:514], u[600:686]])  # 514 of 686: just under three quarters
        x, y = (minhash.signature(np.sort(v), const)[1].view(np.uint64) for v in (a, b))
        assert np.bitwise_count(x ^ y).sum() <= limit
    far = minhash.signature(np.unique(rng.integers(0, 1 << 63, 600, dtype=np.uint64)), const)[1].view(np.uint64)
    assert np.bitwise_count(x ^ far).sum() > limit


@pytest.mark.parametrize("shape", ["path", "star", "random", "none"])
def test_components(spark, shape):
    n, rng = 60, random.Random(1)
    edges = {"path": [(k, k + 1) for k in range(n)], "star": [(40, k) for k in range(n)], "random": [(rng.randrange(90), rng.randrange(90)) for _ in range(60)], "none": []}[shape]
    nodes = sorted({x for a, b in edges for x in (a, b) if a != b})
    want = groups(nodes, lambda a, b: (a, b) in edges or (b, a) in edges)
    rows = components.components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()
    got = {r["node"]: r["root"] for r in rows}
    assert len(rows) == len(got) == len(nodes)
    assert all((got[a] == got[b]) == (want[a] == want[b]) for a in nodes for b in nodes)


VECTORS = "vec_id bigint, embedding array<float>, label int, node string, cell string, digest string, v string"


def check_vectors(spark, rows):
    df = spark.createDataFrame([(*r, "x", "x", "x", "x") for r in rows], VECTORS)
    got = {r["vec_id"]: r for r in embeddings.near_duplicate_vectors(df).collect()}
    unit = {}
    for i, v, label in rows:
        a = None if v is None or label is None or any(x is None for x in v) else np.array(v, np.float32).astype(float)
        if a is not None and np.isfinite(a).all() and (a != 0).any():
            unit[i] = (label, a / np.linalg.norm(a))
    linked = lambda a, b: a in unit and b in unit and unit[a][0] == unit[b][0] and len(unit[a][1]) == len(unit[b][1]) and unit[a][1] @ unit[b][1] >= 0.93
    ids = sorted(r[0] for r in rows)
    want = groups(ids, linked)
    for i in ids:
        assert got[i]["n_links"] == sum(linked(i, j) for j in ids if j != i), i
        assert got[i]["component_id"] == want[i] and got[i]["kept"] == (want[i] == i)


def test_vectors_against_brute_force(spark, monkeypatch):
    rng = np.random.default_rng(3)
    rows, centres = [], rng.standard_normal((6, 64))
    for k in range(240):  # clusters whose members lie on both sides of the threshold
        c = centres[k % 6]
        rows.append((k, (c + rng.standard_normal(64) * rng.choice([0.0, 0.1, 0.25, 0.3])).tolist(), k % 3))
    rows += [(300, None, 1), (301, [0.0] * 64, 1), (302, [math.nan] * 64, 1), (303, [None] * 64, 1), (304, [math.inf] * 64, 1), (305, rows[0][1], None), (306, [2 * x for x in rows[0][1]], 0)]
    rows += [(307, [1.0, 0.0], 0), (308, [1.0, -0.0], 0), (309, [1e-30, 0.0], 0), (310, [1.0], 0), (311, [-0.0] * 64, 0), (312, [], 0)]
    check_vectors(spark, rows)
    monkeypatch.setattr(embeddings, "TILE_VALUES", 8 * 64)
    monkeypatch.setattr(embeddings, "BROADCAST_CELLS", 0)
    monkeypatch.setattr(embeddings, "CHUNK", 3)
    monkeypatch.setattr(embeddings, "PAIRS", 5)
    check_vectors(spark, rows)


def test_vectors_of_nothing(spark):
    assert embeddings.near_duplicate_vectors(spark.createDataFrame([], VECTORS)).count() == 0


def place_brute(doc_id, shards):
    """The tree descent in plain Python."""
    tree = sharding.Topology.of(shards).tree

    def draw(name, w):
        body = str(doc_id).encode() if doc_id is not None else b"null key"
        seed = xxhash.xxh64_intdigest(name.encode(), xxhash.xxh64_intdigest(body, 42))
        return -math.log(((seed >> 11) + 0.5) / (1 << 53)) / w

    weigh = lambda x: x[1] if isinstance(x[0], int) else sum(map(weigh, x))
    r = min(range(len(tree)), key=lambda k: draw(f"region{k}", weigh(tree[k])))
    k = min(range(len(tree[r])), key=lambda j: draw(f"region{r}/rack{j}", weigh(tree[r][j])))
    return min(tree[r][k], key=lambda s: draw(f"shard{s[0]}", s[1]))[0]


def test_sharding_against_brute_force(spark):
    texts = [(i, f"text {i} é") for i in range(400)] + [(5, "text 5 é"), (401, None), (402, ""), (None, "x"), (403, "y" * 100_000)]
    rows = sharding.shard_documents(docs(spark, texts)).collect()
    assert len(rows) == len(texts)
    for r in rows:
        text = next(t for i, t in texts if i == r["doc_id"]) or ""
        assert (r["size"], r["text_crc32"]) == (len(text.encode()) + 1, zlib.crc32(text.encode()))
        assert r["shard"] == place_brute(r["doc_id"], 8) and r["grown_shard"] == place_brute(r["doc_id"], 9) and r["grown_shard"] in (r["shard"], 8)
    for s in range(8):
        slots = sorted(r["slot"] for r in rows if r["shard"] == s)
        assert slots == list(range(len(slots))) and 25 < len(slots) < 80
    chunked = sharding.slots(spark.range(500).withColumn("s", F.lit(0)), "s", ["id"], rows_per_chunk=50)
    assert sorted(r["slot"] for r in chunked.collect()) == list(range(500))
    assert sharding.shard_documents(docs(spark, [])).count() == 0


def test_weight_changes_move_rows_only_with_their_subtree(spark):
    keys = spark.range(3000)
    before = sharding.Topology((((((0, 1.0), (1, 1.0))), ((2, 1.0),)), (((3, 1.0),), ((4, 1.0),))))
    after = sharding.Topology((((((0, 1.0), (1, 3.0))), ((2, 1.0),)), (((3, 1.0),), ((4, 1.0),))))
    rows = keys.select(sharding.locate(F.col("id"), before).alias("a"), sharding.locate(F.col("id"), after).alias("b")).collect()
    moved = [(r["a"], r["b"]) for r in rows if r["a"]["shard"] != r["b"]["shard"]]
    assert moved and all(b["region"] == 0 for _, b in moved) and not any(a["shard"] == 3 and b["shard"] == 4 for a, b in moved)


def test_contract_on_the_small_table(spark, small):
    d = table(spark, small, "documents")
    rows = minhash.near_duplicates(d).collect()
    texts = {r["doc_id"]: r["text"] for r in d.collect()}
    sets = {i: shingles(t) for i, t in texts.items()}
    want = groups(sorted(sets), lambda a, b: 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]))
    assert {r["doc_id"]: r["component_id"] for r in rows} == want
