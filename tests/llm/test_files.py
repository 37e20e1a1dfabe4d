"""Archives and token shards: exact round trips, broken files, edge cases; the pipeline's stages."""

import hashlib
import io
import random
import struct
import zlib

import numpy as np
import pytest

from quorumlab.llm import decontam, minhash, mixing, quality, token_store, warc
from quorumlab.llm.common import fresh_path, table
from quorumlab.llm.queries import tokenizer_file
from tests.llm.helpers import docs

PAGES = "page_id bigint, url string, html string, payload string, digest string"


@pytest.mark.parametrize("broadcast", [0, warc.BROADCAST_BYTES])
def test_archive_round_trip(spark, monkeypatch, broadcast):
    monkeypatch.setattr(warc, "BROADCAST_BYTES", broadcast)
    long, rng = "<p>" + "é" * 60 + "</p>", random.Random(2)
    rows = [(5, "http://a", long), (3, "http://b", long), (9, None, long), (1, "u\r\nX: y", "short"), (2, "v", "short"), (4, "w", None), (6, "x", ""), (7, "y", "z" * 3_000_000), (3, "http://b", long), (None, "n", long)]
    rows += [(100 + k, f"http://p/{k}", "".join(rng.choice("<div>ab ") for _ in range(3000)) if k % 7 else long + "2") for k in range(200)]
    monkeypatch.setattr(warc, "ARCHIVE_BYTES", 40_000)
    pages = spark.createDataFrame([(*r, "x", "x") for r in rows], PAGES)
    manifest = warc.write_archives(pages, fresh_path(spark, "t"))
    got = warc.read_archives(spark, manifest, with_payload=True).collect()
    assert len(manifest) > 1 and len(got) == len(rows) == sum(r["records"] for r in manifest)
    least = {}
    for i, _, html in rows:
        if html and len(html.encode()) >= 100 and i is not None:
            least[html] = min(i, least.get(html, i))
    want = []
    for i, _, html in rows:
        body = (html or "").encode()
        first = least.get(html)
        again = first is not None and i != first
        want.append((i, len(body), hashlib.sha256(body).hexdigest(), "revisit" if again else "response", first if again else None, b"" if again else body))
    assert sorted([(r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"], bytes(r["payload"])) for r in got], key=str) == sorted(want, key=str)
    own = {r["record_id"]: r for r in got}
    assert len(own) == len(got)
    for r in got:  # page 3 is there twice, so that no single record is revisited
        named = own.get(r["target_id"])
        assert (named is None) == (r["refers_to"] in (None, 3)) and (named is None or (named["page_id"], named["payload_digest"], named["record_type"]) == (r["refers_to"], r["payload_digest"], "response"))
    assert sum(r["target_id"] is not None for r in got) > 20
    with warc.open_uri(manifest[0]["path"], "rb") as f:
        kinds = [r["record_type"] for r in warc.read_archive(f)]
    assert kinds[0] == "warcinfo" and "warcinfo" not in kinds[1:] and len(kinds) == manifest[0]["records"] + 1
    assert warc.archive_round_trip(spark.createDataFrame([], PAGES)).count() == 0


def archive(records, dictionary=b""):
    out = io.BytesIO()
    w = warc.ArchiveWriter(out, dictionary)
    for r in records:
        w.add(r)
    return out.getvalue()


def test_broken_archives_are_found():
    body = b"hello" * 30
    record = warc.make_record(1, "http://a", body, len(body), hashlib.sha256(body).hexdigest(), None, "2024-01-01T00:00:00Z")
    good = archive([record, record])
    assert [r["payload"] for r in warc.read_archive(io.BytesIO(good))] == [body, body]
    samples = [bytes(f"<p>sample {k} of the page {k % 7}</p>" * 5, "ascii") for k in range(500)]
    known = warc.train_dictionary(samples)
    assert len(known) > 0 and [r["payload"] for r in warc.read_archive(io.BytesIO(archive([record], known)))] == [body]
    assert warc.train_dictionary([b"x"]) == b""
    read = lambda b: list(warc.read_archive(io.BytesIO(b)))
    for bad in (good[:-5], b"", good[8:], struct.pack("<II", warc.SKIPPABLE_MAGIC, 99), archive([record[:-1]]), archive([record.replace(b"hello", b"hellO", 1)]), archive([b"HTTP/1.1\r\n\r\n\r\n\r\n"]), archive([record.replace(b"WARC-Date: ", b"X: ")])):
        with pytest.raises(warc.ArchiveError):
            read(bad)


def test_records_across_decoder_steps(monkeypatch):
    records = [warc.make_record(k, "u", b"x%d" % k * (k % 50), len(b"x%d" % k * (k % 50)), hashlib.sha256(b"x%d" % k * (k % 50)).hexdigest(), None, "2024-01-01T00:00:00Z") for k in range(300)]
    whole = archive(records)
    for step in (1, 7, 100, 1 << 20):
        monkeypatch.setattr(warc, "STEP", step)
        assert [r["page_id"] for r in warc.read_archive(io.BytesIO(whole))] == list(range(300))


def test_revisit_of_a_foreign_archive():
    record = warc.make_record(1, "http://a", b"", 150, "0" * 64, 7, "2024-01-01T00:00:00Z", target_url="http://b")
    r = warc.parse_record(record)
    assert (r["record_type"], r["payload_bytes"], r["refers_to"], r["target_id"], r["payload"]) == ("revisit", 150, 7, None, b"")
    assert b"WARC-Refers-To-Target-URI: http://b\r\n" in record
    bare = b"HTTP/1.1 200 OK\r\n\r\n"
    headers = [("WARC-Type", "revisit"), ("WARC-Record-ID", "<urn:x>"), ("WARC-Date", "2024-01-01T00:00:00Z"), ("WARC-Profile", warc.REVISIT_PROFILE)]
    assert warc.parse_record(warc._framed(headers, bare))["payload_bytes"] is None


def test_shard_file(tmp_path):
    rng, out = random.Random(5), io.BytesIO()
    w = token_store.ShardWriter(out, 2, block_bytes=600)
    entries = [(None, 0), (-5, 0), *((i, k) for i in sorted(rng.sample(range(10_000), 300)) for k in range(1 + (i % 10 == 0)))]
    want = []
    for i, k in entries:
        ids = [rng.randrange(1 << 16) for _ in range(rng.randint(0, 40))]
        w.add(token_store.make_key(i, k), np.array(ids, "<u2").tobytes())
        want.append((i, ids))
    with pytest.raises(ValueError):
        w.add(token_store.make_key(0), b"")
    w.close()
    r = token_store.ShardReader(io.BytesIO(out.getvalue()))
    assert [(token_store.key_id(k), np.frombuffer(v, "<u2").tolist()) for k, v in r] == want and len(r.index) > 10
    for i in {i for i, _ in want}:
        assert [np.frombuffer(v, "<u2").tolist() for v in r.get(i)] == [ids for j, ids in want if j == i]
    assert all(r.get(i) == [] for i in range(20_000, 20_200))
    for bad in (out.getvalue()[:-1], b"", out.getvalue()[3:]):
        with pytest.raises(ValueError):
            token_store.ShardReader(io.BytesIO(bad))


def test_memo_encoder_equals_the_tokenizer():
    rng, e = random.Random(6), token_store.MemoEncoder(tokenizer_file(), memo=500)
    texts = ["", " ", "a  b", "a\n\nb", "a\n b", "a \nb ", "<|endoftext|> x", "it's we'll", "é è", "tab\tx", "a\x1cb", "᠎b c", "x, y. z!", "Word, word. WORD!?", "a , b", "a.. b), c", ", x", "x_, y", "x.\ny,\nz", "a\x01 b, c", "1, 2.\n3", "e\u0301, f"]
    texts += ["".join(rng.choice(["ab", "Cd", " ", " ", "\n", ",", ".", "1", "é", "'s", "日"]) for _ in range(rng.randint(0, 40))) for _ in range(3000)]
    for at in range(0, len(texts), 500):
        part = texts[at : at + 500]
        assert [np.frombuffer(b, e.kind).tolist() for b in e.encode(part)] == e._ids(part)


def test_memo_encoder_looks_up_distinct_pieces_only(monkeypatch):
    """A group's texts are cut by Arrow; only its distinct pieces are looked up, and pieces with other white space send their texts alone to the tokenizer."""
    e, seen, whole = token_store.MemoEncoder(tokenizer_file()), [], []
    texts = ["one two, two two\nthree", "x one two", "two\ttwo one", " two", "two ", "one", "one  two"]
    want = e._ids(texts)
    monkeypatch.setattr(e, "_look_up", lambda pieces, look=e._look_up: seen.append(pieces) or look(pieces))
    monkeypatch.setattr(e, "_ids", lambda texts, ids=e._ids: whole.extend(texts) or ids(texts))
    assert [np.frombuffer(b, e.kind).tolist() for b in e.encode(texts)] == want
    assert len(seen) == 1 and len(set(seen[0])) == len(seen[0])
    assert {t for t in whole if " " in t[1:] or "\t" in t} == {"two\ttwo one", "two ", "one  two"}


def test_token_shards(spark, small):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_file())
    texts = [(r["doc_id"], r["text"]) for r in table(spark, small, "documents").limit(80).collect()]
    texts += [(1000, None), (1001, ""), (1002, "long word " * 30_000), (3, "again"), (None, "no id"), (-7, "negative")]
    manifest = token_store.write_shards(docs(spark, texts), tokenizer_file(), fresh_path(spark, "t"), shards=5)
    rows = token_store.read_shards(spark, manifest).collect()
    ordered = sorted(rows, key=lambda r: r["start"])
    assert [r["doc_id"] is not None and r["doc_id"] for r in ordered] == sorted((i for i, _ in texts), key=lambda i: (i is not None, i)) or ordered[0]["doc_id"] is None
    ids = {}
    for i, text in texts:
        ids.setdefault(i, []).append(t.encode(text or "", add_special_tokens=False).ids + [2])
    at = 0
    for r in ordered:
        mine = [x for x in ids[r["doc_id"]] if zlib.crc32(np.array(x, "<u4").tobytes()) == r["ids_crc32"]]
        assert mine and r["n_tokens"] == len(mine[0]) and r["start"] == at
        at += len(mine[0])
    for i in (3, 1000, None, -7):
        assert sorted(token_store.lookup(manifest, i)) == sorted(ids[i])
    assert token_store.lookup(manifest, 55_555) == []
    assert token_store.tokenize_to_shards(docs(spark, []), tokenizer_file()).count() == 0


def test_pipeline_stages(spark, small):
    import corpus_pipeline as p

    d = table(spark, small, "documents")
    stages = dict(p.STAGES)
    assert list(stages) == ["quality", "near-duplicates", "decontamination", "mixing", "tokens"]
    ids = lambda df: sorted(r["doc_id"] for r in df.select("doc_id").collect())
    a = stages["quality"](spark, d, small)
    assert a.columns == d.columns and ids(a) == ids(quality.classify(d, table(spark, small, "labels")).where("predicted = 1"))
    b = stages["near-duplicates"](spark, d, small)
    assert b.columns == d.columns and ids(b) == ids(minhash.near_duplicates(d).where("kept"))
    c = stages["decontamination"](spark, d, small)
    assert c.columns == d.columns and ids(c) == ids(decontam.decontamination_report(d, table(spark, small, "benchmark")).where("not contaminated"))
    m = stages["mixing"](spark, d, small)
    assert m.columns == d.columns and m.count() == sum(r["copies"] for r in mixing.mixing_report(d, table(spark, small, "labels"), p.TARGETS).collect())
    t = stages["tokens"](spark, m, small)
    assert ids(t) == ids(m)
    empty = d.limit(0)
    for _, stage in p.STAGES:
        assert stage(spark, empty, small).count() == 0
    out = p.run(spark, small)
    assert 0 < out.count() <= 1.5 * d.count() and set(out.columns) == {"doc_id", "start", "n_tokens", "ids_crc32"}


def test_pipeline_stages_against_brute_force(spark, small):
    """Each stage by other means: rules applied in Python, all pairs of shingles, all windows, rates from posteriors, the tokenizer."""
    from tokenizers import Tokenizer

    import corpus_pipeline as p
    from tests.llm.helpers import groups, shingles
    from tests.llm.test_text_operators import windows_brute

    d, labels = table(spark, small, "documents"), table(spark, small, "labels")
    texts = {r["doc_id"]: r["text"] for r in d.collect()}
    stages = dict(p.STAGES)
    ids = lambda name: sorted(r["doc_id"] for r in stages[name](spark, d, small).select("doc_id").collect())

    model = quality.train(quality.measure(d), labels)

    def good(text):
        v = quality.statistics((text or "").encode())
        holds = lambda rule: all((v[f] > cut) == above for f, above, cut in rule)
        return model.intercept + sum(w for w, rule in model.rules if holds(rule)) >= 0

    assert ids("quality") == sorted(i for i, t in texts.items() if good(t))
    sets = {i: shingles(t) for i, t in texts.items()}
    roots = groups(sorted(sets), lambda a, b: 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]) > 0)
    assert ids("near-duplicates") == sorted(i for i, r in roots.items() if i == r)
    items = [(r["item_id"], r["text"]) for r in table(spark, small, "benchmark").collect()]
    assert ids("decontamination") == sorted(r[0] for r in windows_brute(list(texts.items()), items) if not r[5])
    mixture, members = mixing.fit_mixture(d, labels.select("doc_id", mixing.label_domain().alias("domain")), p.TARGETS)
    copies = {}
    for i in ids("mixing"):
        copies[i] = copies.get(i, 0) + 1
    for r in members.collect():
        rate = 1.0
        for step in mixture.steps:
            rate = max(0.0, rate - sum(r[f"p{j}"] * g for j, g in enumerate(step)))
        assert copies.get(r["doc_id"], 0) - rate == pytest.approx(0, abs=1)
    t, at = Tokenizer.from_file(tokenizer_file()), 0
    for r in stages["tokens"](spark, d, small).orderBy("start").collect():
        mine = [*t.encode(texts[r["doc_id"]] or "", add_special_tokens=False).ids, 2]
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (at, len(mine), zlib.crc32(np.array(mine, "<u4").tobytes()))
        at += len(mine)
    assert at == sum(r["n_tokens"] for r in stages["tokens"](spark, d, small).collect())
