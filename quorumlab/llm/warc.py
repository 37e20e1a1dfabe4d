"""WARC archives with one Zstandard frame for each record and the dictionary in a leading skippable frame.

Writing: the digest of every payload is computed in the scan; among equal payloads of at least
``least`` bytes the record with the smallest page id becomes ``response``, the others ``revisit`` it without
carrying the payload; shorter payloads are always ``response``. Only digests and ids are grouped. What is known of
repeated digests is broadcast up to ``BROADCAST_BYTES``, so that payloads aren't shuffled; beyond, they are joined by shuffle. Each task then
writes archives of about ``ARCHIVE_BYTES``: it trains a dictionary on its first payloads, writes it in a skippable
frame and compresses each record into a frame of its own, a ``warcinfo`` record first. The manifest (a row for each
archive) commits them. A record's id comes from its archive and place, so repeated rows differ; a response that others
revisit has one made from its page id and digest, which their ``WARC-Refers-To`` names. Two headers
are the operator's own: ``X-Page-Id`` and ``X-Refers-To-Page-Id``, as a page's id need not show in its address.

Reading: the skippable frame gives the dictionary, each further frame gives a record, decoded one at a time with
bounded memory. Version line, mandatory headers, lengths, block and payload digests are verified; a
broken archive raises ``ArchiveError`` with the place.

Defined cases: a null html is an empty payload; a null page_id stays null and never is the target of a
revisit; repeated page ids with equal payloads are all responses if theirs is the smallest id, and as no
single one of them is meant, their revisits name address and date, not a record; a revisit in a
foreign archive may leave the payload's length out (null);
an empty table writes no archive and gives no rows.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import drop_written, fresh_path, written
from .token_store import open_uri

#: Fixed values of the formats.
SKIPPABLE_MAGIC = 0x184D2A5D
FRAME_MAGIC = 0xFD2FB528
VERSION = "WARC/1.1"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
MANDATORY = ("WARC-Record-ID", "Content-Length", "WARC-Date", "WARC-Type")

ARCHIVE_BYTES = 256 << 20
DICTIONARY_BYTES = 64 << 10
SAMPLE_BYTES = 4 << 20
LEAST = 100
#: Bytes of the table of repeated digests up to which it is broadcast.
BROADCAST_BYTES = 64 << 20
#: Bytes of an archive handed to the decoder at once; what lies behind a frame's end is copied.
STEP = 16 << 10
MANIFEST = "path string, records bigint"
ROWS = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint, url string, record_id string, target_id string"


class ArchiveError(ValueError):
    pass


def record_id(*parts: object) -> str:
    """An identifier that depends on the parts alone."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, '|'.join(map(str, parts)))}>"


def _one_line(value: str | None) -> str:
    return "".join(c for c in value or "" if c not in "\r\n")


def _framed(headers: list[tuple[str, str]], block: bytes) -> bytes:
    headers = [*headers, ("WARC-Block-Digest", f"sha256:{hashlib.sha256(block).hexdigest()}"), ("Content-Length", str(len(block)))]
    head = VERSION + "\r\n" + "".join(f"{k}: {v}\r\n" for k, v in headers) + "\r\n"
    return head.encode() + block + b"\r\n\r\n"


def make_info(name: str, date: str) -> bytes:
    """The record that describes an archive."""
    headers = [("WARC-Type", "warcinfo"), ("WARC-Record-ID", record_id(name)), ("WARC-Date", date), ("WARC-Filename", name), ("Content-Type", "application/warc-fields")]
    return _framed(headers, b"software: quorumlab\r\nformat: WARC File Format 1.1\r\n")


def make_record(
    page_id: int | None, url: str | None, payload: bytes, size: int, digest: str, refers_to: int | None, date: str, own_id: str | None = None, target_url: str | None = None, target_id: str | None = None
) -> bytes:
    """A record with its headers. A revisit carries HTTP headers only; size and digest are of the full payload."""
    url = _one_line(url)
    kind = "response" if refers_to is None else "revisit"
    block = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
    if kind == "response":
        block += payload
    headers = [
        ("WARC-Type", kind), ("WARC-Record-ID", own_id or record_id(page_id, url, digest)), ("WARC-Date", date), ("WARC-Target-URI", url),
        ("Content-Type", "application/http;msgtype=response"), ("WARC-Payload-Digest", f"sha256:{digest}"), ("X-Page-Id", "" if page_id is None else str(page_id)),
    ]
    if kind == "revisit":
        headers += [("WARC-Profile", REVISIT_PROFILE), ("X-Refers-To-Page-Id", str(refers_to)), ("WARC-Refers-To-Target-URI", _one_line(target_url)), ("WARC-Refers-To-Date", date)]
        if target_id:
            headers.append(("WARC-Refers-To", target_id))
    return _framed(headers, block)


def _http_length(block_head: bytes) -> int | None:
    for line in block_head.split(b"\r\n")[1:]:
        name, _, value = line.partition(b":")
        if name.strip().lower() == b"content-length":
            if not value.strip().isdigit():
                raise ArchiveError(f"an HTTP Content-Length is {value[:20]!r}")
            return int(value)
    return None


def parse_record(data: bytes) -> dict:
    """Headers, type, payload length and digest of a record, all verified."""
    head, mark, rest = data.partition(b"\r\n\r\n")
    lines = head.decode("utf-8").split("\r\n")
    if not mark or lines[0] != VERSION:
        raise ArchiveError(f"a record begins with {lines[0][:40]!r}")
    headers = {}
    for line in lines[1:]:
        name, colon, value = line.partition(":")
        if not colon:
            raise ArchiveError(f"a header line has no colon: {line[:60]!r}")
        headers[name] = value.strip()
    if missing := [h for h in MANDATORY if not headers.get(h)]:
        raise ArchiveError(f"headers are missing: {missing}")
    length = int(headers["Content-Length"])
    if len(rest) != length + 4 or rest[length:] != b"\r\n\r\n":
        raise ArchiveError(f"Content-Length is {length}, the block and its end have {len(rest)} bytes")
    block = rest[:length]
    if headers.get("WARC-Block-Digest", "") != f"sha256:{hashlib.sha256(block).hexdigest()}":
        raise ArchiveError("the block digest differs")
    http, _, payload = block.partition(b"\r\n\r\n")
    kind, digest = headers["WARC-Type"], headers.get("WARC-Payload-Digest", "").removeprefix("sha256:")
    size = _http_length(http)
    if size is None and kind != "revisit":
        size = len(payload)
    if kind == "response" and (len(payload) != size or hashlib.sha256(payload).hexdigest() != digest):
        raise ArchiveError("the payload differs from its length or digest")
    if kind == "revisit" and (payload or headers.get("WARC-Profile") != REVISIT_PROFILE):
        raise ArchiveError("a revisit with a payload or without its profile")
    number = lambda h: int(headers[h]) if headers.get(h) else None
    return {
        "page_id": number("X-Page-Id"), "payload_bytes": size, "payload_digest": digest, "record_type": kind,
        "refers_to": number("X-Refers-To-Page-Id"), "url": headers.get("WARC-Target-URI"), "record_id": headers["WARC-Record-ID"], "target_id": headers.get("WARC-Refers-To"), "payload": payload,
    }


def train_dictionary(samples: list[bytes]) -> bytes:
    """A dictionary from sample payloads, or an empty one if they are too few to train on."""
    import zstandard

    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples).as_bytes()
    except zstandard.ZstdError:
        return b""


class ArchiveWriter:
    def __init__(self, out, dictionary: bytes):
        import zstandard

        self.out, self.size, self.records = out, 8 + len(dictionary), 0
        out.write(struct.pack("<II", SKIPPABLE_MAGIC, len(dictionary)) + dictionary)
        known = zstandard.ZstdCompressionDict(dictionary) if dictionary else None
        if known:
            known.precompute_compress(level=3)
        self.pack = zstandard.ZstdCompressor(dict_data=known) if known else zstandard.ZstdCompressor(level=3)

    def add(self, record: bytes) -> None:
        frame = self.pack.compress(record)
        self.out.write(frame)
        self.size += len(frame)
        self.records += 1


def read_archive(file) -> Iterator[dict]:
    """Records of an archive in order. ``file`` is a binary file object, read once from front to back."""
    import zstandard

    head = file.read(8)
    magic, size = struct.unpack("<II", head) if len(head) == 8 else (0, 0)
    if magic != SKIPPABLE_MAGIC:
        raise ArchiveError("the archive doesn't begin with a dictionary frame")
    dictionary = file.read(size)
    if len(dictionary) != size:
        raise ArchiveError("the dictionary frame ends early")
    if dictionary[:4] == struct.pack("<I", FRAME_MAGIC):  # a dictionary may itself be compressed
        dictionary = zstandard.ZstdDecompressor().decompress(dictionary)
    unpack = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(dictionary)) if dictionary else zstandard.ZstdDecompressor()
    rest, at = memoryview(b""), 0
    while True:
        frame, record = unpack.decompressobj(), []
        while not frame.eof:
            if not rest:
                rest = memoryview(file.read(1 << 20))
                if not rest:
                    break
            piece = rest[:STEP]
            record.append(frame.decompress(piece))
            rest = rest[len(piece) - len(frame.unused_data) :]
        if not frame.eof:
            if record:
                raise ArchiveError(f"the archive ends inside record {at}")
            return
        try:
            yield parse_record(b"".join(record))
        except ArchiveError as e:
            raise ArchiveError(f"record {at}: {e}") from None
        at += 1


def write_archives(pages: DataFrame, where: str, least: int = LEAST, date: str = "2024-01-01T00:00:00Z") -> list:
    """Write the archives; returns the manifest rows."""
    body = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    rows = pages.select(F.col("page_id").cast("bigint").alias("page_id"), F.col("url").cast("string").alias("url"), body.alias("payload"))
    rows = rows.withColumn("size", F.octet_length("payload").cast("bigint")).withColumn("digest", F.sha2("payload", 256))
    copies = rows.where((F.col("size") >= least) & F.col("page_id").isNotNull()).groupBy("digest", "page_id").agg(F.count("*").alias("n"), F.min("url").alias("url"))
    first = copies.groupBy("digest").agg(F.min(F.struct("page_id", "n", "url")).alias("first"), F.sum("n").alias("n"))
    repeated = first.where("n > 1").select(F.col("digest").alias("_digest"), F.col("first.page_id").alias("first_id"), (F.col("first.n") == 1).alias("sole"), F.col("first.url").alias("target_url"))
    repeated = written(repeated, "repeated-digests")
    size = repeated.agg(F.sum(120 + F.coalesce(F.octet_length("target_url"), F.lit(0)))).first()[0] or 0
    both = rows.join(F.broadcast(repeated) if size <= BROADCAST_BYTES else repeated.hint("merge"), (F.col("digest") == F.col("_digest")) & (F.col("size") >= least), "left")
    refers = F.when(F.col("page_id").isNull() | (F.col("page_id") != F.col("first_id")), F.col("first_id"))
    out = both.select("page_id", "url", F.when(refers.isNull(), F.col("payload")).alias("payload"), "size", "digest", refers.alias("refers_to"), "first_id", "sole", "target_url")

    def write(batches: Iterator) -> Iterator:
        import pyarrow as pa

        held: list[dict] = []
        writer = file = path = None
        done: list[tuple[str, int]] = []

        def put(r: dict) -> None:
            nonlocal writer, file, path
            if writer is not None and writer.size >= ARCHIVE_BYTES:
                close()
            if writer is None:
                path = f"{where}/pages-{uuid.uuid4().hex}.warc.zst"
                file = open_uri(path, "wb")
                writer = ArchiveWriter(file, dictionary)
                writer.add(make_info(path.rpartition("/")[2], date))
            target = record_id(r["first_id"], r["digest"]) if r["sole"] else None
            own = target if target and r["refers_to"] is None else record_id(path, writer.records)
            writer.add(make_record(r["page_id"], r["url"], r["payload"] or b"", r["size"], r["digest"], r["refers_to"], date, own, r["target_url"], target))

        def close() -> None:
            nonlocal writer, file
            file.close()
            done.append((path, writer.records - 1))  # but for the warcinfo
            writer = file = None

        dictionary, sampled, trained = b"", 0, False
        for batch in batches:
            for r in batch.to_pylist():
                if not trained:
                    held.append(r)
                    sampled += len(r["payload"] or b"")
                    if sampled < SAMPLE_BYTES:
                        continue
                    dictionary, trained = train_dictionary([x["payload"][: 64 << 10] for x in held if x["payload"]]), True
                    for x in held:
                        put(x)
                    held = []
                else:
                    put(r)
        if held:
            dictionary = train_dictionary([x["payload"][: 64 << 10] for x in held if x["payload"]])
            for x in held:
                put(x)
        if writer is not None:
            close()
        if done:
            yield pa.RecordBatch.from_arrays([pa.array([p for p, _ in done]), pa.array([n for _, n in done], pa.int64())], names=["path", "records"])

    manifest = sorted(out.mapInArrow(write, MANIFEST).collect(), key=lambda r: r["path"])
    drop_written(repeated)
    return manifest


def read_archives(spark: SparkSession, manifest: list, with_payload: bool = False) -> DataFrame:
    """Records of the archives named in the manifest; ``with_payload`` adds the binary payload (empty for revisits)."""
    files = spark.createDataFrame([(r["path"], r["records"]) for r in manifest], MANIFEST)
    schema = ROWS + (", payload binary" if with_payload else "")

    def read(batches: Iterator) -> Iterator:
        import pyarrow as pa

        kinds = {"string": pa.string(), "bigint": pa.int64(), "binary": pa.binary()}
        fields = [(f.split()[0], kinds[f.split()[1]]) for f in schema.split(", ")]
        pack = lambda rows: pa.RecordBatch.from_arrays([pa.array([r[n] for r in rows], t) for n, t in fields], names=[n for n, _ in fields])
        for batch in batches:
            for path, records in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows, seen, held = [], 0, 0
                with open_uri(path, "rb") as f:
                    for r in read_archive(f):
                        if r["record_type"] == "warcinfo":
                            continue
                        rows.append(r)
                        seen += 1
                        held += len(r["payload"])
                        if len(rows) >= 2000 or held > 8 << 20:
                            yield pack(rows)
                            rows, held = [], 0
                if seen != records:
                    raise ArchiveError(f"{path}: {seen} records, {records} in the manifest")
                yield pack(rows)

    spread = files.repartition(max(1, len(manifest)), "path") if manifest else files
    return spread.mapInArrow(read, schema)


def archive_round_trip(pages: DataFrame, least: int = LEAST) -> DataFrame:
    spark = pages.sparkSession
    return read_archives(spark, write_archives(pages, fresh_path(spark, "warc"), least))


#: DuckDB: digests and the smallest page of equal payloads.
ORACLE = """
with q as (select page_id, octet_length(encode(coalesce(html, ''))) n, sha256(coalesce(html, '')) d from pages),
r as (select *, min(page_id) over (partition by d) f from q)
select page_id, n payload_bytes, d payload_digest, case when n >= 100 and f <> page_id then 'revisit' else 'response' end record_type,
  case when n >= 100 and f <> page_id then f end refers_to
from r
"""
