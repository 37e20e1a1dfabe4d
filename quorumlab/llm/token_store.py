"""Token ids in sorted-string-table shards.

Documents are dealt by ranges of their id, sorted, encoded, and written as one file for each range. A
file holds, in this order:

* data blocks. An entry is: bytes shared with the previous key, bytes of the rest of the key, bytes of the value (each as
  a base-128 number), the rest of the key, the value. Keys are a byte that tells a null id (first) from
  others, the document id as eight big-endian bytes with the sign flipped, and eight bytes counting entries with the same id, so byte order is numeric order. A value is
  the number of ids, then the ids at two bytes each (four if the vocabulary needs it). Blocks restart the prefixes and are
  compressed with Zstandard;
* a sparse index with the first key, offset, length and entry count of each block;
* a Bloom filter over the document ids;
* a fixed-size footer with the places of index and filter, the number of entries and of ids, the id width and the magic.

A lookup reads footer, filter and index, finds the block by binary search and reads that block alone.

Shards are committed by their manifest: a task writes under a name of its own and renames at the end; only files
that a finished task names in the manifest are ever read, so retried or duplicated tasks leave no wrong rows.

Defined cases: a null text is an empty one (only the end id); a null id comes first, as one key; repeated ids and rows keep an entry each,
in an order given by their text; an empty table gives no shards and no rows.
"""

from __future__ import annotations

import io
import re
import struct
import zlib
from array import array
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh_path
from .wordpiece import printable_bytes

MAGIC = b"QSST0001"
FOOTER = "<QQQQQQI4x8s"
BLOCK_BYTES = 1 << 18
BLOOM_BITS_PER_KEY, BLOOM_HASHES = 10, 7
END_ID = 2
#: Text bytes for a shard, about.
SHARD_BYTES = 256 << 20
#: Text bytes that are encoded at a time, about.
GROUP_BYTES = 1 << 20
#: Text pieces in a generation of a task's memo; two generations are held.
MEMO = 400_000


# --- encoding -------------------------------------------------------------------------------------------------


class MemoEncoder:
    """Encodes texts with a byte-level tokenizer; each distinct piece of text between spaces is encoded once.

    The tokenizer's splitter never joins characters across a single space or line feed between other
    characters, so a text whose white space is only that is the sum of its pieces. Any other
    text, or one that holds an added token, is encoded whole.
    """

    def __init__(self, path: str, memo: int = MEMO):
        import os

        import numpy as np
        from tokenizers import Tokenizer

        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
        self.tokenizer = Tokenizer.from_file(path)
        vocabulary = self.tokenizer.get_vocab_size(with_added_tokens=True)
        self.kind = np.dtype("<u2") if vocabulary <= 1 << 16 else np.dtype("<u4")
        self.limit, self.tails, self.model, self.code = memo, {}, self.tokenizer.model, self.kind.char
        self.to_printable = {b: c for c, b in printable_bytes().items()}
        feed = self._ids(["\n"])[0]
        self.feed = feed[0] if len(feed) == 1 and self.tokenizer.normalizer is None and self._splits() else None
        # Commas and full stops after a letter or digit become pieces of their own, under keys that no text on this path holds.
        self.marks = {"\x01": np.array(self._ids([","])[0], self.kind).tobytes(), "\x02": np.array(self._ids(["."])[0], self.kind).tobytes()}
        self.odd = re.compile(r"[.,](?<=[\W_].)[ \n]")
        self.known, self.older = dict(self.marks), {}
        self.added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]

    def _ids(self, texts: list[str]) -> list[list[int]]:
        return [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _splits(self) -> bool:
        """Does this tokenizer cut where the memo relies on it?"""
        whole, parts = self._ids(["Ab, c1\nDe. f"])[0], self._ids(["Ab", ",", " c1", "\n", "De", ".", " f"])
        probe = ["The", " quick", " Überfluß", " ñandú", " a"]
        direct = [array(self.code, ids).tobytes() for ids in self._ids(probe)] == self._direct(probe)
        return direct and whole == [i for p in parts for i in p]

    def _direct(self, words: list[str]) -> list[bytes]:
        """Ids of pieces of a space or nothing, and letters: each is one unit of the splitter, so the model alone decides."""
        if not words:
            return []
        written = "\n".join(words).encode().decode("latin-1").translate(self.to_printable).split(self.to_printable[10])
        tokenize = self.model.tokenize
        return [array(self.code, [t.id for t in tokenize(w)]).tobytes() for w in written]

    def _learn(self, pieces: list[str]) -> None:
        """Encode unseen pieces: words by the model, words with marks as word and marks, all else by the whole tokenizer. Pieces that show
        other white space in a text than single spaces and line feeds have None."""
        spaced, fed, rest = [], [], []
        for p in pieces:
            if p.isalpha():
                spaced.append(p)
            elif p[:1] == "\n" and p[1:].isalpha():
                fed.append(p)
            else:
                rest.append(p)
        self.known.update(zip(spaced, self._direct([" " + p for p in spaced]), strict=True))
        feed = array(self.code, [self.feed]).tobytes()
        self.known.update(zip(fed, (feed + b for b in self._direct([p[1:] for p in fed])), strict=True))
        other, marked = [], []
        for p in rest:  # the splitter parts letters from marks
            word = p.rstrip(",.;:!?#$%&*")
            if word != p and word.isalpha():
                marked.append((p, word))
            elif p.split() == [p.removeprefix("\n")]:
                other.append(p)
            else:
                self.known[p] = None
        words = [w for w in {w for _, w in marked} if w not in self.known]
        self.known.update(zip(words, self._direct([" " + w for w in words]), strict=True))
        for p, word in marked:
            tail = p[len(word) :]
            if tail not in self.tails:
                self.tails[tail] = array(self.code, self._ids([tail])[0]).tobytes()
            self.known[p] = self.known[word] + self.tails[tail]
        whole = self._ids([p if p[:1] == "\n" else " " + p for p in other])
        self.known.update((p, array(self.code, ids).tobytes()) for p, ids in zip(other, whole, strict=True))

    def _look_up(self, pieces: list[str]) -> list[bytes | None]:
        """What is known of distinct pieces; unseen ones are learnt."""
        if len(self.known) > self.limit:
            self.known, self.older = dict(self.marks), self.known
        known, older = self.known, self.older
        unseen = [p for p in pieces if p not in known]
        if older:
            known.update({p: older[p] for p in unseen if p in older})
            unseen = [p for p in unseen if p not in known]
        if unseen:
            self._learn(unseen)
        return list(map(known.__getitem__, pieces))

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text, packed. Arrow cuts the texts and finds the distinct pieces."""
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        out: list = [None] * len(texts)
        whole, cut, heads, rests = [], [], [], []
        for k, text in enumerate(texts):
            if self.feed is None or not text or "\x01" in text or "\x02" in text or any(a in text for a in self.added):
                whole.append(k)
                continue
            if not self.odd.search(text):
                text = text.replace(", ", " \x01 ").replace(". ", " \x02 ").replace(",\n", " \x01\n").replace(".\n", " \x02\n")
            head, space, rest = text.replace("\n", " \n").partition(" ")
            if head.split() != [head]:
                whole.append(k)
                continue
            cut.append(k)
            heads.append(head)
            rests.append(rest if space else None)
        parts = pc.split_pattern(pa.array(rests, pa.large_string()), " ")
        coded, ends = parts.flatten().dictionary_encode(), np.concatenate([[0], np.cumsum(pc.fill_null(pc.list_value_length(parts), 0).to_numpy(zero_copy_only=False))]).astype(np.int64)
        known, indices = self._look_up(coded.dictionary.to_numpy(zero_copy_only=False).tolist()), coded.indices.to_numpy(zero_copy_only=False)
        spaced = np.zeros(len(cut), bool)
        if bad := [i for i, b in enumerate(known) if b is None]:
            spaced[np.searchsorted(ends, np.flatnonzero(np.isin(indices, bad)), side="right") - 1] = True
        packed = pa.array([b or b"" for b in known], pa.large_binary()).take(coded.indices)
        places = np.frombuffer(packed.buffers()[1], np.int64)[packed.offset :][ends] if len(packed) else ends * 0
        data = memoryview(packed.buffers()[2] or b"")
        for k, ids, odd, begin, end in zip(cut, self._ids(heads), spaced.tolist(), places[:-1].tolist(), places[1:].tolist(), strict=True):
            if odd:
                whole.append(k)
            else:
                out[k] = array(self.code, ids).tobytes() + data[begin:end]
        for k, ids in zip(whole, self._ids([texts[k] for k in whole]), strict=True):
            out[k] = np.array(ids, self.kind).tobytes()
        return out


# --- the file format ------------------------------------------------------------------------------------------


def _number(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_number(data: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = data[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


def make_key(doc_id: int | None, repeat: int = 0) -> bytes:
    return struct.pack(">BQQ", doc_id is not None, ((doc_id or 0) + (1 << 63)) & ((1 << 64) - 1), repeat)


def key_id(key: bytes) -> int | None:
    return struct.unpack(">Q", key[1:9])[0] - (1 << 63) if key[0] else None


def _bloom_places(doc_id: int | None, bits: int) -> list[int]:
    from xxhash import xxh3_128_intdigest

    h = xxh3_128_intdigest(make_key(doc_id)[:9])
    a, b = h & ((1 << 64) - 1), h >> 64 | 1
    return [(a + k * b) % bits for k in range(BLOOM_HASHES)]


class ShardWriter:
    """Appends entries in key order to a binary file object; memory holds one block, the index and the ids' hashes."""

    def __init__(self, out, width: int, block_bytes: int = BLOCK_BYTES):
        import zstandard

        self.out, self.width, self.block_bytes = out, width, block_bytes
        self.pack = zstandard.ZstdCompressor(level=1)
        self.block, self.first, self.last, self.in_block = bytearray(), b"", b"", 0
        self.index: list[tuple[bytes, int, int, int]] = []
        self.at = self.entries = self.ids = 0
        self.keys: list[int | None] = []

    def add(self, key: bytes, ids: bytes) -> None:
        if key <= self.last:
            raise ValueError("entries must come in key order")
        shared = 0
        if self.in_block:
            while self.last[shared] == key[shared]:
                shared += 1
        else:
            self.first = key
        rest = key[shared:]
        count = len(ids) // self.width
        value = _number(count) + ids
        self.block += _number(shared) + _number(len(rest)) + _number(len(value)) + rest + value
        self.last, self.in_block, self.entries, self.ids = key, self.in_block + 1, self.entries + 1, self.ids + count
        self.keys.append(key_id(key))
        if len(self.block) >= self.block_bytes:
            self._flush()

    def _flush(self) -> None:
        if self.in_block:
            data = self.pack.compress(bytes(self.block))
            self.out.write(data)
            self.index.append((self.first, self.at, len(data), self.in_block))
            self.at += len(data)
            self.block, self.in_block = bytearray(), 0

    def close(self) -> None:
        self._flush()
        index = b"".join(_number(len(k)) + k + _number(at) + _number(size) + _number(n) for k, at, size, n in self.index)
        bits = max(64, len(self.keys) * BLOOM_BITS_PER_KEY + 7 & ~7)
        bloom = bytearray(bits // 8)
        for i in self.keys:
            for p in _bloom_places(i, bits):
                bloom[p >> 3] |= 1 << (p & 7)
        self.out.write(index)
        self.out.write(bytes(bloom))
        self.out.write(struct.pack(FOOTER, self.at, len(index), self.at + len(index), len(bloom), self.entries, self.ids, self.width, MAGIC))


class ShardReader:
    """Reads a shard from a seekable binary file object."""

    def __init__(self, file):
        self.file = file
        file.seek(0, io.SEEK_END)
        size = file.tell()
        if size < struct.calcsize(FOOTER):
            raise ValueError("not a shard: too short")
        index_at, index_size, bloom_at, bloom_size, self.entries, self.ids, self.width, magic = struct.unpack(FOOTER, self._read(size - struct.calcsize(FOOTER), struct.calcsize(FOOTER)))
        if magic != MAGIC or bloom_at + bloom_size + struct.calcsize(FOOTER) != size or index_at + index_size != bloom_at:
            raise ValueError("not a shard: the footer doesn't fit the file")
        self.bloom, self.index = self._read(bloom_at, bloom_size), []
        data, at = self._read(index_at, index_size), 0
        while at < len(data):
            n, at = _read_number(data, at)
            key, at = data[at : at + n], at + n
            place, at = _read_number(data, at)
            length, at = _read_number(data, at)
            count, at = _read_number(data, at)
            self.index.append((key, place, length, count))

    def _read(self, at: int, size: int) -> bytes:
        self.file.seek(at)
        data = self.file.read(size)
        if len(data) != size:
            raise ValueError("the shard ends early")
        return data

    def block(self, k: int) -> Iterator[tuple[bytes, bytes]]:
        """(key, ids) of each entry of block ``k``."""
        import zstandard

        _, place, length, count = self.index[k]
        data, at, key = zstandard.ZstdDecompressor().decompress(self._read(place, length)), 0, b""
        for _ in range(count):
            shared, at = _read_number(data, at)
            rest, at = _read_number(data, at)
            size, at = _read_number(data, at)
            key, at = key[:shared] + data[at : at + rest], at + rest
            n, start = _read_number(data, at)
            at += size
            if at - start != n * self.width:
                raise ValueError("an entry's length doesn't fit its count")
            yield key, data[start:at]
        if at != len(data):
            raise ValueError("bytes are left after a block's entries")

    def __iter__(self) -> Iterator[tuple[bytes, bytes]]:
        for k in range(len(self.index)):
            yield from self.block(k)

    def get(self, doc_id: int) -> list[bytes]:
        """Ids of all entries of a document, by Bloom filter, binary search and the blocks that can hold it."""
        from bisect import bisect_right

        bits = len(self.bloom) * 8
        if not all(self.bloom[p >> 3] >> (p & 7) & 1 for p in _bloom_places(doc_id, bits)):
            return []
        k = max(0, bisect_right([x[0] for x in self.index], make_key(doc_id)) - 1)
        out = []
        while k < len(self.index) and self.index[k][0][:9] <= make_key(doc_id)[:9]:
            out += [ids for key, ids in self.block(k) if key_id(key) == doc_id]
            k += 1
        return out


def open_uri(uri: str, mode: str):
    """A binary file of a shared folder: plain files for file: URIs, else what pyarrow knows of the scheme."""
    import os

    if uri.startswith("file:") or "://" not in uri:
        path = re.sub(r"^file:(//)?(?=/)", "", uri)
        if mode == "wb":
            os.makedirs(os.path.dirname(path), exist_ok=True)
        return open(path, mode)
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(uri)
    return store.open_output_stream(path) if mode == "wb" else store.open_input_file(path)


# --- the distributed writer and reader --------------------------------------------------------------------------

MANIFEST = "shard int, path string, entries bigint, ids bigint, first_id bigint, last_id bigint"
ROWS = "shard int, nth bigint, doc_id bigint, n_tokens bigint, before bigint, ids_crc32 bigint"


def write_shards(docs: DataFrame, tokenizer_path: str, where: str, shards: int | None = None, end_id: int = END_ID, key: str = "doc_id", text: str = "text") -> list:
    """Write the shards and return their manifest rows in ascending id order (one small row for each shard)."""
    spark = docs.sparkSession
    rows = docs.select(F.col(key).cast("bigint").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    if shards is None:
        total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        least = spark.sparkContext.defaultParallelism
        shards = max(1, least, total // SHARD_BYTES + 1)
    dealt = rows.repartitionByRange(shards, "doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))

    def write(batches: Iterator) -> Iterator:
        import itertools
        import uuid

        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc
        from pyspark import TaskContext

        number = TaskContext.get().partitionId()
        path = f"{where}/shard-{number:06d}-{uuid.uuid4().hex}.sst"
        encoder = writer = out = first = last = None
        repeat, any_yet = 0, False
        for batch in batches:
            if not batch.num_rows:
                continue
            if writer is None:
                encoder = MemoEncoder(tokenizer_path)
                end = struct.pack("<H" if encoder.kind.itemsize == 2 else "<I", end_id)
                out = open_uri(path, "wb")
                writer = ShardWriter(out, encoder.kind.itemsize)
            ids, texts = batch.column(0).to_pylist(), batch.column(1)
            group = pc.binary_length(texts).to_numpy(zero_copy_only=False).cumsum(dtype="i8") // GROUP_BYTES
            starts = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), len(ids)]
            for at, stop in itertools.pairwise(starts):
                packed = encoder.encode(texts.slice(at, stop - at).to_pylist())
                for doc_id, body in zip(ids[at:stop], packed, strict=True):
                    repeat = repeat + 1 if any_yet and doc_id == last else 0
                    writer.add(make_key(doc_id, repeat), body + end)
                    first = doc_id if not any_yet else first
                    last, any_yet = doc_id, True
        if writer is not None:
            writer.close()
            out.close()
            row = [[number], [path], [writer.entries], [writer.ids], [first], [last]]
            kinds = [pa.int32(), pa.string(), *[pa.int64()] * 4]
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(row, kinds, strict=True)], names=[c.split()[0] for c in MANIFEST.split(", ")])

    return sorted(dealt.mapInArrow(write, MANIFEST).collect(), key=lambda r: r["shard"])


def read_shards(spark: SparkSession, manifest: list) -> DataFrame:
    """Per entry, from the files: doc_id, start (ids of all entries before it), n_tokens, ids_crc32."""
    starts, at = [], 0
    for r in manifest:
        starts.append((r["shard"], r["path"], at, r["entries"], r["ids"]))
        at += r["ids"]
    files = spark.createDataFrame(starts, "shard int, path string, before bigint, entries bigint, ids bigint")

    def read(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            for shard in batch.to_pylist():
                with open_uri(shard["path"], "rb") as f:
                    reader = ShardReader(f)
                    if (reader.entries, reader.ids) != (shard["entries"], shard["ids"]):
                        raise ValueError(f"{shard['path']} is not the file its manifest row describes")
                    kind, start, seen = np.dtype("<u2" if reader.width == 2 else "<u4"), shard["before"], 0
                    for k in range(len(reader.index)):
                        rows: tuple = ([], [], [], [])
                        for key, ids in reader.block(k):
                            wide = np.frombuffer(ids, kind).astype("<u4")
                            for column, v in zip(rows, (key_id(key), start, len(wide), zlib.crc32(wide.tobytes())), strict=True):
                                column.append(v)
                            start += len(wide)
                            seen += 1
                        yield pa.RecordBatch.from_arrays([pa.array(v, pa.int64()) for v in rows], names=["doc_id", "start", "n_tokens", "ids_crc32"])
                    if seen != reader.entries:
                        raise ValueError(f"{shard['path']}: {seen} entries, {reader.entries} in the footer")

    spread = files.repartition(max(1, len(manifest)), "shard") if manifest else files
    return spread.mapInArrow(read, "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")


def lookup(manifest: list, doc_id: int | None) -> list[list[int]]:
    """Ids of a document by binary search over the manifest, then in the shards whose range holds it."""
    import numpy as np

    found = []
    for r in manifest:
        if make_key(r["first_id"])[:9] <= make_key(doc_id)[:9] <= make_key(r["last_id"])[:9]:
            with open_uri(r["path"], "rb") as f:
                reader = ShardReader(f)
                found += [np.frombuffer(x, "<u2" if reader.width == 2 else "<u4").tolist() for x in reader.get(doc_id)]
    return found


def tokenize_to_shards(docs: DataFrame, tokenizer_path: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    spark = docs.sparkSession
    return read_shards(spark, write_shards(docs, tokenizer_path, fresh_path(spark, "tokens"), key=key, text=text))
