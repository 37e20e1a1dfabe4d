"""Word-piece token counts by a linear longest-match automaton.

A trie holds the pieces that start a word and, below a node of its own, the pieces that continue one. When a
node has no way on for the next byte, the longest pieces up to there are certain: the failure link leads to
the node for what is left, and how many pieces were passed is known beforehand. A word is thus counted in
one pass, each byte moving forward once, and no piece is ever built.

A word that cannot be cut into pieces counts as one unknown token, as in greedy longest-match tokenizers.
Words are runs of non-white-space bytes, or, with ``splitter="bert"``, what the tokenizers library's normaliser and
splitter of that name make of the text (control characters dropped, accents and case folded if asked, punctuation and
ideographs apart). Within a task each distinct word is walked once while it is remembered (a bounded memo).

Defined cases: null and empty texts have no words and no tokens; repeated rows have a result each; a word of more than
``longest_word`` characters, if that is given, is unknown; an empty line of a vocabulary file is no piece.
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Words a task remembers before it starts afresh.
MEMO = 400_000


class PieceCounter:
    """Counts greedy longest-match pieces of byte words."""

    def __init__(self, starting: Iterable[bytes], continuing: Iterable[bytes]):
        ways: dict[int, int] = {}  # node * 256 + byte -> node
        whole = [False, False]  # node 0 starts words, node 1 continues them
        parent = [(-1, 0), (-1, 0)]
        for top, pieces in ((0, starting), (1, continuing)):
            for piece in pieces:
                node = top
                for c in piece:
                    step = node << 8 | c
                    if step not in ways:
                        ways[step] = len(whole)
                        whole.append(False)
                        parent.append((node, c))
                    node = ways[step]
                whole[node] = whole[node] or node > 1
        n = len(whole)
        fail, pops = [-1] * n, [0] * n
        # Nodes were appended after their parents, but a link may lead to a node made later: go by depth.
        depth = [0] * n
        for v in range(2, n):
            depth[v] = depth[parent[v][0]] + 1
        for v in sorted(range(2, n), key=depth.__getitem__):
            if whole[v]:
                fail[v], pops[v] = 1, 1
                continue
            up, c = parent[v]
            z, count = fail[up], pops[up]
            while z != -1 and (z << 8 | c) not in ways:
                count += pops[z]
                z = fail[z]
            if z != -1:
                fail[v], pops[v] = ways[z << 8 | c], count
        self.ways, self.fail, self.pops = ways, fail, pops

    def count(self, word: bytes) -> int:
        """Number of pieces; -1 if the word cannot be cut."""
        ways, fail, pops = self.ways, self.fail, self.pops
        node, count = 0, 0
        for c in word:
            to = ways.get(node << 8 | c)
            while to is None:
                count += pops[node]
                node = fail[node]
                if node == -1:
                    return -1
                to = ways.get(node << 8 | c)
            node = to
        while node > 1:
            count += pops[node]
            node = fail[node]
            if node == -1:
                return -1
        return count


def printable_bytes() -> dict[str, int]:
    """The characters that byte-level vocabularies write for bytes: printable ones stand for themselves, the rest count up from 256."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    other = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(other)}


def pieces_of_byte_vocabulary(path: str) -> tuple[list[bytes], list[bytes]]:
    """(pieces that start a word, pieces that continue one) from a byte-level vocabulary file: a token with a
    leading space starts a word; the others continue one; single bytes do both, so that every word can be cut."""
    with open(path, encoding="utf-8") as f:
        vocabulary = json.load(f)["model"]["vocab"]
    to_byte = printable_bytes()
    starting, continuing = [], []
    for token in vocabulary:
        if all(ch in to_byte for ch in token):
            piece = bytes(to_byte[ch] for ch in token)
            if piece[:1] == b" ":
                starting.append(piece[1:])
            else:
                continuing.append(piece)
                if len(piece) == 1:
                    starting.append(piece)
    return [p for p in starting if p], continuing


def pieces_of_text_vocabulary(path: str, mark: str = "##") -> tuple[list[bytes], list[bytes]]:
    """(pieces that start a word, pieces that continue one) from a file with a piece a line, where ``mark`` leads those that continue."""
    with open(path, encoding="utf-8", newline="\n") as f:
        lines = [line.rstrip("\r\n") for line in f]
    starting = [p.encode() for p in lines if p and not p.startswith(mark)]
    return starting, [p[len(mark) :].encode() for p in lines if p.startswith(mark) and len(p) > len(mark)]


def word_splitter(name: str, lowercase: bool = True) -> Callable[[bytes], list[bytes]]:
    """The words of a UTF-8 text; ``space`` or ``bert``."""
    if name == "space":
        return bytes.split
    if name != "bert":
        raise ValueError(f"no splitter is named {name!r}")
    from tokenizers import normalizers, pre_tokenizers

    normal, cut = normalizers.BertNormalizer(lowercase=lowercase), pre_tokenizers.BertPreTokenizer()

    def split(body: bytes) -> list[bytes]:
        text = normal.normalize_str(body.decode("utf-8", "replace"))
        return [w.encode() for w, _ in cut.pre_tokenize_str(text)] if text else []

    return split


def count_tokens(
    docs: DataFrame, starting: list[bytes], continuing: list[bytes], key: str = "doc_id", text: str = "text", memo: int = MEMO, splitter: str = "space", lowercase: bool = True, longest_word: int | None = None
) -> DataFrame:
    """doc_id, n_words, n_tokens (an unknown word is one), n_unknown. The vocabulary travels as a broadcast; its size is the vocabulary file's."""
    word_splitter(splitter)  # an unknown name fails here
    pieces = docs.sparkSession.sparkContext.broadcast((starting, continuing))

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        counter, split = PieceCounter(*pieces.value), word_splitter(splitter, lowercase)
        known: dict[bytes, int] = {}
        for batch in batches:
            n_words, n_tokens, n_unknown = [], [], []
            for value in batch.column(1):
                words = split(value.as_py() or b"")
                for w in set(words).difference(known):
                    known[w] = -1 if longest_word is not None and len(w.decode("utf-8", "replace")) > longest_word else counter.count(w)
                counts = list(map(known.__getitem__, words))
                missed = counts.count(-1)
                n_words.append(len(words))
                n_tokens.append(sum(counts) + 2 * missed)
                n_unknown.append(missed)
                if len(known) > memo:
                    known.clear()
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array(v, pa.int64()) for v in (n_words, n_tokens, n_unknown))], names=["doc_id", "n_words", "n_tokens", "n_unknown"]
            )

    body = docs.select(F.col(key).cast("bigint").alias("doc_id"), F.col(text).cast("binary").alias("body"))
    return body.mapInArrow(run, "doc_id bigint, n_words bigint, n_tokens bigint, n_unknown bigint")
