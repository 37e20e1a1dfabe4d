"""Secret scanning: base patterns, and weak parts that count only where complementary parts meet.

Base findings, leftmost and non-overlapping for each kind, over the whole text:

* ``assign``: a name such as password, optional quote, ``:`` or ``=``, optional quote, then 6+ value characters;
* ``access``: an access identifier of 20+ characters;
* ``hex``: 24+ lower-case hexadecimal digits.

Multipart linking: identifiers (access keys, key ids, user names), weak secrets (long mixed tokens that no
base pattern reports) and endpoints (URLs, hosts with a port, connection strings) are intervals. A scope
is a paragraph, split into windows around each identifier. An interval join inside the scope, a sweep over
both sorted lists, finds the weak secrets and endpoints within ``reach`` code points of an identifier. A weak
secret is reported (``linked_secret``) only if an identifier lies in reach; an endpoint (``linked_endpoint``) and
an identifier that is no base finding (``linked_id``) only if an identifier and a secret of any kind lie in reach.
Base findings are never removed.

The join runs inside the row that holds the text, so nothing is shuffled and memory is bounded by one batch.

Defined cases: a null or empty text has no findings; repeated rows have a result each; offsets are code points.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from collections.abc import Iterable, Iterator
from itertools import accumulate

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The base patterns, in the order of their kinds.
BASE = (
    ("assign", r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""),
    ("access", r"AKIA[A-Z0-9]+"),
    ("hex", r"[0-9a-f]{24,}"),
)
#: Words without which ``assign`` cannot match, for skipping most texts.
ASSIGN_WORDS = (b"password", b"passwd", b"secret", b"token", b"apikey", b"api_key")
PARTS = (
    ("id", r"(?i:\b(?:access_?key(?:_?id)?|client_?id|account|user(?:name)?|login)\b)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9@._-]{3,})"),
    ("weak", r"(?<![A-Za-z0-9+/_=-])(?=[A-Za-z+/_-]*[0-9])(?=[0-9+/_-]*[A-Za-z])[A-Za-z0-9+/_-]{16,}={0,2}(?![A-Za-z0-9+/_=-])"),
    ("endpoint", r"(?i:\b(?:https?|ftp|jdbc:[a-z]+|postgres(?:ql)?|mysql|mongodb|redis|amqp|s3)://[^\s\"'<>]+)|\b(?:[a-z0-9-]+\.)+[a-z]{2,}:[0-9]{2,5}\b"),
)
PARTS_HINT = re.compile(rb"AKIA|access_?key|client_?id|account|user|login", re.I)
REACH = 200
NONE: tuple[list[int], list[int]] = ([], [])

SCHEMA = "doc_id bigint, n_assign bigint, n_access bigint, n_hex bigint, findings array<struct<kind:string,start:int,end:int>>, n_base int"


def base_findings(text: str, body: bytes, compiled: dict) -> list[tuple[int, int, str, int]]:
    """(start, rank of kind, kind, end), sorted by start and then kind. ``body`` is the text in UTF-8."""
    found = []
    low = body.lower()
    if any(w in low for w in ASSIGN_WORDS):
        found += [(m.start(), 0, "assign", m.end()) for m in compiled["assign"].finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        found += [(m.start(), 1, "access", m.end()) for m in compiled["access"].finditer(text) if len(m[0]) >= 20]
    found += [(m.start(), 2, "hex", m.end()) for m in compiled["hex"].finditer(text)]
    return sorted(found)


def _furthest(spans: Iterable[tuple[int, int]]) -> tuple[list[int], list[int]]:
    ordered = sorted(spans)
    return [s for s, _ in ordered], list(accumulate((e for _, e in ordered), max))


def _near(spans: tuple[list[int], list[int]], at: int, to: int, reach: int) -> bool:
    """Is an interval within reach of [at, to)? Spans are sorted starts, and for each the furthest end up to it."""
    starts, ends = spans
    k = bisect_right(starts, to + reach)
    return k > 0 and ends[k - 1] >= at - reach


def linked_findings(text: str, base: list[tuple[int, int, str, int]], compiled: dict, reach: int = REACH) -> list[tuple[int, int, str, int]]:
    """Weak candidates with complementary parts in reach, inside their paragraph."""
    parts = {kind: [(m.start(), m.end()) for m in compiled[kind].finditer(text)] for kind, _ in PARTS}
    strong = [(s, e) for s, _, kind, e in base if kind != "access"]
    covered = _furthest((s, e) for s, _, _, e in base)

    def inside_base(s: int, e: int) -> bool:
        return _near(covered, s + 1, e - 1, 0)

    access = [(s, e) for s, _, kind, e in base if kind == "access"]
    weak = [p for p in parts["weak"] if not inside_base(*p)]
    out = []
    # A scope is a paragraph: what lies beyond a blank line is out of reach.
    edges = [m.end() for m in re.finditer(r"\n\s*\n", text)]
    scope = lambda at: bisect_right(edges, at)

    def by_scope(spans: list[tuple[int, int]]) -> dict[int, tuple[list[int], list[int]]]:
        cells: dict[int, list[tuple[int, int]]] = {}
        for s, e in spans:
            cells.setdefault(scope(s), []).append((s, e))
        return {k: _furthest(v) for k, v in cells.items()}

    ids = by_scope(parts["id"] + access)
    linked = [p for p in weak if _near(ids.get(scope(p[0]), NONE), *p, reach)]
    secrets = by_scope(strong + linked)
    out += [(s, 3, "linked_secret", e) for s, e in linked]
    for kind, spans in (("linked_endpoint", parts["endpoint"]), ("linked_id", parts["id"])):
        for s, e in spans:
            k = scope(s)
            if _near(ids.get(k, NONE), s, e, reach) and _near(secrets.get(k, NONE), s, e, reach):
                out.append((s, 4 if kind == "linked_endpoint" else 5, kind, e))
    return sorted(out)


def compiled_patterns() -> dict:
    return {kind: re.compile(p, re.ASCII) for kind, p in (*BASE, *PARTS)}


def _scan(batches: Iterator) -> Iterator:
    import pyarrow as pa

    compiled = compiled_patterns()
    for batch in batches:
        rows = {"doc_id": batch.column(0).to_pylist(), "n_assign": [], "n_access": [], "n_hex": [], "findings": [], "n_base": []}
        for value in batch.column(1):
            body = value.as_py() or b""
            text = body.decode("utf-8", "replace")
            base = base_findings(text, body, compiled)
            linked = linked_findings(text, base, compiled) if PARTS_HINT.search(body) else []
            for kind in ("assign", "access", "hex"):
                rows[f"n_{kind}"].append(sum(f[2] == kind for f in base))
            rows["n_base"].append(len(base))
            rows["findings"].append([{"kind": k, "start": s, "end": e} for s, _, k, e in (*base, *linked)])
        spans = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))
        types = {"doc_id": pa.int64(), "findings": spans, "n_base": pa.int32()}
        yield pa.RecordBatch.from_arrays([pa.array(v, types.get(k, pa.int64())) for k, v in rows.items()], names=list(rows))


def find_secrets(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, counts, findings (base ones first, then linked ones, each sorted by start) and how many are base."""
    return docs.select(F.col(key).cast("bigint").alias("doc_id"), F.col(text).cast("binary").alias("body")).mapInArrow(_scan, SCHEMA)


def secret_report(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The digest columns: base spans hashed, and all spans by start and then kind."""
    said = lambda f: F.concat_ws(":", f["kind"], f["start"].cast("string"), f["end"].cast("string"))
    rank = lambda f: F.array_position(F.array(*[F.lit(k) for k in ("assign", "access", "hex", "linked_secret", "linked_endpoint", "linked_id")]), f["kind"])
    ordered = F.array_sort(F.transform("findings", lambda f: F.struct(f["start"].alias("start"), rank(f).alias("rank"), f["end"].alias("end"), f["kind"].alias("kind"))))
    return find_secrets(docs, key, text).select(
        "doc_id", "n_assign", "n_access", "n_hex",
        F.sha2(F.array_join(F.transform(F.slice("findings", F.lit(1), F.col("n_base")), said), ","), 256).alias("base_sha256"),
        F.array_join(F.transform(ordered, said), ",").alias("spans"),
    )


def redact(docs: DataFrame, mask: str = "[secret]", key: str = "doc_id", text: str = "text") -> DataFrame:
    """Documents with every finding replaced; overlapping findings become one mask. All columns kept."""
    schema = docs.schema
    names = [f.name for f in schema]

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        compiled = compiled_patterns()
        for batch in batches:
            fixed = []
            for value in batch.column(names.index(text)):
                body = value.as_py()
                if body is not None:
                    base = base_findings(body, body.encode(), compiled)
                    spans = sorted((s, e) for s, _, _, e in (*base, *linked_findings(body, base, compiled)))
                    parts, at = [], 0
                    for s, e in spans:
                        if s >= at:
                            parts += [body[at:s], mask]
                        at = max(at, e)
                    body = "".join((*parts, body[at:]))
                fixed.append(body)
            columns = [pa.array(fixed, pa.string()) if n == text else batch.column(k) for k, n in enumerate(names)]
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return docs.mapInArrow(run, schema)


#: DuckDB: how many base findings of each kind a text has.
BASE_ORACLE = r"""
select doc_id,
  cast(len(list_filter(regexp_extract_all(coalesce(text, ''), '(?i:(password|passwd|secret|token|api_?key))["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)', 2), lambda x: len(x) >= 6)) as bigint) n_assign,
  cast(len(list_filter(regexp_extract_all(coalesce(text, ''), 'AKIA[A-Z0-9]+'), lambda x: len(x) >= 20)) as bigint) n_access,
  cast(len(list_filter(regexp_extract_all(coalesce(text, ''), '[0-9a-f]+'), lambda x: len(x) >= 24)) as bigint) n_hex from documents
"""
