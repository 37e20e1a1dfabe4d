"""Benchmark decontamination by a broadcast table of normalised word n-grams.

Words are runs of digits, letters a-z (A-Z lowered) and characters beyond ASCII. An item's windows are its
runs of ``window`` consecutive words; an item with fewer words, but some, is one window. Every position of
every document is looked up in the table of window hashes; a found position is verified word by word
before it counts. The scan carries hashes only, so its cost is in proportion to the text, however long; verification reads
the texts with found positions once more, and shuffles them only if the positions are too many to broadcast.

Defined cases: null and empty texts have no words and no hits; null items, or items with a null id, have
no windows; repeated document rows give a result row each; windows shared by items hit all of them;
an empty benchmark leaves every document clean; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower_bytes, spare, written

#: The pattern of a word after lowering, and its complement with capitals kept.
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
WORD_ANY_CASE = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
#: Table bytes (windows and item lists) up to which the window table is broadcast; larger ones are joined by shuffle.
BROADCAST_BYTES = 256 << 20


def word_list(text: Column) -> Column:
    return F.regexp_extract_all(ascii_lower_bytes(text), F.lit(WORD), F.lit(0))


def _grams(hashes: Column, size: int) -> Column:
    """Hash of each run of ``size`` word hashes, in order; empty if there are fewer."""
    last = F.size(hashes) - size
    return F.when(last >= 0, F.transform(F.sequence(F.lit(0), last), lambda i: F.xxhash64(F.slice(hashes, i + 1, size)))).otherwise(
        F.array().cast("array<bigint>")
    )


def window_table(benchmark: DataFrame, window: int = 13) -> DataFrame:
    """One row for each distinct window: gram hash, its words, its length, and the items that have it."""
    words = benchmark.where(F.col("item_id").isNotNull()).select(F.col("item_id").cast("string").alias("item"), word_list(F.col("text")).alias("w"))
    size = F.least(F.size("w"), F.lit(window))
    starts = F.explode(F.sequence(F.lit(1), F.size("w") - size + 1))
    runs = words.where(F.size("w") > 0).select("item", size.alias("len"), "w", starts.alias("at"))
    runs = runs.select("item", "len", F.slice("w", F.col("at"), F.col("len")).alias("run"))
    runs = runs.select("item", "len", F.xxhash64(F.transform("run", lambda x: F.xxhash64(x))).alias("gram"), F.array_join("run", " ").alias("words"))
    return runs.groupBy("gram", "len", "words").agg(F.array_sort(F.collect_set("item")).alias("items"))


def _covered(spans: Column) -> Column:
    """How many positions the union of [at, at + len) covers; spans sorted by start."""
    zero = F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("n"))

    def step(a: Column, s: Column) -> Column:
        end = s["at"] + s["len"]
        fresh = F.greatest(end - F.greatest(s["at"], a["end"]), F.lit(0))
        return F.struct(F.greatest(a["end"], end).alias("end"), (a["n"] + fresh).alias("n"))

    return F.aggregate(spans, zero, step, lambda a: a["n"])


def find_windows(docs: DataFrame, benchmark: DataFrame, window: int = 13, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per document row: key, n_words, spans (sorted array of verified word runs: at from 0, len), items (sorted ids)."""
    table = window_table(benchmark, window)
    known = table.groupBy("len").agg(F.sum(F.octet_length("words") + 64 + 24 * F.size("items")).alias("bytes")).collect()
    sizes = sorted((r["len"] for r in known), reverse=True)  # at most `window` lengths
    small = sum(r["bytes"] for r in known) <= BROADCAST_BYTES

    # Only the hashes are exploded: a row that carried the words would cost a text the square of its length.
    base = docs.select(F.col(key).alias("doc_id"), F.xxhash64(F.col(text)).alias("_text"), F.transform(word_list(F.col(text)), lambda x: F.xxhash64(x)).alias("h"))
    marker = F.array(F.lit(None).cast("bigint"))  # position 0: one row for each document, found or not
    all_grams = F.concat(marker, *[_grams(F.col("h"), n) for n in sizes])
    # The grams stay an expression of the generator: for a column of its own Spark would infer a filter on its size, and compute the words once more for each position.
    places = base.select("doc_id", "_text", F.size("h").alias("n_words"), "h").select("doc_id", "_text", "n_words", F.posexplode(all_grams).alias("slot", "gram"))
    # Where the part for a length begins in all_grams.
    offset, begins = F.lit(1), {}
    for n in sizes:
        begins[n] = offset
        offset = offset + F.greatest(F.col("n_words") - F.lit(n - 1), F.lit(0))
    at = F.lit(None).cast("int")
    for n in sizes:
        at = F.when(F.col("len") == n, F.col("slot") - begins[n]).otherwise(at)
    fit = lambda df: F.broadcast(df) if small else df
    found = places.join(fit(table.select(F.col("gram").alias("_gram"), "len").distinct()), F.col("gram") == F.col("_gram"), "left")
    found = found.where((F.col("slot") == 0) | F.col("len").isNotNull()).select("doc_id", "_text", "n_words", "slot", F.when((at >= 0) & (at + F.col("len") <= F.col("n_words")), F.struct(at.alias("at"), F.col("len"))).alias("span"))
    per_doc = found.groupBy("doc_id", "_text").agg(F.max("n_words").cast("long").alias("n_words"), F.count_if(F.col("slot") == 0).alias("_rows"), F.collect_set("span").alias("maybe"))
    per_doc = written(per_doc, "window-hits")

    # Positions with a known hash are verified by their words, in the texts that have some.
    hits = per_doc.where(F.size("maybe") > 0).select(F.col("doc_id").alias("_id"), F.col("_text").alias("_hash"), "maybe")
    bytes_of_hits = hits.agg(F.sum(64 + 24 * F.size("maybe"))).first()[0] or 0
    bodies = docs.select(F.col(key).alias("_key"), F.xxhash64(F.col(text)).alias("_body_hash"), F.col(text).alias("_body"))
    same = F.col("_key").eqNullSafe(F.col("_id")) & F.col("_body_hash").eqNullSafe(F.col("_hash"))
    bodies = bodies.join(F.broadcast(hits) if bytes_of_hits <= BROADCAST_BYTES else hits, same)
    run = lambda w, s: F.struct(s["at"].alias("at"), s["len"].alias("len"), F.array_join(F.slice(w, s["at"] + 1, s["len"]), " ").alias("words"))
    runs = F.transform(F.array(word_list(F.col("_body"))), lambda w: F.transform("maybe", lambda s: run(w, s)))[0]  # words are split once, as a lambda's argument
    runs = bodies.select("_id", "_hash", F.explode(runs).alias("run")).select("_id", "_hash", F.struct("run.at", "run.len").alias("span"), F.col("run.len").alias("_len"), F.col("run.words").alias("_words"))
    sure = runs.join(fit(table.select("len", "words", "items")), (F.col("_len") == F.col("len")) & (F.col("_words") == F.col("words")))
    sure = sure.groupBy("_id", "_hash").agg(F.array_sort(F.collect_set("span")).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
    both = per_doc.join(sure, F.col("doc_id").eqNullSafe(F.col("_id")) & F.col("_text").eqNullSafe(F.col("_hash")), "left")
    none = lambda c, kind: F.coalesce(c, F.array().cast(kind)).alias(c)
    return both.select("doc_id", "_text", "n_words", "_rows", none("spans", "array<struct<at:int,len:int>>"), none("items", "array<string>"))


def judge(found: DataFrame, least_share: int = 20) -> DataFrame:
    """Add n_hit, n_items, items_sha256 and contaminated: some hit word, and at least one word in ``least_share`` hit."""
    out = found.withColumn("n_hit", _covered(F.col("spans"))).withColumn("n_items", F.size("items").cast("long"))
    out = out.withColumn("items_sha256", F.sha2(F.array_join("items", ","), 256))
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (F.lit(least_share) * F.col("n_hit") >= F.col("n_words")))


def decontamination_report(docs: DataFrame, benchmark: DataFrame, window: int = 13, key: str = "doc_id", text: str = "text") -> DataFrame:
    out = judge(find_windows(docs, benchmark, window, key, text))
    out = out.withColumn("_copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_rows"))))
    return out.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = 13, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents without the contaminated ones, all columns kept."""
    h, bad_id, bad_text = spare(docs, "_text", "_bad", "_bad_text")
    bad = judge(find_windows(docs, benchmark, window, key, text)).where("contaminated").select(F.col("doc_id").alias(bad_id), F.col("_text").alias(bad_text))
    marked = docs.withColumn(h, F.xxhash64(F.col(text)))
    return marked.join(bad, F.col(key).eqNullSafe(F.col(bad_id)) & F.col(h).eqNullSafe(F.col(bad_text)), "left_anti").drop(h)


def remove_spans(docs: DataFrame, benchmark: DataFrame, window: int = 13, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents with every hit word cut from the text; separators stay. Untouched texts come back unchanged."""
    h, hit_id, hit_text, spans = spare(docs, "_text", "_hit", "_hit_text", "_spans")
    found = find_windows(docs, benchmark, window, key, text).where(F.size("spans") > 0)
    hits = found.select(F.col("doc_id").alias(hit_id), F.col("_text").alias(hit_text), F.col("spans").alias(spans))
    body = docs.withColumn(h, F.xxhash64(F.col(text)))
    both = body.join(hits, F.col(key).eqNullSafe(F.col(hit_id)) & F.col(h).eqNullSafe(F.col(hit_text)), "left")
    words, gaps = F.regexp_extract_all(F.col(text), F.lit(WORD_ANY_CASE), F.lit(0)), F.split(F.col(text), WORD_ANY_CASE)
    kept = F.transform(words, lambda w, i: F.when(F.exists(spans, lambda s: (s["at"] <= i) & (i < s["at"] + s["len"])), F.lit("")).otherwise(w))
    rebuilt = F.array_join(F.zip_with(gaps, kept, lambda g, w: F.concat(g, F.coalesce(w, F.lit("")))), "")
    return both.withColumn(text, F.when(F.col(spans).isNotNull(), rebuilt).otherwise(F.col(text))).drop(h, hit_id, hit_text, spans)


#: DuckDB: every window, every position, joined by its words.
ORACLE = r"""
with d as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') w from documents),
b as (select item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') w from benchmark),
bw as (select item_id, w, least(len(w), 13) k, unnest(generate_series(1, len(w) - least(len(w), 13) + 1)) i from b where len(w) > 0),
g as (select distinct item_id, k, array_to_string(w[i:i + k - 1], ' ') s from bw),
ks as (select distinct k from g),
dw as (select doc_id, w, k, unnest(generate_series(1, len(w) - k + 1)) i from d, ks where len(w) >= k),
h as (select doc_id, i, x.k, item_id from (select doc_id, i, k, array_to_string(w[i:i + k - 1], ' ') s from dw) x join g on x.k = g.k and x.s = g.s),
hit as (select doc_id, count(distinct p) n from (select doc_id, unnest(generate_series(i, i + k - 1)) p from (select distinct doc_id, i, k from h)) group by 1),
items as (select doc_id, count(*) n, string_agg(x, ',' order by x) s from (select distinct doc_id, cast(item_id as varchar) x from h) group by 1)
select d.doc_id, cast(len(w) as bigint) n_words, cast(coalesce(hit.n, 0) as bigint) n_hit, cast(coalesce(items.n, 0) as bigint) n_items,
  sha256(coalesce(items.s, '')) items_sha256, coalesce(hit.n, 0) > 0 and 20 * coalesce(hit.n, 0) >= len(w) contaminated
from d left join hit using (doc_id) left join items using (doc_id)
"""
