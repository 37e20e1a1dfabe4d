"""A training corpus from the documents table: five stages, each over all that its predecessor kept.

STAGES are (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame that is written and
read again as the next one's docs. All but the last return the columns of documents.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quorumlab.llm import decontam, minhash, mixing, quality, token_store
from quorumlab.llm.common import table, written
from quorumlab.llm.queries import tokenizer_file

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Target token shares. Low quality isn't among them, as the first stage has removed it.
TARGETS = {"clean": 0.97, "toxic": 0.03}


def _only(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The documents whose id is among ids; null ids match each other."""
    return docs.join(ids.select(F.col("doc_id").alias("_id")), F.col("doc_id").eqNullSafe(F.col("_id")), "left_semi").select(*COLUMNS)


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that the quality classifier predicts as label 0."""
    judged = quality.classify(docs, table(spark, sf_dir, "labels"))
    return _only(docs, judged.where("predicted = 1"))


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one document of each group of near-duplicates, that with the smallest id."""
    return _only(docs, minhash.near_duplicates(docs).where("kept"))


def keep_clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents contaminated by benchmark passages."""
    return decontam.drop_contaminated(docs, table(spark, sf_dir, "benchmark")).select(*COLUMNS)


def mix_domains(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeat or thin documents so that expected domain totals match the target weights."""
    return mixing.mix(docs.select(*COLUMNS), table(spark, sf_dir, "labels"), TARGETS)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Encode into sorted-string-table shards and read them back: doc_id, start, n_tokens, ids_crc32."""
    return token_store.tokenize_to_shards(docs, tokenizer_file())


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality", keep_good), ("near-duplicates", keep_one_of_each), ("decontamination", keep_clean), ("mixing", mix_domains), ("tokens", write_tokens),
]

#: A learned classifier and hashed copies have no SQL form; tests hold the stages against brute force on the smallest tables.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
