"""The registered queries of the training-data operators, each over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import decontam, embeddings, minhash, mixing, quality, secrets, sharding, token_store, warc, wordpiece
from .common import table


def tokenizer_file(name: str = "byte_bpe_50k.json") -> str:
    """A vocabulary file of the installed public tokenizers."""
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.decontamination_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = warc.archive_round_trip(table(spark, sf_dir, "pages"))
    return out.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op4_near_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddings.near_duplicate_vectors(table(spark, sf_dir, "embeddings"))


def op5_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixing_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    starting, continuing = wordpiece.pieces_of_byte_vocabulary(tokenizer_file())
    return wordpiece.count_tokens(table(spark, sf_dir, "documents"), starting, continuing)


def op7_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_store.tokenize_to_shards(table(spark, sf_dir, "documents"), tokenizer_file())


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents"))


def op9_shard(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = sharding.shard_documents(table(spark, sf_dir, "documents"), shards=8)
    return out.select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard", "region", "rack")


def op10_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_report(table(spark, sf_dir, "documents"))


def secret_base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The part of op10 that SQL can express: base findings of each kind."""
    return secrets.find_secrets(table(spark, sf_dir, "documents")).select("doc_id", "n_assign", "n_access", "n_hex")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_quality, op2_decontaminate, op3_warc, op4_near_vectors, op5_mix, op6_token_counts, op7_token_shards, op8_near_duplicates, op9_shard, op10_secrets, secret_base_counts)}


def oracle_sql() -> dict[str, str]:
    return {"op2_decontaminate": decontam.ORACLE, "op3_warc": warc.ORACLE, "op4_near_vectors": embeddings.ORACLE, "op8_near_duplicates": minhash.ORACLE, "secret_base_counts": secrets.BASE_ORACLE}
