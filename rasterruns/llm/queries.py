"""The queries of the training-data operators and the SQL that checks them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rasterruns.llm import bpe, chat_windows, embedding_join, language_fusion, minhash_dedup, mixing, oracles, ordinal_quality, resharding, suffix_dedup, vector_file
from rasterruns.llm.common import table
from rasterruns.runtime import shared_file


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return bpe.round_trip_digests(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op2_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash_dedup.near_duplicates(table(spark, sf_dir, "documents"), words=3, percent=85)


def op3_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_join.near_duplicates(table(spark, sf_dir, "embeddings"))


def op4_vector_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_file.search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op5_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return resharding.digests(table(spark, sf_dir, "documents"), shared_file(spark, "shards"))


def op6_chat_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    text = "</s>[INST] ok [/INST]"
    probe = spark.createDataFrame([(-7, 0, "user", text), (-7, 1, "assistant", text)], turns.schema)
    return chat_windows.conversation_digests(chat_windows.format_windows(turns.union(probe), charged=False))


def op7_ordinal_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ordinal_quality.scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.removal_digests(table(spark, sf_dir, "documents"))


def op9_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def op10_language_fusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_fusion.identify(table(spark, sf_dir, "pages"), table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_byte_bpe, op2_minhash_dedup, op3_embedding_dedup, op4_vector_search, op5_sharding, op6_chat_windows, op7_ordinal_quality, op8_suffix_dedup, op9_source_mixing, op10_language_fusion)}


def oracle_sql() -> dict[str, str]:
    """The others are tested against brute force: SQL has no merges, flows, trained models or seeded hashes."""
    return {"op2_minhash_dedup": oracles.OP2, "op3_embedding_dedup": oracles.OP3, "op4_vector_search": oracles.OP4, "op6_chat_windows": oracles.OP6}
