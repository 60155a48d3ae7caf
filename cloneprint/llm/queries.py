"""The registered queries of this subpackage and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import decontaminate, embedding_dedup, language_id, minhash_dedup, packing, quality, substring_dedup, token_ids, token_rollup, warc
from .common import read_table
from .encode import public_path


def op7_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash_dedup.near_duplicates(read_table(spark, sf_dir, "documents", "doc_id", "text"))


def op4_token_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_ids.round_trip(read_table(spark, sf_dir, "documents", "doc_id", "text"), public_path(), end=2)


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(read_table(spark, sf_dir, "documents", "doc_id", "text"), public_path(), window=1024, end=0)


def op1_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(read_table(spark, sf_dir, "pages", "page_id", "url", "html"), least=0)


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(read_table(spark, sf_dir, "documents", "doc_id", "text", "lang"))


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(read_table(spark, sf_dir, "documents", "doc_id", "text"), read_table(spark, sf_dir, "labels", "doc_id", "quality"))


def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(read_table(spark, sf_dir, "documents", "doc_id", "text"), read_table(spark, sf_dir, "benchmark"))


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.dedup_units(read_table(spark, sf_dir, "documents", "doc_id", "text"))


def op5_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_rollup.replay(read_table(spark, sf_dir, "documents", "doc_id", "text", "source", "lang"), read_table(spark, sf_dir, "labels"))


def op6_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.near_duplicates(read_table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_warc": op1_warc,
    "op2_language_id": op2_language_id,
    "op3_decontamination": op3_decontamination,
    "op4_token_ids": op4_token_ids,
    "op5_token_rollup": op5_token_rollup,
    "op6_embedding_dedup": op6_embedding_dedup,
    "op7_minhash_dedup": op7_minhash_dedup,
    "op8_substring_dedup": op8_substring_dedup,
    "op9_quality": op9_quality,
    "op10_packing": op10_packing,
}
ORACLE: dict[str, str] = {"op5_token_rollup": token_rollup.REPLAY_SQL}
