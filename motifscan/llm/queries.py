"""The queries of the training-data operators, as __spark_entry__.py registers them, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from motifscan.llm import ann, bpe, flac, langid, licences, lines, mixing, neardup, oracles, repeats, sharding
from motifscan.llm.common import table


def op1_flac(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flac.to_media(table(spark, sf_dir, "documents"))


def op2_pivotal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.plan_mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op3_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lines.dedup_report(table(spark, sf_dir, "documents"))


def op4_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op5_splitters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_by_bytes(table(spark, sf_dir, "documents"), shards=40)


def op6_cross_polytope(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(table(spark, sf_dir, "embeddings"))


def op7_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan_licences(table(spark, sf_dir, "documents"))


def op8_recompression(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.dedup_substrings(table(spark, sf_dir, "documents"))


def op9_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return langid.identify(docs, langid.learn(docs))


def op10_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"), percent=85)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_flac": op1_flac,
        "op2_pivotal": op2_pivotal,
        "op3_lines": op3_lines,
        "op4_bpe": op4_bpe,
        "op5_splitters": op5_splitters,
        "op6_cross_polytope": op6_cross_polytope,
        "op7_licences": op7_licences,
        "op8_recompression": op8_recompression,
        "op9_crf": op9_crf,
        "op10_minhash": op10_minhash,
    }


def oracle_sql() -> dict[str, str]:
    return {"op3_lines": oracles.LINES, "op8_recompression": oracles.SUBSTRINGS, "op10_minhash": oracles.NEAR_DUPLICATES}
