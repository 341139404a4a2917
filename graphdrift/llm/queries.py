"""Registered queries of the text operators, with their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from graphdrift.llm import common, merkle, mixing, pieces, pu_quality, sharding, suffix_dedup, superminhash, token_scan, transcripts, webp


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixed_documents(common.read_documents(spark, sf_dir))


def op2_webp_payloads(spark: SparkSession, sf_dir: str) -> DataFrame:
    return webp.media_digests(common.read_documents(spark, sf_dir))


def op3_repeated_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.removal_digests(common.read_documents(spark, sf_dir))


def op4_quality_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pu_quality.quality_scores(common.read_documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op5_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return superminhash.near_duplicates(common.read_documents(spark, sf_dir), percent=85)


def op6_merkle_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return merkle.compare_next(common.read_documents(spark, sf_dir))


def op7_shard_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(common.read_documents(spark, sf_dir))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_scan.token_counts(common.read_documents(spark, sf_dir))


def op9_transcript_roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return transcripts.recovered_roles(spark.read.parquet(f"{sf_dir}/conversations.parquet"))


def op10_piece_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.piece_digests(common.read_documents(spark, sf_dir))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if name.startswith("op") and name[2].isdigit()}


def oracle_sql() -> dict[str, str]:
    return {"op1_mix_sources": mixing.mix_sql()}
