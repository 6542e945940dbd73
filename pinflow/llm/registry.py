"""Queries and SQL of the training-data operators: thin ``opN_`` callables over whole tables."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from . import ann, bpe, exact_dedup, langid, minhash, mixing, sharding, suffix_dedup, token_counts, toxicity
from .common import read_table

BPE_FILE = "byte_bpe_multi_50k.tiktoken"
COUNT_FILE = "byte_bpe_multi_50k.tiktoken"


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixing_report(read_table(spark, sf_dir, "documents"))


def op2_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(read_table(spark, sf_dir, "documents"))


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.dedup_report(read_table(spark, sf_dir, "documents"))


def op4_vantage_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search_report(read_table(spark, sf_dir, "embeddings"))


def op5_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_report(read_table(spark, sf_dir, "documents"))


def op6_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.language_report(read_table(spark, sf_dir, "documents"))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity_report(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_report(read_table(spark, sf_dir, "documents"), public_tokenizers.path(COUNT_FILE))


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(read_table(spark, sf_dir, "documents"))


def op10_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encoding_report(read_table(spark, sf_dir, "documents"), public_tokenizers.path(BPE_FILE))


QUERIES = {f.__name__: f for f in (op1_mixing, op2_minhash, op3_suffix_dedup, op4_vantage_ann, op5_sharding, op6_langid, op7_toxicity, op8_token_counts, op9_exact_dedup, op10_bpe)}
ORACLES = {"op1_mixing": mixing.oracle(), "op9_exact_dedup": exact_dedup.ORACLE, "op2_minhash": minhash.ORACLE, "op3_suffix_dedup": suffix_dedup.ORACLE, "op4_vantage_ann": ann.ORACLE}
