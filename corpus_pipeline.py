"""Corpus pipeline: language ID, exact dedup, near dedup, mixing, tokens. Each stage reads what the last one wrote.

All stages but the last return the columns of their input, whatever further ones are called. Nulls: a null text counts as
empty and goes with language ID; null ids, languages and sources are values like others. Repeated rows: one of each text is
left by exact dedup. Ties: the largest id stays among equal texts, the smallest among near copies. An empty table passes
through all stages as an empty table."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from pinflow.llm import bpe, exact_dedup, langid, minhash, mixing
from pinflow.llm.common import cut, discard, read_table


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without an identified language: null or empty texts, no letters, or no language ahead of the others."""
    return langid.keep_identified(docs)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts (A-Z lower-cased) the row with the largest id stays; one row of each text, also where ids repeat or are null."""
    return exact_dedup.keep_one(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of every component of near-duplicates the smallest id stays; rows with a null id are not compared and stay."""
    return minhash.keep_one(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Draws documents, and repeats of scarce ones, so that source, language and topic are raked to their target shares of tokens."""
    return mixing.keep_mixed(docs)


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token numbers and digests of what is left, with the decoded bytes' digest as the round trip's proof."""
    return bpe.encoding_report(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))


STAGES = [
    ("language_id", identify_language),
    ("exact_dedup", drop_exact_copies),
    ("minhash_near_dedup", drop_near_copies),
    ("source_mixing", mix_sources),
    ("bpe_encoding", encode_tokens),
]

#: Language ID has no SQL form; tests/llm/test_pipeline.py replays all stages by brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    before = None
    for name, stage in STAGES:
        after = cut(stage(spark, docs, sf_dir), f"stage-{name}")
        if before is not None:
            discard(before)
        docs = before = after
    return docs
