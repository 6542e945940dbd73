"""Stateless placements: hashing, modulo, round robin, contiguous ranges, seeded random. Pure expressions."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def hash_block(key, k: int, seed: int | None = None) -> F.Column:
    """32 bits of an MD5 modulo k: the same block in any engine."""
    text = key.cast("string") if seed is None else F.concat(F.lit(f"{seed}:"), key.cast("string"))
    return (F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("bigint") % k).cast("int")


def fast_hash_block(key, k: int) -> F.Column:
    return F.pmod(F.xxhash64(key), F.lit(k)).cast("int")


def hashing(vertices: DataFrame, k: int) -> DataFrame:
    return vertices.select("vertex_id", hash_block(F.col("vertex_id"), k).alias("block"))


def modulo(vertices: DataFrame, k: int) -> DataFrame:
    return vertices.select("vertex_id", F.pmod("vertex_id", F.lit(k)).cast("int").alias("block"))


def round_robin(vertices: DataFrame, k: int) -> DataFrame:
    return vertices.select("vertex_id", (F.col("seq") % k).cast("int").alias("block"))


def contiguous(vertices: DataFrame, k: int, n: int) -> DataFrame:
    return vertices.select("vertex_id", F.expr(f"int(seq * {k} div {n})").alias("block"))


def random_blocks(vertices: DataFrame, k: int, seed: int) -> DataFrame:
    return vertices.select("vertex_id", hash_block(F.col("vertex_id"), k, seed).alias("block"))


def edge_hash(edges: DataFrame, k: int) -> DataFrame:
    """Edge-at-a-time by hash: src, dst, block."""
    key = F.concat_ws("-", F.col("src").cast("string"), F.col("dst").cast("string"))
    return edges.select("src", "dst", hash_block(key, k).alias("block"))
