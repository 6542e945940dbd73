"""Joins on keys of which a few hold much of a table."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def salted_join(left: DataFrame, right: DataFrame, key: str, share: float = 0.01, salts: int = 32, how: str = "inner") -> DataFrame:
    """left join right on ``key``, where keys with more than ``share`` of left's rows are dealt over ``salts`` tasks.

    There are fewer than 1 / share such keys, so the table of them is broadcast; right's rows of these keys, and no others, are
    repeated for every salt. how: 'inner' or 'left'. Null keys join nothing and stay in a left join."""
    if how not in ("inner", "left"):
        raise ValueError("how is 'inner' or 'left'")
    total = left.count()
    hot = left.groupBy(key).agg(F.count("*").alias("__n")).filter((F.col("__n") > share * total) & F.col(key).isNotNull()).select(key, F.lit(salts).alias("__salts"))
    width = F.coalesce("__salts", F.lit(1))
    a = left.join(F.broadcast(hot), key, "left").withColumn("__salt", F.pmod(F.xxhash64(*left.columns), width).cast("int")).drop("__salts")
    b = right.join(F.broadcast(hot), key, "left").withColumn("__salt", F.explode(F.sequence(F.lit(0), width - 1))).drop("__salts")
    return a.join(b, [key, "__salt"], how).drop("__salt")
