"""Two-pass external shuffle into shards.

Pass one counts the bytes and scatters records uniformly over buckets small enough for memory, by a seeded
hash of the record. Pass two holds one bucket at a time, orders it by id, applies a seeded Fisher-Yates
shuffle and streams it out. The concatenation of the shuffled buckets is one random permutation of all
records; cutting it at even row positions gives shards whose counts differ by one at most (law ``rows``).

Defined results: null texts have size 16 (no bytes); nulls hash like values; repeated rows are dealt like
any other (records alike in id and text that are more than a bucket's share are spread over several, and docs is
written once more for that); an empty table gives an empty result; further columns ride along unchanged, except that the operator's own shard and slot
replace columns of these names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from .common import cut, numbered, require_columns, shuffle_width, trimmed

RECORD_OVERHEAD = 16


def record_size(text) -> F.Column:
    return (F.coalesce(F.octet_length(text), F.lit(0)) + RECORD_OVERHEAD).cast("long")


def fisher_yates(n: int, rng: np.random.Generator) -> np.ndarray:
    """A uniform permutation; numpy's in-place shuffle walks down the array swapping with a random earlier slot."""
    order = np.arange(n)
    rng.shuffle(order)
    return order


def external_shuffle(docs: DataFrame, shards: int = 40, seed: int = 11, bucket_bytes: int = 32 << 20, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All columns of docs with shard (int) and slot (long, gapless from 0 in each shard)."""
    if shards < 1:
        raise ValueError("shards must be positive")
    require_columns(docs, id_col, text_col)
    docs = docs.drop("shard", "slot")
    names = docs.columns
    docs, id_col, text_col = numbered(docs), f"c{names.index(id_col)}", f"c{names.index(text_col)}"
    spark = docs.sparkSession
    key = F.xxhash64(F.lit(seed), F.col(id_col), F.xxhash64(F.col(text_col)))
    size = docs.agg(F.coalesce(F.sum(record_size(F.col(text_col))), F.lit(0)).alias("b")).first()["b"]  # one row
    buckets = max(2 * shuffle_width(spark), -(-int(size) // bucket_bytes))
    marker = "__salt" + "_" * max(map(len, names))  # longer than any name of docs
    share = max(1000, -(-docs.count() // buckets))
    # A record that repeats more often than a bucket has rows: fewer such than buckets, so they can be broadcast.
    often = docs.groupBy(key.alias("__key")).agg(F.count("*").alias("__n")).filter(F.col("__n") > share)
    often = often.select("__key", F.ceil(F.col("__n") / share).cast("int").alias("__spread"))
    if not often.isEmpty():
        width = len(docs.columns)
        salted = docs.withColumn("__key", key).join(F.broadcast(often), "__key", "left")
        salt = F.pmod(F.monotonically_increasing_id(), F.coalesce("__spread", F.lit(1)))
        docs = cut(salted.withColumn("__salt", salt).select(*docs.columns, "__salt"), "salted")  # the salts hold from here on
        docs, key = docs.withColumnRenamed("__salt", f"c{width}"), F.xxhash64(F.lit(seed), F.col(id_col), F.xxhash64(F.col(text_col)), F.col(f"c{width}"))
        names = [*names, marker]
    bucket = F.pmod(key, F.lit(buckets)).cast("int")
    # One pair per bucket, so the number is bounded by bytes / bucket_bytes: 100 TB make 3 million, 24 MB of offsets.
    counts = {r["b"]: r["n"] for r in docs.groupBy(bucket.alias("b")).agg(F.count("*").alias("n")).toLocalIterator()}
    sizes = np.array([counts.get(b, 0) for b in range(buckets)], dtype=np.int64)
    firsts = np.concatenate([[0], np.cumsum(sizes)])
    total = int(firsts[-1])
    offsets = spark.sparkContext.broadcast(firsts)
    out = StructType([*docs.schema.fields, StructField("shard", IntegerType()), StructField("slot", LongType())])
    width = len(docs.columns)

    def place(table: pa.Table, b: int):
        first = int(offsets.value[b])
        order = fisher_yates(table.num_rows, np.random.default_rng([seed, b]))
        at = first + np.arange(table.num_rows, dtype=np.int64)
        shard = at * shards // total
        slot = at - -(-shard * total // shards)
        table = table.take(pa.array(order))
        for batch in table.append_column("shard", pa.array(shard.astype(np.int32))).append_column("slot", pa.array(slot)).combine_chunks().to_batches(max_chunksize=4096):
            yield batch

    def shuffle_buckets(batches):
        held, current = [], None
        for batch in batches:
            ids = batch.column(width).to_numpy(zero_copy_only=False)
            rows = batch.select(list(range(width)))
            edges = [0, *(np.flatnonzero(np.diff(ids)) + 1).tolist(), len(ids)]
            for a, z in zip(edges, edges[1:]):
                if a == z:
                    continue
                if current is not None and ids[a] != current:
                    yield from place(pa.Table.from_batches(held), current)
                    held = []
                current = int(ids[a])
                held.append(rows.slice(a, z - a))
        if held:
            yield from place(pa.Table.from_batches(held), current)

    tasks = min(buckets, max(4 * shuffle_width(spark), buckets // 4))
    return (
        docs.withColumn("__bucket", bucket)
        .repartition(tasks, "__bucket")
        .sortWithinPartitions("__bucket", id_col, F.xxhash64(F.col(text_col)))
        .mapInArrow(trimmed(shuffle_buckets), out)
        .toDF(*names, "shard", "slot")
        .drop(marker)
    )


def shard_report(docs: DataFrame, shards: int = 40) -> DataFrame:
    placed = external_shuffle(docs.select("doc_id", "text"), shards)
    return placed.select(
        "doc_id",
        record_size(F.col("text")).alias("size"),
        F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"),
        F.lit("rows").alias("law"),
        "shard",
        "slot",
        F.lit(None).cast("int").alias("grown_shard"),
    )


def write_shards(docs: DataFrame, path: str, shards: int = 40, **how) -> None:
    """Parquet files by shard, rows in slot order."""
    external_shuffle(docs, shards, **how).repartition("shard").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
