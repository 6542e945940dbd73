"""Token counts of documents in flat token files without an index.

A token file is a run of fixed-size blocks of 16-bit ids in which every document ends with a separator id.
Blocks are scanned on their own, each with one vectorised search for the separator; a prefix scan over a
file's blocks carries the number of separators and the place of the latest one across the block boundaries,
which is all that a document cut by boundaries needs.

Ids of the separator or above are an error: they would be cut to 16 bits or taken for a document's end.

Defined results: null and empty texts are documents of 0 tokens; a document may span any number of blocks; a tail
without a separator is a document with closed = false; repeated rows are counted like any other; empty tables
and files give no rows; further columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window as W, functions as F

from .bpe import codec, text_chunks
from .common import cut, require_columns

SEPARATOR = 50_256  # the first free id of the 50k tokenizer files
BLOCK = 1 << 16  # tokens


def token_files(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK, separator: int = SEPARATOR) -> DataFrame:
    """Rows (file_id, block_no, data) with data little-endian 16-bit ids, and rows (file_id, ordinal, doc) that name what was written.

    One file per input partition; the names only serve to give counts back to ids, the scan doesn't use them."""
    require_columns(docs, id_col, text_col)
    if not 0 <= separator < 1 << 16:
        raise ValueError("the separator must fit 16 bits")

    def run(batches):
        tool, file_id = codec(path), TaskContext.get().partitionId()
        end = np.array([separator], dtype="<u2")
        held, size, number, ordinal = [], 0, 0, 0

        def blocks(last: bool):
            nonlocal held, size, number
            flat = np.concatenate(held) if held else np.empty(0, dtype="<u2")
            full = len(flat) if last else len(flat) // block * block
            out = [flat[i : min(i + block, full)].tobytes() for i in range(0, full, block)]
            held, size = [flat[full:]], len(flat) - full
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([file_id] * len(out), pa.int32()), pa.array(range(number, number + len(out)), pa.int64()), pa.array(out, pa.binary()), pa.nulls(len(out), pa.int64())], ["file_id", "number", "data", "doc"])
            number += len(out)

        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            for a, z in text_chunks(texts):
                for ids in tool.encode(texts[a:z]):
                    if len(ids) and int(ids.max()) >= separator:
                        raise ValueError(f"id {int(ids.max())} is not below the separator {separator}")
                    held += [ids.astype("<u2"), end]
                    size += len(ids) + 1
                if size >= 16 * block:
                    yield from blocks(False)
            n = len(texts)
            yield pa.RecordBatch.from_arrays([pa.array([file_id] * n, pa.int32()), pa.array(range(ordinal, ordinal + n), pa.int64()), pa.nulls(n, pa.binary()), batch.column(0)], ["file_id", "number", "data", "doc"])
            ordinal += n
        yield from blocks(True)

    return docs.select(F.col(id_col).cast("long"), text_col).mapInArrow(run, "file_id int, number bigint, data binary, doc bigint")


def scan_separators(files: DataFrame, separator: int = SEPARATOR, block: int = BLOCK) -> DataFrame:
    """(file_id, number, size, n_ends, first_end, last_end, inner): positions count from the file's start; inner has the lengths between a block's own separators."""

    def run(batches):
        for batch in batches:
            rows = []
            for file_id, number, data in zip(*(batch.column(i).to_pylist() for i in range(3))):
                ids = np.frombuffer(data, dtype="<u2")
                at = np.flatnonzero(ids == separator) + number * block
                rows.append((file_id, number, len(ids), len(at), int(at[0]) if len(at) else None, int(at[-1]) if len(at) else None, np.diff(at) - 1))
            cols = list(zip(*rows)) if rows else [[]] * 7
            types = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64())]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], ["file_id", "number", "size", "n_ends", "first_end", "last_end", "inner"])

    return files.select("file_id", "number", "data").mapInArrow(run, "file_id int, number bigint, size bigint, n_ends bigint, first_end bigint, last_end bigint, inner array<bigint>")


def stitch(blocks: DataFrame) -> DataFrame:
    """(file_id, ordinal, n_tokens, closed) by a prefix scan over each file's block summaries."""
    before = W.partitionBy("file_id").orderBy("number").rowsBetween(W.unboundedPreceding, -1)
    carried = blocks.withColumns({
        "base": F.coalesce(F.sum("n_ends").over(before), F.lit(0)),
        "prior": F.coalesce(F.last("last_end", ignorenulls=True).over(before), F.lit(-1)),
    })
    lengths = F.concat(F.array(F.col("first_end") - F.col("prior") - 1), "inner")
    closed = carried.filter("n_ends > 0").select("file_id", "base", F.posexplode(lengths).alias("k", "n_tokens")).select("file_id", (F.col("base") + F.col("k")).alias("ordinal"), "n_tokens", F.lit(True).alias("closed"))
    ends = blocks.groupBy("file_id").agg(F.sum("size").alias("all"), F.sum("n_ends").alias("ordinal"), F.coalesce(F.max("last_end"), F.lit(-1)).alias("last"))
    tail = ends.filter("all - 1 > last").select("file_id", "ordinal", (F.col("all") - 1 - F.col("last")).alias("n_tokens"), F.lit(False).alias("closed"))
    return closed.union(tail)


def count_report(docs: DataFrame, path: str, block: int = BLOCK) -> DataFrame:
    """doc_id, file_id, ordinal, n_tokens: token files are written to the shared folder, then scanned."""
    written = cut(token_files(docs, path, block=block), "token-files")
    counts = stitch(scan_separators(written.filter("data is not null"), block=block))
    names = written.filter("data is null").select("file_id", F.col("number").alias("ordinal"), F.col("doc").alias("doc_id"))
    return names.join(counts, ["file_id", "ordinal"]).select("doc_id", "file_id", "ordinal", "n_tokens")
