"""Room in blocks: acceptance in arrival order and water-filling, without a window over a whole block."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window as W, functions as F

from ..lineage import cut

SLICE = 4096  # ranks within a slice are counted in one window; slices carry prefix sums


def rank_in(df: DataFrame, group: str, order: str, width: int = SLICE) -> DataFrame:
    """Adds rank (from 0) by ``order`` (a dense bigint) within ``group``: slices of the order are counted apart and stitched.

    A window holds rows of one slice, another one row per slice; no group is one task's window."""
    sliced = df.withColumn("__slice", F.floor(F.col(order) / width))
    sizes = sliced.groupBy(group, "__slice").agg(F.count("*").alias("__n"))
    firsts = sizes.select(group, "__slice", (F.sum("__n").over(W.partitionBy(group).orderBy("__slice")) - F.col("__n")).alias("__first"))
    local = F.row_number().over(W.partitionBy(group, "__slice").orderBy(order)) - 1
    return sliced.withColumn("__local", local).join(firsts, [group, "__slice"]).withColumn("rank", F.col("__first") + F.col("__local")).drop("__slice", "__local", "__first")


def accept(wishes: DataFrame, free: list[int]) -> DataFrame:
    """wishes (seq, block, ...) with accepted: the first free[block] of each block, by seq."""
    room = F.array(*[F.lit(int(x)) for x in free])  # k numbers
    return rank_in(wishes, "block", "seq").withColumn("accepted", F.col("rank") < F.element_at(room, F.col("block") + 1)).drop("rank")


def fill_plan(loads: list[int], capacity: int) -> tuple[np.ndarray, np.ndarray, list[list[int]]]:
    """Where the t-th of a row of vertices without votes goes when each takes the lightest block (smallest id first).

    Returns segment starts in t, base levels and the blocks of each segment: within a segment the same blocks take turns."""
    order = sorted(range(len(loads)), key=lambda b: (loads[b], b))
    starts, levels, members = [0], [], []
    active: list[int] = []
    i = 0
    while i < len(order):
        level = loads[order[i]]
        while i < len(order) and loads[order[i]] == level:
            active.append(order[i])
            i += 1
        top = loads[order[i]] if i < len(order) else capacity
        levels.append(level)
        members.append(sorted(active))
        starts.append(starts[-1] + (min(top, capacity) - level) * len(active) if top > level else starts[-1])
    return np.array(starts, dtype=np.int64), np.array(levels, dtype=np.int64), members


def fill(rest: DataFrame, loads: list[int], capacity: int, rank: str = "rank") -> DataFrame:
    """rest with block by rank (0..): a search among at most k segments replaces the range join. More rows than room are an error."""
    starts, _, members = fill_plan(loads, capacity)
    sizes = np.array([len(m) for m in members], dtype=np.int64)
    flat, first = np.concatenate([np.array(m, dtype=np.int32) for m in members]), np.cumsum(sizes) - sizes

    @F.pandas_udf("int")
    def slot(t: pd.Series) -> pd.Series:
        at = t.to_numpy()
        if len(at) and at.max() >= starts[-1]:
            raise ValueError(f"{starts[-1]} places are free, row {at.max()} has none")
        segment = np.minimum(np.searchsorted(starts, at, side="right") - 1, len(sizes) - 1)
        return pd.Series(flat[first[segment] + (at - starts[segment]) % sizes[segment]])

    return rest.withColumn("block", slot(F.col(rank)))


def filled_loads(loads: list[int], capacity: int, count: int) -> list[int]:
    """The loads after ``fill`` gave ``count`` vertices their places."""
    starts, levels, members = fill_plan(loads, capacity)
    out = list(loads)
    for start, end, level, own in zip(starts, starts[1:], levels, members):
        rounds, extra = divmod(max(0, min(int(end), count) - int(start)), len(own))
        if count > start:
            for i, b in enumerate(own):
                out[b] = int(level) + rounds + (i < extra)
    return out


def accept_weighted(wishes: DataFrame, free: list[float], width: int = SLICE) -> DataFrame:
    """wishes (seq, block, c, ...) with accepted: by arrival, as long as a block's room holds all weights so far."""
    sliced = wishes.withColumn("__slice", F.floor(F.col("seq") / width))
    sums = sliced.groupBy("block", "__slice").agg(F.sum("c").alias("__c"))
    firsts = sums.select("block", "__slice", (F.sum("__c").over(W.partitionBy("block").orderBy("__slice")) - F.col("__c")).alias("__first"))
    local = F.sum("c").over(W.partitionBy("block", "__slice").orderBy("seq").rowsBetween(W.unboundedPreceding, 0))
    room = F.element_at(F.array(*[F.lit(float(x)) for x in free]), F.col("block") + 1)  # k numbers
    summed = sliced.withColumn("__local", local).join(firsts, ["block", "__slice"])
    return summed.withColumn("accepted", F.col("__first") + F.col("__local") <= room).drop("__slice", "__local", "__first")


FILLED = "seq bigint, vertex_id bigint, c double, block int"


def fill_weighted(rest: DataFrame, loads: list[float], capacity: float, count: int, width: int = 1 << 20) -> DataFrame:
    """rest (seq, vertex_id, c) with block: by arrival, each to the lightest block.

    Slices of about ``width`` rows share out the blocks' room by their weight and are filled side by side; what a share
    can't hold is left for the next pass, and the last slice takes the lightest block of all, room or not."""
    import pyarrow as pa

    rest = rest.select("seq", "vertex_id", "c")
    slices = -(-count // width)
    if slices > 1:
        ends = rest.agg(F.min("seq").alias("lo"), F.max("seq").alias("hi")).first()  # one row
        place = F.floor((F.col("seq") - ends["lo"]) * slices / (ends["hi"] - ends["lo"] + 1)).cast("int")
        rest = rest.withColumn("slice", place)
        weights = {r["slice"]: r["c"] for r in rest.groupBy("slice").agg(F.sum("c").alias("c")).collect()}  # one row per slice
        whole = sum(weights.values()) or 1.0
        shares = {s: [max(0.0, capacity - x) * w / whole for x in loads] for s, w in weights.items()}
    else:
        rest, shares = rest.withColumn("slice", F.lit(0)), None

    def run(batches):
        import heapq

        current, heap = None, []
        for batch in batches:
            out = []
            for c, s in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                if s != current:
                    current = s
                    heap = [(-x, b) for b, x in enumerate(shares[s])] if shares else [(x, b) for b, x in enumerate(loads)]
                    heapq.heapify(heap)
                at, b = heap[0]
                if shares and -at < c:
                    out.append(None)
                else:
                    heapq.heapreplace(heap, (at + c, b))
                    out.append(b)
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(out, pa.int32())], ["seq", "vertex_id", "c", "block"])

    done = rest.repartition(slices, "slice").sortWithinPartitions("slice", "seq").mapInArrow(run, FILLED)
    if not shares:
        return done
    done = cut(done, "filled-slices")
    left = done.filter("block IS NULL").count()
    if not left:
        return done
    after = list(loads)
    for r in done.filter("block IS NOT NULL").groupBy("block").agg(F.sum("c").alias("c")).collect():  # k rows
        after[r["block"]] += r["c"]
    more = fill_weighted(done.filter("block IS NULL"), after, capacity, left, max(width, left if left == count else width))
    return done.filter("block IS NOT NULL").union(more)
