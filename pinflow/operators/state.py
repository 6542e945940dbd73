"""State as of a moment, in relational form."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window as W, functions as F

SLICE = 1 << 20  # seq numbers a window may hold; slices carry their outcome to the next ones


def before(rows: DataFrame, group: str, values: dict[str, tuple[str, Column]], width: int = SLICE) -> DataFrame:
    """Adds per name the ``last``, ``min``, ``max`` or ``sum`` of a column over the group's rows of smaller seq; null if none.

    seq is unique within a group. A window holds one slice of the sequence or one row per slice of a group, so a
    group of any size is spread over tasks: the order is split by range and boundaries are carried."""
    slim = rows.withColumn("__slice", F.floor(F.col("seq") / width))
    whole = {"last": lambda c: F.max_by(c, "seq"), "min": F.min, "max": F.max, "sum": F.sum}
    running = {"last": F.last, "min": F.min, "max": F.max, "sum": F.sum}
    merged = {"last": lambda a, b: F.coalesce(a, b), "min": F.least, "max": F.greatest, "sum": lambda a, b: F.coalesce(a + b, a, b)}
    # A struct tells a null of an earlier row from no earlier row.
    columns = {n: (how, F.struct(c.alias("v")) if how == "last" else c) for n, (how, c) in values.items()}
    sums = slim.groupBy(group, "__slice").agg(*[whole[how](c).alias(n) for n, (how, c) in columns.items()])
    slices = W.partitionBy(group).orderBy("__slice").rowsBetween(W.unboundedPreceding, -1)
    carried = sums.select(group, "__slice", *[running[how](n).over(slices).alias(f"__from_{n}") for n, (how, _) in columns.items()])
    carried = carried.filter(reduce(lambda a, b: a | b, [F.col(f"__from_{n}").isNotNull() for n in columns]))
    here = W.partitionBy(group, "__slice").orderBy("seq").rowsBetween(W.unboundedPreceding, -1)
    local = slim.select("*", *[running[how](c).over(here).alias(f"__in_{n}") for n, (how, c) in columns.items()])
    both = local.join(carried, [group, "__slice"], "left")
    found = {n: merged[how](F.col(f"__in_{n}"), F.col(f"__from_{n}")) for n, (how, _) in columns.items()}
    return both.select(*rows.columns, *[(found[n]["v"] if how == "last" else found[n]).alias(n) for n, (how, _) in columns.items()])


def as_of_net(pins: DataFrame, assign: DataFrame, width: int = SLICE) -> DataFrame:
    """Per pin: the net's last block and whether it was cut before the vertex arrived. assign has seq."""
    rows = pins.join(assign.select("vertex_id", "seq", "block"), "vertex_id")
    block = F.col("block")
    state = before(rows, "net_id", {"last_block": ("last", block), "__low": ("min", block), "__high": ("max", block)}, width)
    return state.select("net_id", "vertex_id", "seq", "block", "last_block", F.coalesce(F.col("__low") != F.col("__high"), F.lit(False)).alias("is_cut"))


def loads_before(assign: DataFrame, k: int, width: int = SLICE) -> DataFrame:
    """(seq, candidate, load): load of every block before each arrival, n * k rows: audits of bounded runs."""
    blocks = F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    rows = assign.select("seq", "block", blocks.alias("candidate"))
    mine = F.when(F.col("block") == F.col("candidate"), 1).otherwise(0)
    return before(rows, "candidate", {"load": ("sum", mine)}, width).select("seq", "candidate", F.coalesce("load", F.lit(0)).alias("load"))


def net_state(pins: DataFrame, assign: DataFrame) -> DataFrame:
    """NET_STATE after all arrivals."""
    rows = pins.join(assign.select("vertex_id", "seq", "block"), "vertex_id")
    return rows.groupBy("net_id").agg(F.max_by("block", "seq").alias("last_block"), (F.min("block") != F.max("block")).alias("is_cut"), F.max("seq").alias("last_seq"))
