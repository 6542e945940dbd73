"""Connected components by alternating large and small stars, as joins and aggregates."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from .common import cut, discard


def _print(edges: DataFrame):
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first())


def components(links: DataFrame) -> DataFrame:
    """links (a, b) -> (node, component): the smallest node that can be reached, for every node of a link.

    Neighbourhoods are never gathered: each round takes minima per node (partial aggregation) and joins them
    back, a join whose large keys the adaptive planner may split.
    """
    edges = cut(links.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).filter("hi <> lo").distinct(), "edges")
    before = _print(edges)
    while before[0]:
        both = edges.select("hi", "lo").union(edges.select("lo", "hi")).toDF("u", "v")
        least = both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).filter("hi <> lo").distinct()
        large = cut(large, "large-star")
        least = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(least, "hi").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).filter("hi <> lo")
        now = cut(small.union(least.select("hi", F.col("m").alias("lo"))).distinct(), "small-star")
        discard(large)
        discard(edges)
        edges, after = now, _print(now)
        if after == before:
            break
        before = after
    centres = edges.select(F.col("lo").alias("node")).distinct()
    return edges.select(F.col("hi").alias("node"), F.col("lo").alias("component")).union(centres.select("node", F.col("node").alias("component")))
