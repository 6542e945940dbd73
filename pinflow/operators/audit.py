"""Checks of finished assignments that know nothing of the engine that made them."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..params import PartitionSpec
from .shape import Hypergraph
from .state import as_of_net, loads_before


def penalty_column(strength: float, gamma: float, load) -> F.Column:
    if gamma == 1.5:
        return F.lit(strength) * F.sqrt(load)
    return F.lit(strength) * (F.lit(1.0) if gamma == 1 else load.cast("double") if gamma == 2 else F.pow(load, F.lit(gamma - 1)))


def scores(pins: DataFrame, assign: DataFrame, spec: PartitionSpec, capacity: int, strength: float) -> DataFrame:
    """(seq, block, candidate, score, load): every eligible block's score at each arrival, unit weights."""
    state = as_of_net(pins, assign).filter("last_block IS NOT NULL")
    if spec.objective == "cut":
        state = state.filter("NOT is_cut")
    votes = state.groupBy("seq", F.col("last_block").alias("candidate")).agg(F.count("*").cast("double").alias("votes"))
    rows = loads_before(assign, spec.k).join(votes, ["seq", "candidate"], "left")
    score = F.coalesce("votes", F.lit(0.0)) - penalty_column(strength, spec.gamma, F.col("load"))
    return rows.filter(F.col("load") + 1 <= capacity).select("seq", "candidate", "load", score.alias("score")).join(assign.select("seq", "block"), "seq")


def decision_audit(h: Hypergraph, assign: DataFrame, spec: PartitionSpec, capacity: int, strength: float) -> DataFrame:
    """n_checked, n_violations: each vertex once, its block eligible and of the best score."""
    scored = scores(h.pins, assign, spec, capacity, strength)
    best = scored.groupBy("seq").agg(F.max("score").alias("best"), F.max(F.when(F.col("candidate") == F.col("block"), F.col("score"))).alias("own"))
    per = h.vertices.select("vertex_id", F.col("seq").alias("s")).join(assign.select("vertex_id", "seq"), "vertex_id", "left").join(best, "seq", "left")
    bad = F.col("own").isNull() | (F.col("own") < F.col("best")) | ~F.col("seq").eqNullSafe(F.col("s"))
    return per.agg(F.count("*").alias("n_checked"), F.count_if(bad).alias("n_violations"))


def diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """n_checked, n_violations between two assignments: vertices on one side only or in different blocks."""
    both = a.select("vertex_id", F.col("block").alias("x")).join(b.select("vertex_id", F.col("block").alias("y")), "vertex_id", "full")
    return both.agg(F.count("*").alias("n_checked"), F.count_if(~F.col("x").eqNullSafe(F.col("y"))).alias("n_violations"))


def balance_audit(h: Hypergraph, assign: DataFrame, spec: PartitionSpec) -> DataFrame:
    """n_checked, n_violations: vertices, and blocks above the bound, out of range or vertices not placed once."""
    capacity = spec.capacity(h.stats()["total"])
    per = h.vertices.join(assign.groupBy("vertex_id").agg(F.count("*").alias("times"), F.min("block").alias("block")), "vertex_id", "left")
    wrong = per.agg(F.count("*").alias("n_checked"), F.count_if(F.coalesce(F.col("times"), F.lit(0)) != 1).alias("a"), F.count_if((F.col("block") < 0) | (F.col("block") >= spec.k)).alias("b"))
    over = per.groupBy("block").agg(F.sum("weight").alias("load")).agg(F.count_if(F.col("load") > capacity).alias("c"))
    return wrong.crossJoin(over).select("n_checked", (F.col("a") + F.col("b") + F.col("c")).alias("n_violations"))


def block_overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("vertex_id", F.col("block").alias("block_a")).join(b.select("vertex_id", F.col("block").alias("block_b")), "vertex_id").groupBy("block_a", "block_b").agg(F.count("*").alias("vertices"))
