"""Fast in-memory stand-in: size-constrained label propagation, as joins and aggregates."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..lineage import cut, discard
from ..params import PartitionSpec
from .capacity import rank_in
from .controls import round_robin
from .shape import Hypergraph


def inmem_fast(h: Hypergraph, spec: PartitionSpec, iters: int = 5, stop: float = 0.001) -> DataFrame:
    """vertex_id, block. Starts from even shares in turn; each round the vertices wish for the block that holds most of their
    nets' pins and move, by arrival, while it has room: the bound holds from the first round to the last."""
    capacity, n = spec.capacity(h.stats()["total"]), h.stats()["n"]
    sizes = h.pins.groupBy("net_id").agg(F.count("*").alias("size"))
    pins = cut(h.pins.join(sizes, "net_id"), "sized-pins")
    order = cut(h.vertices.select("vertex_id", "seq"), "order")
    assign = cut(round_robin(h.vertices, spec.k), "labels")
    for _ in range(iters):
        held = pins.join(assign, "vertex_id")
        weight = held.groupBy("net_id", "block").agg((F.count("*") / F.first("size")).alias("w"))
        pull = pins.select("net_id", "vertex_id").join(weight, "net_id").groupBy("vertex_id", "block").agg(F.round(F.sum("w"), 9).alias("w"))
        best = pull.groupBy("vertex_id").agg(F.max(F.struct("w", (-F.col("block")).alias("b"))).alias("x")).select("vertex_id", (-F.col("x.b")).cast("int").alias("want"))
        wishes = assign.join(best, "vertex_id").filter("want <> block").join(order, "vertex_id").select("vertex_id", "seq", F.col("want").alias("block"))
        room = [capacity] * spec.k
        for row in assign.groupBy("block").agg(F.count("*").alias("c")).collect():  # k rows
            room[row["block"]] = max(0, capacity - row["c"])
        free = F.array(*[F.lit(int(x)) for x in room])
        moves = cut(rank_in(wishes, "block", "seq").filter(F.col("rank") < F.element_at(free, F.col("block") + 1)).select("vertex_id", F.col("block").alias("to")), "moves")
        moved = moves.count()
        after = cut(assign.join(moves, "vertex_id", "left").select("vertex_id", F.coalesce("to", "block").alias("block")), "labels")
        discard(assign)
        assign = after
        if moved <= stop * n:
            break
    return assign
