"""Objectives, balance and structure measures of an assignment."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..params import PartitionSpec


def placed(pins: DataFrame, assign: DataFrame) -> DataFrame:
    return pins.join(assign.select("vertex_id", "block"), "vertex_id")


def _weighed(per_net: DataFrame, nets: DataFrame | None) -> DataFrame:
    return per_net.withColumn("weight", F.lit(1.0)) if nets is None else per_net.join(nets.select("net_id", "weight"), "net_id")


def cut_net(pins: DataFrame, assign: DataFrame, nets: DataFrame | None = None) -> DataFrame:
    """Weight of the nets in more than one block, each once: minimum and maximum tell, no distinct needed."""
    per = placed(pins, assign).groupBy("net_id").agg(F.min("block").alias("lo"), F.max("block").alias("hi")).filter("lo <> hi")
    return _weighed(per, nets).agg(F.coalesce(F.sum("weight"), F.lit(0.0)).alias("value"))


def net_span(pins: DataFrame, assign: DataFrame) -> DataFrame:
    """net_id, lambda: blocks that a net touches. Two phases: distinct (net, block), then counts."""
    return placed(pins, assign).select("net_id", "block").distinct().groupBy("net_id").agg(F.count("*").cast("int").alias("lambda"))


def connectivity(pins: DataFrame, assign: DataFrame, nets: DataFrame | None = None) -> DataFrame:
    """Sum of (lambda - 1) * weight."""
    return _weighed(net_span(pins, assign), nets).agg(F.coalesce(F.sum((F.col("lambda") - 1) * F.col("weight")), F.lit(0.0)).alias("value"))


def block_mask(pins: DataFrame, assign: DataFrame) -> DataFrame:
    """lambda for k <= 63 by a mergeable bit mask: one aggregation with partial results, no distinct."""
    return placed(pins, assign).groupBy("net_id").agg(F.bit_count(F.expr("bit_or(shiftleft(1L, block))")).cast("int").alias("lambda"))


def packed_masks(cells: list) -> tuple[list[F.Column], list[tuple[int, int]]]:
    """Bit masks of several placements (block column, k <= 63) in as few bigint columns as hold them, and each one's (column, first bit)."""
    words, spots, room = [], [], 0
    for block, k in cells:
        if k > 63:
            raise ValueError("a mask holds 63 blocks at most")
        if k > room:
            words.append(F.lit(0).cast("bigint"))
            room = 63
        at = 63 - room
        words[-1] = words[-1].bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), block + F.lit(at)))
        spots.append((len(words) - 1, at))
        room -= k
    return words, spots


def spans_of(pins: DataFrame, vertices: DataFrame, cells: list) -> tuple[DataFrame, list[F.Column]]:
    """A row per net with the merged masks of several placements of ``vertices`` and whether it is wide, of two different pins
    at least; and the column that reads lambda of each.

    Rows stay one per pin, and the join is a sort-merge join: a table of vertices times placements is far larger than the
    planner thinks, and broadcast it fills the driver."""
    words, spots = packed_masks(cells)
    names = [f"w{i}" for i in range(len(words))]
    masks = vertices.select("vertex_id", *[w.alias(n) for w, n in zip(words, names)])
    merged = pins.join(masks.hint("merge"), "vertex_id").groupBy("net_id").agg(*[F.bit_or(n).alias(n) for n in names], (F.min("vertex_id") < F.max("vertex_id")).alias("wide"))
    spans = [F.bit_count(F.shiftright(names[word], at).bitwiseAND(F.lit((1 << k) - 1).cast("bigint"))).cast("bigint") for (word, at), (_, k) in zip(spots, cells)]
    return merged, spans


def span_histogram(pins: DataFrame, assign: DataFrame) -> DataFrame:
    return net_span(pins, assign).groupBy("lambda").agg(F.count("*").alias("nets"))


def sum_of_external_degrees(pins: DataFrame, assign: DataFrame) -> DataFrame:
    return net_span(pins, assign).filter(F.col("lambda") > 1).agg(F.coalesce(F.sum("lambda"), F.lit(0)).alias("value"))


def edge_cut(edges: DataFrame, assign: DataFrame) -> DataFrame:
    a = assign.select(F.col("vertex_id").alias("src"), F.col("block").alias("ba"))
    b = assign.select(F.col("vertex_id").alias("dst"), F.col("block").alias("bb"))
    return edges.join(a, "src").join(b, "dst").filter("ba <> bb").agg(F.coalesce(F.sum("weight"), F.lit(0.0)).alias("value"))


def balance(vertices: DataFrame, assign: DataFrame, spec: PartitionSpec) -> DataFrame:
    """block, load, l_max, over for all k blocks, empty ones too."""
    spark = vertices.sparkSession
    total = vertices.agg(F.coalesce(F.sum("weight"), F.lit(0.0)).alias("t")).first()["t"]
    loads = vertices.join(assign, "vertex_id").groupBy("block").agg(F.sum("weight").alias("load"))
    blocks = spark.range(spec.k).select(F.col("id").cast("int").alias("block"))
    return blocks.join(loads, "block", "left").select("block", F.coalesce("load", F.lit(0.0)).alias("load"), F.lit(float(spec.capacity(total))).alias("l_max")).withColumn("over", F.col("load") > F.col("l_max"))


def imbalance(vertices: DataFrame, assign: DataFrame, k: int) -> DataFrame:
    loads = vertices.join(assign, "vertex_id").groupBy("block").agg(F.sum("weight").alias("load"))
    return loads.agg((F.max("load") * k / F.sum("load") - 1).alias("value"))


def replication(pins: DataFrame, assign: DataFrame) -> DataFrame:
    return net_span(pins, assign).agg((F.sum("lambda") / F.count("*")).alias("value"))


def edge_replication(placed_edges: DataFrame) -> DataFrame:
    """Mean number of blocks that hold an edge of a vertex."""
    ends = placed_edges.select(F.col("src").alias("v"), "block").union(placed_edges.select("dst", "block")).distinct()
    return ends.groupBy("v").agg(F.count("*").alias("c")).agg((F.sum("c") / F.count("*")).alias("value"))


def boundary_vertices(pins: DataFrame, assign: DataFrame) -> DataFrame:
    cut = net_span(pins, assign).filter(F.col("lambda") > 1).select("net_id")
    return pins.join(cut, "net_id", "left_semi").select("vertex_id").distinct()


def weighted_profile(pins: DataFrame, nets: DataFrame, vertices: DataFrame) -> DataFrame:
    """total, net_weight, heaviest_vertex, heaviest_net and widest, the largest sum of a vertex's net weights."""
    degrees = pins.join(nets.select("net_id", "weight"), "net_id").groupBy("vertex_id").agg(F.sum("weight").alias("w"))
    a = vertices.agg(F.sum("weight").alias("total"), F.max("weight").alias("heaviest_vertex"))
    b = nets.agg(F.sum("weight").alias("net_weight"), F.max("weight").alias("heaviest_net"))
    return a.crossJoin(b).crossJoin(degrees.agg(F.max("w").alias("widest")))


def profile(pins: DataFrame) -> DataFrame:
    """n, m, pins, xi (largest net), delta (largest degree), single (nets of one pin)."""
    nets = pins.groupBy("net_id").agg(F.count("*").alias("s"))
    degrees = pins.groupBy("vertex_id").agg(F.count("*").alias("d"))
    a = nets.agg(F.count("*").alias("m"), F.coalesce(F.sum("s"), F.lit(0)).alias("pins"), F.max("s").alias("xi"), F.count_if(F.col("s") == 1).alias("single"))
    return a.crossJoin(degrees.agg(F.count("*").alias("n"), F.max("d").alias("delta")))


def state_entries(pins: DataFrame, assign: DataFrame, k: int) -> DataFrame:
    """Entries that each method keeps: one per net and block (greedy), one per (net, block) met (lists), one per vertex (graph rule)."""
    spans = net_span(pins, assign)
    n = assign.agg(F.count("*").alias("n"))
    return spans.agg((F.count("*") + k).alias("greedy"), (F.sum("lambda") + k).alias("lists"), (F.count("*") * k).alias("lists_worst")).crossJoin(n.select((F.col("n") + k).alias("graph")))
