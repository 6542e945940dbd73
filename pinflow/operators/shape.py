"""Normal forms of hypergraphs, dense ids, arrival orders and the stream formats."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window as W, functions as F

from ..lineage import cut, discard, small_broadcasts
from .state import SLICE, before


@dataclass
class Hypergraph:
    """pins (net_id, vertex_id), vertices (vertex_id, seq, weight), nets (net_id, weight, size) or None for unit weights.

    numbered: what ``numbered_stream`` wrote, once it is asked for."""

    pins: DataFrame
    vertices: DataFrame
    nets: DataFrame | None = None
    _stats: dict | None = None
    numbered: DataFrame | None = None

    def stats(self) -> dict:
        """n, m, pins and the weight totals: one row to the driver."""
        if self._stats is None:
            with small_broadcasts(self.pins.sparkSession):
                v = self.vertices.agg(F.count("*").alias("n"), F.coalesce(F.sum("weight"), F.lit(0.0)).alias("total")).first()
                p = self.pins.agg(F.count("*").alias("pins"), F.count_distinct("net_id").alias("m")).first()
                w = self.nets.agg(F.coalesce(F.sum("weight"), F.lit(0.0)).alias("w")).first()["w"] if self.nets is not None else float(p["m"])
            self._stats = {"n": v["n"], "total": v["total"], "pins": p["pins"], "m": p["m"], "net_weight": w}
        return self._stats


def net_sizes(pins: DataFrame) -> DataFrame:
    return pins.groupBy("net_id").agg(F.count("*").cast("int").alias("size"))


def parallel_groups(pins: DataFrame) -> DataFrame:
    """(net_id, keeper): nets with one pin set share the smallest id. Fingerprints find them, a join of pins confirms; no set is gathered."""
    prints = pins.groupBy("net_id").agg(F.count("*").alias("size"), F.expr("bit_xor(xxhash64(vertex_id))").alias("f1"), F.expr("bit_xor(xxhash64(vertex_id, 1))").alias("f2"))
    twins = prints.groupBy("size", "f1", "f2").agg(F.count("*").alias("nets")).filter("nets > 1")
    suspects = prints.join(twins, ["size", "f1", "f2"])
    heads = suspects.groupBy("size", "f1", "f2").agg(F.min("net_id").alias("keeper"))
    paired = suspects.join(heads, ["size", "f1", "f2"]).select("net_id", "size", "keeper")
    # Pin by pin against the keeper's pins: a net is its twin if all of its pins are there, as their numbers are equal.
    own = pins.join(paired, "net_id").select("net_id", "size", "keeper", "vertex_id")
    kept = pins.join(heads.select(F.col("keeper").alias("net_id")), "net_id", "left_semi").select(F.col("net_id").alias("keeper"), "vertex_id")
    same = own.join(kept, ["keeper", "vertex_id"]).groupBy("net_id", "keeper", "size").agg(F.count("*").alias("shared"))
    return same.filter("shared = size").select("net_id", "keeper")


def normalize(pins: DataFrame, parallel: str = "keep", min_pins: int = 2) -> tuple[DataFrame, DataFrame]:
    """(pins, nets): distinct pins, nets of min_pins at least; parallel nets kept, dropped, or merged with summed weight."""
    if parallel not in ("keep", "drop", "merge"):
        raise ValueError("parallel is 'keep', 'drop' or 'merge'")
    pins = pins.filter("net_id IS NOT NULL AND vertex_id IS NOT NULL").repartition("net_id").distinct()
    sizes = net_sizes(pins).filter(F.col("size") >= min_pins)
    nets = sizes.select("net_id", F.lit(1.0).alias("weight"), "size")
    pins = pins.join(sizes.select("net_id"), "net_id", "left_semi")
    if parallel != "keep":
        groups = parallel_groups(pins)
        gone = groups.filter("net_id <> keeper").select("net_id")
        if parallel == "merge":
            weights = groups.groupBy("keeper").agg(F.count("*").cast("double").alias("w")).withColumnRenamed("keeper", "net_id")
            nets = nets.join(weights, "net_id", "left").select("net_id", F.coalesce("w", "weight").alias("weight"), "size")
        nets = nets.join(gone, "net_id", "left_anti")
        pins = pins.join(gone, "net_id", "left_anti")
    return pins, nets


def dense_ids(df: DataFrame, *keys, name: str = "dense_id") -> DataFrame:
    """Adds 0..n-1 in key order: range partitions are written once, their sizes give each its offset. No global window."""
    ranged = df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumns({"__part": F.spark_partition_id(), "__row": F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))})
    ranged = cut(ranged, "ranged")
    sizes = ranged.groupBy("__part").agg(F.count("*").alias("n"))
    # One row per partition: the window holds as many rows as there are partitions.
    offsets = sizes.select("__part", (F.sum("n").over(W.orderBy("__part")) - F.col("n")).alias("__first"))
    return ranged.join(F.broadcast(offsets), "__part").withColumn(name, F.col("__first") + F.col("__row")).drop("__part", "__row", "__first")


def with_seq(vertices: DataFrame, order: str = "natural", seed: int = 0, by: str | None = None) -> DataFrame:
    """Adds seq 0..n-1. order: natural (id), random (seeded hash), time or degree (column ``by``, then id)."""
    if order == "natural":
        return dense_ids(vertices, F.col("vertex_id"), name="seq")
    if order == "random":
        key = F.md5(F.concat(F.lit(f"{seed}:"), F.col("vertex_id").cast("string")).cast("binary"))
        return dense_ids(vertices.withColumn("__key", key), F.col("__key"), F.col("vertex_id"), name="seq").drop("__key")
    if order in ("time", "degree"):
        if by is None:
            raise ValueError(f"order {order!r} needs the column to go by")
        return dense_ids(vertices, F.col(by), F.col("vertex_id"), name="seq")
    raise ValueError("order is 'natural', 'random', 'time' or 'degree'")


def prepare(pins: DataFrame, order: str = "natural", parallel: str = "keep", weights: DataFrame | None = None, net_weights: DataFrame | None = None, seed: int = 0, by: DataFrame | None = None, once: bool = False) -> Hypergraph:
    """Normalised hypergraph whose vertices are all ids of pins, isolated ones too. weights (vertex_id, weight), net_weights (net_id, weight).

    order 'time' goes by the column ``key`` of by (vertex_id, key), nulls first; 'degree' by the number of pins if by is not
    given. Vertices without a weight weigh 0, nets without one weigh 1. once: the given pins are written first, where making
    them costs more than that; vertices, their range bounds and the normal form then read them."""
    if once:
        given = pins = cut(pins, "given-pins")
    ids = pins.select("vertex_id").filter("vertex_id IS NOT NULL").distinct()
    if weights is None:
        vertices = ids.withColumn("weight", F.lit(1.0))
    else:
        vertices = ids.join(weights, "vertex_id", "left").select("vertex_id", F.coalesce(F.col("weight").cast("double"), F.lit(0.0)).alias("weight"))
    if order == "degree" and by is None:
        by = pins.filter("net_id IS NOT NULL").distinct().groupBy("vertex_id").agg(F.count("*").alias("key"))
    if by is not None:
        vertices = vertices.join(by.select("vertex_id", F.col("key").alias("__by")), "vertex_id", "left")
    vertices = with_seq(vertices, order, seed, None if by is None else "__by").drop("__by")
    pins, nets = normalize(pins, parallel)
    if net_weights is not None:
        nets = nets.drop("weight").join(net_weights, "net_id", "left").select("net_id", F.coalesce(F.col("weight").cast("double"), F.lit(1.0)).alias("weight"), "size")
    pins = cut(pins, "pins")
    if once:
        discard(given)
    return Hypergraph(pins, vertices, nets if parallel == "merge" or net_weights is not None else None)


def vertex_stream(h: Hypergraph) -> DataFrame:
    """seq, vertex_id, weight, nets: a vertex with its nets, isolated vertices with none."""
    pins = h.pins.join(h.nets.select("net_id", "weight"), "net_id") if h.nets is not None else h.pins.withColumn("weight", F.lit(1.0))
    nets = pins.groupBy("vertex_id").agg(F.sort_array(F.collect_list(F.struct("net_id", "weight"))).alias("nets"))
    empty = F.array().cast("array<struct<net_id:bigint,weight:double>>")
    return h.vertices.join(nets, "vertex_id", "left").select("seq", "vertex_id", "weight", F.coalesce("nets", empty).alias("nets"))


def numbered_stream(h: Hypergraph) -> DataFrame:
    """seq, vertex_id, nets, written once for all walks over h: nets are numbers 0..m-1, so that arrays hold their states."""
    if h.numbered is None:

        def rank(batches):
            part, at, last = TaskContext.get().partitionId(), -1, None
            for batch in batches:
                net = batch.column(0).to_numpy()
                if len(net):
                    fresh = np.concatenate([[net[0] != last], net[1:] != net[:-1]])
                    ranks = at + np.cumsum(fresh)
                    at, last = int(ranks[-1]), net[-1]
                    yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(np.full(len(net), part, dtype=np.int32)), pa.array(ranks)], ["vertex_id", "part", "rank"])

        # Ranks within each partition of whole nets, then each partition's offset: no table of nets is joined with the pins.
        ranked = cut(h.pins.select("net_id", "vertex_id").repartition("net_id").sortWithinPartitions("net_id").mapInArrow(rank, "vertex_id bigint, part int, rank bigint"), "ranked-pins")
        sizes = ranked.groupBy("part").agg((F.max("rank") + 1).alias("nets"))
        offsets = sizes.select("part", (F.sum("nets").over(W.orderBy("part")) - F.col("nets")).alias("first"))  # a row per partition
        own = ranked.join(F.broadcast(offsets), "part").groupBy("vertex_id").agg(F.collect_list(F.col("first") + F.col("rank")).alias("nets"))
        stream = h.vertices.select("vertex_id", "seq").join(own, "vertex_id", "left").select("seq", "vertex_id", F.coalesce("nets", F.array().cast("array<bigint>")).alias("nets"))
        h.numbered = cut(stream, "numbered-stream")
        discard(ranked)
    return h.numbered


def vertex_stream_expanded(h: Hypergraph, max_size: int = 10_000) -> DataFrame:
    """The costly format: a vertex with all pins of its nets, sum of size squared entries."""
    largest = net_sizes(h.pins).agg(F.max("size").alias("x")).first()["x"] or 0
    if largest > max_size:
        raise ValueError(f"a net has {largest} pins, above {max_size}")
    other = h.pins.withColumnRenamed("vertex_id", "pin")
    return h.pins.join(other, "net_id").groupBy("vertex_id").agg(F.count("*").alias("entries"), F.collect_list(F.struct("net_id", "pin")).alias("pins"))


def adjacency_stream(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """The vertex stream of a graph: nets holds the neighbours."""
    both = edges.select(F.col("src").alias("vertex_id"), F.col("dst").alias("net_id"), "weight").union(edges.select("dst", "src", "weight"))
    near = both.groupBy("vertex_id").agg(F.sort_array(F.collect_list(F.struct("net_id", "weight"))).alias("nets"))
    empty = F.array().cast("array<struct<net_id:bigint,weight:double>>")
    return vertices.join(near, "vertex_id", "left").select("seq", "vertex_id", "weight", F.coalesce("nets", empty).alias("nets"))


def edge_stream(edges: DataFrame) -> DataFrame:
    """seq, src, dst in (src, dst) order."""
    return dense_ids(edges.select("src", "dst"), F.col("src"), F.col("dst"), name="seq")


def graph_vertices(edges: DataFrame) -> DataFrame:
    ids = edges.select(F.col("src").alias("vertex_id")).union(edges.select("dst")).distinct()
    return with_seq(ids.withColumn("weight", F.lit(1.0)))


def edges_to_pins(edges: DataFrame) -> DataFrame:
    """Every edge a net of two pins."""
    named = dense_ids(edges.select("src", "dst"), F.col("src"), F.col("dst"), name="net_id")
    return named.select("net_id", F.explode(F.array("src", "dst")).alias("vertex_id"))


def predecessor_arcs(h: Hypergraph, width: int = SLICE) -> DataFrame:
    """(vertex_id, pred, weight): for every pin the net's pin before it in arrival order, summed over shared nets."""
    pins = h.pins.join(h.vertices.select("vertex_id", "seq"), "vertex_id")
    if h.nets is not None:
        pins = pins.join(h.nets.select("net_id", "weight"), "net_id")
    else:
        pins = pins.withColumn("weight", F.lit(1.0))
    arcs = before(pins, "net_id", {"pred": ("last", F.col("vertex_id"))}, width).filter("pred IS NOT NULL")
    return arcs.groupBy("vertex_id", "pred").agg(F.sum("weight").alias("weight"))


def induced(pins: DataFrame, keep: DataFrame) -> DataFrame:
    """Pins of the vertices in keep (vertex_id)."""
    return pins.join(keep.select("vertex_id"), "vertex_id", "left_semi")
