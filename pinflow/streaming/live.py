"""Live lanes: vertices that arrive without end, placed once.

The exact lane keeps its state by net and by vertex: a micro-batch reads and writes what its own vertices touch, and k
loads. Rows of a micro-batch are ordered by seq inside the group, as Spark promises no order there. The bound follows a
horizon (expected vertices) or, without one, the arrivals so far. ``ttl`` forgets vertices and nets that were not written for
so long. Pins that come late, with a vertex already placed, are dropped or, with ``late='apply'``, give their nets its block.
The other lane places each micro-batch in one round against the net states of the batches before it, kept by
batch id, so a retried batch starts from the same state."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StructField, StructType

from ..kernel.batched import Batched
from ..kernel.greedy import Greedy
from ..lineage import cut
from ..params import PartitionSpec
from ..plans.rounds import settle, wishes_of

OUT = "stream_id bigint, seq bigint, vertex_id bigint, block int"
PROVIDER = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def _long(name: str) -> StructType:
    return StructType([StructField(name, LongType())])


class _Placer(StatefulProcessor):
    def __init__(self, spec: PartitionSpec, horizon: int | None, nets: int | None, late: str, ttl_ms: int | None):
        self.spec, self.horizon, self.expected, self.late, self.ttl_ms = spec, horizon, nets, late, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.nets = handle.getMapState("nets", _long("net_id"), _long("state"), self.ttl_ms)
        self.placed = handle.getMapState("placed", _long("vertex_id"), StructType([StructField("block", IntegerType())]), self.ttl_ms)
        self.totals = handle.getValueState("totals", StructType([StructField("loads", ArrayType(DoubleType())), StructField("arrived", LongType()), StructField("met", LongType())]))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        loads, arrived, met = self.totals.get() if self.totals.exists() else ([0.0] * self.spec.k, 0, 0)
        n = self.horizon or 1
        engine = Greedy(self.spec, self.spec.capacity(n), self.spec.strength(n, self.expected or n))
        engine.index.load = list(loads)
        engine.index.heap = [(x, b) for b, x in enumerate(loads)]
        heapq.heapify(engine.index.heap)
        looked: set[int] = set()
        here: dict[int, int] = {}
        out = []
        batch = pd.concat(rows).sort_values("seq", kind="stable")
        for seq, vertex, own in zip(batch["seq"].tolist(), batch["vertex_id"].tolist(), batch["nets"]):
            nets = [int(x) for x in (own if own is not None else ())]
            for net in nets:
                if net not in looked:
                    looked.add(net)
                    if self.nets.containsKey((net,)):
                        engine.last[net] = self.nets.getValue((net,))[0]
            block = here.get(vertex)
            if block is None and self.placed.containsKey((vertex,)):
                block = self.placed.getValue((vertex,))[0]
            pairs = [(net, 1.0) for net in nets]
            if block is not None:  # a vertex is placed once
                if self.late == "apply":
                    met += sum(net not in engine.last for net in nets)
                    engine.settle(pairs, block)
                continue
            if self.horizon is None:
                engine.capacity = self.spec.capacity(arrived + 1)
                engine.strength = self.spec.strength(arrived + 1, max(1, met))
            met += sum(net not in engine.last for net in nets)
            block = engine.place(1.0, pairs)[0]
            here[vertex] = block
            arrived += 1
            out.append((key[0], seq, vertex, block))
        for net in looked & engine.last.keys():
            self.nets.updateValue((net,), (engine.last[net],))
        for vertex, block in here.items():
            self.placed.updateValue((vertex,), (block,))
        self.totals.update(([float(x) for x in engine.index.load], arrived, met))
        yield pd.DataFrame(out, columns=["stream_id", "seq", "vertex_id", "block"])

    def close(self) -> None:
        pass


def partition_stream(stream: DataFrame, spec: PartitionSpec, horizon: int | None = None, nets: int | None = None, late: str = "drop", ttl_ms: int | None = None) -> DataFrame:
    """stream: stream_id, seq, vertex_id, nets (array<bigint>); placements in append mode. Sets the RocksDB state store."""
    if spec.tie == "ladder" or spec.weighted:
        raise ValueError("the live lane breaks ties by block number and counts vertices")
    if late not in ("drop", "apply"):
        raise ValueError("late is 'drop' or 'apply'")
    stream.sparkSession.conf.set("spark.sql.streaming.stateStore.providerClass", PROVIDER)
    return stream.groupBy("stream_id").transformWithStateInPandas(_Placer(spec, horizon, nets, late, ttl_ms), OUT, "append", "processingTime" if ttl_ms else "none")


def deduplicated(stream: DataFrame, delay: str = "2 hours") -> DataFrame:
    """ts must be TIMESTAMP: a vertex that comes again within the delay is dropped."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["vertex_id"])


def windowed_loads(stream: DataFrame, width: str = "1 day", delay: str = "2 hours") -> DataFrame:
    """Arrivals per block and time window."""
    return stream.withWatermark("ts", delay).groupBy(F.window("ts", width), "block").agg(F.count("*").alias("arrivals"))


def with_table(stream: DataFrame, table: DataFrame, key: str) -> DataFrame:
    """Stream rows with the columns of a table, read anew in every micro-batch; no state."""
    return stream.join(table, key)


def with_stream(arrivals: DataFrame, pins: DataFrame, key: str, within: str = "30 days", delay: str = "2 hours") -> DataFrame:
    """Arrivals (key, ts) with their pins (key, pin_ts, ...) that come within a time span: both sides are watermarked, so
    the join forgets an arrival once no pin can be in its span any more."""
    a = arrivals.withWatermark("ts", delay).alias("a")
    p = pins.withWatermark("pin_ts", delay).alias("p")
    span = F.col("p.pin_ts").between(F.col("a.ts"), F.col("a.ts") + F.expr(f"INTERVAL {within}"))
    return a.join(p, (F.col(f"a.{key}") == F.col(f"p.{key}")) & span).drop(F.col(f"p.{key}"))


def rounds_sink(place, state_path: str, out_path: str):
    """A foreachBatch function: place(batch, state) -> (placements, state). State of batch i is read from i - 1 and written to i."""

    def each(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        state = spark.read.parquet(f"{state_path}/{batch_id - 1}") if batch_id else None
        placed, after = place(batch, state)
        placed.write.mode("overwrite").parquet(f"{out_path}/batch={batch_id}")
        after.write.mode("overwrite").parquet(f"{state_path}/{batch_id}")

    return each


STATE = "kind string, id bigint, block int, shut boolean, load double"
WALKED = f"{STATE}, seq bigint"


def _walked_round(spec: PartitionSpec, capacity: int, strength: float):
    """round_of where one task takes the state and the micro-batch: two short jobs each, the same placements and state."""

    def walk(batches):
        engine, rows = Batched(spec, capacity, strength), []
        for batch in batches:
            for kind, key, block, shut, load, seq, weight, nets in zip(*(batch.column(i).to_pylist() for i in range(8))):
                if kind == "net":
                    engine.last[key] = block << 1 | shut
                elif kind == "block":
                    engine.load[block] = load
                else:
                    rows.append((seq, key, weight, [(net, 1.0) for net in nets or ()]))
        rows.sort(key=lambda r: r[0])
        blocks = engine.round([r[2:] for r in rows])
        out = [("vertex", r[1], b, None, None, r[0]) for r, b in zip(rows, blocks)]
        out += [("net", net, x >> 1, bool(x & 1), None, None) for net, x in engine.last.items()]
        out += [("block", None, b, None, float(x), None) for b, x in enumerate(engine.load)]
        types = [pa.string(), pa.int64(), pa.int32(), pa.bool_(), pa.float64(), pa.int64()]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], ["kind", "id", "block", "shut", "load", "seq"])

    def place(batch: DataFrame, state: DataFrame | None) -> tuple[DataFrame, DataFrame]:
        rows = batch.select(F.lit("vertex").alias("kind"), F.col("vertex_id").alias("id"), F.lit(None).cast("int").alias("block"), F.lit(None).cast("boolean").alias("shut"), F.lit(None).cast("double").alias("load"), "seq", F.col("weight").cast("double"), F.col("nets").cast("array<bigint>"))
        if state is not None:
            rows = rows.unionByName(state, allowMissingColumns=True)
        made = rows.repartition(1).mapInArrow(walk, WALKED)
        return made.filter("kind = 'vertex'").select("seq", F.col("id").alias("vertex_id"), "block"), made.filter("kind <> 'vertex'").drop("seq")

    return place


def round_of(spec: PartitionSpec, capacity: int, strength: float, walk: bool = False):
    """A place function for rounds_sink: one round per micro-batch (seq, vertex_id, weight, nets) against the state before it.

    State: a row per net with its latest block and whether it is cut, and a row per block with its load. walk: micro-batches
    and net states fit a task."""
    if walk:
        return _walked_round(spec, capacity, strength)

    def place(batch: DataFrame, state: DataFrame | None) -> tuple[DataFrame, DataFrame]:
        batch = cut(batch, "micro-batch")
        mine = batch.select("seq", "vertex_id", F.col("weight").cast("double").alias("c"))
        pins = batch.select("seq", "vertex_id", F.explode("nets").alias("net_id"))
        loads = [0.0] * spec.k
        if state is None:
            state = batch.sparkSession.createDataFrame([], STATE)
        for row in state.filter("kind = 'block'").collect():  # k rows
            loads[row["block"]] = row["load"]
        nets = state.filter("kind = 'net'").select(F.col("id").alias("net_id"), F.col("block").alias("was"), "shut")
        told = pins.join(nets, "net_id")
        if spec.objective == "cut":
            told = told.filter("NOT shut")
        votes = told.groupBy("vertex_id", F.col("was").alias("block")).agg(F.count("*").cast("double").alias("votes"))
        wishes = cut(wishes_of(mine, votes, loads, spec, capacity, strength), "wishes")
        placed, loads, _ = settle(wishes, loads, spec, capacity)
        placed = cut(placed, "placed")
        met = pins.join(placed.select("seq", "block"), "seq").groupBy("net_id").agg(F.max(F.struct("seq", "block")).alias("x"), F.min("block").alias("lo"), F.max("block").alias("hi"))
        both = nets.join(met, "net_id", "full")
        moved = (F.col("lo") != F.col("hi")) | (F.coalesce("was", "lo") != F.col("lo"))
        after = both.select(F.lit("net").alias("kind"), F.col("net_id").alias("id"), F.coalesce("x.block", "was").alias("block"), (F.coalesce("shut", F.lit(False)) | F.coalesce(moved, F.lit(False))).alias("shut"), F.lit(None).cast("double").alias("load"))
        sums = batch.sparkSession.createDataFrame([("block", None, b, None, float(x)) for b, x in enumerate(loads)], STATE)
        return placed, after.union(sums)

    return place
