"""The scale lane: batches of vertices are scored in parallel against the state before the batch.

Arcs are made once: for every pin of a batch, the net's latest pin in an earlier batch. A vote is the block of that
predecessor; for cut-net, a row per net and batch that met it tells whether the net was cut by then. The pins lie in a
folder per batch, so a round reads its own pins, the placements and, for cut-net, those rows. It aggregates votes per
(vertex, block), compares with the lightest block, accepts wishes by arrival where a block has not room for all, spreads
the rest from the lightest block up and appends its placements. Driver state is k loads, kept by each round's own counts.

The first ``prefix`` vertices are walked by the exact lane. From there batches grow geometrically (a share ``beta`` of
what is placed), so the number of rounds is logarithmic and each decision misses at most that share. Batches of one
vertex are the sequential rule exactly.

Fixed batches of up to ``WALKED`` vertices have nothing to share out: a Spark job each costs more than their scoring. Where
one task holds the net states, it walks them all with the same rule."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from ..kernel import batched, greedy as kernel
from ..lineage import cut, discard, scratch_path
from ..operators.capacity import accept, accept_weighted, fill, fill_weighted, filled_loads, rank_in
from ..operators.shape import Hypergraph, vertex_stream
from ..params import PartitionSpec
from .ordered import _rows, limits, run_one_pass


def batch_bounds(n: int, prefix: int, beta: float, batch: int | None = None) -> list[int]:
    """Ends of the batches: fixed size ``batch``, or ``prefix`` and then a share beta of what is placed."""
    ends = [min(n, batch or prefix)]
    while ends[-1] < n:
        ends.append(min(n, ends[-1] + (batch or max(1, int(ends[-1] * beta)))))
    return ends


def batched_pins(h: Hypergraph, ends: list[int]) -> DataFrame:
    """(net_id, vertex_id, seq, batch, pred, weight): pred is the seq of the net's latest pin in an earlier batch."""
    cuts = F.array(*[F.lit(e) for e in ends])  # one number per round
    seqs = h.vertices.select("vertex_id", "seq", F.size(F.filter(cuts, lambda e: e <= F.col("seq"))).alias("batch"))
    pins = h.pins.join(seqs, "vertex_id")
    pins = pins.join(h.nets.select("net_id", "weight"), "net_id") if h.nets is not None else pins.withColumn("weight", F.lit(1.0))
    # One row per net and batch goes through the window, never the pins of a large net.
    latest = pins.groupBy("net_id", "batch").agg(F.max("seq").alias("__latest"))
    earlier = W.partitionBy("net_id").orderBy("batch").rowsBetween(W.unboundedPreceding, -1)
    return pins.join(latest.select("net_id", "batch", F.max("__latest").over(earlier).alias("pred")), ["net_id", "batch"])


PREFIX = 1 << 17
WALKED = 1 << 12
PLACED = "seq bigint, vertex_id bigint, block int"


def _score(votes, spec: PartitionSpec, strength: float, c, load) -> F.Column:
    own = F.lit(strength) * c
    penalty = own * F.sqrt(load) if spec.gamma == 1.5 else own * (F.lit(1.0) if spec.gamma == 1 else load.cast("double") if spec.gamma == 2 else F.pow(load, F.lit(spec.gamma - 1)))
    return votes - penalty


def wishes_of(mine: DataFrame, votes: DataFrame, loads: list[float], spec: PartitionSpec, capacity: int, strength: float) -> DataFrame:
    """mine (seq, vertex_id, c) with block: the best voted block that beats the lightest one; null where none does."""
    light = min(range(spec.k), key=lambda b: (loads[b], b))
    load = F.element_at(F.array(*[F.lit(float(x)) for x in loads]), F.col("block") + 1)
    scored = votes.join(mine.select("vertex_id", "c"), "vertex_id").withColumn("load", load).filter(F.col("load") + F.col("c") <= capacity)
    scored = scored.withColumn("score", _score(F.col("votes"), spec, strength, F.col("c"), F.col("load")))
    best = scored.groupBy("vertex_id").agg(F.max(F.struct("score", (-F.col("load")).alias("l"), (-F.col("block")).alias("b"))).alias("x"))
    rival = F.struct(_score(F.lit(0.0), spec, strength, F.col("c"), F.lit(float(loads[light]))).alias("score"), F.lit(-float(loads[light])).alias("l"), F.lit(-light).alias("b"))
    wish = F.when(F.col("x") > rival, (-F.col("x.b")).cast("int"))
    return mine.join(best, "vertex_id", "left").select("seq", "vertex_id", "c", wish.alias("block"))


def settle(wishes: DataFrame, loads: list[float], spec: PartitionSpec, capacity: int) -> tuple[DataFrame, list[float], list[DataFrame]]:
    """(seq, vertex_id, block) of a batch's wishes (written), the loads after it, and written tables that it still reads."""
    loads, used = list(loads), []
    counts = wishes.groupBy("block").agg(F.count("*").alias("n"), F.sum("c").alias("c")).collect()  # k + 1 rows
    full = [r["block"] for r in counts if r["block"] is not None and loads[r["block"]] + r["c"] > capacity]
    for r in counts:
        if r["block"] is not None and r["block"] not in full:
            loads[r["block"]] += r["c"]
    lost = sum(r["n"] for r in counts if r["block"] is None)
    over = F.col("block").isin(full) if full else F.lit(False)
    kept, rest = wishes.filter(F.col("block").isNotNull() & ~over), wishes.filter("block IS NULL")
    if full:
        free = [capacity - x for x in loads]
        took = cut((accept_weighted if spec.weighted else accept)(wishes.filter(over), free), "accepted")
        used.append(took)
        for r in took.groupBy("block").agg(F.sum(F.when(F.col("accepted"), F.col("c")).otherwise(0.0)).alias("c"), F.count_if(~F.col("accepted")).alias("n")).collect():  # k rows
            loads[r["block"]] += r["c"]
            lost += r["n"]
        kept = kept.unionByName(took.filter("accepted").drop("accepted"))
        rest = rest.unionByName(took.filter("not accepted").drop("accepted"))
    if not lost:
        return kept.select("seq", "vertex_id", "block"), loads, used
    if spec.weighted:
        filled = cut(fill_weighted(rest, loads, capacity, lost), "filled")
        used.append(filled)
        for r in filled.groupBy("block").agg(F.sum("c").alias("c")).collect():  # k rows
            loads[r["block"]] += r["c"]
    else:
        filled = fill(rank_in(rest.withColumn("all", F.lit(0)), "all", "seq"), [int(x) for x in loads], capacity)
        loads = [float(x) for x in filled_loads([int(x) for x in loads], capacity, lost)]
    return kept.select("seq", "vertex_id", "block").union(filled.select("seq", "vertex_id", "block")), loads, used


def walked(h: Hypergraph, spec: PartitionSpec, batch: int) -> DataFrame:
    """seq, vertex_id, block of rounds of a fixed size, by one task."""
    capacity, strength = limits(h, spec)

    def walk(batches):
        engine, held = batched.Batched(spec, capacity, strength), []

        def close():
            blocks = engine.round([(weight, nets) for _, _, weight, nets in held])
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in held], pa.int64()), pa.array([r[1] for r in held], pa.int64()), pa.array(blocks, pa.int32())], ["seq", "vertex_id", "block"])

        for rows in batches:
            for row in _rows(rows):
                if held and row[0] // batch != held[0][0] // batch:
                    yield close()
                    held = []
                held.append(row)
        if held:
            yield close()

    return vertex_stream(h).select("seq", "vertex_id", F.col("weight").cast("double"), "nets").repartition(1).sortWithinPartitions("seq").mapInArrow(walk, PLACED)


def greedy(h: Hypergraph, spec: PartitionSpec, prefix: int = PREFIX, beta: float = 0.1, batch: int | None = None, walk: int = WALKED) -> DataFrame:
    """seq, vertex_id, block. batch: batches of that fixed size from the first vertex on, without an exact prefix; batches
    of up to ``walk`` vertices are walked in one task where it can hold the net states.

    With unit weights every block stays within its bound; a vertex that fits nowhere goes to the lightest block, as in the
    exact lane. Ties go to the smaller block: the ladder's order exists in the exact lane only."""
    if spec.tie == "ladder":
        raise ValueError("the rounds lane breaks ties by block number; use tie='lowest_id'")
    from .choose import lane

    if batch is not None and batch <= walk and lane(h.stats(), spec) == "ordered":
        return walked(h, spec, batch)
    spark, n = h.pins.sparkSession, h.stats()["n"]
    capacity, strength = limits(h, spec)
    ends = batch_bounds(n, prefix, beta, batch)
    pins = cut(batched_pins(h, ends), "batched-pins", by="batch")
    vertices = cut(h.vertices.select("vertex_id", "seq", F.col("weight").cast("double").alias("c")), "vertices")
    home = scratch_path(spark, "placed", kept=True)
    marks = scratch_path(spark, "marks", kept=True)
    loads, first = [0.0] * spec.k, 0
    for r, end in enumerate(ends):
        mine = vertices.filter((F.col("seq") >= first) & (F.col("seq") < end))
        own, seen, temporary = pins.filter(F.col("batch") == r), None, []
        if spec.objective == "cut":  # what each net of the batch was like before it
            before = own.withColumns({"was": F.lit(None).cast("int"), "shut": F.lit(False)})
            if r:
                known = spark.read.schema("net_id bigint, pred bigint, was int, shut boolean").parquet(marks)
                before = own.join(known, ["net_id", "pred"], "left").withColumn("shut", F.coalesce("shut", F.lit(False)))
            seen = cut(before.select("net_id", "vertex_id", "seq", "weight", "was", "shut"), "seen")
            temporary.append(seen)
        if r == 0 and batch is None:
            part = Hypergraph(h.pins.join(mine.select("vertex_id"), "vertex_id", "left_semi"), h.vertices.filter(F.col("seq") < end), h.nets)
            placed = run_one_pass(vertex_stream(part), lambda: kernel.Greedy(spec, capacity, strength)).select("seq", "vertex_id", "block")
        else:
            if r == 0:
                wishes = mine.withColumn("block", F.lit(None).cast("int"))
            else:
                if seen is not None:
                    votes = seen.filter("was IS NOT NULL AND NOT shut").select("vertex_id", F.col("was").alias("block"), "weight")
                else:
                    done = spark.read.schema(PLACED).parquet(home).select(F.col("seq").alias("pred"), "block")
                    votes = own.filter("pred IS NOT NULL").join(done, "pred").select("vertex_id", "block", "weight")
                wishes = wishes_of(mine, votes.groupBy("vertex_id", "block").agg(F.sum("weight").alias("votes")), loads, spec, capacity, strength)
            wishes = cut(wishes, "wishes")
            placed, loads, used = settle(wishes, loads, spec, capacity)
            temporary += [wishes, *used]
        placed.write.parquet(f"{home}/round={r}")
        placed = spark.read.schema(PLACED).parquet(f"{home}/round={r}")
        if r == 0 and batch is None:
            for row in placed.join(mine.select("seq", "c"), "seq").groupBy("block").agg(F.sum("c").alias("c")).collect():  # k rows
                loads[row["block"]] = row["c"]
        if seen is not None and end < n:
            now = seen.join(placed.select("seq", "block"), "seq").groupBy("net_id").agg(F.max(F.struct("seq", "block")).alias("x"), F.min("block").alias("lo"), F.max("block").alias("hi"), F.first("was").alias("was"), F.first("shut").alias("shut"))
            shut = F.col("shut") | (F.col("lo") != F.col("hi")) | (F.coalesce("was", "lo") != F.col("lo"))
            now.select("net_id", F.col("x.seq").alias("pred"), F.col("x.block").alias("was"), shut.alias("shut")).write.parquet(f"{marks}/round={r}")
        for t in temporary:
            discard(t)
        first = end
    discard(pins)
    return spark.read.schema(PLACED).parquet(home) if n else vertices.select("seq", "vertex_id", F.lit(0).alias("block"))


def fixpoint(h: Hypergraph, spec: PartitionSpec, max_sweeps: int | None = None) -> DataFrame:
    """The sequential answer by sweeps: every position decides again from the last sweep's placements before it.

    The correct prefix grows by one position a sweep at least, and the only fixpoint is the sequential answer. All k
    blocks are scored per position, so this is for short inputs and as a check of the other lanes."""
    capacity, strength = limits(h, spec)
    from ..operators.audit import scores

    assign = cut(h.vertices.select("vertex_id", "seq", F.lit(0).alias("block")), "sweep")
    for _ in range(max_sweeps or h.stats()["n"] + 1):
        scored = scores(h.pins, assign, spec, capacity, strength)
        best = scored.groupBy("seq").agg(F.max(F.struct("score", (-F.col("load")).alias("l"), (-F.col("candidate")).alias("b"))).alias("x"))
        # Placements of a wrong prefix can fill every block: such a position waits at the first one.
        after = cut(assign.select("vertex_id", "seq").join(best, "seq", "left").select("vertex_id", "seq", F.coalesce(-F.col("x.b"), F.lit(0)).cast("int").alias("block")), "sweep")
        changed = after.join(assign.withColumnRenamed("block", "was"), ["vertex_id", "seq"]).filter("block <> was").limit(1).count()
        assign = after
        if not changed:
            return assign
    raise RuntimeError("no fixpoint within the allowed sweeps")
