"""Lanes, measures and shapes on small frames."""

import math

import pytest
from pyspark.sql import Window as W, functions as F

from pinflow import catalog, report
from pinflow.operators import audit, capacity, controls, measures, shape, state
from pinflow.params import PartitionSpec
from pinflow.plans import choose, ordered, rounds
from pinflow.sources import builders


@pytest.fixture(scope="module")
def seven(spark):
    nets = {1: (0, 1, 2), 2: (2, 3), 3: (1, 3, 4, 6), 4: (4, 5), 5: (6,)}
    rows = [(e, v) for e, pins in nets.items() for v in pins] + [(1, 0)]
    return shape.prepare(spark.createDataFrame(rows, "net_id bigint, vertex_id bigint"))


def test_ordered_lane_and_measures(seven):
    assert seven.stats()["n"] == 7 and seven.stats()["m"] == 4 and seven.stats()["pins"] == 11
    placed = ordered.greedy(seven, PartitionSpec(3)).select("vertex_id", "block")
    assert [r["block"] for r in placed.orderBy("vertex_id").collect()] == [0, 0, 0, 1, 1, 1, 2]
    assert measures.cut_net(seven.pins, placed).first()["value"] == 2
    assert measures.connectivity(seven.pins, placed).first()["value"] == 3
    assert {r["net_id"]: r["lambda"] for r in measures.block_mask(seven.pins, placed).collect()} == {1: 1, 2: 2, 3: 3, 4: 1}


@pytest.mark.parametrize("objective", ["con", "cut"])
def test_rounds_of_one_and_fixpoint_are_the_sequential_rule(seven, objective):
    spec = PartitionSpec(3, objective=objective)
    want = ordered.greedy(seven, spec)
    for other in (rounds.greedy(seven, spec, batch=1), rounds.fixpoint(seven, spec)):
        assert audit.diff(want, other).first()["n_violations"] == 0


def test_cut_counts_a_wide_net_once(spark):
    pins = spark.createDataFrame([(1, 0), (1, 1), (1, 2)], "net_id bigint, vertex_id bigint")
    assign = spark.createDataFrame([(0, 0), (1, 1), (2, 2)], "vertex_id bigint, block int")
    nets = spark.createDataFrame([(1, 2.0)], "net_id bigint, weight double")
    assert measures.cut_net(pins, assign, nets).first()["value"] == 2
    assert measures.connectivity(pins, assign, nets).first()["value"] == 4


def test_parallel_nets_merge(spark):
    pins = spark.createDataFrame([(1, 1), (1, 2), (2, 1), (2, 2), (3, 2), (3, 3), (4, 9), (None, 1)], "net_id bigint, vertex_id bigint")
    kept, nets = shape.normalize(pins, "merge")
    assert {r["net_id"]: r["weight"] for r in nets.collect()} == {1: 2.0, 3: 1.0}
    assert kept.count() == 4


def test_fill_is_what_consecutive_placements_do():
    loads, cap, want = [3, 0, 5, 0], 6, []
    now = list(loads)
    for _ in range(sum(cap - x for x in loads)):
        b = min(range(4), key=lambda x: (now[x], x))
        want.append(b)
        now[b] += 1
    starts, _, members = capacity.fill_plan(loads, cap)
    got = []
    for t in range(len(want)):
        s = max(i for i in range(len(members)) if starts[i] <= t)
        got.append(members[s][(t - starts[s]) % len(members[s])])
    assert got == want


def test_reports(spark):
    runs = spark.createDataFrame([("i", 2, "A", 2.0), ("i", 2, "B", 3.0), ("j", 2, "A", 2.0), ("j", 2, "B", 2.0)], "instance string, k int, algorithm string, connectivity double")
    imp = {(r["instance"], r["algorithm"]): r["improvement"] for r in report.improvement(runs, "B").collect()}
    assert imp["i", "A"] == 50.0 and imp["j", "A"] == 0.0
    prof = {(r["algorithm"], r["tau"]): r["share"] for r in report.profile(runs, "connectivity", [1.0, 2.0]).collect()}
    assert prof["A", 1.0] == 1.0 and prof["B", 1.0] == 0.5 and prof["B", 2.0] == 1.0


def test_empty_and_lane_choice(spark):
    empty = spark.createDataFrame([], "net_id bigint, vertex_id bigint")
    h = shape.prepare(empty)
    assert ordered.greedy(h, PartitionSpec(2)).count() == 0
    assert choose.lane({"m": 10**12, "pins": 10**13}, PartitionSpec(2)) == "rounds"
    assert choose.lane({"m": 100, "pins": 1000}, PartitionSpec(2)) == "ordered"
    assert catalog.expected_rounds(10**11, 10**6, 0.1) == 122


def test_every_oracle_has_a_query():
    assert set(catalog.ORACLES) <= set(catalog.QUERIES)


@pytest.mark.parametrize("name", ["hash_connectivity", "greedy_audit_con", "greedy_con_suppliers_placed", "minmax_suppliers", "capacity_fill"])
def test_queries_match_duckdb(spark, sf, name):
    import duckdb

    con = duckdb.connect()
    for t in ("lineitem", "orders", "part"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    want = con.execute(catalog.ORACLES[name]).df()
    got = catalog.QUERIES[name](spark, sf).toPandas()[list(want.columns)]
    order = list(want.columns)
    assert got.sort_values(order).values.tolist() == want.sort_values(order).values.tolist()


def test_flagship(spark, sf):
    rows = catalog.flagship(spark, sf).collect()
    assert sum(r["vertices"] for r in rows) == 200 and len(rows) == 8


def test_hash_beats_nothing_structured(spark, sf):
    """On lines shared by documents the connectivity rule cuts less than hashing."""
    h = catalog.hypergraph(spark, sf, "docs_by_line")
    mine = measures.connectivity(h.pins, ordered.greedy(h, PartitionSpec(8))).first()["value"]
    base = measures.connectivity(h.pins, controls.hashing(h.vertices, 8)).first()["value"]
    assert mine < base


def test_ranges_of_a_hot_net_carry_their_state(spark):
    # Net 0 holds every vertex, nets 1-5 are sparse: slices of 1, of 7 and one for all agree with a plain window.
    seqs = spark.range(60).select(F.col("id").alias("vertex_id"), F.col("id").alias("seq"), (F.col("id") * 7 % 11 % 4).cast("int").alias("block"))
    pins = seqs.select(F.lit(0).cast("bigint").alias("net_id"), "vertex_id").union(seqs.filter("seq % 3 = 1").select((F.col("seq") % 5 + 1).alias("net_id"), "vertex_id"))
    earlier = W.partitionBy("net_id").orderBy("seq").rowsBetween(W.unboundedPreceding, -1)
    rows = pins.join(seqs, "vertex_id")
    want = rows.select("net_id", "seq", F.last("block").over(earlier).alias("b"), F.coalesce(F.min("block").over(earlier) != F.max("block").over(earlier), F.lit(False)).alias("c"))
    want = sorted(map(str, want.collect()))
    for width in (1, 7, 100):
        got = state.as_of_net(pins, seqs, width).select("net_id", "seq", F.col("last_block").alias("b"), F.col("is_cut").alias("c"))
        assert sorted(map(str, got.collect())) == want
        loads = {(r["seq"], r["candidate"]): r["load"] for r in state.loads_before(seqs, 4, width).collect()}
        blocks = [r["block"] for r in seqs.orderBy("seq").collect()]
        assert loads == {(s, b): blocks[:s].count(b) for s in range(60) for b in range(4)}
    h = shape.Hypergraph(pins, seqs)
    arcs = [sorted(map(tuple, shape.predecessor_arcs(h, w).collect())) for w in (1, 7, 100)]
    assert arcs[0] == arcs[1] == arcs[2] and len(arcs[0]) > 59


def test_a_null_before_is_not_nothing_before(spark):
    rows = spark.createDataFrame([(1, 0, 5), (1, 1, None), (1, 2, 6)], "g bigint, seq bigint, x int")
    for width in (1, 2, 9):
        got = state.before(rows, "g", {"was": ("last", F.col("x"))}, width).orderBy("seq").collect()
        assert [r["was"] for r in got] == [None, 5, None]


def test_predecessors_of_batches(spark):
    pins = spark.range(40).select((F.col("id") % 2).alias("net_id"), F.col("id").alias("vertex_id"))
    h = shape.Hypergraph(pins, spark.range(40).select(F.col("id").alias("vertex_id"), F.col("id").alias("seq")))
    ends = [4, 10, 25, 40]
    for r in rounds.batched_pins(h, ends).collect():
        before = [s for s in range(r["seq"] % 2, ([0] + ends)[r["batch"]], 2)]
        assert r["pred"] == (before[-1] if before else None)


def test_pairs_of_nets_of_any_size(spark):
    # 300 and 70 pins in two nets that overlap, nets of one and two pins, negative ids.
    nets = {1: range(-100, 200), 2: range(150, 220), 3: (5,), 4: (5, 199)}
    want = {}
    for own in nets.values():
        for a in own:
            for b in own:
                if a < b:
                    want[a, b] = want.get((a, b), 0) + 1
    pins = spark.createDataFrame([(e, v) for e, own in nets.items() for v in own], "net_id bigint, vertex_id bigint")
    for how in ({}, {"width": 7}, {"width": 1000}):
        got = builders.copurchase(pins, **how).collect()
        assert {(r["src"], r["dst"]): r["weight"] for r in got} == want and len(got) == len(want)


def plain_walk(nets, order, k, cap, strength, objective):
    """The sequential rule: vertex -> block. nets: net -> vertices."""
    of, last, broken, load, out = {}, {}, set(), [0] * k, {}
    for e, own in nets.items():
        for v in set(own):
            of.setdefault(v, []).append(e)
    for v in order:
        votes = [0] * k
        for e in of.get(v, ()):
            if e in last and not (objective == "cut" and e in broken):
                votes[last[e]] += 1
        b = max((b for b in range(k) if load[b] + 1 <= cap), key=lambda b: (votes[b] - strength * math.sqrt(load[b]), -load[b], -b))
        load[b] += 1
        for e in of.get(v, ()):
            if last.setdefault(e, b) != b:
                broken.add(e)
            last[e] = b
        out[v] = b
    return out


@pytest.mark.parametrize("objective", ["con", "cut"])
def test_lanes_agree_on_a_whole_instance_with_full_blocks(spark, objective):
    """One net holds all vertices, heavy votes fill a block to its bound: every vertex is compared, the last ones too."""
    nets = {0: range(12)} | {e: range(e % 3, 12, 2) for e in range(1, 5)} | {10 + e: (e, e + 5, (e * 7) % 12) for e in range(7)}
    h = shape.prepare(spark.createDataFrame([(e, v) for e, own in nets.items() for v in set(own)], "net_id bigint, vertex_id bigint"))
    spec = PartitionSpec(3, objective=objective, alpha_scale=0.1)
    cap, strength = ordered.limits(h, spec)
    want = plain_walk(nets, range(12), 3, cap, strength, objective)
    assert cap in [list(want.values()).count(b) for b in range(3)]
    for lane in (ordered.greedy(h, spec), rounds.greedy(h, spec, batch=1), rounds.greedy(h, spec, prefix=5, beta=0.01)):
        assert {r["vertex_id"]: r["block"] for r in lane.collect()} == want
    assert not {"rounds_batch1_diff", "rounds_fixpoint_diff"} & set(catalog.QUERIES)


def test_ladder_is_walked_to_the_end(spark, sf):
    keys = ("l_orderkey", "l_partkey", "l_suppkey", "l_quantity")
    lines = sorted(map(tuple, spark.read.parquet(f"{sf}/lineitem.parquet").select(*keys).collect()))

    def plain(blocks, k, every):
        load, out = [0] * k, []
        for i, b in enumerate(blocks, 1):
            load[b] += 1
            if i % every == 0:
                out.append((i, min(load), len(set(load))))
        return out

    want = plain([r[2] % 100 for r in lines], 100, 100)
    assert len(want) == len(lines) // 100 > 20
    assert sorted(map(tuple, catalog.QUERIES["ladder_trace"](spark, sf).collect())) == want
    blocks = [i * i % 7 % 5 for i in range(300)]
    bumps = spark.createDataFrame(list(enumerate(blocks)), "seq bigint, block int")
    for width in (37, 64):
        assert sorted(map(tuple, catalog.ladder_steps(bumps, 5, 10, width).collect())) == plain(blocks, 5, 10)


def test_larger_instances_by_brute_force(spark, sf):
    """Blocks, loads and measures of the whole instances: greedy in both objectives, and the min-max rule."""

    def instance(source):
        h = catalog.hypergraph(spark, sf, source)
        nets = {}
        for e, v in h.pins.select("net_id", "vertex_id").collect():
            nets.setdefault(e, []).append(v)
        return h, nets, [r["vertex_id"] for r in h.vertices.orderBy("seq").collect()]

    def walked(i, k, objective):
        h, nets, order = i
        return plain_walk(nets, order, k, *ordered.limits(h, PartitionSpec(k, objective=objective)), objective)

    def minmax(i, k):
        h, nets, order = i
        cap = PartitionSpec(k).capacity(len(order))
        slack, load, met, out = max(1, cap - -(-len(order) // k)), [0] * k, {e: set() for e in nets}, {}
        of = {}
        for e, own in nets.items():
            for v in own:
                of.setdefault(v, []).append(e)
        for v in order:
            fits = [b for b in range(k) if load[b] + 1 <= cap and load[b] <= min(load) + slack]
            b = out[v] = max(fits, key=lambda b: (sum(b in met[e] for e in of.get(v, ())), -load[b], -b))
            load[b] += 1
            for e in of.get(v, ()):
                met[e].add(b)
        return out

    rows = lambda name: catalog.QUERIES[name](spark, sf).collect()
    blocks = lambda name: {r["vertex_id"]: r["block"] for r in rows(name)}
    loads = lambda name: {r["block"]: r["load"] for r in rows(name)}
    count = lambda want: {b: list(want.values()).count(b) for b in set(want.values())}
    parts, customers, clauses = map(instance, ("parts_by_order", "customers_by_part", "signed_clauses"))
    for objective, name in (("con", "greedy_con_parts"), ("cut", "greedy_cut_parts")):
        want = walked(parts, 16, objective)
        assert blocks(name) == want
        spans = [len({want[v] for v in own}) for own in parts[1].values()]
        assert tuple(rows(f"greedy_{objective}_quality")[0]) == (sum(s > 1 for s in spans), sum(s - 1 for s in spans))
    assert loads("greedy_con_customers") == count(walked(customers, 8, "con"))
    assert blocks("greedy_cut_clauses") == walked(clauses, 32, "cut")
    assert blocks("minmax_parts") == minmax(parts, 16)
    assert loads("minmax_customers") == count(minmax(customers, 8))
    assert len(blocks("greedy_weighted_parts")) == len(parts[2])


def test_fill_stays_within_its_capacity(spark, tmp_path):
    rows = spark.range(12).select(F.col("id").alias("seq"))
    assert capacity.fill(rows, [0, 4], 8, "seq").count() == 12
    with pytest.raises(Exception, match="places are free"):
        capacity.fill(rows, [0, 4], 7, "seq").collect()
    spark.range(90_000).select(F.col("id").alias("p_partkey")).write.parquet(f"{tmp_path}/part.parquet")
    loads = {r["block"]: r["c"] + r["block"] ** 2 for r in catalog.QUERIES["capacity_fill"](spark, str(tmp_path)).groupBy("block").agg(F.count("*").alias("c")).collect()}
    assert sum(loads.values()) == 90_140 and max(loads.values()) == 11_268


@pytest.mark.parametrize("objective", ["con", "cut"])
def test_weighted_rounds_are_the_weighted_rule(spark, objective):
    """Batches of one vertex with weights of vertices and nets place like the exact lane, and larger ones keep the bound."""
    nets = {e: {(e * 3) % 14, (e * 5 + 1) % 14, (e + 7) % 14} for e in range(20)}
    pins = spark.createDataFrame([(e, v) for e, own in nets.items() for v in own], "net_id bigint, vertex_id bigint")
    weights = spark.createDataFrame([(v, float(1 + v % 3)) for v in range(14)], "vertex_id bigint, weight double")
    heavy = spark.createDataFrame([(e, float(1 + e % 4)) for e in range(18)], "net_id bigint, weight double")  # two nets have none
    h = shape.prepare(pins, weights=weights, net_weights=heavy)
    assert h.stats()["net_weight"] == sum(1 + e % 4 for e in range(18)) + 2
    spec = PartitionSpec(3, "0.2", objective=objective, weighted=True)
    want = ordered.greedy(h, spec)
    assert audit.diff(want, rounds.greedy(h, spec, batch=1)).first()["n_violations"] == 0
    for how in ({"batch": 5}, {"prefix": 4, "beta": 1.0}):
        assert audit.balance_audit(h, rounds.greedy(h, spec, **how), spec).first()["n_violations"] == 0


def test_twelve_weighted_vertices_keep_their_bound(spark):
    pins = spark.createDataFrame([(1, v) for v in range(12)] + [(2, v) for v in range(0, 12, 2)], "net_id bigint, vertex_id bigint")
    weights = spark.createDataFrame([(v, float(1 + v % 4)) for v in range(12)], "vertex_id bigint, weight double")
    h, spec = shape.prepare(pins, weights=weights), PartitionSpec(2, "0.1", weighted=True)
    assert audit.balance_audit(h, rounds.greedy(h, spec, batch=6), spec).first()["n_violations"] == 0
    with pytest.raises(ValueError, match="ladder|block number"):
        rounds.greedy(h, PartitionSpec(2, tie="ladder"))


def test_weighted_fill_in_slices(spark):
    rows = spark.range(500).select(F.col("id").alias("seq"), F.col("id").alias("vertex_id"), (F.col("id") % 5 + 1).cast("double").alias("c"))
    for width in (1 << 20, 64):
        got = capacity.fill_weighted(rows, [0.0, 100.0, 30.0, 0.0], 420.0, 500, width).collect()
        loads = [0.0, 100.0, 30.0, 0.0]
        for r in got:
            loads[r["block"]] += r["c"]
        assert sorted(r["seq"] for r in got) == list(range(500)) and max(loads) <= 420


def test_loads_after_a_fill():
    for loads, cap in (([3, 0, 5, 0], 6), ([1, 1, 1], 2), ([0], 9)):
        now = list(loads)
        for n in range(sum(cap - x for x in loads) + 1):
            assert capacity.filled_loads(loads, cap, n) == now
            b = min(range(len(now)), key=lambda x: (now[x], x))
            now[b] += 1


def test_orders_by_time_and_degree(spark):
    pins = spark.createDataFrame([(1, 5), (2, 5), (3, 5), (1, 6), (2, 7), (3, 7)], "net_id bigint, vertex_id bigint")
    seq = lambda **how: [r["vertex_id"] for r in shape.prepare(pins, **how).vertices.orderBy("seq").collect()]
    assert seq(order="degree") == [6, 7, 5]
    assert seq(order="time", by=spark.createDataFrame([(5, 2), (6, 9)], "vertex_id bigint, key int")) == [7, 5, 6]
    with pytest.raises(ValueError, match="needs the column"):
        shape.prepare(pins, order="time")


def test_parallel_nets_are_confirmed_pin_by_pin(spark):
    nets = {1: (1, 2, 3), 2: (3, 2, 1), 3: (1, 2, 4), 4: (1, 2), 5: (2, 1), 6: (1, 2)}
    pins = spark.createDataFrame([(e, v) for e, own in nets.items() for v in own], "net_id bigint, vertex_id bigint")
    assert {tuple(r) for r in shape.parallel_groups(pins).collect()} == {(1, 1), (2, 1), (4, 4), (5, 4), (6, 4)}


def test_clause_and_matrix_files(spark, tmp_path):
    from pinflow.sources import netlist

    (tmp_path / "a.cnf").write_text("c three clauses\np cnf 4 3\n1 -2 0\n-1 -3 4 0\n2 3 0\n")
    got = {}
    for e, v in netlist.read_signed_clauses(spark, str(tmp_path / "a.cnf")).collect():
        got.setdefault(e, set()).add(v)
    assert sorted(map(sorted, got.values())) == [[1, 2], [1, 3, 4], [2, 3]]
    (tmp_path / "a.mtx").write_text("%%MatrixMarket matrix coordinate real general\n% x\n3 4 4\n1 2 0.5\n1 4 1\n3 2 -1\n2 1 7\n")
    assert {tuple(r) for r in netlist.read_coordinates(spark, str(tmp_path / "a.mtx")).collect()} == {(1, 2), (1, 4), (3, 2), (2, 1)}


def test_live_loads_and_late_pins(spark, tmp_path):
    """Window counts of a stream, repeated vertices dropped by watermark, and late pins that pull later vertices."""
    from pinflow.streaming import live

    rows = [(1, 0, 1, [10]), (1, 1, 2, [11]), (1, 2, 1, [12]), (1, 3, 3, [12])]
    schema = "stream_id bigint, seq bigint, vertex_id bigint, nets array<bigint>"
    spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / "in"))

    def placed(late):
        out = str(tmp_path / late)
        stream = live.partition_stream(spark.readStream.schema(schema).parquet(str(tmp_path / "in")), PartitionSpec(2, "1"), 4, 4, late)
        stream.writeStream.format("parquet").option("checkpointLocation", out + "-ckpt").trigger(availableNow=True).start(out).awaitTermination()
        return {r["vertex_id"]: r["block"] for r in spark.read.schema(live.OUT).parquet(out).collect()}

    drop, apply = placed("drop"), placed("apply")
    assert drop[1] == apply[1] and drop[2] == apply[2] and set(drop) == {1, 2, 3} and apply[3] == apply[1]
    times = [("2024-01-01 00:10:00", 1, 0), ("2024-01-01 00:20:00", 1, 0), ("2024-01-01 05:00:00", 2, 1)]
    events = spark.createDataFrame(times, "ts string, vertex_id bigint, block int").select(F.col("ts").cast("timestamp").alias("ts"), "vertex_id", "block")
    events.coalesce(1).write.parquet(str(tmp_path / "ev"))
    stream = lambda: spark.readStream.schema(events.schema).parquet(str(tmp_path / "ev"))
    once, loads = str(tmp_path / "once"), str(tmp_path / "loads")
    live.deduplicated(stream()).writeStream.format("parquet").option("checkpointLocation", once + "-c").trigger(availableNow=True).start(once).awaitTermination()
    assert sorted(r["vertex_id"] for r in spark.read.parquet(once).collect()) == [1, 2]
    live.windowed_loads(stream(), "1 hour").writeStream.format("memory").queryName("loads_now").outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    assert {(r["block"], r["arrivals"]) for r in spark.table("loads_now").collect()} == {(0, 2), (1, 1)}


def test_a_cluster_needs_a_shared_folder():
    from pinflow import lineage

    class Conf:
        def get(self, name, default=None):
            return {"spark.master": "spark://host:7077"}.get(name, default)

    class Session:
        conf = Conf()

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        lineage.scratch_path(Session(), "x")


def test_salted_join_is_the_join(spark):
    from pinflow.operators.skew import salted_join

    left = spark.createDataFrame([(1, i) for i in range(60)] + [(2, 5), (3, 6), (None, 7)], "k int, x int")
    right = spark.createDataFrame([(1, "a"), (1, "b"), (2, "c"), (None, "z"), (9, "q")], "k int, y string")
    for how in ("inner", "left"):
        got = salted_join(left, right, "k", share=0.3, salts=7, how=how)
        assert sorted(map(str, got.collect())) == sorted(map(str, left.join(right, "k", how).collect()))


def test_lines_as_a_stream(spark, tmp_path):
    from pinflow.sources import netlist
    from pinflow.streaming import live

    (tmp_path / "in").mkdir()
    (tmp_path / "in" / "a.txt").write_text("# vertex nets\n0 10 11\n1 12\n\n2\n3 10 11\n")
    out = str(tmp_path / "out")
    stream = live.partition_stream(netlist.stream_netlist(spark, str(tmp_path / "in")), PartitionSpec(2, "1"), 4, 3)
    stream.writeStream.format("parquet").option("checkpointLocation", out + "-c").trigger(availableNow=True).start(out).awaitTermination()
    got = {r["vertex_id"]: r["block"] for r in spark.read.schema(live.OUT).parquet(out).collect()}
    assert set(got) == {0, 1, 2, 3} and got[3] == got[0] != got[1]


def test_chosen_lane_places(spark, seven):
    spec = PartitionSpec(3)
    want = {r["vertex_id"]: r["block"] for r in ordered.greedy(seven, spec).collect()}
    for how in ({}, {"pin_limit": 1}):
        assert {r["vertex_id"]: r["block"] for r in choose.place(seven, spec, **how).collect()} == want


def test_spans_of_many_placements_stay_one_row_per_pin(spark, seven):
    vertices = spark.createDataFrame([(v,) for v in range(7)], "vertex_id bigint")
    cells = [(controls.hash_block(F.col("vertex_id"), k, s), k) for k in (2, 16, 40) for s in (0, 1, 2)]
    merged, spans = measures.spans_of(seven.pins, vertices, cells)
    plan = merged._jdf.queryExecution().executedPlan().toString()
    assert "Broadcast" not in plan and "Generate" not in plan
    got = {r["net_id"]: list(r)[1:] for r in merged.select("net_id", *[l.alias(str(i)) for i, l in enumerate(spans)]).collect()}
    for i, (block, _) in enumerate(cells):
        want = measures.net_span(seven.pins, vertices.select("vertex_id", block.alias("block")))
        assert {r["net_id"]: r["lambda"] for r in want.collect()} == {net: row[i] for net, row in got.items()}


def test_control_runs_end_where_the_session_broadcasts_freely(spark, sf):
    runs = catalog.control_runs(spark, sf)
    assert runs.count() == 54 and runs.filter("cut_net > connectivity").isEmpty()


@pytest.mark.parametrize("objective", ["con", "cut"])
@pytest.mark.parametrize("weighted", [False, True])
def test_walked_rounds_are_the_parallel_rounds(spark, objective, weighted):
    import random

    draw = random.Random(5)
    pins = spark.createDataFrame([(draw.randrange(12), v) for v in range(60) for _ in range(draw.randrange(4))] + [(99, v) for v in range(60)], "net_id bigint, vertex_id bigint")
    weights = spark.createDataFrame([(v, float(1 + v % 3)) for v in range(60)], "vertex_id bigint, weight double") if weighted else None
    h = shape.prepare(pins, weights=weights)
    spec = PartitionSpec(4, objective=objective, weighted=weighted)
    want = {r["vertex_id"]: r["block"] for r in rounds.greedy(h, spec, batch=13, walk=0).collect()}
    assert {r["vertex_id"]: r["block"] for r in rounds.greedy(h, spec, batch=13).collect()} == want and len(want) == 60


def test_small_batches_take_no_job_each(spark):
    h = shape.prepare(spark.createDataFrame([(v % 7, v) for v in range(400)], "net_id bigint, vertex_id bigint"))
    tracker = spark.sparkContext.statusTracker()
    spark.sparkContext.setJobGroup("small-batches", "")
    assert rounds.greedy(h, PartitionSpec(4), batch=4).count() == 400
    assert len(tracker.getJobIdsForGroup("small-batches")) < 20
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


@pytest.mark.parametrize("objective", ["con", "cut"])
def test_walked_micro_batches_keep_the_state_of_the_parallel_ones(spark, objective):
    from pinflow.streaming import live

    spec = PartitionSpec(3, objective=objective)
    rows = [(v, v + 100, 1.0, [v % 4, 10 + v % 3, 20 + v // 5][: v % 4]) for v in range(24)]
    states = {False: None, True: None}
    for first in (0, 9, 18):
        batch = spark.createDataFrame(rows[first : first + 9], "seq bigint, vertex_id bigint, weight double, nets array<bigint>")
        seen = {}
        for walk in states:
            placed, after = live.round_of(spec, 9, 0.2, walk)(batch, states[walk])
            states[walk] = spark.createDataFrame(after.collect(), live.STATE)
            seen[walk] = sorted(map(tuple, placed.collect())), sorted(map(str, states[walk].collect()))
        assert seen[True] == seen[False] and len(seen[True][0]) == min(9, 24 - first)


def test_files_in_turn_stream_in_order(spark, tmp_path):
    from pinflow.lineage import write_in_turn

    rows = spark.range(230).select(F.col("id").alias("seq"))
    write_in_turn(rows, str(tmp_path / "in"), "seq", 7)
    files = sorted((tmp_path / "in").glob("part-*"), key=lambda f: f.stat().st_mtime)
    assert [r["seq"] for f in files for r in spark.read.parquet(str(f)).collect()] == list(range(230)) and len(files) == 33


def test_written_plans_broadcast_small_tables_only(spark):
    from pinflow.lineage import _bytes, small_broadcasts

    name = "spark.sql.autoBroadcastJoinThreshold"
    before = spark.conf.get(name)
    assert [_bytes(x) for x in ("-1", "10485760b", "256k", "10MB", "7")] == [-1, 10 << 20, 1 << 18, 10 << 20, 7]

    def plan():
        return spark.range(10**6).join(spark.range(10**5), "id")._jdf.queryExecution().executedPlan().toString()

    assert "BroadcastHashJoin" in plan()
    with small_broadcasts(spark):
        assert "BroadcastHashJoin" not in plan()
    assert spark.conf.get(name) == before


@pytest.mark.parametrize("engine", ["split", "scan"])
def test_graph_rule_by_classes_is_the_rule_by_pairs(spark, engine):
    """Copies, nets of one pin and lone vertices among others: blocks as from the table of edges."""
    rows = [(e, v) for v in range(120) for e in {v % 6, 10 + v % 6 // 2, 20 + v * v % 11 * (v > 60), 1000 + v}] + [(5000, 500), (5000, 500), (None, 7)]
    pins = spark.createDataFrame(rows, "net_id bigint, vertex_id bigint")
    edges = builders.copurchase(pins.dropna().distinct()).withColumn("weight", F.lit(1.0)).localCheckpoint()
    want = ordered.graph_greedy(edges, PartitionSpec(7), engine).select("vertex_id", "block").collect()
    got = ordered.shared_net_greedy(pins, PartitionSpec(7), engine).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, want)) and len(got) == 120


def test_graph_rule_makes_no_pairs_of_copies():
    """20,000 copies are 2 * 10^8 pairs."""
    import numpy as np

    from pinflow.kernel.shared import SharedNets

    shared = SharedNets([np.array([1, 2 + v % 2]) for v in range(20_000)])
    assert len(shared.nets) == 2 and shared.edges() == 20_000 * 19_999 // 2
    assert np.bincount(shared.place(PartitionSpec(4), "split")).max() <= 5150


def test_methods_are_run_one_after_another(spark, sf, monkeypatch):
    """A method's placement is written before the next method starts."""
    events, cut, methods = [], catalog.cut, dict(catalog.METHODS)
    monkeypatch.setattr(catalog, "COMPARED", ("suppliers_by_order",))
    monkeypatch.setattr(catalog, "_compared", {})
    monkeypatch.setattr(catalog, "cut", lambda df, label, *a: (events.append(label), cut(df, label, *a))[1])
    monkeypatch.setattr(catalog, "METHODS", {name: (rule, lambda h, s, place=place: (events.append("walk"), place(h, s))[1]) for name, (rule, place) in methods.items()})
    assert catalog.method_runs(spark, sf).count() == 10
    assert events == ["walk", "placement"] * 10 + ["method-runs"]


def test_control_runs_read_their_tables_once(spark, tmp_path, monkeypatch):
    """The pins are made by one job of the builder; nets of one pin count for nothing, an instance without others has no runs."""
    made = spark.sparkContext.accumulator(0)

    def seen(x):
        made.add(1)
        return x

    tick = F.udf(seen, "bigint").asNondeterministic()
    rows = [(1, 0), (1, 1), (1, 2), (2, 2), (2, 3), (3, 4), (4, 0), (4, 4)]
    table = lambda own: lambda s, d: s.createDataFrame(own, "net_id bigint, vertex_id bigint").select("net_id", tick("vertex_id").alias("vertex_id"))
    monkeypatch.setattr(builders, "HYPERGRAPHS", {"a": table(rows), "b": table([(1, 0), (2, 1)])})
    monkeypatch.setattr(catalog, "INSTANCES", ("a", "b"))
    found = {(r["instance"], r["k"], r["algorithm"], r["seed"]): (r["cut_net"], r["connectivity"]) for r in catalog.control_runs(spark, str(tmp_path)).collect()}
    assert made.value == len(rows) + 2
    assert {k[0] for k in found} == {"a"} and len(found) == 18
    assert found["a", 4, "round_robin", 0] == (2.0, 3.0) and found["a", 8, "round_robin", 0] == (3.0, 4.0)


@pytest.fixture(scope="module")
def wide(tmp_path_factory):
    """Tables of 100,000 lines, some twice, whose vertices have ids that hardly compress."""
    import duckdb

    d = tmp_path_factory.mktemp("wide")
    con = duckdb.connect()
    key = lambda column, n: f"CAST(hash({n}) >> 1 AS BIGINT) AS {column}"
    lines = f"{key('l_orderkey', 'i % 30011')}, {key('l_partkey', 'i * 7 % 50021')}, {key('l_suppkey', 'i * 11 % 40009')}"
    con.execute(f"COPY (SELECT {lines} FROM (SELECT range % 90000 AS i FROM range(100000))) TO '{d}/lineitem.parquet'")
    con.execute(f"COPY (SELECT {key('o_orderkey', 'range')}, {key('o_custkey', 'range * 3 % 29989')} FROM range(30011)) TO '{d}/orders.parquet'")
    return str(d)


def broadcast_rows(spark, after: int = -1) -> tuple[int, int]:
    """The most rows in one broadcast of the plans run since execution ``after``, and the number of the last one."""
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    store, most, last = spark._jsparkSession.sharedState().statusStore(), 0, after
    every = lambda seq: (seq.apply(i) for i in range(seq.size()))
    for run in every(store.executionsList()):
        number = run.executionId()
        last = max(last, number)
        if number > after:
            told = store.executionMetrics(number)
            for node in every(store.planGraph(number).allNodes()):
                for metric in every(node.metrics()) if node.name() == "BroadcastExchange" else ():
                    found = told.get(metric.accumulatorId())
                    if metric.name() == "number of output rows" and found.isDefined():
                        most = max(most, int(found.get().replace(",", "")))
    return most, last


@pytest.mark.parametrize("name", ["mean_geomean", "profile_curve", "rank_stability", "report_cube"])
def test_reports_over_control_runs_broadcast_no_table_that_grows(spark, wide, name):
    """The driver builds what is broadcast: neither vertices nor their placements are, and the result is the SQL's."""
    import duckdb

    _, before = broadcast_rows(spark)
    found = catalog.QUERIES[name](spark, wide)
    got = found.collect()
    most, last = broadcast_rows(spark, before)
    assert last > before and 0 < most < 1000
    con = duckdb.connect()
    for t in ("lineitem", "orders"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{wide}/{t}.parquet')")
    want = con.execute(catalog.ORACLES[name])
    names = [c[0] for c in want.description]
    assert sorted((tuple(r[c] for c in names) for r in got), key=str) == sorted(want.fetchall(), key=str)


def test_method_runs_make_pins_and_walk_stream_once(spark, tmp_path, monkeypatch):
    """The builder's rows are made by one job and the vertices with their nets written once, for all walks; runs are those of the rules."""
    made, labels = spark.sparkContext.accumulator(0), []

    def seen(x):
        made.add(1)
        return x

    tick = F.udf(seen, "bigint").asNondeterministic()
    rows = [(7 * (i * i % 23), i % 61) for i in range(400)] + [(9999, 77)]
    pins = spark.createDataFrame(rows, "net_id bigint, vertex_id bigint")
    monkeypatch.setattr(builders, "HYPERGRAPHS", {"a": lambda s, d: pins.select("net_id", tick("vertex_id").alias("vertex_id"))})
    monkeypatch.setattr(catalog, "COMPARED", ("a",))
    monkeypatch.setattr(catalog, "_compared", {})
    monkeypatch.setattr(shape, "cut", lambda df, label, *a, write=shape.cut: (labels.append(label), write(df, label, *a))[1])
    found = {(r["k"], r["algorithm"]): (r["cut_net"], r["connectivity"]) for r in catalog.method_runs(spark, str(tmp_path)).collect()}
    assert made.value == len(rows) and labels.count("numbered-stream") == 1 and len(found) == 10
    h = shape.prepare(pins)
    slow = {
        "greedy_con": lambda s: ordered.greedy(h, s), "greedy_cut": lambda s: ordered.greedy(h, PartitionSpec(s.k, objective="cut")),
        "minmax_lists": lambda s: ordered.minmax_place(h, s), "minmax_capped": lambda s: ordered.minmax_place(h, s, "capped"),
    }
    for name, place in slow.items():
        assert found[8, name] == tuple(catalog.quality(h, place(PartitionSpec(8)).select("vertex_id", "block")).first())


def test_small_broadcasts_of_threads_put_the_settings_back(spark):
    """Two that overlap: the first one out does not restore, the last one does."""
    from pinflow.lineage import BROADCAST, small_broadcasts

    name = "spark.sql.autoBroadcastJoinThreshold"
    before = spark.conf.get(name)
    a, b = small_broadcasts(spark), small_broadcasts(spark)
    a.__enter__()
    b.__enter__()
    a.__exit__(None, None, None)
    assert spark.conf.get(name) == str(BROADCAST)
    b.__exit__(None, None, None)
    assert spark.conf.get(name) == before
