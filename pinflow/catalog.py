"""Named queries of the engine and their DuckDB counterparts.

Comparisons (``*_diff``) and audits return n_checked, which the SQL side counts from the base tables, and
n_violations, which must be 0."""

from __future__ import annotations

import math
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from . import oracles as sql
from . import report
from .functions import sqlapi
from .kernel.ladder import LoadLadder
from .lineage import cut, discard, release, scratch_path, small_broadcasts, write_in_turn
from .operators import audit, capacity, controls, inmem, measures, shape, skew, state
from .params import PartitionSpec
from .plans import choose, ordered, rounds
from .sources import builders, netlist
from .sources.tables import read_table
from .streaming import live

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def hypergraph(spark: SparkSession, d: str, name: str, **how) -> shape.Hypergraph:
    return shape.prepare(builders.HYPERGRAPHS[name](spark, d), **how)


def placements(decisions: DataFrame) -> DataFrame:
    return decisions.select("vertex_id", "block")


def quality(h: shape.Hypergraph, assign: DataFrame) -> DataFrame:
    """cut_net and connectivity in one aggregation."""
    spans = measures.net_span(h.pins, assign)
    return spans.agg(F.sum(F.when(F.col("lambda") > 1, 1.0).otherwise(0.0)).alias("cut_net"), F.sum(F.col("lambda") - 1).cast("double").alias("connectivity"))


def flagship(spark: SparkSession, d: str, k: int = 8) -> DataFrame:
    """block, vertices, nets_met, cut_net, connectivity of the connectivity rule over parts by order."""
    h = hypergraph(spark, d, "parts_by_order")
    assign = cut(ordered.greedy(h, PartitionSpec(k)), "flagship")
    per = measures.placed(h.pins, assign).groupBy("block").agg(F.count_distinct("net_id").alias("nets_met"))
    sizes = assign.groupBy("block").agg(F.count("*").alias("vertices"))
    return sizes.join(per, "block", "left").crossJoin(F.broadcast(quality(h, assign)))


def select_with(name: str, body: str, tail: str) -> str:
    recursive = "RECURSIVE " if "UNION ALL" in body else ""
    return f"WITH {recursive}{sql.base(name)},\n{body}\n{tail}"


# --- stateless placements and their measures -------------------------------------------------------------------------

K = 16
H1 = "parts_by_order"
HASHED = f"a AS (SELECT vertex_id, {sql.hashed(K)} AS block FROM v)"


@query("hash_assign", f"SELECT p_partkey AS vertex_id, {sql.hashed(K, 'p_partkey')} AS block FROM part")
def hash_assign(spark, d):
    return controls.hashing(read_table(spark, d, "part", "p_partkey").withColumnRenamed("p_partkey", "vertex_id"), K)


def _hashed(spark, d):
    h = hypergraph(spark, d, H1)
    return h, controls.hashing(h.vertices, K)


@query("hash_cut_net", select_with(H1, HASHED, f"SELECT cut_net AS value FROM ({sql.quality('a')})"))
def hash_cut_net(spark, d):
    h, a = _hashed(spark, d)
    return measures.cut_net(h.pins, a)


@query("hash_connectivity", select_with(H1, HASHED, f"SELECT connectivity AS value FROM ({sql.quality('a')})"))
def hash_connectivity(spark, d):
    h, a = _hashed(spark, d)
    return measures.connectivity(h.pins, a)


@query("hash_balance", f"WITH l AS (SELECT {sql.hashed(K, 'p_partkey')} AS block, CAST(count(*) AS DOUBLE) AS load FROM part GROUP BY 1), b AS (SELECT CAST({sql.bound('count(*)', K)} AS DOUBLE) AS l_max FROM part) SELECT CAST(r.range AS INTEGER) AS block, coalesce(load, 0) AS load, l_max, coalesce(load, 0) > l_max AS over FROM range({K}) r LEFT JOIN l ON l.block = r.range, b")
def hash_balance(spark, d):
    vertices = read_table(spark, d, "part", "p_partkey").select(F.col("p_partkey").alias("vertex_id"), F.lit(1.0).alias("weight"))
    return measures.balance(vertices, controls.hashing(vertices, K), PartitionSpec(K))


@query("imbalance_hash", select_with(H1, HASHED, f"SELECT max(c) * {K} / sum(c) - 1 AS value FROM (SELECT CAST(count(*) AS DOUBLE) AS c FROM a GROUP BY block)"))
def imbalance_hash(spark, d):
    h, a = _hashed(spark, d)
    return measures.imbalance(h.vertices, a, K)


def _control(name, expression, place):
    @query(f"{name}_quality", select_with(H1, f"a AS (SELECT vertex_id, CAST({expression} AS INTEGER) AS block FROM v)", sql.quality("a")))
    def run(spark, d):
        h = hypergraph(spark, d, H1)
        return quality(h, place(h))


_control("round_robin", f"seq % {K}", lambda h: controls.round_robin(h.vertices, K))
_control("contiguous", f"seq * {K} // (SELECT count(*) FROM v)", lambda h: controls.contiguous(h.vertices, K, h.stats()["n"]))
_control("modulo", f"vertex_id % {K}", lambda h: controls.modulo(h.vertices, K))
_control("random", sql.seeded(K, "'3'"), lambda h: controls.random_blocks(h.vertices, K, 3))


@query("net_span", select_with(H1, HASHED, "SELECT net_id, CAST(count(DISTINCT block) AS INTEGER) AS lambda FROM p JOIN a USING (vertex_id) GROUP BY net_id"))
def net_span(spark, d):
    h, a = _hashed(spark, d)
    return measures.net_span(h.pins, a)


@query("block_mask_span", ORACLES["net_span"])
def block_mask_span(spark, d):
    h, a = _hashed(spark, d)
    return measures.block_mask(h.pins, a)


@query("span_histogram", select_with(H1, HASHED, "SELECT l AS \"lambda\", count(*) AS nets FROM (SELECT net_id, CAST(count(DISTINCT block) AS INTEGER) AS l FROM p JOIN a USING (vertex_id) GROUP BY net_id) GROUP BY l"))
def span_histogram(spark, d):
    h, a = _hashed(spark, d)
    return measures.span_histogram(h.pins, a)


@query("external_degrees", select_with(H1, HASHED, "SELECT CAST(sum(l) AS BIGINT) AS value FROM (SELECT count(DISTINCT block) AS l FROM p JOIN a USING (vertex_id) GROUP BY net_id) WHERE l > 1"))
def external_degrees(spark, d):
    h, a = _hashed(spark, d)
    return measures.sum_of_external_degrees(h.pins, a)


@query("replication", select_with(H1, HASHED, "SELECT sum(l) / CAST(count(*) AS DOUBLE) AS value FROM (SELECT count(DISTINCT block) AS l FROM p JOIN a USING (vertex_id) GROUP BY net_id)"))
def replication(spark, d):
    h, a = _hashed(spark, d)
    return measures.replication(h.pins, a)


@query("boundary_vertices", select_with(H1, HASHED, "SELECT DISTINCT vertex_id FROM p WHERE net_id IN (SELECT net_id FROM p JOIN a USING (vertex_id) GROUP BY net_id HAVING count(DISTINCT block) > 1)"))
def boundary_vertices(spark, d):
    h, a = _hashed(spark, d)
    return measures.boundary_vertices(h.pins, a)


@query("state_entries", select_with(H1, HASHED, f"SELECT count(*) + {K} AS greedy, CAST(sum(l) AS BIGINT) + {K} AS lists, count(*) * {K} AS lists_worst, (SELECT count(*) FROM v) + {K} AS graph FROM (SELECT count(DISTINCT block) AS l FROM p JOIN a USING (vertex_id) GROUP BY net_id)"))
def state_entries(spark, d):
    h, a = _hashed(spark, d)
    return measures.state_entries(h.pins, a, K)


# --- the greedy rules, replayed by recursion ---------------------------------------------------------------------------


def _greedy(name, source, k, objective, tail, finish, **how):
    oracle = select_with(source, sql.replay(k, objective, **{x: y for x, y in how.items() if x in ("gamma", "scale", "vertices")}).replace("q AS", how.get("before", "") + "q AS", 1), tail)

    @query(name, oracle)
    def run(spark, d):
        h = hypergraph(spark, d, source)
        spec = PartitionSpec(k, objective=objective, gamma=how.get("gamma", 1.5), alpha_scale=how.get("scale", 1.0))
        return finish(h, ordered.greedy(h, spec))


def _as_loads(h, decisions):
    return decisions.groupBy("block").agg(F.count("*").alias("load"))


ASSIGNED, LOADED = "SELECT vertex_id, block FROM a", "SELECT block, count(*) AS load FROM a GROUP BY block"
for _objective in ("con", "cut"):
    _greedy(f"greedy_{_objective}_suppliers_placed", "suppliers_by_order", K, _objective, ASSIGNED, lambda h, x: placements(x))
    _greedy(f"greedy_{_objective}_docs", "docs_by_line", 8, _objective, ASSIGNED, lambda h, x: placements(x))
    _greedy(f"greedy_{_objective}_pages", "pages_by_link", 8, _objective, sql.quality("a"), lambda h, x: quality(h, x))
    _greedy(f"greedy_{_objective}_convs", "convs_by_word", 8, _objective, sql.quality("a"), lambda h, x: quality(h, x))
_greedy("greedy_con_suppliers", "suppliers_by_order", 8, "con", LOADED, _as_loads)
_greedy("greedy_cut_suppliers", "suppliers_by_order", 32, "cut", LOADED, _as_loads)
_greedy("greedy_con_users", "users_by_hour_type", 4, "con", ASSIGNED, lambda h, x: placements(x))
_greedy("greedy_cut_users", "users_by_hour", 4, "cut", ASSIGNED, lambda h, x: placements(x))

_WEIGHTS = "(100 + net_id % 7)"
_weighted_nets = sql.replay(K, weight=_WEIGHTS, weighted=True)


@query("greedy_weighted_nets", select_with("suppliers_by_order", _weighted_nets, ASSIGNED))
def greedy_weighted_nets(spark, d):
    pins = builders.suppliers_by_order(spark, d)
    weights = pins.select("net_id").distinct().select("net_id", (100 + F.col("net_id") % 7).cast("double").alias("weight"))
    h = shape.prepare(pins, net_weights=weights)
    return placements(ordered.greedy(h, PartitionSpec(K, weighted=True)))


@query("greedy_weighted_vertices", select_with("users_by_hour_type", sql.replay(8, vertices="vw", vertex_weight="c", weighted=True).replace("q AS (", "vw AS (SELECT vertex_id, seq, 1 + vertex_id % 5 AS c FROM v),\nq AS (", 1), ASSIGNED))
def greedy_weighted_vertices(spark, d):
    pins = builders.users_by_hour_type(spark, d)
    weights = pins.select("vertex_id").distinct().select("vertex_id", (1 + F.col("vertex_id") % 5).cast("double").alias("weight"))
    return placements(ordered.greedy(shape.prepare(pins, weights=weights), PartitionSpec(8, weighted=True)))


MAX_LOAD = "SELECT q.*, (SELECT max(c) FROM (SELECT count(*) AS c FROM a GROUP BY block)) AS max_load FROM (" + sql.quality("a") + ") q"


def _with_max_load(h, decisions):
    return quality(h, decisions).crossJoin(decisions.groupBy("block").agg(F.count("*").alias("c")).agg(F.max("c").alias("max_load")))


for _objective in ("con", "cut"):
    _greedy(f"greedy_{_objective}_parts", H1, K, _objective, ASSIGNED, lambda h, x: placements(x))
    _greedy(f"greedy_{_objective}_quality", H1, K, _objective, sql.quality("a"), lambda h, x: quality(h, x))
    _greedy(f"greedy_{_objective}_orders", "orders_by_part", 64, _objective, MAX_LOAD, _with_max_load)
    _greedy(f"greedy_{_objective}_customers", "customers_by_part", 8, _objective, LOADED, _as_loads)
    _greedy(f"greedy_{_objective}_clauses", "signed_clauses", 32, _objective, ASSIGNED, lambda h, x: placements(x))
    _greedy(f"greedy_{_objective}_words", "docs_by_word", 8, _objective, MAX_LOAD, _with_max_load)
    _greedy(f"greedy_{_objective}_dense_rows", "parts_by_supplier", K, _objective, sql.quality("a"), lambda h, x: quality(h, x))


def _weighted(name, source, weights_sql, weights, k, nets_sql=None, net_weights=None):
    """Vertices, or nets, that weigh a column of their tables."""
    walk = sql.replay(k, vertices="vw", vertex_weight="c", weighted=True, **({"weight": "nw"} if nets_sql else {}), **({"pins": "pw"} if nets_sql else {}))
    before = f"vw AS MATERIALIZED ({weights_sql}),\n" + (f"pw AS MATERIALIZED ({nets_sql}),\n" if nets_sql else "")

    @query(name, select_with(source, before + walk, ASSIGNED))
    def run(spark, d):
        h = hypergraph(spark, d, source, weights=weights(spark, d) if weights else None, net_weights=net_weights(spark, d) if net_weights else None)
        return placements(ordered.greedy(h, PartitionSpec(k, weighted=True)))


_weighted("greedy_weighted_parts", "parts_by_customer", "SELECT vertex_id, seq, CAST(p_size AS BIGINT) AS c FROM v JOIN part ON p_partkey = vertex_id", lambda spark, d: read_table(spark, d, "part", "p_partkey", "p_size").select(F.col("p_partkey").alias("vertex_id"), F.col("p_size").cast("double").alias("weight")), K)
_weighted("greedy_priced_orders", H1, "SELECT vertex_id, seq, 1 AS c FROM v", None, K, "SELECT p.*, floor(o_totalprice) AS nw FROM p JOIN orders ON o_orderkey = net_id", lambda spark, d: read_table(spark, d, "orders", "o_orderkey", "o_totalprice").select(F.col("o_orderkey").alias("net_id"), F.floor("o_totalprice").cast("double").alias("weight")))

_SEEDS = range(5)


@query("greedy_order_seeds", f"WITH RECURSIVE {sql.base('users_by_hour_type')},\n" + ",\n".join(f"v{i} AS MATERIALIZED (SELECT vertex_id, row_number() OVER (ORDER BY md5('{i}:' || vertex_id), vertex_id) - 1 AS seq FROM v),\n" + sql.replay(8, tag=f"r{i}", vertices=f"v{i}") for i in _SEEDS) + "\n" + " UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS seed, cut_net, connectivity FROM ({sql.quality(f'ar{i}')})" for i in _SEEDS))
def greedy_order_seeds(spark, d):
    """Five random arrival orders of one instance."""
    pins, rows = builders.users_by_hour_type(spark, d), []
    for seed in _SEEDS:
        h = shape.prepare(pins, order="random", seed=seed)
        rows.append(quality(h, ordered.greedy(h, PartitionSpec(8))).select(F.lit(seed).alias("seed"), "cut_net", "connectivity"))
    return _union(rows)


@query("greedy_degree_order", select_with(H1, "vd AS MATERIALIZED (SELECT vertex_id, row_number() OVER (ORDER BY deg, vertex_id) - 1 AS seq FROM (SELECT vertex_id, count(*) AS deg FROM raw GROUP BY vertex_id)),\n" + sql.replay(K, vertices="vd"), ASSIGNED))
def greedy_degree_order(spark, d):
    """Arrival by number of nets."""
    h = shape.prepare(builders.parts_by_order(spark, d), order="degree")
    return placements(ordered.greedy(h, PartitionSpec(K)))


@query("greedy_time_order", select_with("users_by_hour_type", "vt AS MATERIALIZED (SELECT user_id AS vertex_id, row_number() OVER (ORDER BY min(ts), user_id) - 1 AS seq FROM events GROUP BY user_id),\n" + sql.replay(8, vertices="vt"), ASSIGNED))
def greedy_time_order(spark, d):
    """Arrival by a user's first event."""
    first = read_table(spark, d, "events", "user_id", "ts").groupBy(F.col("user_id").alias("vertex_id")).agg(F.min(F.col("ts").cast("timestamp")).alias("key"))
    h = shape.prepare(builders.users_by_hour_type(spark, d), order="time", by=first)
    return placements(ordered.greedy(h, PartitionSpec(8)))


_GAMMAS = [(g, s) for g in (1.0, 1.5, 2.0) for s in (0.0, 1.0, 4.0)]


@query("greedy_gamma_sweep", f"WITH RECURSIVE {sql.base('users_by_hour')},\n" + ",\n".join(sql.replay(8, gamma=g, scale=s, tag=str(i)) for i, (g, s) in enumerate(_GAMMAS)) + "\n" + " UNION ALL ".join(f"SELECT CAST({g} AS DOUBLE) AS gamma, CAST({s} AS DOUBLE) AS alpha_scale, connectivity FROM ({sql.quality(f'a{i}')})" for i, (g, s) in enumerate(_GAMMAS)))
def greedy_gamma_sweep(spark, d):
    h = hypergraph(spark, d, "users_by_hour")
    rows = [quality(h, ordered.greedy(h, PartitionSpec(8, gamma=g, alpha_scale=s))).select(F.lit(g).alias("gamma"), F.lit(s).alias("alpha_scale"), "connectivity") for g, s in _GAMMAS]
    return _union(rows)


def _union(frames):
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


_KS = (2, 4, 8, 16, 32, 64)


@query("greedy_k_sweep", f"WITH RECURSIVE {sql.base('users_by_hour_type')},\n" + ",\n".join(sql.replay(k, tag=str(k)) for k in _KS) + "\n" + " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS k, cut_net, connectivity FROM ({sql.quality(f'a{k}')})" for k in _KS))
def greedy_k_sweep(spark, d):
    h = hypergraph(spark, d, "users_by_hour_type")
    return _union([quality(h, ordered.greedy(h, PartitionSpec(k))).select(F.lit(k).alias("k"), "cut_net", "connectivity") for k in _KS])


@query("greedy_orders_balance", select_with("orders_by_part", "x AS (SELECT 1)", "SELECT count(*) AS n_checked, CAST(0 AS BIGINT) AS n_violations FROM v"))
def greedy_orders_balance(spark, d):
    h = hypergraph(spark, d, "orders_by_part")
    spec = PartitionSpec(64, tie="ladder")
    return audit.balance_audit(h, ordered.greedy(h, spec), spec)


CHECKED = "SELECT count(*) AS n_checked, CAST(0 AS BIGINT) AS n_violations FROM v"


@query("greedy_engine_diff", select_with(H1, "x AS (SELECT 1)", "SELECT 3 * count(*) AS n_checked, CAST(0 AS BIGINT) AS n_violations FROM v"))
def greedy_engine_diff(spark, d):
    """scan = split in either objective; bucket queue and ladder give every block the same loads."""
    h = hypergraph(spark, d, H1)
    diffs = []
    for objective in ("con", "cut"):
        spec = PartitionSpec(K, objective=objective)
        diffs.append(audit.diff(ordered.greedy(h, spec, "split"), ordered.greedy(h, spec, "scan")))
    scan = ordered.greedy(h, PartitionSpec(K), "scan", "heap")
    diffs.append(audit.diff(scan, ordered.greedy(h, PartitionSpec(K), "split", "heap")))
    return _union(diffs).agg(F.sum("n_checked").alias("n_checked"), F.sum("n_violations").alias("n_violations"))


def _audit(objective):
    @query(f"greedy_audit_{objective}", select_with(H1, "x AS (SELECT 1)", CHECKED))
    def run(spark, d):
        h = hypergraph(spark, d, H1)
        spec = PartitionSpec(K, objective=objective, tie="ladder")
        cap, strength = ordered.limits(h, spec)
        return audit.decision_audit(h, cut(ordered.greedy(h, spec), "decisions"), spec, cap, strength)


_audit("con")
_audit("cut")


@query("queue_audit", select_with(H1, "x AS (SELECT 1)", CHECKED))
def queue_audit(spark, d):
    h = hypergraph(spark, d, H1)
    spec = PartitionSpec(K, tie="ladder")
    cap, strength = ordered.limits(h, spec)
    return audit.decision_audit(h, cut(ordered.greedy(h, spec, index="queue"), "decisions"), spec, cap, strength)


@query("evaluation_counts", select_with(H1, sql.replay(64), "SELECT count(*) AS vertices, CAST(sum(touched) AS BIGINT) AS touched, CAST(sum(evaluated) AS BIGINT) AS evaluated, count(*) * 64 AS scanned FROM a"))
def evaluation_counts(spark, d):
    """Scores that the split engine computes, as its kernel counts them, and that a scan of all blocks would."""
    work = ordered.greedy(hypergraph(spark, d, H1), PartitionSpec(64))
    return work.agg(F.count("*").alias("vertices"), F.sum("touched").alias("touched"), F.sum("evaluated").alias("evaluated"), (F.count("*") * 64).alias("scanned"))


_WORK_KS = (8, 64, 512)


@query("split_work_by_k", f"WITH RECURSIVE {sql.base('pages_by_link')},\n" + ",\n".join(sql.replay(k, tag=f"w{k}") for k in _WORK_KS) + "\n" + " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS k, CAST(sum(evaluated) AS BIGINT) AS evaluated, round(CAST(count(*) * {k} AS DOUBLE) / sum(evaluated), 6) AS ratio FROM aw{k}" for k in _WORK_KS))
def split_work_by_k(spark, d):
    """How many times the scan's work exceeds the split's, by k."""
    h = hypergraph(spark, d, "pages_by_link")
    rows = [ordered.greedy(h, PartitionSpec(k)).agg(F.lit(k).alias("k"), F.sum("evaluated").alias("evaluated"), F.round(F.count("*") * float(k) / F.sum("evaluated"), 6).alias("ratio")) for k in _WORK_KS]
    return _union(rows)


@query("scan_evaluations", select_with(H1, "x AS (SELECT 1)", f"SELECT count(*) * {K} AS evaluated FROM v"))
def scan_evaluations(spark, d):
    """The direct scan scores every block at every arrival."""
    return ordered.greedy(hypergraph(spark, d, H1), PartitionSpec(K), "scan").agg(F.sum("evaluated").alias("evaluated"))


def ladder_steps(bumps: DataFrame, k: int, every: int = 100, width: int = 50_000) -> DataFrame:
    """step, lightest_load, distinct_loads after every ``every``-th of the bumps (seq from 0, block).

    Slices of ``width`` bumps are walked side by side, each from the loads that the slices before it leave."""
    import pandas as pd

    sliced = bumps.withColumn("slice", F.floor(F.col("seq") / width))
    counts = sliced.groupBy("slice", "block").agg(F.count("*").alias("c"))
    grid = counts.select("slice").distinct().withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))
    # One row per slice and block goes through the window.
    earlier = W.partitionBy("block").orderBy("slice").rowsBetween(W.unboundedPreceding, -1)
    starts = grid.join(counts, ["slice", "block"], "left").select(F.col("slice").alias("first_of"), "block", F.coalesce(F.sum("c").over(earlier), F.lit(0)).alias("start"))

    def walk(rows, start):
        ladder, out = LoadLadder(k, start.sort_values("block")["start"].tolist()), []
        for seq, block in rows.sort_values("seq")[["seq", "block"]].itertuples(index=False):
            ladder.bump(int(block))
            if (seq + 1) % every == 0:
                out.append((seq + 1, ladder.load[ladder.lightest()], len(ladder.range)))
        return pd.DataFrame(out, columns=["step", "lightest_load", "distinct_loads"]).astype("int64")

    return sliced.groupBy("slice").cogroup(starts.groupBy("first_of")).applyInPandas(walk, "step bigint, lightest_load bigint, distinct_loads bigint")


LADDER = """WITH l AS MATERIALIZED (SELECT row_number() OVER (ORDER BY l_orderkey, l_partkey, l_suppkey, l_quantity) - 1 AS seq, l_suppkey % 100 AS block FROM lineitem),
c AS MATERIALIZED (SELECT seq // 100 AS s, block, count(*) AS c FROM l GROUP BY ALL),
g AS (SELECT s.range AS s, b.range AS block, coalesce(c.c, 0) AS c FROM range((SELECT count(*) // 100 FROM l)) s CROSS JOIN range(100) b LEFT JOIN c ON c.s = s.range AND c.block = b.range),
w AS (SELECT s, sum(c) OVER (PARTITION BY block ORDER BY s) AS load FROM g)
SELECT CAST((s + 1) * 100 AS BIGINT) AS step, CAST(min(load) AS BIGINT) AS lightest_load, count(DISTINCT load) AS distinct_loads FROM w GROUP BY s"""


@query("ladder_trace", LADDER)
def ladder_trace(spark, d):
    """The ladder of 100 blocks under all lines' suppliers in key order: lightest load and number of distinct loads at every hundredth step."""
    keys = ("l_orderkey", "l_partkey", "l_suppkey", "l_quantity")
    rows = shape.dense_ids(read_table(spark, d, "lineitem", *keys), *map(F.col, keys), name="seq")
    return ladder_steps(rows.select("seq", (F.col("l_suppkey") % 100).cast("int").alias("block")), 100)


# --- graphs ------------------------------------------------------------------------------------------------------------


def _knn(spark, d):
    return cut(builders.knn_edges(read_table(spark, d, "embeddings", "vec_id", "embedding")), "knn")


GRAPH = f"WITH RECURSIVE e AS ({sql.KNN}), v AS (SELECT vertex_id, row_number() OVER (ORDER BY vertex_id) - 1 AS seq FROM (SELECT src AS vertex_id FROM e UNION SELECT dst FROM e)),\n"


@query("embedding_knn_edges", f"{sql.KNN}")
def embedding_knn_edges(spark, d):
    return _knn(spark, d).select("src", "dst")


@query("graph_greedy_knn", GRAPH + sql.replay(8, graph=True, pins="e") + "\n" + ASSIGNED)
def graph_greedy_knn(spark, d):
    return placements(ordered.graph_greedy(_knn(spark, d), PartitionSpec(8)))


@query("graph_greedy_scan", ORACLES["graph_greedy_knn"])
def graph_greedy_scan(spark, d):
    return placements(ordered.graph_greedy(_knn(spark, d), PartitionSpec(8), "scan"))


@query("graph_vs_net_diff", GRAPH.replace("RECURSIVE ", "").rstrip(",\n") + " SELECT 2 * count(*) AS n_checked, CAST(0 AS BIGINT) AS n_violations FROM v")
def graph_vs_net_diff(spark, d):
    """Two-pin nets: both objectives and the graph rule place alike."""
    edges = _knn(spark, d)
    graph = cut(placements(ordered.graph_greedy(edges, PartitionSpec(8))), "graph-rule")
    h = shape.prepare(shape.edges_to_pins(edges))
    diffs = [audit.diff(graph, ordered.greedy(h, PartitionSpec(8, objective=o))) for o in ("con", "cut")]
    return _union(diffs).agg(F.sum("n_checked").alias("n_checked"), F.sum("n_violations").alias("n_violations"))


@query("edge_cut_hash", f"WITH raw AS ({sql.PINS[H1]}), e AS ({sql.COPURCHASE}) SELECT sum(weight) AS value FROM e WHERE {sql.hashed(K, 'src')} <> {sql.hashed(K, 'dst')}")
def edge_cut_hash(spark, d):
    pins = builders.parts_by_order(spark, d)
    ids = pins.select("vertex_id").distinct()
    return measures.edge_cut(builders.copurchase(pins), controls.hashing(ids, K))


@query("copurchase_profile", f"WITH raw AS ({sql.PINS[H1]}), e AS ({sql.COPURCHASE}) SELECT count(*) AS edges, sum(weight) AS weight FROM e")
def copurchase_profile(spark, d):
    return builders.copurchase(builders.parts_by_order(spark, d)).agg(F.count("*").alias("edges"), F.sum("weight").alias("weight"))


def _edge_graph(edges_sql: str) -> str:
    return f"WITH RECURSIVE raw AS MATERIALIZED ({{raw}}), e AS MATERIALIZED ({edges_sql}), v AS MATERIALIZED (SELECT vertex_id, row_number() OVER (ORDER BY vertex_id) - 1 AS seq FROM (SELECT src AS vertex_id FROM e UNION SELECT dst FROM e)),\n"


def _graph_of(name, source, k, engine, pairs=True):
    """pairs: over a table of edges; else by classes of vertices, for sources with very many copies."""

    @query(name, _edge_graph(sql.COPURCHASE).replace("{raw}", sql.PINS[source]) + sql.replay(k, graph=True, pins="e") + "\n" + ASSIGNED)
    def run(spark, d):
        pins = builders.HYPERGRAPHS[source](spark, d)
        if not pairs:
            return ordered.shared_net_greedy(pins, PartitionSpec(k), engine)
        edges = cut(builders.copurchase(pins).withColumn("weight", F.lit(1.0)), "edges")
        return placements(ordered.graph_greedy(edges, PartitionSpec(k), engine))


_graph_of("graph_greedy_copurchase", H1, K, "split")
_graph_of("graph_greedy_pages", "pages_by_link", 64, "split", pairs=False)
_graph_of("graph_scan_pages", "pages_by_link", 64, "scan", pairs=False)


EDGE_BLOCK = sql.hashed(8, "src || '-' || dst")


@query("edge_stream_hash", f"WITH raw AS ({sql.PINS[H1]}), e AS ({sql.COPURCHASE}), b AS (SELECT src, dst, {EDGE_BLOCK} AS block FROM e), u AS (SELECT src AS v, block FROM b UNION SELECT dst, block FROM b) SELECT sum(c) / CAST(count(*) AS DOUBLE) AS value FROM (SELECT count(*) AS c FROM u GROUP BY v)")
def edge_stream_hash(spark, d):
    return measures.edge_replication(controls.edge_hash(builders.copurchase(builders.parts_by_order(spark, d)), 8))


@query("edge_stream_greedy", f"WITH RECURSIVE e AS MATERIALIZED ({sql.KNN}),\n{sql.edge_replay(8)}\nSELECT src, dst, block FROM a")
def edge_stream_greedy(spark, d):
    """Edge-at-a-time greedy: every edge's block."""
    return ordered.edge_greedy(_knn(spark, d), PartitionSpec(8))


@query("pages_sharing_link", f"WITH raw AS ({sql.PINS['pages_by_link']}), e AS ({sql.COPURCHASE}) SELECT src, dst, weight FROM e")
def pages_sharing_link(spark, d):
    return builders.pages_sharing_link(spark, d)


# --- baselines -----------------------------------------------------------------------------------------------------------


@query("minmax_suppliers", select_with("suppliers_by_order", sql.replay(K, rule="minmax"), ASSIGNED))
def minmax_suppliers(spark, d):
    return placements(ordered.minmax_place(hypergraph(spark, d, "suppliers_by_order"), PartitionSpec(K)))


@query("minmax_users", select_with("users_by_hour", sql.replay(8, rule="minmax"), LOADED))
def minmax_users(spark, d):
    return _as_loads(None, ordered.minmax_place(hypergraph(spark, d, "users_by_hour"), PartitionSpec(8)))



def _same(name, source, k, first, second):
    @query(name, select_with(source, "x AS (SELECT 1)", CHECKED))
    def run(spark, d):
        h, spec = hypergraph(spark, d, source), PartitionSpec(k)
        return audit.diff(ordered.minmax_place(h, spec, **first), ordered.minmax_place(h, spec, **second))


def _baseline(name, source, k, rule, tail, finish, place, **how):
    @query(name, select_with(source, sql.replay(k, rule=rule, **how), tail))
    def run(spark, d):
        h = hypergraph(spark, d, source)
        return finish(h, place(h, PartitionSpec(k)))


_placed, _measured = (lambda h, x: placements(x)), (lambda h, x: quality(h, x))
_baseline("minmax_parts", H1, K, "minmax", ASSIGNED, _placed, ordered.minmax_place)
_baseline("minmax_customers", "customers_by_part", 8, "minmax", LOADED, _as_loads, ordered.minmax_place)
_baseline("minmax_docs", "docs_by_line", 8, "minmax", ASSIGNED, _placed, ordered.minmax_place)
for _ell in (1, 2, 5):
    _baseline("minmax_capped_parts" if _ell == 5 else f"minmax_capped_{_ell}", H1, K, "capped", ASSIGNED, _placed, lambda h, s, ell=_ell: ordered.minmax_place(h, s, "capped", ell=ell), ell=_ell)
_baseline("minmax_capped_customers", "customers_by_part", 32, "capped", sql.quality("a"), _measured, lambda h, s: ordered.minmax_place(h, s, "capped"))
_baseline("signature_suppliers", "suppliers_by_order", K, "signature", ASSIGNED, _placed, lambda h, s: ordered.minmax_place(h, s, "minhash"))
_baseline("signature_parts", H1, K, "signature", ASSIGNED, _placed, lambda h, s: ordered.minmax_place(h, s, "minhash"))
_baseline("multisection_parts", H1, 16, "sections", ASSIGNED, _placed, lambda h, s: ordered.multisection(h, s, 4), fanout=4)
_baseline("multisection_pages", "pages_by_link", 64, "sections", sql.quality("a"), _measured, lambda h, s: ordered.multisection(h, s, 8), fanout=8)

_same("minmax_index_diff", "customers_by_part", 16, {"index": "lists"}, {"index": "sets"})
_same("minmax_capped_limit_diff", "customers_by_part", 16, {"index": "lists"}, {"index": "capped", "ell": 16})
_same("minmax_bloom_diff", "users_by_hour_type", 8, {"index": "lists"}, {"index": "bloom", "bits": 1 << 24, "hashes": 4})


def _balanced(name, source, k, place):
    @query(name, select_with(source, "x AS (SELECT 1)", CHECKED))
    def run(spark, d):
        h, spec = hypergraph(spark, d, source), PartitionSpec(k)
        return audit.balance_audit(h, cut(placements(place(h, spec)), "placements"), spec)


_balanced("minmax_capped_balance", "customers_by_part", 16, lambda h, s: ordered.minmax_place(h, s, "capped"))
_balanced("minmax_capped_random_balance", "customers_by_part", 16, lambda h, s: ordered.minmax_place(h, s, "capped", evict="random"))
_balanced("minmax_bloom_balance", H1, K, lambda h, s: ordered.minmax_place(h, s, "bloom", bits=1 << 16))
_balanced("minmax_minhash_balance", "docs_by_line", 8, lambda h, s: ordered.minmax_place(h, s, "minhash"))
_balanced("buffered_strict_balance", H1, K, lambda h, s: ordered.buffered_place(h, s, "strict"))
_balanced("buffered_relaxed_balance", H1, K, lambda h, s: ordered.buffered_place(h, s, "relaxed"))
_balanced("buffered_selective_balance", H1, K, lambda h, s: ordered.buffered_place(h, s, "relaxed_small"))
_balanced("inmem_multilevel_balance", "customers_by_part", 8, ordered.inmem_multilevel)
_balanced("multisection_balance", H1, 16, lambda h, s: ordered.multisection(h, s, 4))
_balanced("rounds_balance", H1, K, lambda h, s: rounds.greedy(h, s, prefix=256, beta=1.0))


for _iters in (1, 3):

    @query("inmem_fast_placed" if _iters == 3 else "inmem_fast_one_round", select_with("customers_by_part", sql.spread(8, _iters), f"SELECT vertex_id, block FROM l{_iters}"))
    def _spread(spark, d, iters=_iters):
        return inmem.inmem_fast(hypergraph(spark, d, "customers_by_part"), PartitionSpec(8), iters, stop=0.0).select("vertex_id", "block")


@query("inmem_fast_quality", select_with("docs_by_line", sql.spread(16, 5), sql.quality("l5")))
def inmem_fast_quality(spark, d):
    h = hypergraph(spark, d, "docs_by_line")
    return quality(h, inmem.inmem_fast(h, PartitionSpec(16), 5, stop=0.0))


_balanced("inmem_fast_balance", "docs_by_line", 16, inmem.inmem_fast)


def _told(name, source, k, mode, objective="con"):
    """What placements and moves told of the objective is what a count of the final assignment gives."""

    @query(name, select_with(source, "x AS (SELECT 1)", CHECKED))
    def run(spark, d):
        h, spec = hypergraph(spark, d, source), PartitionSpec(k, objective=objective)
        done = cut(ordered.buffered_place(h, spec, mode), "buffered")
        value = (measures.connectivity if objective == "con" else measures.cut_net)(h.pins, done)
        once = done.agg(F.count_distinct("vertex_id").alias("n_checked"), F.count("*").alias("rows"), F.max("told").alias("told")).crossJoin(value)
        bad = (F.abs(F.col("told") - F.col("value")) > 1e-6).cast("long") + (F.col("rows") - F.col("n_checked"))
        return once.select("n_checked", F.coalesce(bad, F.col("n_checked")).alias("n_violations"))


_told("buffered_gain", H1, K, "strict")
_told("buffered_gain_cut", "docs_by_line", 8, "strict", "cut")
_told("buffered_gain_relaxed", H1, K, "relaxed")
_told("buffered_gain_selective", "docs_by_line", 8, "relaxed_small")


@query("multilevel_audit", select_with("docs_by_line", f"b AS (SELECT vertex_id, {sql.hashed(8)} AS block FROM v)", f"SELECT (SELECT count(*) FROM v) AS n_checked, CAST(0 AS BIGINT) AS n_violations, connectivity AS hashing FROM ({sql.quality('b')})"))
def multilevel_audit(spark, d):
    """The in-memory multilevel method: each vertex once, blocks within the bound, and less connectivity than the one-pass rule and hashing."""
    h, spec = hypergraph(spark, d, "docs_by_line"), PartitionSpec(8)
    mine = cut(ordered.inmem_multilevel(h, spec), "multilevel")
    values = [measures.connectivity(h.pins, x).select(F.col("value").alias(n)) for n, x in (("mine", mine), ("greedy", placements(ordered.greedy(h, spec))), ("hashing", controls.hashing(h.vertices, 8)))]
    rows = audit.balance_audit(h, mine, spec).crossJoin(values[0]).crossJoin(values[1]).crossJoin(values[2])
    worse = F.when(F.col("mine") > F.least("greedy", "hashing"), 1).otherwise(0)
    return rows.select("n_checked", (F.col("n_violations") + worse).alias("n_violations"), "hashing")


@query("minhash_signatures", "WITH raw AS (" + sql.PINS["docs_by_line"] + ") SELECT vertex_id, i.range AS i, min(md5(i.range || ':' || net_id)) AS sig FROM raw, range(4) i GROUP BY ALL")
def minhash_signatures(spark, d):
    """Signatures by four seeded minima over the text of the lines."""
    docs = read_table(spark, d, "documents", "doc_id", "text")
    lines = docs.select(F.col("doc_id").alias("vertex_id"), F.explode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("w")).filter("w <> ''")
    seeded = [F.struct(F.lit(i).cast("bigint").alias("i"), F.md5(F.concat(F.lit(f"{i}:"), F.col("w")).cast("binary")).alias("h")) for i in range(4)]
    return lines.select("vertex_id", F.explode(F.array(*seeded)).alias("x")).groupBy("vertex_id", F.col("x.i").alias("i")).agg(F.min("x.h").alias("sig"))


# --- rounds lane -----------------------------------------------------------------------------------------------------------


def _fixed_batches(name, source, k, objective, size, most):
    """Batches of one size; ``most`` of them at least cover the instance, further ones are empty."""
    ends = [size * (i + 1) for i in range(most)]

    @query(name, select_with(source, sql.rounds(k, ends, objective), "SELECT vertex_id, block FROM d"))
    def run(spark, d):
        h = hypergraph(spark, d, source)
        return placements(rounds.greedy(h, PartitionSpec(k, objective=objective), batch=size))


_fixed_batches("rounds_con_pages", "pages_by_link", 8, "con", 60, 8)
_fixed_batches("rounds_cut_pages", "pages_by_link", 8, "cut", 60, 8)
_fixed_batches("rounds_con_customers", "customers_by_part", 8, "con", 400, 8)
_fixed_batches("rounds_cut_suppliers", "suppliers_by_order", 4, "cut", 25, 8)


@query("predecessor_arcs", select_with(H1, "q AS (SELECT net_id, vertex_id, lag(vertex_id) OVER (PARTITION BY net_id ORDER BY vertex_id) AS pred FROM p)", "SELECT vertex_id, pred, CAST(count(*) AS DOUBLE) AS weight FROM q WHERE pred IS NOT NULL GROUP BY ALL"))
def predecessor_arcs(spark, d):
    return shape.predecessor_arcs(hypergraph(spark, d, H1))


@query("as_of_net_state", select_with(H1, HASHED, "SELECT net_id, vertex_id, last_value(block) OVER w AS last_block, coalesce(min(block) OVER w <> max(block) OVER w, false) AS is_cut FROM p JOIN a USING (vertex_id) WINDOW w AS (PARTITION BY net_id ORDER BY vertex_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"))
def as_of_net_state(spark, d):
    h, a = _hashed(spark, d)
    return state.as_of_net(h.pins, a.join(h.vertices, "vertex_id")).select("net_id", "vertex_id", "last_block", "is_cut")


@query("net_state", select_with(H1, HASHED, "SELECT net_id, arg_max(block, vertex_id) AS last_block, min(block) <> max(block) AS is_cut FROM p JOIN a USING (vertex_id) GROUP BY net_id"))
def net_state(spark, d):
    h, a = _hashed(spark, d)
    return state.net_state(h.pins, a.join(h.vertices, "vertex_id")).select("net_id", "last_block", "is_cut")


@query("capacity_fill", "WITH v AS (SELECT row_number() OVER (ORDER BY p_partkey) - 1 AS seq FROM part), s AS (SELECT b.range AS block, l.range AS level FROM range(8) b, (SELECT range FROM range(10000)) l WHERE l.range >= b.range * b.range), t AS (SELECT block, row_number() OVER (ORDER BY level, block) - 1 AS seq FROM s) SELECT v.seq, CAST(t.block AS INTEGER) AS block FROM v JOIN t USING (seq)")
def capacity_fill(spark, d):
    """Water-filling over eight blocks of loads 0, 1, 4, ..., 49."""
    parts = shape.dense_ids(read_table(spark, d, "part", "p_partkey"), F.col("p_partkey"), name="seq")
    loads = [b * b for b in range(8)]
    room = max(*loads, -(-(parts.count() + sum(loads)) // len(loads)))
    return capacity.fill(parts, loads, room, "seq").select("seq", "block")


@query("capacity_accept", f"WITH w AS (SELECT p_partkey AS seq, {sql.hashed(8, 'p_partkey')} AS block FROM part), r AS (SELECT *, row_number() OVER (PARTITION BY block ORDER BY seq) AS r FROM w) SELECT seq, block, r <= 20 * (block + 1) AS accepted FROM r")
def capacity_accept(spark, d):
    wishes = read_table(spark, d, "part", "p_partkey").select(F.col("p_partkey").alias("seq"), controls.hash_block(F.col("p_partkey"), 8).alias("block"))
    return capacity.accept(wishes, [20 * (b + 1) for b in range(8)]).select("seq", "block", "accepted")


# --- shapes and formats -------------------------------------------------------------------------------------------------------

PROFILE = "SELECT CAST('{0}' AS VARCHAR) AS instance, (SELECT count(DISTINCT vertex_id) FROM r) AS n, (SELECT count(*) FROM s) AS m, (SELECT count(*) FROM r) AS pins, (SELECT max(c) FROM s) AS xi, (SELECT max(c) FROM (SELECT count(*) AS c FROM r GROUP BY vertex_id)) AS delta, (SELECT count(*) FROM s WHERE c = 1) AS single"


def _profile_sql(name):
    return f"SELECT * FROM (WITH r AS ({sql.PINS[name]}), s AS (SELECT count(*) AS c FROM r GROUP BY net_id) {PROFILE.format(name)})"


for _name in builders.HYPERGRAPHS:

    @query(f"build_{_name}", _profile_sql(_name))
    def _build(spark, d, name=_name):
        return measures.profile(builders.HYPERGRAPHS[name](spark, d)).select(F.lit(name).alias("instance"), "n", "m", "pins", "xi", "delta", "single")


@query("hypergraph_profile", " UNION ALL ".join(_profile_sql(n) for n in builders.HYPERGRAPHS))
def hypergraph_profile(spark, d):
    return _union([QUERIES[f"build_{n}"](spark, d) for n in builders.HYPERGRAPHS])


@query("weighted_profile", select_with(H1, "w AS MATERIALIZED (SELECT net_id, floor(any_value(o_totalprice)) AS w FROM p JOIN orders ON o_orderkey = net_id GROUP BY net_id), z AS (SELECT CAST(p_size AS DOUBLE) AS c FROM v JOIN part ON p_partkey = vertex_id)", "SELECT (SELECT sum(c) FROM z) AS total, (SELECT max(c) FROM z) AS heaviest_vertex, (SELECT sum(w) FROM w) AS net_weight, (SELECT max(w) FROM w) AS heaviest_net, (SELECT max(s) FROM (SELECT sum(w) AS s FROM p JOIN w USING (net_id) GROUP BY vertex_id)) AS widest"))
def weighted_profile(spark, d):
    """Parts that weigh their size, orders that weigh their price."""
    sizes = read_table(spark, d, "part", "p_partkey", "p_size").select(F.col("p_partkey").alias("vertex_id"), F.col("p_size").cast("double").alias("weight"))
    prices = read_table(spark, d, "orders", "o_orderkey", "o_totalprice").select(F.col("o_orderkey").alias("net_id"), F.floor("o_totalprice").cast("double").alias("weight"))
    h = hypergraph(spark, d, H1, weights=sizes, net_weights=prices)
    return measures.weighted_profile(h.pins, h.nets, h.vertices)


@query("chosen_lanes", " UNION ALL ".join(f"SELECT * FROM (WITH {sql.base(n)} SELECT '{n}' AS instance, CASE WHEN (SELECT count(DISTINCT net_id) FROM p) * 120 + 16 * 200 <= 200000 AND (SELECT count(*) FROM p) <= 50000 THEN 'ordered' ELSE 'rounds' END AS lane)" for n in ("parts_by_order", "parts_by_supplier", "pages_by_link", "docs_by_line")))
def chosen_lanes(spark, d):
    """The lane that tasks of 200 kB and 50,000 pins would leave each instance."""
    spec, rows = PartitionSpec(16), []
    for name in ("parts_by_order", "parts_by_supplier", "pages_by_link", "docs_by_line"):
        rows.append((name, choose.lane(hypergraph(spark, d, name).stats(), spec, 200_000, 50_000)))
    return spark.createDataFrame(rows, "instance string, lane string")


@query("session_nets", "WITH e AS (SELECT event_id, user_id, ts, CASE WHEN ts > lag(ts) OVER w + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT user_id, sum(f) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM e), g AS (SELECT user_id, n, count(*) AS c FROM s GROUP BY ALL) SELECT count(*) AS nets, CAST(sum(c) AS BIGINT) AS pins, max(c) AS largest FROM g")
def session_nets(spark, d):
    return builders.session_nets(spark, d).groupBy("net_id").agg(F.count("*").alias("c")).agg(F.count("*").alias("nets"), F.sum("c").alias("pins"), F.max("c").alias("largest"))


@query("shingle_nets", "WITH w AS (SELECT doc_id, list_filter(string_split_regex(lower(coalesce(text, '')), '[ \\n.,;:!?]+'), lambda x: x <> '') AS ws FROM documents), s AS (SELECT DISTINCT doc_id, array_to_string(ws[i : i + 2], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS i FROM w)) SELECT count(*) AS pins, count(DISTINCT g) AS nets FROM s")
def shingle_nets(spark, d):
    return builders.shingles(read_table(spark, d, "documents", "doc_id", "text"), "doc_id", "text").agg(F.count("*").alias("pins"), F.count_distinct("net_id").alias("nets"))


@query("signed_literals", "SELECT count(*) AS literals, (SELECT count(*) FROM (SELECT l_orderkey, l_partkey FROM lineitem GROUP BY ALL HAVING count(DISTINCT l_returnflag = 'R') = 2)) AS both_signs FROM (SELECT DISTINCT l_orderkey, l_partkey, l_returnflag = 'R' FROM lineitem)")
def signed_literals(spark, d):
    rows = builders.literals(spark, d)
    both = rows.groupBy("l_orderkey", "l_partkey").agg(F.count("*").alias("c")).filter("c = 2").agg(F.count("*").alias("both_signs"))
    return rows.agg(F.count("*").alias("literals")).crossJoin(both)


@query("normalize_parts", select_with(H1, "g AS (SELECT list(vertex_id ORDER BY vertex_id) AS set FROM p GROUP BY net_id)", "SELECT count(DISTINCT set) AS nets, CAST(sum(len(set)) AS BIGINT) AS pins FROM (SELECT DISTINCT set FROM g)"))
def normalize_parts(spark, d):
    pins, nets = shape.normalize(builders.parts_by_order(spark, d), "drop")
    return nets.agg(F.count("*").alias("nets")).crossJoin(pins.agg(F.count("*").alias("pins")))


@query("parallel_nets", select_with("docs_by_line", "g AS (SELECT list(vertex_id ORDER BY vertex_id) AS set FROM p GROUP BY net_id)", "SELECT CAST(count(*) AS BIGINT) AS nets, CAST(sum(c) AS DOUBLE) AS weight, CAST(max(c) AS DOUBLE) AS heaviest FROM (SELECT count(*) AS c FROM g GROUP BY set)"))
def parallel_nets(spark, d):
    _, nets = shape.normalize(builders.docs_by_line(spark, d), "merge")
    return nets.agg(F.count("*").alias("nets"), F.sum("weight").alias("weight"), F.max("weight").alias("heaviest"))


@query("vertex_stream_rows", select_with(H1, "x AS (SELECT 1)", "SELECT v.seq, v.vertex_id, count(p.net_id) AS degree, coalesce(min(p.net_id), -1) AS first_net FROM v LEFT JOIN p USING (vertex_id) GROUP BY ALL"))
def vertex_stream_rows(spark, d):
    rows = shape.vertex_stream(hypergraph(spark, d, H1))
    return rows.select("seq", "vertex_id", F.size("nets").cast("bigint").alias("degree"), F.coalesce(F.get("nets.net_id", F.lit(0)), F.lit(-1)).alias("first_net"))


@query("expanded_stream_volume", select_with(H1, "x AS (SELECT 1)", "SELECT CAST(sum(c * c) AS BIGINT) AS entries FROM (SELECT count(*) AS c FROM p GROUP BY net_id)"))
def expanded_stream_volume(spark, d):
    return shape.vertex_stream_expanded(hypergraph(spark, d, H1)).agg(F.sum("entries").alias("entries"))


@query("adjacency_rows", f"WITH e AS ({sql.KNN}) SELECT x AS vertex_id, count(*) AS degree FROM (SELECT src AS x FROM e UNION ALL SELECT dst FROM e) GROUP BY x")
def adjacency_rows(spark, d):
    edges = _knn(spark, d)
    return shape.adjacency_stream(edges, shape.graph_vertices(edges)).select("vertex_id", F.size("nets").cast("bigint").alias("degree"))


@query("edge_stream_rows", f"WITH e AS ({sql.KNN}) SELECT row_number() OVER (ORDER BY src, dst) - 1 AS seq, src, dst FROM e")
def edge_stream_rows(spark, d):
    return shape.edge_stream(_knn(spark, d)).select("seq", "src", "dst")


@query("induced_pins", f"WITH raw AS ({sql.PINS[H1]}) SELECT net_id, vertex_id FROM raw WHERE vertex_id IN (SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20)")
def induced_pins(spark, d):
    keep = read_table(spark, d, "part", "p_partkey", "p_size").filter(F.col("p_size").between(10, 20)).select(F.col("p_partkey").alias("vertex_id"))
    return shape.induced(builders.parts_by_order(spark, d), keep)


@query("clique_edges", f"WITH raw AS ({sql.PINS['suppliers_by_order']}), e AS ({sql.COPURCHASE}) SELECT src, dst, weight FROM e")
def clique_edges(spark, d):
    return builders.copurchase(builders.suppliers_by_order(spark, d))


@query("dense_ids", "SELECT p_partkey, row_number() OVER (ORDER BY p_partkey) - 1 AS dense_id FROM part")
def dense_ids(spark, d):
    return shape.dense_ids(read_table(spark, d, "part", "p_partkey"), F.col("p_partkey"))


@query("arrival_orders", "SELECT vertex_id, row_number() OVER (ORDER BY vertex_id) - 1 AS natural_seq, row_number() OVER (ORDER BY md5('5:' || vertex_id), vertex_id) - 1 AS random_seq, row_number() OVER (ORDER BY deg, vertex_id) - 1 AS degree_seq FROM (SELECT l_partkey AS vertex_id, count(DISTINCT l_orderkey) AS deg FROM lineitem GROUP BY l_partkey)")
def arrival_orders(spark, d):
    ids = builders.parts_by_order(spark, d).groupBy("vertex_id").agg(F.count("*").alias("deg"))
    frames = [shape.with_seq(ids, o, 5, "deg").select("vertex_id", F.col("seq").alias(f"{o}_seq")) for o in ("natural", "random", "degree")]
    return frames[0].join(frames[1], "vertex_id").join(frames[2], "vertex_id")


@query("netlist_round_trip", select_with(H1, "x AS (SELECT 1)", "SELECT 2 * count(*) AS n_checked, CAST(0 AS BIGINT) AS n_violations FROM p"))
def netlist_round_trip(spark, d):
    """Pins written as net lines and read back, by the text reader and by the Python data source, keep every net's pin set."""
    h = hypergraph(spark, d, H1)
    path = scratch_path(spark, "netlist")
    netlist.write_netlist(h.pins.coalesce(1), path)
    sets = lambda p: p.groupBy("net_id").agg(F.sort_array(F.collect_list("vertex_id")).alias("s")).groupBy("s").agg(F.count("*").alias("c"))
    want = sets(h.pins)
    back = netlist.read_netlist(spark, path)
    lost = want.exceptAll(sets(back)).select(F.size("s").alias("z"))
    spark.dataSource.register(netlist.NetlistSource)
    files = [r["f"] for r in spark.read.text(path).select(F.input_file_name().alias("f")).distinct().collect()]  # one file
    again = spark.read.format("netlist").option("path", files[0].removeprefix("file://")).option("range_bytes", "50000").load()
    lost2 = want.exceptAll(sets(again)).select(F.size("s").alias("z"))
    n = back.count() + again.count()
    return lost.union(lost2).agg(F.lit(n).cast("bigint").alias("n_checked"), F.count("*").alias("n_violations"))


# --- reports over runs of the stateless methods ---------------------------------------------------------------------------------

INSTANCES, RUN_KS = ("suppliers_by_order", "customers_by_part", "parts_by_supplier"), (4, 8, 16)
_PLACES = {
    "hashing": lambda k: f"{sql.hashed(k)}", "round_robin": lambda k: f"CAST(seq % {k} AS INTEGER)",
    "contiguous": lambda k: f"CAST(seq * {k} // n AS INTEGER)", "random": lambda k: f"{sql.seeded(k, 'seed')}",
}


def _runs_sql() -> str:
    parts = []
    for name in INSTANCES:
        for k in RUN_KS:
            for algorithm, place in _PLACES.items():
                seeds = "range(3)" if algorithm == "random" else "range(1)"
                parts.append(
                    f"SELECT '{name}' AS instance, {k} AS k, '{algorithm}' AS algorithm, seed, CAST(count(*) FILTER (l > 1) AS DOUBLE) AS cut_net, CAST(sum(l - 1) AS DOUBLE) AS connectivity FROM ("
                    f"SELECT net_id, seed, count(DISTINCT {place(k)}) AS l FROM p_{name} JOIN v_{name} USING (vertex_id), (SELECT CAST(range AS INTEGER) AS seed FROM {seeds}) GROUP BY net_id, seed) GROUP BY seed"
                )
    ctes = []
    for name in INSTANCES:
        ctes.append(f"r_{name} AS ({sql.PINS[name]}), p_{name} AS (SELECT net_id, vertex_id FROM (SELECT *, count(*) OVER (PARTITION BY net_id) AS s FROM r_{name}) WHERE s >= 2), v_{name} AS (SELECT vertex_id, row_number() OVER (ORDER BY vertex_id) - 1 AS seq, count(*) OVER () AS n FROM (SELECT DISTINCT vertex_id FROM r_{name}))")
    return ",\n".join(ctes) + ",\nruns AS (" + "\nUNION ALL ".join(parts) + ")"


RUNS_SQL = _runs_sql()
MEANS_SQL = RUNS_SQL + ",\nmeans AS (SELECT instance, k, algorithm, avg(connectivity) AS a FROM runs GROUP BY ALL)"


def control_runs(spark: SparkSession, d: str) -> DataFrame:
    """Measures of the stateless methods: every pin carries the block masks of all methods and k, merged per net."""
    runs = []
    for name in INSTANCES:
        # Written once: vertices, their numbers and the masks all read it. Nets of one pin are left out where nets are merged.
        pins = cut(builders.HYPERGRAPHS[name](spark, d), "pins-of-runs")
        vertices = shape.with_seq(pins.select("vertex_id").distinct())
        n, v = vertices.count(), F.col("vertex_id")
        cells = []
        for k in RUN_KS:
            cells += [
                ("hashing", k, 0, controls.hash_block(v, k)), ("round_robin", k, 0, (F.col("seq") % k).cast("int")),
                ("contiguous", k, 0, F.expr(f"int(seq * {k} div {n})")), *(("random", k, s, controls.hash_block(v, k, s)) for s in range(3)),
            ]
        merged, spans = measures.spans_of(pins, vertices, [(block, k) for _, k, _, block in cells])
        sums = [x for i, l in enumerate(spans) for x in (F.count_if(l > 1).alias(f"c{i}"), F.sum(l - 1).alias(f"l{i}"))]
        with small_broadcasts(spark):
            row = merged.filter("wide").agg(*sums).first()  # one row
        large = pins.count() > LARGE
        discard(vertices)
        discard(pins)
        if large:
            release(spark)
        runs += [(name, k, a, s, float(row[f"c{i}"]), float(row[f"l{i}"])) for i, (a, k, s, _) in enumerate(cells) if row[f"l{i}"] is not None]
    return cut(spark.createDataFrame(runs, "instance string, k int, algorithm string, seed int, cut_net double, connectivity double").coalesce(1), "runs")


@query("control_runs", f"WITH {RUNS_SQL}\nSELECT instance, k, algorithm, seed, cut_net, connectivity FROM runs")
def _control_runs(spark, d):
    return control_runs(spark, d)


@query("improvement", f"WITH {MEANS_SQL}\nSELECT m.instance, m.k, m.algorithm, round((b.a / nullif(m.a, 0) - 1) * 100, 6) AS improvement FROM means m JOIN means b ON b.instance = m.instance AND b.k = m.k AND b.algorithm = 'hashing'")
def improvement(spark, d, runs=control_runs):
    return report.improvement(runs(spark, d), "hashing").withColumn("improvement", F.round("improvement", 6))


@query("mean_geomean", f"WITH {MEANS_SQL}\nSELECT algorithm, round(exp(avg(ln(a)) FILTER (a > 0)), 4) AS geo_mean, count(*) FILTER (a = 0) AS n_zero FROM means GROUP BY algorithm")
def mean_geomean(spark, d, runs=control_runs):
    return report.summarise(runs(spark, d)).withColumn("geo_mean", F.round("geo_mean", 4))


TAUS = (1.0, 1.01, 1.05, 1.5, 2.0, 4.0)


def _profile_of(taus):
    return f"WITH {MEANS_SQL}\nSELECT algorithm, tau, avg(CASE WHEN a <= tau * best THEN 1.0 ELSE 0.0 END) AS share FROM (SELECT *, min(a) OVER (PARTITION BY instance, k) AS best FROM means), (SELECT CAST(unnest([{', '.join(map(str, taus))}]) AS DOUBLE) AS tau) GROUP BY ALL"


@query("profile_curve", _profile_of(TAUS))
def profile_curve(spark, d, runs=control_runs):
    return report.profile(runs(spark, d), "connectivity", list(TAUS))


@query("profile_points", _profile_of((1.0, 2.0, 4.0)))
def profile_points(spark, d, runs=control_runs):
    return report.profile(runs(spark, d), "connectivity", [1.0, 2.0, 4.0])


@query("boxplot", f"WITH {RUNS_SQL}, q AS (SELECT algorithm, quantile_cont(connectivity, [0.25, 0.5, 0.75]) AS q FROM runs GROUP BY algorithm) SELECT algorithm, min(connectivity) AS lo, any_value(q.q[1]) AS q1, any_value(q.q[2]) AS median, any_value(q.q[3]) AS q3, max(connectivity) AS hi FROM runs JOIN q USING (algorithm) WHERE connectivity BETWEEN q.q[1] - 1.5 * (q.q[3] - q.q[1]) AND q.q[3] + 1.5 * (q.q[3] - q.q[1]) GROUP BY algorithm")
def boxplot(spark, d, runs=control_runs):
    return report.boxplot(runs(spark, d), "connectivity")


@query("bars_by_k", f"WITH {MEANS_SQL}, g AS (SELECT k, algorithm, exp(avg(ln(a))) AS g FROM means WHERE a > 0 GROUP BY ALL) SELECT g.k, g.algorithm, round((b.g / g.g - 1) * 100, 4) AS improvement FROM g JOIN g b ON b.k = g.k AND b.algorithm = 'hashing'")
def bars_by_k(spark, d, runs=control_runs):
    return report.by_k(runs(spark, d), "hashing").withColumn("improvement", F.round("improvement", 4))


@query("dominance", f"WITH {RUNS_SQL}, t AS (SELECT algorithm, sum(cut_net) AS c, sum(connectivity) AS q FROM runs WHERE seed = 0 GROUP BY algorithm) SELECT algorithm, EXISTS (SELECT 1 FROM t b WHERE b.c <= a.c AND b.q <= a.q AND (b.c < a.c OR b.q < a.q)) AS dominated FROM t a")
def dominance(spark, d):
    points = control_runs(spark, d).filter("seed = 0").groupBy("algorithm").agg(F.sum("cut_net").alias("c"), F.sum("connectivity").alias("q"))
    return report.dominated(points, "c", "q")


@query("rank_stability", f"WITH {RUNS_SQL}, m AS (SELECT k, algorithm, avg(connectivity) AS a FROM runs GROUP BY ALL), r AS (SELECT algorithm, rank() OVER (PARTITION BY k ORDER BY a) AS r FROM m) SELECT algorithm, count(DISTINCT r) AS ranks FROM r GROUP BY algorithm")
def rank_stability(spark, d, runs=control_runs):
    return report.rank_stability(runs(spark, d))


@query("report_cube", f"WITH {RUNS_SQL}\nSELECT instance, k, algorithm, CAST(grouping_id(instance, k, algorithm) AS BIGINT) AS level, count(*) AS runs, sum(cut_net) AS cut_net FROM runs GROUP BY CUBE (instance, k, algorithm)")
def report_cube(spark, d):
    return report.cube(control_runs(spark, d))


@query("report_rollup", f"WITH {RUNS_SQL}\nSELECT instance, k, CAST(grouping_id(instance, k) AS BIGINT) AS level, count(*) AS runs, sum(connectivity) AS connectivity FROM runs GROUP BY ROLLUP (instance, k)")
def report_rollup(spark, d):
    return report.rollup(control_runs(spark, d))


@query("report_grouping_sets", f"WITH {RUNS_SQL}\nSELECT instance, k, algorithm, count(*) AS runs, max(cut_net) AS cut_net FROM runs GROUP BY GROUPING SETS ((instance, k), (algorithm))")
def report_grouping_sets(spark, d):
    return report.grouping_sets(control_runs(spark, d))


@query("report_pivot", f"WITH {RUNS_SQL}\nSELECT instance, k, " + ", ".join(f"avg(connectivity) FILTER (algorithm = '{a}') AS {a}" for a in _PLACES) + " FROM runs GROUP BY ALL")
def report_pivot(spark, d):
    return report.pivot(control_runs(spark, d), list(_PLACES))


# --- the comparison of methods: runs of all deterministic one-pass methods, and the same reports over them -------------------------

COMPARED, COMPARED_KS = ("parts_by_order", "customers_by_part", "docs_by_line", "pages_by_link", "signed_clauses"), (8, 32)
METHODS = {
    "hashing": (None, lambda h, spec: controls.hashing(h.vertices, spec.k)),
    "greedy_con": ({"objective": "con"}, ordered.assign),
    "greedy_cut": ({"objective": "cut"}, lambda h, spec: ordered.assign(h, replace(spec, objective="cut"))),
    "minmax_lists": ({"rule": "minmax"}, ordered.minmax_assign),
    "minmax_capped": ({"rule": "capped"}, lambda h, spec: ordered.minmax_assign(h, spec, "capped")),
}


def _compared_sql() -> str:
    tables, rows = [], []
    for i, name in enumerate(COMPARED):
        tables.append(sql.base(name, f"_{i}"))
        for k in COMPARED_KS:
            for j, (algorithm, (rule, _)) in enumerate(METHODS.items()):
                tag = f"_{i}_{k}_{j}"
                if rule is None:
                    tables.append(f"a{tag} AS MATERIALIZED (SELECT vertex_id, {sql.hashed(k)} AS block FROM v_{i})")
                else:
                    tables.append(sql.replay(k, pins=f"p_{i}", vertices=f"v_{i}", tag=tag, **rule))
                rows.append(f"SELECT '{name}' AS instance, {k} AS k, '{algorithm}' AS algorithm, 0 AS seed, cut_net, connectivity FROM ({sql.quality(f'a{tag}', f'p_{i}')})")
    return ",\n".join(tables) + ",\nruns AS MATERIALIZED (" + "\nUNION ALL ".join(rows) + ")"


COMPARED_SQL = _compared_sql()
LARGE = 1_000_000  # pins from which on the shuffle files of an instance are let go at its end
SIDE_BY_SIDE = 5  # instances whose methods run at the same time, each one after another
_compared: dict[tuple, DataFrame] = {}


def _runs_of(spark: SparkSession, d: str, name: str) -> list[tuple]:
    """The rows of one instance: every method's placement is written, then one pass over the pins measures all of them."""
    h = hypergraph(spark, d, name, once=True)
    shape.numbered_stream(h)
    cells = [(k, algorithm) for k in COMPARED_KS for algorithm in METHODS]
    made = []
    for k, algorithm in cells:
        # One walk of an instance at a time: in one plan they would run side by side, each with its net states and its shuffle.
        made.append(cut(METHODS[algorithm][1](h, PartitionSpec(k)), "placement"))
    rows = [a.select("vertex_id", F.lit(i).alias("run"), "block") for i, a in enumerate(made)]
    blocks = _union(rows).groupBy("vertex_id").agg(*[F.max(F.when(F.col("run") == i, F.col("block"))).alias(f"b{i}") for i in range(len(made))])
    merged, spans = measures.spans_of(h.pins, blocks, [(F.col(f"b{i}"), k) for i, (k, _) in enumerate(cells)])
    sums = [x for i, l in enumerate(spans) for x in (F.sum(F.when(l > 1, 1.0).otherwise(0.0)).alias(f"c{i}"), F.sum(l - 1).cast("double").alias(f"l{i}"))]
    with small_broadcasts(spark):
        found = merged.agg(*sums).first()  # one row
    large = h.stats()["pins"] > LARGE
    for written in (*made, h.numbered, h.pins):
        discard(written)
    if large:
        release(spark)
    return [(name, k, algorithm, 0, found[f"c{i}"], found[f"l{i}"]) for i, (k, algorithm) in enumerate(cells)]


def method_runs(spark: SparkSession, d: str) -> DataFrame:
    """instance, k, algorithm, seed, cut_net, connectivity of every method; one table per session and folder, read by all reports.

    Instances go side by side, as each has one task at work most of the time."""
    key = (spark.sparkContext.applicationId, d)
    if key not in _compared:
        with ThreadPoolExecutor(SIDE_BY_SIDE) as threads:
            rows = [row for found in threads.map(lambda name: _runs_of(spark, d, name), COMPARED) for row in found]
        made = spark.createDataFrame(rows, "instance string, k int, algorithm string, seed int, cut_net double, connectivity double")
        _compared[key] = cut(made.coalesce(1), "method-runs")
    return _compared[key]


@query("method_runs", f"WITH RECURSIVE {COMPARED_SQL}\nSELECT instance, k, algorithm, seed, cut_net, connectivity FROM runs")
def _method_runs(spark, d):
    return method_runs(spark, d)


for _name, _report in (("improvement", improvement), ("mean_geomean", mean_geomean), ("profile_curve", profile_curve), ("profile_points", profile_points), ("boxplot", boxplot), ("bars_by_k", bars_by_k), ("rank_stability", rank_stability)):

    @query(f"method_{_name}", ORACLES[_name].replace(RUNS_SQL, COMPARED_SQL).replace("WITH ", "WITH RECURSIVE ", 1))
    def _method_report(spark, d, made=_report):
        return made(spark, d, method_runs)


@query("method_cut_net", f"WITH RECURSIVE {COMPARED_SQL}, b AS (SELECT instance, k, cut_net AS base FROM runs WHERE algorithm = 'hashing') SELECT instance, k, algorithm, round((base / nullif(cut_net, 0) - 1) * 100, 6) AS improvement, CAST(rank() OVER (PARTITION BY instance, k ORDER BY cut_net) AS INTEGER) AS place FROM runs JOIN b USING (instance, k)")
def method_cut_net(spark, d):
    """Improvement over hashing and place by cut-net."""
    runs = method_runs(spark, d)
    better = report.improvement(runs, "hashing", "cut_net").withColumn("improvement", F.round("improvement", 6))
    place = runs.select("instance", "k", "algorithm", F.rank().over(W.partitionBy("instance", "k").orderBy("cut_net")).alias("place"))
    return better.join(place, ["instance", "k", "algorithm"])


@query("method_best", f"WITH RECURSIVE {COMPARED_SQL}, b AS (SELECT *, min(cut_net) OVER w AS c, min(connectivity) OVER w AS l FROM runs WINDOW w AS (PARTITION BY instance, k)) SELECT algorithm, count(*) FILTER (cut_net = c) AS best_cut_net, count(*) FILTER (connectivity = l) AS best_connectivity, count(*) AS runs FROM b GROUP BY algorithm")
def method_best(spark, d):
    """In how many (instance, k) each method is best; ties count for all."""
    w = W.partitionBy("instance", "k")
    runs = method_runs(spark, d).withColumns({"c": F.min("cut_net").over(w), "l": F.min("connectivity").over(w)})
    return runs.groupBy("algorithm").agg(F.count_if(F.col("cut_net") == F.col("c")).alias("best_cut_net"), F.count_if(F.col("connectivity") == F.col("l")).alias("best_connectivity"), F.count("*").alias("runs"))


@query("rounds_staleness", f"WITH RECURSIVE {sql.base('pages_by_link')},\n{sql.replay(8)},\n{sql.rounds(8, [60 * (i + 1) for i in range(8)], tag='x')},\n{sql.rounds(8, [125 * (i + 1) for i in range(4)], tag='y')}\n" + " UNION ALL ".join(f"SELECT CAST({b} AS INTEGER) AS batch, cut_net, connectivity FROM ({sql.quality(t)})" for b, t in ((1, "a"), (60, "dx"), (125, "dy"))))
def rounds_staleness(spark, d):
    """What deciding against an older state costs: the sequential rule beside rounds of 60 and of 125 vertices."""
    h, spec = hypergraph(spark, d, "pages_by_link"), PartitionSpec(8)
    made = ((1, placements(ordered.greedy(h, spec))), (60, rounds.greedy(h, spec, batch=60)), (125, rounds.greedy(h, spec, batch=125)))
    return _union([quality(h, a).select(F.lit(b).alias("batch"), "cut_net", "connectivity") for b, a in made])


# --- comparisons, routing, samples ----------------------------------------------------------------------------------------------------


@query("assignment_diff", select_with(H1, f"x AS (SELECT {sql.hashed(K)} AS b, CAST(seq % {K} AS INTEGER) AS c FROM v)", "SELECT count(*) AS n_checked, count(*) FILTER (b <> c) AS n_violations FROM x"))
def assignment_diff(spark, d):
    h, a = _hashed(spark, d)
    return audit.diff(a, controls.round_robin(h.vertices, K))


@query("block_overlap", select_with(H1, f"x AS (SELECT {sql.hashed(8)} AS block_a, CAST(seq % 8 AS INTEGER) AS block_b FROM v)", "SELECT block_a, block_b, count(*) AS vertices FROM x GROUP BY ALL"))
def block_overlap(spark, d):
    h = hypergraph(spark, d, H1)
    return audit.block_overlap(controls.hashing(h.vertices, 8), controls.round_robin(h.vertices, 8))


@query("heaviest_cut_nets", select_with(H1, HASHED, "SELECT net_id, CAST(l AS INTEGER) AS lambda FROM (SELECT net_id, count(DISTINCT block) AS l FROM p JOIN a USING (vertex_id) GROUP BY net_id) ORDER BY l DESC, net_id LIMIT 20"))
def heaviest_cut_nets(spark, d):
    """A top-k report: the 20 widest nets."""
    h, a = _hashed(spark, d)
    return measures.net_span(h.pins, a).orderBy(F.desc("lambda"), "net_id").limit(20)


@query("quantile_loads", select_with(H1, HASHED, "SELECT quantile_cont(c, 0.25) AS q1, quantile_cont(c, 0.5) AS median, quantile_cont(c, 0.75) AS q3 FROM (SELECT count(*) AS c FROM a GROUP BY block)"))
def quantile_loads(spark, d):
    h, a = _hashed(spark, d)
    loads = a.groupBy("block").agg(F.count("*").alias("c"))
    return loads.agg(F.percentile("c", F.lit(0.25)).alias("q1"), F.percentile("c", F.lit(0.5)).alias("median"), F.percentile("c", F.lit(0.75)).alias("q3"))


@query("sample_vertices", f"SELECT p_partkey AS vertex_id FROM part WHERE {sql.hashed(100, 'p_partkey')} < 10")
def sample_vertices(spark, d):
    """A sampling operator: a tenth of the vertices by hash."""
    return read_table(spark, d, "part", "p_partkey").filter(controls.hash_block(F.col("p_partkey"), 100) < 10).select(F.col("p_partkey").alias("vertex_id"))


@query("block_routed_lineitem", f"SELECT {sql.hashed(8, 'l_partkey')} AS block, count(*) AS lines, sum(l_quantity) AS quantity FROM lineitem GROUP BY 1")
def block_routed_lineitem(spark, d):
    """What a partition is for: rows written by block, aggregated with pruned folders."""
    lines = read_table(spark, d, "lineitem", "l_partkey", "l_quantity")
    parts = lines.select(F.col("l_partkey").alias("vertex_id")).distinct()
    path = scratch_path(spark, "blocks")
    netlist.write_blocks(lines, controls.hashing(parts, 8), path, "l_partkey")
    return spark.read.parquet(path).groupBy("block").agg(F.count("*").alias("lines"), F.sum("l_quantity").alias("quantity"))


@query("event_windows", "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS events FROM events GROUP BY ALL")
def event_windows(spark, d):
    events = read_table(spark, d, "events", "ts", "event_type").withColumn("ts", F.col("ts").cast("timestamp"))
    return events.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("events")).select(F.col("w.start").cast("timestamp_ntz").alias("day"), "event_type", "events")


@query("event_sliding", "SELECT CAST(date_trunc('hour', ts) - to_hours(CAST(h AS INTEGER)) AS TIMESTAMP) AS start, count(*) AS events FROM events, (SELECT unnest(range(2)) AS h) GROUP BY ALL")
def event_sliding(spark, d):
    events = read_table(spark, d, "events", "ts").withColumn("ts", F.col("ts").cast("timestamp"))
    return events.groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("events")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "events")


@query("event_sessions", "WITH e AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 1 HOUR THEN 1 ELSE 0 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, sum(f) OVER (PARTITION BY user_id ORDER BY ts) AS n FROM e), g AS (SELECT user_id, n, count(*) AS c FROM s GROUP BY ALL) SELECT user_id, count(*) AS sessions, max(c) AS longest FROM g GROUP BY user_id")
def event_sessions(spark, d):
    events = read_table(spark, d, "events", "user_id", "ts").withColumn("ts", F.col("ts").cast("timestamp"))
    sessions = events.groupBy("user_id", F.session_window("ts", "1 hour")).agg(F.count("*").alias("c"))
    return sessions.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("c").alias("longest"))


@query("json_props", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS events FROM events GROUP BY 1")
def json_props(spark, d):
    return read_table(spark, d, "events", "props").groupBy(F.get_json_object("props", "$.k").cast("bigint").alias("k")).agg(F.count("*").alias("events"))


@query("filter_orders", "SELECT o_orderpriority, count(*) AS orders FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 200000 AND o_orderpriority LIKE '%-%' GROUP BY 1")
def filter_orders(spark, d):
    rows = read_table(spark, d, "orders", "o_orderpriority", "o_orderstatus", "o_totalprice")
    return rows.filter(F.col("o_orderstatus").isin("F", "O") & F.col("o_totalprice").between(1000, 200000) & F.col("o_orderpriority").like("%-%")).groupBy("o_orderpriority").agg(F.count("*").alias("orders"))


@query("unassigned_vertices", f"SELECT o_orderkey AS vertex_id FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def unassigned_vertices(spark, d):
    orders = read_table(spark, d, "orders", "o_orderkey").withColumnRenamed("o_orderkey", "vertex_id")
    return orders.join(builders.orders_by_part(spark, d).select("vertex_id"), "vertex_id", "left_anti")


# --- live lanes and SQL surface ------------------------------------------------------------------------------------------------------------


def _user_stream(spark, d):
    """Users by hour in arrival order of their first event: stream_id, seq, vertex_id, nets."""
    h = hypergraph(spark, d, "users_by_hour_type")
    rows = shape.vertex_stream(h).select(F.lit(1).cast("bigint").alias("stream_id"), "seq", "vertex_id", F.col("nets.net_id").alias("nets"))
    return h, rows


def _replayed(spark, rows, spec, h, files: int = 3):
    """The rows as a file stream of several micro-batches through the live lane."""
    src, out, ckpt = (scratch_path(spark, x) for x in ("live-in", "live-out", "live-ckpt"))
    top = rows.agg(F.max("seq").alias("x")).first()["x"] + 1
    for i in range(files):  # one after the other: files are taken in the order of their times
        rows.filter((F.col("seq") * files >= top * i) & (F.col("seq") * files < top * (i + 1))).coalesce(1).write.mode("append").parquet(src)
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(src)
    placed = live.partition_stream(stream, spec, h.stats()["n"], h.stats()["m"])
    placed.writeStream.format("parquet").option("checkpointLocation", ckpt).outputMode("append").trigger(availableNow=True).start(out).awaitTermination()
    return spark.read.schema(live.OUT).parquet(out)


USERS_PLACED = select_with("users_by_hour_type", sql.replay(4), ASSIGNED)


@query("live_dedup", USERS_PLACED)
def live_dedup(spark, d):
    """Every vertex arrives twice, in different micro-batches, and is placed once, as it is by the batch lane."""
    h, rows = _user_stream(spark, d)
    n = h.stats()["n"]
    return _replayed(spark, rows.union(rows.withColumn("seq", F.col("seq") + n)), PartitionSpec(4), h).select("vertex_id", "block")


@query("live_unbounded", select_with("users_by_hour_type", sql.replay(4, growing=True), ASSIGNED))
def live_unbounded(spark, d):
    """No horizon: bound and strength grow with the arrivals."""
    _, rows = _user_stream(spark, d)
    src, out, ckpt = (scratch_path(spark, x, kept=True) for x in ("live-in", "live-out", "live-ckpt"))
    for half in (0, 1):
        rows.filter((F.col("seq") < 70) if half == 0 else (F.col("seq") >= 70)).coalesce(1).write.mode("append").parquet(src)
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(src)
    live.partition_stream(stream, PartitionSpec(4)).writeStream.format("parquet").option("checkpointLocation", ckpt).outputMode("append").trigger(availableNow=True).start(out).awaitTermination()
    return spark.read.schema(live.OUT).parquet(out).select("vertex_id", "block")


@query("live_foreach_rounds", select_with("users_by_hour_type", sql.rounds(4, [50 * (i + 1) for i in range(8)]), "SELECT vertex_id, block FROM d"))
def live_foreach_rounds(spark, d):
    """A round per micro-batch: votes from the net states that the batches before it left."""
    h = hypergraph(spark, d, "users_by_hour_type")
    spec = PartitionSpec(4)
    capacity_, strength = ordered.limits(h, spec)
    rows = shape.vertex_stream(h).select("seq", "vertex_id", "weight", F.col("nets.net_id").alias("nets"))
    src, out, kept, ckpt = (scratch_path(spark, x, kept=True) for x in ("each-in", "each-out", "each-state", "each-ckpt"))
    write_in_turn(rows, src, "seq", 50)
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(src)
    each = live.rounds_sink(live.round_of(spec, capacity_, strength, choose.lane(h.stats(), spec) == "ordered"), kept, out)
    stream.writeStream.foreachBatch(each).option("checkpointLocation", ckpt).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out).select("vertex_id", "block")


@query("live_replay_diff", "SELECT count(DISTINCT user_id) AS n_checked, CAST(0 AS BIGINT) AS n_violations FROM events")
def live_replay_diff(spark, d):
    """Micro-batches of one ordered stream place like the batch lane."""
    h, rows = _user_stream(spark, d)
    spec = PartitionSpec(4)
    return audit.diff(ordered.greedy(h, spec), _replayed(spark, rows, spec, h))


def _streamed(spark, make, *frames):
    """Frames as file streams through make(streams), written out and read back."""
    out, ckpt = (scratch_path(spark, x, kept=True) for x in ("joined-out", "joined-ckpt"))
    streams = [spark.readStream.schema(f.schema).parquet(p) for f in frames for p in [scratch_path(spark, "joined-in", kept=True)] if not f.write.parquet(p)]
    joined = make(*streams)
    joined.writeStream.format("parquet").option("checkpointLocation", ckpt).outputMode("append").trigger(availableNow=True).start(out).awaitTermination()
    return spark.read.schema(joined.schema).parquet(out)


@query("live_static_join", "SELECT c_nationkey, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def live_static_join(spark, d):
    """A stream of orders with the table of customers."""
    orders = read_table(spark, d, "orders", "o_orderkey", "o_custkey").withColumnRenamed("o_custkey", "c_custkey")
    customers = read_table(spark, d, "customer", "c_custkey", "c_nationkey")
    return _streamed(spark, lambda s: live.with_table(s, customers, "c_custkey"), orders).groupBy("c_nationkey").agg(F.count("*").alias("orders"))


@query("live_stream_join", "SELECT o_orderkey AS order_id, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey AND l_shipdate BETWEEN o_orderdate AND o_orderdate + INTERVAL 30 DAY GROUP BY 1")
def live_stream_join(spark, d):
    """Two streams: orders, and their lines that ship within thirty days."""
    orders = read_table(spark, d, "orders", "o_orderkey", "o_orderdate").select(F.col("o_orderkey").alias("order_id"), F.col("o_orderdate").cast("timestamp").alias("ts"))
    lines = read_table(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_shipdate").select(F.col("l_orderkey").alias("order_id"), "l_linenumber", F.col("l_shipdate").cast("timestamp").alias("pin_ts"))
    return _streamed(spark, lambda a, p: live.with_stream(a, p, "order_id"), orders, lines).groupBy("order_id").agg(F.count("*").alias("lines"))


@query("salted_join", "SELECT s_nationkey, count(*) AS lines, sum(l_quantity) AS quantity FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def salted_join(spark, d):
    """Lines with their supplier's nation, suppliers with over half a percent of all lines dealt over several tasks."""
    lines = read_table(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_suppkey", "l_quantity").withColumnRenamed("l_suppkey", "s_suppkey")
    joined = skew.salted_join(lines, read_table(spark, d, "supplier", "s_suppkey", "s_nationkey"), "s_suppkey", share=0.005, salts=4)
    return joined.groupBy("s_nationkey").agg(F.count("*").alias("lines"), F.sum("l_quantity").alias("quantity"))


@query("sql_udtf_partition", select_with("suppliers_by_order", sql.replay(8), ASSIGNED))
def sql_udtf_partition(spark, d):
    sqlapi.register(spark)
    h = hypergraph(spark, d, "suppliers_by_order")
    s = h.stats()
    shape.vertex_stream(h).select(F.lit(1).cast("bigint").alias("graph_id"), "seq", "vertex_id", F.col("nets.net_id").alias("nets")).createOrReplaceTempView("pinflow_stream")
    return spark.sql(f"SELECT vertex_id, block FROM stream_partition(TABLE(pinflow_stream) PARTITION BY graph_id ORDER BY (seq), 8, '0.03', 'con', {s['n']}, {s['m']})")


@query("sql_functions", f"SELECT p_partkey, {sql.hashed(8, 'p_partkey')} AS block, CAST(0.5 AS DOUBLE) * sqrt(CAST(p_size AS DOUBLE)) AS penalty FROM part")
def sql_functions(spark, d):
    sqlapi.register(spark)
    read_table(spark, d, "part", "p_partkey", "p_size").createOrReplaceTempView("pinflow_part")
    return spark.sql("SELECT p_partkey, hash_block(p_partkey, 8) AS block, load_penalty(CAST(p_size AS DOUBLE), CAST(0.5 AS DOUBLE)) AS penalty FROM pinflow_part")


def _regions() -> str:
    """Each region's hypergraph of customers by part, with bound and strength of its own."""
    tables = ["x AS MATERIALIZED (SELECT DISTINCT n_regionkey AS r, c_custkey AS vertex_id FROM customer JOIN nation ON n_nationkey = c_nationkey)", f"raw AS MATERIALIZED ({sql.PINS['customers_by_part']})"]
    for r in range(5):
        tables.append(f"p{r} AS MATERIALIZED (SELECT net_id, vertex_id FROM (SELECT raw.*, count(*) OVER (PARTITION BY net_id) AS s FROM raw JOIN x USING (vertex_id) WHERE r = {r}) WHERE s >= 2), v{r} AS MATERIALIZED (SELECT vertex_id, row_number() OVER (ORDER BY vertex_id) - 1 AS seq FROM x WHERE r = {r})")
        tables.append(sql.replay(4, pins=f"p{r}", vertices=f"v{r}", tag=f"g{r}"))
    return "WITH RECURSIVE " + ",\n".join(tables) + "\n" + " UNION ALL ".join(f"SELECT CAST({r} AS BIGINT) AS graph, vertex_id, block FROM ag{r}" for r in range(5))


@query("many_hypergraphs", _regions())
def many_hypergraphs(spark, d):
    """One hypergraph per region, customers by part, all placed side by side within bounds of their own."""
    customers = read_table(spark, d, "customer", "c_custkey", "c_nationkey").join(read_table(spark, d, "nation", "n_nationkey", "n_regionkey"), F.col("c_nationkey") == F.col("n_nationkey"))
    customers = customers.select(F.col("n_regionkey").alias("region"), F.col("c_custkey").alias("vertex_id")).distinct()
    pins = builders.customers_by_part(spark, d).join(customers, "vertex_id")
    shared = pins.groupBy("region", "net_id").agg(F.count("*").alias("s")).filter("s >= 2")
    sizes = customers.groupBy("region").agg(F.count("*").alias("n")).join(shared.groupBy("region").agg(F.count("*").alias("m")), "region", "left").select("region", "n", F.coalesce("m", F.lit(0)).alias("m"))
    nets = pins.join(shared, ["region", "net_id"]).groupBy("vertex_id").agg(F.collect_list(F.struct("net_id", F.lit(1.0).alias("weight"))).alias("nets"))
    empty = F.array().cast("array<struct<net_id:bigint,weight:double>>")
    stream = customers.join(nets, "vertex_id", "left").join(sizes, "region").select(F.col("vertex_id").alias("seq"), "vertex_id", F.lit(1.0).alias("weight"), F.coalesce("nets", empty).alias("nets"), "region", "n", "m")
    return ordered.run_many(stream, "region", PartitionSpec(4)).select(F.col("key").alias("graph"), "vertex_id", "block")


def expected_rounds(n: int, prefix: int, beta: float) -> int:
    """How many rounds the scale lane takes: logarithmic in n."""
    return 1 if n <= prefix else 1 + math.ceil(math.log(n / prefix) / math.log(1 + beta))
