"""Headline timings: prints one JSON line. BENCH_SF_DIR and BENCH_CPUS choose the tables and the local cores.

``queries``: seconds of warmed runs in Spark, placements written out; medians of ``REPEATS`` where one k is timed. ``facts``: the
comparison of methods (improvement over hashing, profile points, best shares, dominance by time and connectivity), time per pin of the
runs and of the bare kernels, growth with k, sweeps of buffer and list bounds, and split over scan on graphs."""

from __future__ import annotations

import json
import os
import statistics
import sys
import time

from pyspark.sql import SparkSession, functions as F

from pinflow import report
from pinflow.catalog import quality
from pinflow.kernel import buffered, greedy, minmax
from pinflow.kernel.fast import unit_walker
from pinflow.lineage import cut, discard
from pinflow.operators import controls, inmem, shape
from pinflow.params import PartitionSpec
from pinflow.plans import ordered, rounds
from pinflow.sources import builders

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
KS = (512, 1024, 1536, 2048, 2560)
REPEATS = 3
INSTANCES = ("docs_by_line", "pages_by_link", "parts_by_order")
METHODS = {
    "hashing": lambda h, s: controls.hashing(h.vertices, s.k),
    "con": ordered.assign,
    "cut": lambda h, s: ordered.assign(h, PartitionSpec(s.k, objective="cut")),
    "capped": lambda h, s: ordered.minmax_place(h, s, "capped").select("vertex_id", "block"),
    "net_index": lambda h, s: ordered.minmax_place(h, s, "lists").select("vertex_id", "block"),
    "buffered": lambda h, s: ordered.buffered_place(h, s, "relaxed_small").select("vertex_id", "block"),
    "fast_in_memory": lambda h, s: inmem.inmem_fast(h, s, 3),
    "multilevel": lambda h, s: ordered.inmem_multilevel(h, s),
}


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    seconds, facts, runs = {}, {}, []

    def load(source, **how):
        h = shape.prepare(builders.HYPERGRAPHS[source](spark, SF), **how)
        h.vertices = cut(h.vertices, "bench-vertices")
        h.stats()
        return h

    def run(h, spec, place, times=1):
        """Median seconds of writing the placements, and their measures."""
        took = []
        for _ in range(times):
            began = time.time()
            done = cut(place(h, spec), "bench-run")
            took.append(time.time() - began)
            if len(took) < times:
                discard(done)
        row = quality(h, done).first()
        discard(done)
        return statistics.median(took), row["cut_net"], row["connectivity"]

    hypergraphs = {name: load(name) for name in (*INSTANCES, "orders_by_part")}
    for place in METHODS.values():  # compile and start workers
        run(hypergraphs["pages_by_link"], PartitionSpec(16), place)

    # All methods on three instances.
    for name in INSTANCES:
        h = hypergraphs[name]
        for algorithm, place in METHODS.items():
            quick = algorithm in ("hashing", "con", "cut")
            took, cut_net, con = run(h, PartitionSpec(512), place, REPEATS if quick else 1)
            seconds[f"{algorithm}_{name}_k512"] = round(took, 3)
            runs.append((name, 512, algorithm, 0, h.stats()["pins"], cut_net, con, int(took * 1e9)))
    # Growth with k.
    for name in ("docs_by_line", "orders_by_part"):
        h = hypergraphs[name]
        for k in KS:
            for algorithm in ("hashing", "con", "cut", "capped"):
                if (name, k) == ("docs_by_line", 512):
                    continue
                took, cut_net, con = run(h, PartitionSpec(k), METHODS[algorithm], REPEATS if k == 2560 and algorithm != "capped" else 1)
                seconds[f"{algorithm}_{name}_k{k}"] = round(took, 3)
                runs.append((name, k, algorithm, 0, h.stats()["pins"], cut_net, con, int(took * 1e9)))
    h = hypergraphs["orders_by_part"]
    took, _, con = run(h, PartitionSpec(2560), lambda x, s: rounds.greedy(x, s).select("vertex_id", "block"))
    seconds["rounds_orders_by_part_k2560"], facts["rounds_connectivity"] = round(took, 3), con
    for beta, prefix in ((0.1, 8192), (0.5, 2048), (1.0, 512)):
        took, _, con = run(hypergraphs["parts_by_order"], PartitionSpec(512), lambda x, s, b=beta, p=prefix: rounds.greedy(x, s, prefix=p, beta=b).select("vertex_id", "block"))
        facts[f"rounds_parts_prefix{prefix}_beta{beta}"] = {"seconds": round(took, 2), "connectivity": con}

    # Reports over the runs.
    table = spark.createDataFrame(runs, "instance string, k int, algorithm string, seed int, pins bigint, cut_net double, connectivity double, wall_ns bigint")
    whole = table.filter(F.col("instance").isin(*INSTANCES) & (F.col("k") == 512))
    for measure in ("connectivity", "cut_net"):
        facts[f"improvement_over_hashing_{measure}_percent"] = {r["algorithm"]: round(r["improvement"], 1) for r in report.by_k(whole, "hashing", measure).collect()}
        facts[f"profile_{measure}"] = {f"{r['algorithm']}@{r['tau']:g}": round(r["share"], 2) for r in report.profile(whole, measure, [1.0, 2.0, 4.0]).orderBy("algorithm", "tau").collect()}
    facts["profile_time"] = {f"{r['algorithm']}@{r['tau']:g}": round(r["share"], 2) for r in report.profile(whole, "wall_ns", [1.0, 2.0, 4.0]).orderBy("algorithm", "tau").collect()}
    means = whole.groupBy("algorithm").agg(F.exp(F.avg(F.log("wall_ns"))).alias("t"), F.exp(F.avg(F.log(F.greatest("connectivity", F.lit(1.0))))).alias("q"))
    facts["dominated_by_time_and_connectivity"] = sorted(r["algorithm"] for r in report.dominated(means, "t", "q").filter("dominated").collect())
    per_pin = table.withColumn("ns", F.col("wall_ns") / F.col("pins")).groupBy("algorithm").agg(F.median("ns").alias("ns")).collect()
    facts["median_ns_per_pin"] = {r["algorithm"]: round(r["ns"]) for r in per_pin}
    for algorithm in ("con", "cut"):
        facts[f"{algorithm}_over_hashing_orders_k2560"] = round(seconds[f"{algorithm}_orders_by_part_k2560"] / seconds["hashing_orders_by_part_k2560"], 2)
        facts[f"{algorithm}_orders_k2560_over_k512"] = round(seconds[f"{algorithm}_orders_by_part_k2560"] / seconds[f"{algorithm}_orders_by_part_k512"], 2)

    # Bare kernels on streams in memory: what the method costs without Spark around it.
    def stream(h):
        rows = [(r["vertex_id"], [n["net_id"] for n in r["nets"]]) for r in shape.vertex_stream(h).orderBy("seq").select("vertex_id", "nets").collect()]  # an in-memory measurement
        return [v for v, _ in rows], [n for _, n in rows]

    def clock(work):
        took = []
        for _ in range(REPEATS):
            began = time.perf_counter()
            work()
            took.append(time.perf_counter() - began)
        return statistics.median(took)

    h, spec = hypergraphs["docs_by_line"], PartitionSpec(2560)
    ids, nets = stream(h)
    pins, pairs = sum(map(len, nets)), [[(e, 1.0) for e in own] for own in nets]
    cap, strength = ordered.limits(h, spec)
    sizes, flat = [len(x) for x in nets], [e for x in nets for e in x]
    kernels = {
        "hashing": lambda: [minmax.hash64(v) % spec.k for v in ids],
        "con": lambda: unit_walker(spec, cap, strength)(sizes, flat),
        "cut": lambda: unit_walker(PartitionSpec(spec.k, objective="cut"), cap, strength)(sizes, flat),
    }
    slack = ordered.default_slack(spec, len(ids))

    def walk(make):
        engine = make()
        for own in pairs:
            engine.place(1.0, own)

    kernels["capped"] = lambda: walk(lambda: minmax.MinMax(spec, cap, slack, minmax.Capped(5)))
    kernels["net_index"] = lambda: walk(lambda: minmax.MinMax(spec, cap, slack, minmax.Lists()))
    facts["kernel_ns_per_pin_docs_k2560"] = {name: round(clock(work) / pins * 1e9) for name, work in kernels.items()}

    # Sweeps of the buffer's share and of the lists' bound.
    spec = PartitionSpec(64)
    cap, slack = spec.capacity(len(ids)), ordered.default_slack(spec, len(ids))

    def connectivity(blocks):
        met: dict[int, set] = {}
        for v, own in zip(ids, nets):
            for e in own:
                met.setdefault(e, set()).add(blocks[v])
        return sum(len(s) - 1 for s in met.values())

    for share in (0.05, 0.15, 0.5):
        engine, blocks = buffered.Buffered(spec, cap, slack, max(1, int(share * pins)), "relaxed"), {}
        for v, own in zip(ids, pairs):
            blocks.update(engine.arrive(v, 1.0, own))
        blocks.update(engine.flush())
        facts[f"buffered_connectivity_share{share}"] = connectivity(blocks)
    for ell in (1, 2, 5, 10):
        engine = minmax.MinMax(spec, cap, slack, minmax.Capped(ell))
        facts[f"capped_connectivity_ell{ell}"] = connectivity({v: engine.place(1.0, own)[0] for v, own in zip(ids, pairs)})
    seeds = []
    for seed in range(5):
        engine = minmax.MinMax(spec, cap, slack, minmax.Capped(5, "random", seed))
        seeds.append(connectivity({v: engine.place(1.0, own)[0] for v, own in zip(ids, pairs)}))
    facts["capped_random_five_seeds"] = {"mean": statistics.mean(seeds), "least": min(seeds), "most": max(seeds)}

    # From disk and from memory.
    h = hypergraphs["orders_by_part"]
    h2 = shape.Hypergraph(h.pins.cache(), h.vertices.cache(), None, h.stats())
    h2.pins.count(), h2.vertices.count()
    facts["con_orders_k512_seconds"] = {"disk": round(run(h, PartitionSpec(512), ordered.assign, REPEATS)[0], 3), "memory": round(run(h2, PartitionSpec(512), ordered.assign, REPEATS)[0], 3)}

    # Graphs: the split rule against the scan of all blocks, in Spark and as bare kernels, by k.
    pages = cut(builders.pages_sharing_link(spark, SF).withColumn("weight", F.lit(1.0)), "bench-pages")
    near = cut(builders.knn_edges(spark.read.parquet(f"{SF}/embeddings.parquet").select("vec_id", "embedding")), "bench-knn")
    speed = {}
    for name, edges in (("pages", pages), ("knn", near)):
        vertices = cut(shape.graph_vertices(edges), "bench-graph")
        rows = shape.adjacency_stream(edges, vertices).orderBy("seq").select("vertex_id", "nets").collect()  # an in-memory measurement
        adjacent = [(r["vertex_id"], [(n[0], n[1]) for n in r["nets"]]) for r in rows]
        for k in (512, 2560):
            spec = PartitionSpec(k)
            n, m = len(adjacent), edges.count()
            took = {}
            for engine in ("split", "scan"):
                if name == "knn" and k == 512:
                    seconds[f"graph_{engine}_k512"] = round(run_graph(edges, spec, engine, vertices), 3)
                began = time.perf_counter()
                walker = greedy.GraphGreedy(spec, spec.capacity(n), spec.strength(n, m), engine)
                for v, own in adjacent:
                    walker.place_vertex(v, 1.0, own)
                took[engine] = time.perf_counter() - began
            speed[f"{name}_k{k}"] = round(took["scan"] / took["split"], 1)
    facts["graph_scan_over_split_kernel"] = speed
    print(json.dumps({"metric": "partitioning_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "facts": facts, "sf": SF.rsplit("sf", 1)[-1]}))
    sys.stdout.flush()
    spark.stop()


def run_graph(edges, spec, engine, vertices) -> float:
    began = time.time()
    discard(cut(ordered.graph_greedy(edges, spec, engine, vertices).select("vertex_id", "block"), "bench-graph-run"))
    return time.time() - began


if __name__ == "__main__":
    main()
