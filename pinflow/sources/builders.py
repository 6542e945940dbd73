"""Hypergraphs and graphs from the given tables. Pins come as distinct (net_id, vertex_id) rows without nulls."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from .tables import read_table

SPLIT = r"[ \n.,;:!?]+"  # the word rule that builders and oracles share


def bipartite(df: DataFrame, vertex, net) -> DataFrame:
    """Pins of any two columns. Dealing by net first lets the distinct and later per-net steps share one exchange."""
    pins = df.select(net.cast("long").alias("net_id"), vertex.cast("long").alias("vertex_id"))
    return pins.filter("net_id IS NOT NULL AND vertex_id IS NOT NULL").repartition("net_id").distinct()


def text_id(value) -> F.Column:
    return F.xxhash64(value)


def parts_by_order(spark: SparkSession, d: str) -> DataFrame:
    return bipartite(read_table(spark, d, "lineitem", "l_orderkey", "l_partkey"), F.col("l_partkey"), F.col("l_orderkey"))


def orders_by_part(spark, d):
    return bipartite(read_table(spark, d, "lineitem", "l_orderkey", "l_partkey"), F.col("l_orderkey"), F.col("l_partkey"))


def suppliers_by_order(spark, d):
    return bipartite(read_table(spark, d, "lineitem", "l_orderkey", "l_suppkey"), F.col("l_suppkey"), F.col("l_orderkey"))


def parts_by_supplier(spark, d):
    return bipartite(read_table(spark, d, "lineitem", "l_partkey", "l_suppkey"), F.col("l_partkey"), F.col("l_suppkey"))


def _bought(spark, d):
    lines = read_table(spark, d, "lineitem", "l_orderkey", "l_partkey")
    return lines.join(read_table(spark, d, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))


def parts_by_customer(spark, d):
    return bipartite(_bought(spark, d), F.col("l_partkey"), F.col("o_custkey"))


def customers_by_part(spark, d):
    return bipartite(_bought(spark, d), F.col("o_custkey"), F.col("l_partkey"))


def words(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    word = F.explode(F.split(F.lower(F.coalesce(F.col(text_col), F.lit(""))), SPLIT))
    return bipartite(df.select(F.col(id_col).alias("v"), word.alias("w")).filter("w <> ''"), F.col("v"), text_id(F.col("w")))


def lines(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    line = F.explode(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n"))
    return bipartite(df.select(F.col(id_col).alias("v"), line.alias("w")).filter("w <> ''"), F.col("v"), text_id(F.col("w")))


def shingles(df: DataFrame, id_col: str, text_col: str, n: int = 3) -> DataFrame:
    ws = F.filter(F.split(F.lower(F.coalesce(F.col(text_col), F.lit(""))), SPLIT), lambda w: w != "")
    rows = df.select(F.col(id_col).alias("v"), ws.alias("ws")).filter(F.size("ws") >= n)
    grams = F.transform(F.sequence(F.lit(1), F.size("ws") - n + 1), lambda i: F.array_join(F.slice("ws", i, F.lit(n)), " "))
    return bipartite(rows.select("v", F.explode(grams).alias("w")), F.col("v"), text_id(F.col("w")))


def docs_by_word(spark, d):
    return words(read_table(spark, d, "documents", "doc_id", "text"), "doc_id", "text")


def docs_by_line(spark, d):
    return lines(read_table(spark, d, "documents", "doc_id", "text"), "doc_id", "text")


def convs_by_word(spark, d):
    return words(read_table(spark, d, "conversations", "conv_id", "text"), "conv_id", "text")


def pages_by_link(spark, d):
    pages = read_table(spark, d, "pages", "page_id", "html")
    link = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))
    return bipartite(pages.select(F.col("page_id").alias("v"), link.alias("w")), F.col("v"), text_id(F.col("w")))


def _events(spark, d, *columns):
    return read_table(spark, d, "events", "user_id", "ts", *columns).withColumn("hour", F.date_trunc("hour", F.col("ts").cast("timestamp")))


def users_by_hour(spark, d):
    return bipartite(_events(spark, d), F.col("user_id"), F.unix_timestamp("hour"))


def users_by_hour_type(spark, d):
    return bipartite(_events(spark, d, "event_type"), F.col("user_id"), F.xxhash64("hour", "event_type"))


def session_nets(spark, d, gap: str = "30 minutes"):
    """Nets are a user's sessions over event types' ids: vertices are event rows, nets are sessions."""
    events = read_table(spark, d, "events", "event_id", "user_id", "ts").withColumn("ts", F.col("ts").cast("timestamp"))
    order = W.partitionBy("user_id").orderBy("ts", "event_id")
    fresh = F.when(F.col("ts") > F.lag("ts").over(order) + F.expr(f"INTERVAL {gap}"), 1).otherwise(0)
    named = events.withColumn("fresh", fresh).withColumn("session", F.sum("fresh").over(order))
    return bipartite(named, F.col("event_id"), F.xxhash64("user_id", "session"))


def signed_clauses(spark, d):
    """Clauses are orders, literals parts with a sign; a variable and its complement are one vertex."""
    return bipartite(literals(spark, d), F.col("l_partkey"), F.col("l_orderkey"))


def literals(spark, d):
    rows = read_table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_returnflag")
    return rows.select("l_orderkey", "l_partkey", (F.col("l_returnflag") == "R").alias("negated")).distinct()


HYPERGRAPHS = {
    "parts_by_order": parts_by_order, "orders_by_part": orders_by_part, "suppliers_by_order": suppliers_by_order,
    "parts_by_supplier": parts_by_supplier, "parts_by_customer": parts_by_customer, "customers_by_part": customers_by_part,
    "docs_by_word": docs_by_word, "docs_by_line": docs_by_line, "users_by_hour_type": users_by_hour_type,
    "users_by_hour": users_by_hour, "pages_by_link": pages_by_link, "convs_by_word": convs_by_word, "signed_clauses": signed_clauses,
}


PAIR_BLOCK = 128  # pins of one net that meet as many others in one join key


def copurchase(pins: DataFrame, width: int = PAIR_BLOCK) -> DataFrame:
    """EDGES between vertices that share a net; weight: how many. Exact for nets of any size.

    A net is dealt into blocks of about ``width`` pins by a hash of the vertex. As a source a pin goes to its block's row of
    the net's block grid, as a target to its column, so every pair meets in one cell and no cell holds a whole large net."""
    blocks = pins.groupBy("net_id").agg(F.ceil(F.count("*") / width).cast("int").alias("n"))
    dealt = pins.join(blocks, "net_id").withColumn("own", F.pmod(F.xxhash64("vertex_id"), F.col("n")).cast("int"))
    others = F.explode(F.sequence(F.lit(0), F.col("n") - 1))
    a = dealt.select("net_id", F.col("vertex_id").alias("src"), F.col("own").alias("i"), others.alias("j"))
    b = dealt.select("net_id", F.col("vertex_id").alias("dst"), others.alias("i"), F.col("own").alias("j"))
    return a.join(b, ["net_id", "i", "j"]).filter("src < dst").groupBy("src", "dst").agg(F.count("*").cast("double").alias("weight"))


def knn_edges(vectors: DataFrame, j: int = 5, block: int = 4096) -> DataFrame:
    """Symmetrised j nearest by cosine, src < dst, weight 1, ties to the smaller id; null and zero vectors have no neighbours.

    Vectors are dealt into blocks of about ``block``, and every pair of blocks is one task's matrix product, of which only
    the j best of each row (and what rounding can't tell from them) leave it. The work is quadratic, no row is a pair."""
    v = vectors.select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("e")).filter("id IS NOT NULL AND exists(e, x -> x <> 0)")
    blocks = max(1, -(-vectors.count() // block))
    v = v.withColumn("own", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    others = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    rows = v.select(F.lit(True).alias("asks"), "id", "e", F.col("own").alias("i"), others.alias("k"))
    columns = v.select(F.lit(False).alias("asks"), "id", "e", others.alias("i"), F.col("own").alias("k"))

    def meet(cell: pd.DataFrame) -> pd.DataFrame:
        a, b = (cell[cell["asks"] == x].sort_values("id") for x in (True, False))
        empty = pd.DataFrame({"id": pd.Series(dtype="int64"), "id2": pd.Series(dtype="int64"), "cos": pd.Series(dtype="float64")})
        if a.empty or b.empty:
            return empty
        x, y = np.stack(a["e"].to_numpy()), np.stack(b["e"].to_numpy())
        ids, ids2 = a["id"].to_numpy(), b["id"].to_numpy()
        near = (x / np.linalg.norm(x, axis=1)[:, None]) @ (y / np.linalg.norm(y, axis=1)[:, None]).T
        near[ids[:, None] == ids2[None, :]] = -np.inf
        keep = min(j, near.shape[1])
        least = np.partition(near, near.shape[1] - keep, axis=1)[:, near.shape[1] - keep]
        r, c = np.nonzero((near >= least[:, None] - 1e-9) & np.isfinite(near))
        dot, xx, yy = np.zeros(len(r)), np.zeros(len(r)), np.zeros(len(r))
        for d in range(x.shape[1]):  # components in order: equal vectors have equal cosines
            p, q = x[r, d], y[c, d]
            dot, xx, yy = dot + p * q, xx + p * p, yy + q * q
        return pd.DataFrame({"id": ids[r], "id2": ids2[c], "cos": dot / (np.sqrt(xx) * np.sqrt(yy))})

    found = rows.union(columns).groupBy("i", "k").applyInPandas(meet, "id bigint, id2 bigint, cos double")
    near = found.withColumn("r", F.row_number().over(W.partitionBy("id").orderBy(F.desc("cos"), "id2"))).filter(F.col("r") <= j)
    return near.select(F.least("id", "id2").alias("src"), F.greatest("id", "id2").alias("dst"), F.lit(1.0).alias("weight")).distinct()


def pages_sharing_link(spark, d) -> DataFrame:
    return copurchase(pages_by_link(spark, d))
