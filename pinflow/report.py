"""Comparisons over RUNS: improvements, means, profiles, box plots, dominance, ranks, cubes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window as W, functions as F


def improvement(runs: DataFrame, base: str, measure: str = "connectivity") -> DataFrame:
    """instance, k, algorithm, improvement: percent by which base's measure exceeds the algorithm's; null where that is 0."""
    other = runs.filter(F.col("algorithm") == base).groupBy("instance", "k").agg(F.avg(measure).alias("b"))
    mine = runs.groupBy("instance", "k", "algorithm").agg(F.avg(measure).alias("a"))
    return mine.join(other, ["instance", "k"]).select("instance", "k", "algorithm", ((F.col("b") / F.nullif(F.col("a"), F.lit(0.0)) - 1) * 100).alias("improvement"))


def summarise(runs: DataFrame, measure: str = "connectivity") -> DataFrame:
    """algorithm, geo_mean over instances and k of the mean over seeds, n_zero: zeros left out and counted."""
    mean = runs.groupBy("instance", "k", "algorithm").agg(F.avg(measure).alias("a"))
    return mean.groupBy("algorithm").agg(F.exp(F.avg(F.when(F.col("a") > 0, F.ln("a")))).alias("geo_mean"), F.count_if(F.col("a") == 0).alias("n_zero"))


def by_k(runs: DataFrame, base: str, measure: str = "connectivity") -> DataFrame:
    """k, algorithm, improvement of the geometric means."""
    mean = runs.groupBy("instance", "k", "algorithm").agg(F.avg(measure).alias("a")).filter("a > 0")
    geo = mean.groupBy("k", "algorithm").agg(F.exp(F.avg(F.ln("a"))).alias("g"))
    other = geo.filter(F.col("algorithm") == base).select("k", F.col("g").alias("b"))
    return geo.join(other, "k").select("k", "algorithm", ((F.col("b") / F.col("g") - 1) * 100).alias("improvement"))


def profile(runs: DataFrame, measure: str, taus: list[float]) -> DataFrame:
    """algorithm, tau, share of (instance, k) within tau times the best; ties count for every winner."""
    spark = runs.sparkSession
    mean = runs.groupBy("instance", "k", "algorithm").agg(F.avg(measure).alias("a"))
    best = mean.withColumn("best", F.min("a").over(W.partitionBy("instance", "k")))
    grid = spark.createDataFrame([(float(t),) for t in taus], "tau double")
    return best.crossJoin(F.broadcast(grid)).groupBy("algorithm", "tau").agg(F.avg(F.when(F.col("a") <= F.col("tau") * F.col("best"), 1.0).otherwise(0.0)).alias("share"))


def boxplot(values: DataFrame, measure: str) -> DataFrame:
    """algorithm, lo, q1, median, q3, hi: quartiles, and extremes within 1.5 quartile distances."""
    q = values.groupBy("algorithm").agg(F.percentile(measure, F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75))).alias("q"))
    inside = values.join(q, "algorithm").filter(F.col(measure).between(F.col("q")[0] - 1.5 * (F.col("q")[2] - F.col("q")[0]), F.col("q")[2] + 1.5 * (F.col("q")[2] - F.col("q")[0])))
    ends = inside.groupBy("algorithm").agg(F.min(measure).alias("lo"), F.max(measure).alias("hi"))
    return q.join(ends, "algorithm").select("algorithm", "lo", F.col("q")[0].alias("q1"), F.col("q")[1].alias("median"), F.col("q")[2].alias("q3"), "hi")


def dominated(points: DataFrame, cost: str, quality: str) -> DataFrame:
    """algorithm (cost and quality both to be small) and whether another is no worse in both and better in one."""
    a, b = points.alias("a"), points.alias("b")
    worse = (F.col(f"b.{cost}") <= F.col(f"a.{cost}")) & (F.col(f"b.{quality}") <= F.col(f"a.{quality}")) & ((F.col(f"b.{cost}") < F.col(f"a.{cost}")) | (F.col(f"b.{quality}") < F.col(f"a.{quality}")))
    beaten = a.join(b, worse, "left_semi").select("algorithm")
    return points.join(beaten.withColumn("d", F.lit(True)), "algorithm", "left").select("algorithm", F.coalesce("d", F.lit(False)).alias("dominated"))


def rank_stability(runs: DataFrame, measure: str = "connectivity") -> DataFrame:
    """algorithm, ranks: how many different ranks its mean takes over the values of k."""
    mean = runs.groupBy("k", "algorithm").agg(F.avg(measure).alias("a"))
    return mean.withColumn("r", F.rank().over(W.partitionBy("k").orderBy("a"))).groupBy("algorithm").agg(F.count_distinct("r").alias("ranks"))


def cube(runs: DataFrame) -> DataFrame:
    return runs.cube("instance", "k", "algorithm").agg(F.grouping_id().alias("level"), F.count("*").alias("runs"), F.sum("cut_net").alias("cut_net"))


def rollup(runs: DataFrame) -> DataFrame:
    return runs.rollup("instance", "k").agg(F.grouping_id().alias("level"), F.count("*").alias("runs"), F.sum("connectivity").alias("connectivity"))


def grouping_sets(runs: DataFrame) -> DataFrame:
    runs.createOrReplaceTempView("pinflow_runs")
    return runs.sparkSession.sql("SELECT instance, k, algorithm, count(*) AS runs, max(cut_net) AS cut_net FROM pinflow_runs GROUP BY GROUPING SETS ((instance, k), (algorithm))")


def pivot(runs: DataFrame, algorithms: list[str], measure: str = "connectivity") -> DataFrame:
    return runs.groupBy("instance", "k").pivot("algorithm", algorithms).agg(F.avg(measure))


def speedup(runs: DataFrame, fast: str, slow: str) -> DataFrame:
    """instance, k, ratio of wall times."""
    mean = runs.groupBy("instance", "k", "algorithm").agg(F.avg("wall_ns").alias("t"))
    a, b = (mean.filter(F.col("algorithm") == x).select("instance", "k", F.col("t").alias(n)) for x, n in ((fast, "tf"), (slow, "ts")))
    return a.join(b, ["instance", "k"]).select("instance", "k", (F.col("ts") / F.col("tf")).alias("ratio"))
