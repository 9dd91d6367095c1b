"""Accuracy and cost measures over result tables (qid, rnk, obj_id, dist)."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def recall(result: DataFrame, truth: DataFrame, k: int, denominator: str = "k") -> DataFrame:
    """(qid, recall): share of returned objects among the exact k; queries without results count 0."""
    hit = result.select("qid", "obj_id").join(truth.where(F.col("rnk") <= k).select("qid", "obj_id"), ["qid", "obj_id"]).groupBy("qid").agg(F.count("*").alias("hits"))
    n = truth.where(F.col("rnk") <= k).groupBy("qid").agg(F.count("*").alias("n"))
    if denominator == "returned":
        n = n.select("qid").join(result.groupBy("qid").agg(F.count("*").alias("n")), "qid", "left")
    return n.join(hit, "qid", "left").select("qid", F.coalesce(F.col("hits") / F.col("n"), F.lit(0.0)).alias("recall"))


def overall_ratio(result: DataFrame, truth: DataFrame, zero: float = 1e-7) -> DataFrame:
    """(qid, ratio, n_zero): mean of distance over exact distance by rank; 0/0 is 1, other x/0 are left out and counted.

    Distances up to `zero` count as 0: angles of equal vectors come out as rounding noise of up to some 1e-8.
    """
    both = result.select("qid", "rnk", "dist").join(truth.select("qid", "rnk", F.col("dist").alias("best")), ["qid", "rnk"])
    value = F.when(F.col("best") > zero, F.col("dist") / F.col("best")).when(F.col("dist") <= zero, 1.0)
    return both.groupBy("qid").agg(F.avg(value).alias("ratio"), F.sum(F.when(value.isNull(), 1).otherwise(0)).alias("n_zero"))


def is_c_approx(result: DataFrame, truth: DataFrame, c: float) -> DataFrame:
    """(qid, ok): every rank is within c times the exact distance."""
    both = truth.select("qid", "rnk", F.col("dist").alias("best")).join(result.select("qid", "rnk", "dist"), ["qid", "rnk"], "left")
    return both.groupBy("qid").agg(F.bool_and(F.coalesce(F.col("dist") <= c * F.col("best") + 1e-12, F.lit(False))).alias("ok"))


def timed(df: DataFrame) -> float:
    start = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def timed_call(f) -> float:
    start = time.perf_counter()
    f()
    return time.perf_counter() - start


def summarize(runs: DataFrame) -> DataFrame:
    return runs.groupBy("method", "params").agg(F.avg("recall").alias("recall"), F.avg("ratio").alias("ratio"), F.avg("seconds").alias("seconds"), F.count("*").alias("runs"))


def pareto(results: DataFrame, levels: list[float]) -> DataFrame:
    """Least time of each method at each recall level, over its parameters."""
    spark = results.sparkSession
    lv = spark.createDataFrame([(float(x),) for x in levels], "level double")
    reach = results.join(F.broadcast(lv), F.col("recall") >= F.col("level"))
    return reach.groupBy("method", "level").agg(F.min("seconds").alias("seconds"), F.min_by("params", F.struct("seconds", "params")).alias("params"))


def budget_curve(results: DataFrame, level: float = 0.5) -> DataFrame:
    """Least time at a recall level with an index of at most the row's size."""
    w = Window.partitionBy("method").orderBy("index_bytes").rangeBetween(Window.unboundedPreceding, 0)
    return results.where(F.col("recall") >= level).withColumn("best_seconds", F.min("seconds").over(w)).select("method", "index_bytes", "best_seconds").distinct()


def acceleration(other, ours):
    return (other / ours - 1) * 100


def report(results: DataFrame) -> DataFrame:
    """Means by method and parameters, by method, and over all."""
    return results.rollup("method", "params").agg(F.avg("recall").alias("recall"), F.min("seconds").alias("seconds"), F.grouping_id().cast("int").alias("level"))
