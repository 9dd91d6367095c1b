"""Connected components, and the staged tables of the sources."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringann.sources.staging import shared_dir, stage, unstage

__all__ = ["components", "shared_dir", "stage", "unstage"]


def components(edges: DataFrame) -> DataFrame:
    """(node, comp): smallest node reachable, for nodes of `edges`(a, b), both LONG.

    Alternating large-star and small-star rounds on written edge tables: each round keeps connectivity,
    shuffles at most the edges once per star and never gathers a node's neighbours in one row. Ends when a
    round leaves every edge between a node and a component's smallest node.
    """
    cur = stage(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    while True:
        both = cur.union(cur.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.where("a <> b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e")).select("e.*")
        new = stage(small.where("a <> b").distinct())
        state = new.agg(F.count("*").alias("n"), F.count_distinct("a").alias("k")).first()
        inner = 0 if state["n"] != state["k"] else new.join(new.select(F.col("a").alias("b")), "b", "left_semi").limit(1).count()
        unstage(cur)
        cur = new
        if state["n"] == state["k"] and not inner:
            break
    return cur.select(F.col("a").alias("node"), F.col("b").alias("comp")).union(cur.select(F.col("b").alias("node"), F.col("b").alias("comp")).distinct())
