"""Top-k per query, in the form that Spark cuts before the shuffle (WindowGroupLimit)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def top_k(df: DataFrame, k: int, by: list, key: str = "qid", rank: str = "rnk") -> DataFrame:
    w = Window.partitionBy(key).orderBy(*by)
    return df.withColumn(rank, F.row_number().over(w)).where(F.col(rank) <= k)


def broadcast_queries(queries: DataFrame, limit: int = 100_000) -> DataFrame:
    """queries under a broadcast hint if there are at most `limit`; a larger set is joined as Spark sees fit."""
    few = queries.limit(limit + 1).count() <= limit
    return F.broadcast(queries) if few else queries
