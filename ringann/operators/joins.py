"""Joins that Spark has no operator for, as equi-joins and windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of_join(left: DataFrame, right: DataFrame, key: str, time: str, values: list[str]) -> DataFrame:
    """left rows with `values` of the latest right row of the same key that is not later; null where there is none.

    Both sides are put in one order by time, right rows first among equals, and the last right row is carried on: one
    shuffle by key, no pairs. A null key or time meets nothing.
    """
    names = [f"__l_{c}" for c in left.columns]
    held = F.struct(*[F.col(v) for v in values])
    a = left.select(F.col(key).alias("__k"), F.col(time).alias("__t"), F.lit(1).alias("__side"), F.struct(*[F.col(c).alias(n) for c, n in zip(left.columns, names)]).alias("__row"), F.lit(None).cast(right.select(held.alias("h")).schema["h"].dataType).alias("__held"))
    b = right.where(F.col(key).isNotNull() & F.col(time).isNotNull()).select(F.col(key).alias("__k"), F.col(time).alias("__t"), F.lit(0).alias("__side"), F.lit(None).cast(a.schema["__row"].dataType).alias("__row"), held.alias("__held"))
    order = Window.partitionBy("__k").orderBy(F.col("__t").asc_nulls_first(), "__side").rowsBetween(Window.unboundedPreceding, 0)
    carried = a.union(b).withColumn("__last", F.last("__held", ignorenulls=True).over(order)).where("__side = 1")
    return carried.select(*[F.col(f"__row.{n}").alias(c) for c, n in zip(left.columns, names)], *[F.col(f"__last.{v}").alias(v) for v in values])


def band_join(left: DataFrame, right: DataFrame, a: str, b: str, width: float) -> DataFrame:
    """Pairs with |a - b| <= width: bins of that width, three for each right row, then the exact test. Nulls meet nothing."""
    x = left.withColumn("__bin", F.floor(F.col(a) / width))
    y = right.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(b) / width) - 1, F.floor(F.col(b) / width) + 1)))
    return x.join(y, "__bin").where(F.abs(F.col(a) - F.col(b)) <= width).drop("__bin")
