"""Readers: the given tables, and vectors in common formats."""

from __future__ import annotations

import struct

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_vectors(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """(obj_id, vec) from parquet, orc or json with these columns; csv or text with the id and then numbers; or fvecs."""
    if fmt in ("parquet", "orc", "json"):
        return spark.read.schema("obj_id long, vec array<double>").format(fmt).load(path)
    if fmt in ("csv", "text"):
        cells = F.split("value", r"[,\s]+")
        return spark.read.text(path).select(F.get(cells, F.lit(0)).cast("long").alias("obj_id"), F.slice(cells, 2, F.size(cells) - 1).cast("array<double>").alias("vec"))
    spark.dataSource.register(FvecsSource)
    return spark.read.format("fvecs").load(path)


class FvecsSource(DataSource):
    """Binary vectors: for each an int32 dimension and as many float32. Needs a path that executors can open."""

    @classmethod
    def name(cls):
        return "fvecs"

    def schema(self):
        return "obj_id long, vec array<double>"

    def reader(self, schema):
        return FvecsReader(self.options)


class FvecsReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.parts = options["path"], int(options.get("partitions", "8"))

    def partitions(self):
        import os

        with open(self.path, "rb") as f:
            d = struct.unpack("<i", f.read(4))[0]
        n = os.path.getsize(self.path) // (4 + 4 * d)
        step = max(1, -(-n // self.parts))
        return [InputPartition((lo, min(lo + step, n), d)) for lo in range(0, n, step)]

    def read(self, partition):
        lo, hi, d = partition.value
        with open(self.path, "rb") as f:
            f.seek(lo * (4 + 4 * d))
            for i in range(lo, hi):
                row = struct.unpack(f"<i{d}f", f.read(4 + 4 * d))
                yield i, list(row[1:])
