"""Tables written to the folder that executors and driver share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir; a temporary one only where that is unset (tests)."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        kept = spark.sparkContext._jsc.sc().getCheckpointDir()
        path = kept.get() if kept.isDefined() else tempfile.mkdtemp(prefix="ringann-")
        if not kept.isDefined():
            spark.sparkContext.setCheckpointDir(path)
    return path


def stage(df: DataFrame) -> DataFrame:
    """df as a written table: cuts lineage, is read more than once, outlives executors."""
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/stage-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.staged_at = path
    return out


def unstage(*tables: DataFrame) -> None:
    """Deletes tables made by `stage` that no later result reads; other DataFrames are left alone."""
    for df in tables:
        path = df.__dict__.get("staged_at")
        if path:
            place = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(place, True)
