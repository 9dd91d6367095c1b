"""Structured Streaming around the index."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringann.operators.search import build_index, exact_knn, read_index, ring_search
from ringann.operators.topk import top_k


def event_profiles(events: DataFrame, window: str = "1 day", watermark: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(user_id, start, n, avg_value, hours ARRAY<LONG>) by event-time window; batch or stream.

    Time stamps without zone are read as UTC, which watermarks need. Rows later than the watermark are dropped
    by the stream.
    """
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if rows.isStreaming:
        rows = rows.withWatermark("ts", watermark)
    hours = [F.sum((F.hour("ts") == h).cast("long")).alias(f"h{h}") for h in range(24)]
    wide = rows.groupBy("user_id", F.window("ts", window, slide or window).alias("w")).agg(F.count("*").alias("n"), F.avg("value").alias("avg_value"), *hours)
    return wide.select("user_id", F.col("w.start").alias("start"), "n", "avg_value", F.array(*[f"h{h}" for h in range(24)]).alias("hours"))


def session_profiles(events: DataFrame, gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if rows.isStreaming:
        rows = rows.withWatermark("ts", watermark)
    return rows.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"), F.avg("value").alias("avg_value")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "avg_value")


def stream_search(queries: DataFrame, index: DataFrame, family, lam: int, k: int, sink: str, checkpoint: str):
    """Answers a stream of queries(qid, vec): each micro-batch is one batch search, appended to `sink`."""

    def answer(batch: DataFrame, number: int) -> None:
        ring_search(index, family, batch, lam, k).write.mode("append").parquet(sink)

    return queries.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint).start()


def stream_ingest(rows: DataFrame, delta: str, checkpoint: str):
    """Writes a stream of (obj_id, vec) to the delta table, searched exactly until compact() folds it in. A micro-batch
    has a folder of its own, so that one that is tried again replaces what it left."""

    def add(batch: DataFrame, number: int) -> None:
        batch.select("obj_id", F.col("vec").cast("array<double>").alias("vec")).write.mode("overwrite").parquet(f"{delta}/batch={number}")

    return rows.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).start()


def _folders(spark, delta: str) -> list:
    """(file system, path) of every micro-batch that has ended."""
    hadoop = spark._jvm.org.apache.hadoop.fs
    root = hadoop.Path(delta)
    system = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    found = [x.getPath() for x in system.listStatus(root)] if system.exists(root) else []
    return [(system, x) for x in found if system.exists(hadoop.Path(x, "_SUCCESS"))]


def read_delta(spark, delta: str) -> DataFrame:
    """(obj_id, vec) of the delta table; empty where nothing has been added."""
    schema = "obj_id long, vec array<double>"
    paths = [x.toString() for _, x in _folders(spark, delta)]
    return spark.read.schema(schema).parquet(*paths) if paths else spark.createDataFrame([], schema)


def compact(spark, delta: str, family, path: str, shard_rows: int) -> int:
    """Folds the delta table into new shards of the index at `path` and empties it; returns the number of rows moved.

    New shards are numbered after the old ones. The micro-batches read are removed only once the shards are written;
    what a stream adds meanwhile stays for the next call.
    """
    taken = _folders(spark, delta)
    if not taken:
        return 0
    rows = spark.read.schema("obj_id long, vec array<double>").parquet(*[x.toString() for _, x in taken])
    n = rows.count()
    if n:
        root = spark._jvm.org.apache.hadoop.fs.Path(path)
        exists = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(root)
        old = read_index(spark, path).agg(F.max("shard")).first()[0] if exists else None
        fresh = build_index(rows, family, shard_rows, rows=n).withColumn("shard", F.col("shard") + (0 if old is None else old + 1))
        fresh.write.mode("append").partitionBy("shard").parquet(path)
    for system, x in taken:
        system.delete(x, True)
    return n


def search_with_delta(index: DataFrame, delta: DataFrame, family, queries: DataFrame, lam: int, k: int) -> DataFrame:
    """Nearest k of the index's candidates and, exactly, of the delta table; an object in both counts once."""
    cols = ["qid", "obj_id", "dist"]
    both = ring_search(index, family, queries, lam, k).select(cols).union(exact_knn(delta, queries, k, family.metric).select(cols))
    return top_k(both.dropDuplicates(["qid", "obj_id"]), k, ["dist", "obj_id"]).select("qid", "rnk", "obj_id", "dist")


def drift_alarms(events: DataFrame, share: float = 0.2, factor: float = 3.0, least: int = 5):
    """(user_id, event_id, value, mean): events of a stream whose value exceeds `factor` times the user's running
    mean, an exponential one with weight `share`, once `least` events are known. Events of a micro-batch are taken by time."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def watch(key, frames, state):
        mean, n = state.get if state.exists else (0.0, 0)
        out = []
        for row in pd.concat(list(frames)).sort_values(["ts", "event_id"]).itertuples():
            if n >= least and row.value > factor * mean:
                out.append((key[0], row.event_id, row.value, mean))
            mean, n = (row.value if n == 0 else (1 - share) * mean + share * row.value), n + 1
        state.update((mean, n))
        yield pd.DataFrame(out, columns=["user_id", "event_id", "value", "mean"])

    rows = events.where("user_id IS NOT NULL AND value IS NOT NULL").select("user_id", "event_id", F.col("ts").cast("timestamp").alias("ts"), "value")
    return rows.groupBy("user_id").applyInPandasWithState(watch, "user_id long, event_id long, value double, mean double", "mean double, n long", "append", GroupStateTimeout.NoTimeout)
