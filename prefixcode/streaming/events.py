"""Streams of log records: windows, joins, duplicates, state, and ingestion as sorted runs.

Each function runs the stream over what is there (availableNow) and gives the sink's rows. Results
that a mode rewrites go through foreachBatch, which replaces what it wrote; a batch that comes again
writes the same.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefixcode.sources import scratch
from prefixcode.sources.store import RunStore


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events as a stream, time as a timestamp."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{sf_dir}/events.parquet*")
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def run(stream: DataFrame, mode: str, spark: SparkSession) -> DataFrame:
    path, kept = scratch.fresh(spark, "stream"), scratch.fresh(spark, "stream-progress")
    schema = stream.schema

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(path if mode == "complete" else f"{path}/batch={number}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", kept).trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    return spark.read.schema(schema).parquet(path if mode == "complete" else f"{path}/batch=*")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = source(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 2).alias("total"))
    return run(x, "complete", spark).select(F.col("window.start").cast("timestamp_ntz").alias("win_start"), "event_type", "n", "total")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = source(spark, sf_dir).groupBy(F.window("ts", "2 days", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    return run(x, "complete", spark).select(F.col("window.start").cast("timestamp_ntz").alias("win_start"), "n")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = source(spark, sf_dir).withWatermark("ts", "30 days").groupBy("user_id", F.session_window("ts", "12 hours")).agg(F.count(F.lit(1)).alias("n"))
    return run(x, "complete", spark).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("session_start"), "n")


def distinct_in_watermark(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = source(spark, sf_dir).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
    return run(x, "append", spark)


def with_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_mktsegment")
    x = source(spark, sf_dir).join(customers, F.col("user_id") == F.col("c_custkey")).select("event_id", "user_id", "c_mktsegment")
    return run(x, "append", spark)


def pairs_in_time(spark: SparkSession, sf_dir: str, first: str, then: str, hours: int = 6) -> DataFrame:
    """Stream-stream join: an event of the one kind, then within some hours one of the other, same user."""
    a = source(spark, sf_dir).where(F.col("event_type") == first).select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts")).withWatermark("a_ts", "40 days")
    b = source(spark, sf_dir).where(F.col("event_type") == then).select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts")).withWatermark("b_ts", "40 days")
    x = a.join(b, F.expr(f"a_user = b_user AND b_ts >= a_ts AND b_ts <= a_ts + INTERVAL {hours} HOURS")).select("a_id", "b_id")
    return run(x, "append", spark)


def _state(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    n, last = state.get if state.exists else (0, 0)
    for b in batches:
        n, last = n + len(b), max(last, int(b["event_id"].max()))
    state.update((n, last))
    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last_event": [last]})


def stateful_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups kept in state over out-of-order input; each batch sends the groups it changed."""
    x = source(spark, sf_dir).select("user_id", "event_id").groupBy("user_id").applyInPandasWithState(_state, "user_id long, n long, last_event long", "n long, last long", "update", "NoTimeout")
    out = run(x, "update", spark)
    return out.groupBy("user_id").agg(F.max("n").alias("n"), F.max("last_event").alias("last_event"))


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows behind the watermark are dropped, and counted: those read less those in windows.

    The days from the fifteenth on come first, then the first ten days: all of them are late.
    """
    path = scratch.fresh(spark, "late")
    x = spark.read.parquet(f"{sf_dir}/events.parquet")
    since = x.agg(F.min("ts").alias("t0"))
    x = x.crossJoin(F.broadcast(since))  # one row
    own = ["event_id", "ts"]
    for part, wanted in (("0", "ts >= t0 + INTERVAL 15 DAYS"), ("1", "ts < t0 + INTERVAL 10 DAYS")):
        x.where(wanted).select(*own).coalesce(1).write.parquet(f"{path}/part={part}")
    kept = scratch.fresh(spark, "late-progress")
    out = scratch.fresh(spark, "late-windows")
    read = 0
    for part in ("0", "1"):  # the same stream, stopped and started again after more rows have come
        stream = spark.readStream.schema(x.select(*own).schema).parquet(f"{path}/part=[0-{part}]").withColumn("ts", F.col("ts").cast("timestamp"))
        counts = stream.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
        put: Callable[[DataFrame, int], None] = lambda batch, number: batch.write.mode("overwrite").parquet(f"{out}/batch={number}")
        query = counts.writeStream.outputMode("update").option("checkpointLocation", kept).trigger(availableNow=True).foreachBatch(put).start()
        query.awaitTermination()
        read += sum(p["numInputRows"] for p in query.recentProgress)
    windows = spark.read.parquet(f"{out}/batch=*").groupBy("window").agg(F.max("n").alias("n"))
    return windows.agg(F.sum("n").alias("in_time")).withColumn("late", F.lit(read).cast("long") - F.col("in_time"))


def rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A source read at a bounded rate: numbers of events counted by digit, a file a batch."""
    counts = source(spark, sf_dir).groupBy((F.col("event_id") % 3).alias("digit")).agg(F.count(F.lit(1)).alias("n"))
    return run(counts, "complete", spark)


def ingest(spark: SparkSession, sf_dir: str, keys: list[str], fan_in: int = 4, path: str | None = None) -> RunStore:
    """Every micro-batch becomes a sorted run; full levels are merged."""
    store = RunStore(spark, keys, fan_in, path)
    put: Callable[[DataFrame, int], None] = lambda batch, number: store.append_run(batch, number)
    query = source(spark, sf_dir).writeStream.option("checkpointLocation", scratch.fresh(spark, "ingest")).trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    return store
