"""Structured Streaming: co-mention counts in windows, late rows, deduplication, running strengths, joins with requests.

Event time is cast to a timestamp first: NTZ columns take no watermark.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def event_stream(spark: SparkSession, path: str, schema, max_files: int = 1) -> DataFrame:
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def window_counts(events: DataFrame, width: str = "1 hour", delay: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Users by tumbling (or sliding) window: start, user_id, n."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    rows = events.withWatermark("ts", delay) if events.isStreaming else events
    return rows.groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def session_counts(events: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    rows = events.withWatermark("ts", delay) if events.isStreaming else events
    return rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


def deduplicated(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """First of the rows with equal event_id within the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def with_requests(events: DataFrame, requests: DataFrame) -> DataFrame:
    """Stream-static join: events of users that requests name."""
    return events.join(requests.select(F.col("target").cast("long").alias("user_id"), "request_id"), "user_id")


def followed_by(events: DataFrame, first: str, then: str, within: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: `then` events of a user at most `within` after a `first` event."""
    a = events.filter(F.col("event_type") == first).select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("a_ts")).withWatermark("a_ts", delay)
    b = events.filter(F.col("event_type") == then).select(F.col("event_id").alias("b"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts")).withWatermark("b_ts", delay)
    return a.join(b, (F.col("user_id") == F.col("b_user")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"interval {within}"))).select("a", "b", "user_id")


def running_visits(events: DataFrame) -> DataFrame:
    """Running count of each user's events, kept as state: user_id, visits (a row at each change)."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((seen,))
        yield pd.DataFrame({"user_id": [key[0]], "visits": [seen]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, visits long", "visits long", "update", "NoTimeout")


def merge_into_store(stream: DataFrame, path: str, checkpoint: str):
    """foreachBatch sink: every batch's counts as one Parquet folder by batch id, so a batch written twice replaces itself."""

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def drain(stream: DataFrame, folder: str, mode: str) -> DataFrame:
    """Runs a query over all that is there into Parquet under `folder` (shared), a folder by batch; `complete` gives the last batch, other modes all of them."""
    spark = stream.sparkSession

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/batch={batch_id}")

    q = stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    if q.lastProgress is None:
        return spark.createDataFrame([], stream.schema)
    rows = spark.read.schema(T.StructType([*stream.schema.fields, T.StructField("batch", T.LongType())])).parquet(f"{folder}/out")
    if mode == "complete":
        last = rows.agg(F.max("batch").alias("last"))  # one row
        rows = rows.join(F.broadcast(last), F.col("batch") == F.col("last"))
    return rows.select(*stream.columns)
