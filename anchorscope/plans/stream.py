"""Streaming queries, drained over the given event table, with batch SQL as their twins."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from .. import streaming
from ..functions.session import shared_folder
from ..sources import table
from . import query


def events(spark, d):
    # a stream reads a folder, so the one file is named by a glob
    schema = table(spark, d, "events").schema
    return streaming.event_stream(spark, f"{d}/events.parque[t]", schema)


def drained(spark, df, mode):
    return streaming.drain(df, f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}", mode)


@query("select date_trunc('hour', ts) as start, user_id, count(*) as n from events group by all")
def stream_tumbling(spark, d):
    return drained(spark, streaming.window_counts(events(spark, d)), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("select * from (select date_trunc('hour', ts) as start, user_id, count(*) as n from events group by all) where start + interval 1 hour <= (select max(ts) - interval 1 hour from events)")
def stream_append_closed(spark, d):
    return drained(spark, streaming.window_counts(events(spark, d)), "append").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("select distinct event_id from events")
def stream_dedup(spark, d):
    return drained(spark, streaming.deduplicated(events(spark, d)).select("event_id"), "append")


@query("select a.event_id as a, b.event_id as b, a.user_id from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'view' and b.event_type = 'purchase'")
def stream_interval_join(spark, d):
    return drained(spark, streaming.followed_by(events(spark, d), "view", "purchase", "1 hour"), "append")


@query("select e.event_id, e.user_id, 'r' || e.user_id as request_id from events e where user_id in (1, 2, 3)")
def stream_static_requests(spark, d):
    requests = spark.createDataFrame([("1", "r1"), ("2", "r2"), ("3", "r3")], "target string, request_id string")
    return drained(spark, streaming.with_requests(events(spark, d), requests).select("event_id", "user_id", "request_id"), "append")


@query("select user_id, count(*) as visits from events group by user_id")
def stream_running_visits(spark, d):
    rows = drained(spark, streaming.running_visits(events(spark, d)), "update")
    return rows.groupBy("user_id").agg(F.max("visits").alias("visits"))


@query("""with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minutes then 0 else 1 end as begins from events where ts is not null),
    s as (select user_id, ts, sum(begins) over (partition by user_id order by ts, begins desc rows between unbounded preceding and current row) as session from g)
    select min(ts) as start, user_id, count(*) as n from s group by user_id, session having max(ts) + interval 30 minutes <= (select max(ts) - interval 1 hour from events)""")  # fmt: skip
def stream_sessions(spark, d):
    rows = drained(spark, streaming.session_counts(events(spark, d)), "append")
    return rows.select(F.col("start").cast("timestamp_ntz").alias("start"), "user_id", "n")


@query("select s as start, user_id, count(*) as n from (select user_id, unnest([time_bucket(interval 30 minutes, ts), time_bucket(interval 30 minutes, ts) - interval 30 minutes]) as s from events) group by all")
def stream_sliding(spark, d):
    return drained(spark, streaming.window_counts(events(spark, d), slide="30 minutes"), "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


LATE = "event_id % 10 = 3 and ts < (select min(ts) + (max(ts) - min(ts)) / 10 from events)"


@query(f"select * from (select date_trunc('hour', ts) as start, user_id, count(*) as n from events where not ({LATE}) group by all) where start + interval 1 hour <= (select max(ts) - interval 1 hour from events)")
def stream_late_rows(spark, d):
    """Events in three files by time, but for some early ones that come with the last file: beyond the watermark, so they are dropped."""
    rows = table(spark, d, "events")
    lo, hi = rows.agg(F.min("ts"), F.max("ts")).first()
    late = (F.col("event_id") % 10 == 3) & (F.col("ts") < F.lit(lo + (hi - lo) / 10).cast("timestamp_ntz"))
    third = F.when(late, 2).otherwise(F.when(F.col("ts") < F.lit(lo + (hi - lo) / 3).cast("timestamp_ntz"), 0).when(F.col("ts") < F.lit(lo + (hi - lo) * 2 / 3).cast("timestamp_ntz"), 1).otherwise(2))
    folder = f"{shared_folder(spark)}/arrivals-{uuid.uuid4().hex}"
    for k in range(3):  # files are read in the order in which they were written, one a batch
        rows.filter(third == k).coalesce(1).write.mode("append").parquet(folder)
    stream = streaming.event_stream(spark, folder, rows.schema)
    return drained(spark, streaming.window_counts(stream), "append").withColumn("start", F.col("start").cast("timestamp_ntz"))
