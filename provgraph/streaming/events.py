"""Structured Streaming over the event table: windows, sessions, deduplication, joins, state, late data."""
from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provgraph.functions.durable import checkpoint_folder
from provgraph.plans.registry import workload

COLUMNS = "event_id BIGINT, ts TIMESTAMP, user_id BIGINT, event_type STRING, value DOUBLE"


def _root(spark: SparkSession) -> str:
    return f"{checkpoint_folder(spark)}/stream-{uuid.uuid4().hex}"


def replay(spark: SparkSession, folder: str, *, files: int = 4, repeat: bool = False) -> DataFrame:
    """The event table as a stream of files; with ``repeat`` every event arrives twice."""
    rows = spark.read.parquet(f"{folder}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    if repeat:
        rows = rows.withColumn("_c", F.explode(F.array(F.lit(0), F.lit(1)))).drop("_c")
    path = f"{_root(spark)}/in"
    rows.repartitionByRange(files, "ts").write.parquet(path)
    return spark.readStream.schema(COLUMNS).option("maxFilesPerTrigger", files).parquet(path)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the query over all that is there and gives its result: Parquet in append mode, else the last whole batch."""
    spark, root = stream.sparkSession, _root(stream.sparkSession)
    if mode == "append":
        stream.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/check").outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{root}/out")

    def keep(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/out/batch={n}")
        last[0] = n

    last = [-1]
    stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{root}/check").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{root}/out/batch={last[0]}")


def tumbling(events: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", "1 day").groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))


def _start():
    return F.col("w.start").cast("timestamp_ntz").alias("start_at")


@workload("stream_tumbling", "select time_bucket(interval 6 hours, ts) start_at, event_type, count(*)::bigint n, round(sum(value), 4) total from events group by 1, 2")
def stream_tumbling(spark, d):
    return drain(tumbling(replay(spark, d), "6 hours"), "complete").select(_start(), "event_type", "n", "total")


@workload("stream_sliding", "select s start_at, event_type, count(*)::bigint n, round(sum(value), 4) total from (select *, unnest([time_bucket(interval 3 hours, ts), time_bucket(interval 3 hours, ts) - interval 3 hours]) s from events) group by 1, 2")
def stream_sliding(spark, d):
    return drain(tumbling(replay(spark, d), "6 hours", "3 hours"), "complete").select(_start(), "event_type", "n", "total")


@workload("stream_session", """with g as (select *, case when ts < lag(ts) over w + interval 6 hours then 0 else 1 end n from events window w as (partition by user_id order by ts, event_id)), s as (select *, sum(n) over (partition by user_id order by ts, event_id rows unbounded preceding) k from g)
 select user_id, min(ts) start_at, count(*)::bigint n from s group by user_id, k""")
def stream_session(spark, d):
    s = replay(spark, d).withWatermark("ts", "1 day").groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return drain(s, "complete").select("user_id", _start(), "n")


@workload("stream_dedup", "select event_type, count(*)::bigint n from events group by 1")
def stream_dedup(spark, d):
    """Every event arrives twice; within the watermark one of them counts."""
    s = replay(spark, d, repeat=True).withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type")
    return drain(s).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@workload("stream_static_join", "select c_mktsegment, count(*)::bigint n from events join customer on user_id = c_custkey group by 1")
def stream_static_join(spark, d):
    c = spark.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_mktsegment")
    return drain(replay(spark, d).join(c, F.col("user_id") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "complete")


@workload("stream_interval_join", "select a.event_id click, b.event_id error from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'error' and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour")
def stream_interval_join(spark, d):
    a = replay(spark, d).where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("at")).withWatermark("at", "2 hours")
    b = replay(spark, d).where("event_type = 'error'").select(F.col("event_id").alias("error"), "user_id", "ts").withWatermark("ts", "2 hours")
    return drain(a.join(b, F.expr("u = user_id and ts >= at and ts <= at + interval 1 hour")).select("click", "error"))


@workload("stream_state", "select user_id, count(*)::bigint n, max(event_id) last_event from events group by 1")
def stream_state(spark, d):
    """Per user the count and latest event, kept as state across batches."""

    def step(key, rows: Iterator[pd.DataFrame], state):
        n, last = state.get if state.exists else (0, -1)
        for pdf in rows:
            n, last = n + len(pdf), max(last, int(pdf["event_id"].max()))
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last_event": [last]})

    s = replay(spark, d, files=2).groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, last_event long", "n long, last long", "update", "NoTimeout")
    root = _root(spark)
    s.writeStream.foreachBatch(lambda b, i: b.write.mode("append").parquet(f"{root}/out")).option("checkpointLocation", f"{root}/check").outputMode("update").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{root}/out").groupBy("user_id").agg(F.max("n").alias("n"), F.max("last_event").alias("last_event"))


@workload("stream_late")
def stream_late(spark, d):
    """Old events that come after the watermark has passed are dropped; counts per day of what was kept."""
    rows = spark.read.parquet(f"{d}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    path = f"{_root(spark)}/in"
    late = F.col("event_id") % 10 == 0
    rows.where(~late).coalesce(1).write.parquet(path)
    rows.where(late).coalesce(1).write.mode("append").parquet(path)
    s = spark.readStream.schema(COLUMNS).option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drain(s).select(_start(), "n")
