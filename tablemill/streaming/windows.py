"""Structured Streaming over activity logs: windows, sessions, late rows, joins and sandbox expiry."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def scratch(spark: SparkSession, name: str) -> str:
    """A folder in the cluster's shared store."""
    at = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.sql.warehouse.dir")
    return f"{at.rstrip('/')}/tablemill/stream-{name}-{uuid.uuid4().hex}"


def replayed(events: DataFrame, parts: int = 6, order: str = "event_id") -> DataFrame:
    """The events as a file stream in the order of a column: ranges are written one after the other, as arrival times decide the order of files."""
    spark, path = events.sparkSession, scratch(events.sparkSession, "input")
    cuts = sorted(set(events.approxQuantile(order, [i / parts for i in range(1, parts)], 0.001)))
    place = sum((F.col(order) > c).cast("int") for c in cuts) if cuts else F.lit(0)
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    for i in range(len(cuts) + 1):
        timed.where(place == i).write.mode("append").parquet(path)
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 2).parquet(path)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there, into files, and read them. Complete and update results keep their last state."""
    spark, out = stream.sparkSession, scratch(stream.sparkSession, "output")
    writer = stream.writeStream.option("checkpointLocation", scratch(spark, "checkpoint")).trigger(availableNow=True)
    if mode == "append":
        query = writer.outputMode("append").format("parquet").option("path", out).start()
    else:

        def keep(df: DataFrame, number: int) -> None:
            df.withColumn("_batch", F.lit(number)).write.mode("append").parquet(out)

        query = writer.outputMode(mode).foreachBatch(keep).start()
    query.awaitTermination()
    result = spark.read.parquet(out)
    if mode == "append":
        return result
    last = result.agg(F.max("_batch")).first()[0]
    return result.where(F.col("_batch") == last).drop("_batch")


def tumbling(stream: DataFrame, width: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    w = stream.withWatermark("ts", delay).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


def sliding(stream: DataFrame, width: str = "6 hours", slide: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    w = stream.withWatermark("ts", delay).groupBy(F.window("ts", width, slide), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "6 hours", delay: str = "2 hours") -> DataFrame:
    w = stream.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return w.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def deduplicated(stream: DataFrame, delay: str = "2 hours") -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def expired(stream: DataFrame, idle_s: int = 6 * 3600, delay: str = "1 hour") -> DataFrame:
    """(session, last_activity, expires_at) of sandboxes idle past the limit: one state row and one event-time timer a session."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def watch(key, frames, state: GroupState):
        if state.hasTimedOut:
            (last,) = state.get
            state.remove()
            yield pd.DataFrame({"session": [key[0]], "last_activity": [last], "expires_at": [last + idle_s * 1000]})
            return
        stamps = sorted(int(t.timestamp() * 1000) for f in frames for t in f.ts)
        last = state.get[0] if state.exists else None
        rows = []
        for t in stamps:
            if last is not None and t - last >= idle_s * 1000:
                rows.append((key[0], last, last + idle_s * 1000))
            last = t if last is None else max(last, t)
        state.update((last,))
        state.setTimeoutTimestamp(max(last + idle_s * 1000, state.getCurrentWatermarkMs() + 1))
        if rows:
            yield pd.DataFrame(rows, columns=["session", "last_activity", "expires_at"])

    keyed = stream.withWatermark("ts", delay).select(F.col("user_id").alias("session"), "ts")
    return keyed.groupBy("session").applyInPandasWithState(watch, "session long, last_activity long, expires_at long", "last long", "append", GroupStateTimeout.EventTimeTimeout)
