"""The observed feed as a stream: windows, sessions, duplicates, state, requests against a timetable.

Functions take a frame (ts, stop_id, vehicle, ...) that may be a stream or a table."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

LOG = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def read_log(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream of the observed feed."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.select(F.col("user_id").alias("vehicle"), F.col("ts").cast("timestamp").alias("ts"), F.get_json_object("props", "$.k").cast("long").alias("stop_id"), "event_id", "value")


def _marked(log: DataFrame, delay: str) -> DataFrame:
    log = log.withColumn("ts", F.col("ts").cast("timestamp"))
    return log.withWatermark("ts", delay) if log.isStreaming else log


def events_per_hour(log: DataFrame, delay: str = "1 hour") -> DataFrame:
    return _marked(log, delay).groupBy(F.window("ts", "1 hour"), "stop_id").agg(F.count("*").alias("n"))


def sliding_load(log: DataFrame, delay: str = "1 hour") -> DataFrame:
    return _marked(log, delay).groupBy(F.window("ts", "2 hours", "30 minutes"), "stop_id").agg(F.count("*").alias("n"))


def sessions(log: DataFrame, gap: str = "6 hours", delay: str = "6 hours") -> DataFrame:
    """Trips of a vehicle: events with gaps under gap."""
    return _marked(log, delay).groupBy(F.session_window("ts", gap).alias("session"), "vehicle").agg(F.count("*").alias("n"))


def without_repeats(log: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Reports sent twice come once, as long as both are within the watermark."""
    return _marked(log, delay).dropDuplicatesWithinWatermark(["event_id"]) if log.isStreaming else log.dropDuplicates(["event_id"])


def next_vehicle(requests: DataFrame, log: DataFrame, within: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """Interval join of two streams: each request (req_id, stop_id, at) with the vehicles that call at
    its stop within some time."""
    r = requests.withColumnRenamed("stop_id", "want")
    r = r.withWatermark("at", delay) if requests.isStreaming else r
    e = _marked(log, delay)
    return r.join(e, (F.col("want") == F.col("stop_id")) & (F.col("ts") >= F.col("at")) & (F.col("ts") <= F.col("at") + F.expr(f"INTERVAL {within}"))).select("req_id", "stop_id", "at", "ts", "vehicle")


def last_seen(log: DataFrame) -> DataFrame:
    """Arbitrary state: after every batch the last stop of each vehicle that moved, and how many stops
    it has been seen at."""

    def step(key, frames, state: GroupState):
        at, stop, n = state.get if state.exists else (0, -1, 0)
        for f in frames:
            n += len(f)
            f = f.sort_values(["ts", "event_id"])
            t = int(f["ts"].iat[-1].value)
            if t >= at:
                at, stop = t, int(f["stop_id"].iat[-1])
        state.update((at, stop, n))
        yield pd.DataFrame({"vehicle": [key[0]], "stop_id": [stop], "seen": [n]})

    return log.groupBy("vehicle").applyInPandasWithState(step, "vehicle long, stop_id long, seen long", "at long, stop long, n long", "update", GroupStateTimeout.NoTimeout)


def answer_requests(requests: DataFrame, route: Callable[[DataFrame], DataFrame], write: Callable[[DataFrame, int], None]):
    """A writer that answers each micro-batch of requests against a fixed timetable with a batch router:
    its rounds use windows that a streaming plan doesn't have."""
    return requests.writeStream.foreachBatch(lambda batch, epoch: write(route(batch), epoch))
