"""Feeds in, results out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import footpaths, timetable
from .schema import REQUESTS, Network, struct

#: Files of a feed and their columns; walks may be absent.
FEED = {"stop_times": "trip_id bigint, idx int, stop_id bigint, arr int", "walks": "a bigint, b bigint, secs int"}


def read_feed(spark: SparkSession, path: str, fmt: str = "parquet", name: str = "feed", walks: bool = True) -> Network:
    """A network from a folder of feed files (csv with header, json or parquet), read with declared
    schemas: routes and ranks are derived, overtaking trips split off, walks closed."""

    def read(part):
        r = spark.read.schema(FEED[part])
        return {"csv": lambda p: r.option("header", True).csv(p), "json": r.json, "parquet": r.parquet}[fmt](f"{path}/{part}")

    return timetable.from_events(name, read("stop_times"), footpaths.close(read("walks")) if walks else None)


def read_requests(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(REQUESTS).json(path)


def from_rows(spark: SparkSession, stop_times: list[tuple], walks: list[tuple] = (), name: str = "rows") -> Network:
    return timetable.from_events(name, spark.createDataFrame(stop_times, struct(FEED["stop_times"])), footpaths.close(spark.createDataFrame(list(walks), struct(FEED["walks"]))))


def write_network(net: Network, path: str) -> None:
    """Parquet per part; stop events sorted by route, rank and index, so row groups can be skipped."""
    for part in ("stops", "route_stops", "trips", "walks"):
        getattr(net, part).write.mode("overwrite").parquet(f"{path}/{part}")
    net.events.repartition("route_id").sortWithinPartitions("route_id", "rank", "idx").write.mode("overwrite").parquet(f"{path}/events")


def read_network(spark: SparkSession, path: str, name: str) -> Network:
    return Network(name, *(spark.read.parquet(f"{path}/{p}") for p in ("stops", "route_stops", "trips", "events", "walks")))


def write_transfers(found: DataFrame, name: str, buckets: int = 64) -> None:
    """A table bucketed by the trip that is left, so every round's join reads it without a shuffle."""
    found.write.mode("overwrite").bucketBy(buckets, "t1").sortBy("t1", "i1").saveAsTable(name)


def write_labels(labels: DataFrame, path: str, fmt: str = "parquet") -> None:
    out = labels.withColumn("legs", F.to_json("legs")) if "legs" in labels.columns and fmt == "csv" else labels
    w = out.write.mode("overwrite")
    {"parquet": w.parquet, "json": w.json, "csv": w.option("header", True).csv}[fmt](path)
