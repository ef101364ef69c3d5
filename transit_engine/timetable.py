"""Routes from stop sequences, precedence, first-in-first-out, checks."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import footpaths
from .schema import Network


def derive_routes(stop_times: DataFrame) -> DataFrame:
    """(trip_id, route_id, len): trips with the same stop sequence share a route, numbered from 1 in the
    order of the sequences; sequences themselves are compared, not hashes."""
    seq = stop_times.groupBy("trip_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("idx", "stop_id"))), lambda s: s["stop_id"]).alias("stops"))
    kinds = seq.select("stops").distinct()
    ids = kinds.withColumn("route_id", F.row_number().over(Window.orderBy(F.transform("stops", lambda s: s))).cast("long"))
    return seq.join(ids, "stops").select("trip_id", "route_id", F.size("stops").cast("int").alias("len"))


def rank_trips(events: DataFrame) -> DataFrame:
    """(trip_id, route_id, rank): precedence on a route by times at its stops, first index first."""
    v = events.groupBy("route_id", "trip_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("idx", "arr"))), lambda s: s["arr"]).alias("times"))
    return v.select("trip_id", "route_id", (F.row_number().over(Window.partitionBy("route_id").orderBy("times", "trip_id")) - 1).cast("int").alias("rank"))


def fifo_violations(events: DataFrame) -> DataFrame:
    """(route_id, trip_id) of trips that arrive somewhere before a trip that stands before them."""
    w = Window.partitionBy("route_id", "idx").orderBy("rank").rowsBetween(Window.unboundedPreceding, -1)
    return events.withColumn("top", F.max("arr").over(w)).where("arr < top").select("route_id", "trip_id").distinct()


def enforce_fifo(events: DataFrame, mode: str = "drop") -> DataFrame:
    """events (trip_id, route_id, rank, idx, stop_id, arr, dep) without overtaking. drop: a trip that
    overtakes one kept before goes; split: it moves to the first sub-route where it doesn't, routes
    renumbered route_id * 1000 + part. Ranks are dense anew."""

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["rank", "idx"])
        size = int(pdf.idx.max()) + 1
        times = pdf.arr.to_numpy().reshape(-1, size)
        tops: list[np.ndarray] = []
        count: list[int] = []
        part, rank = np.full(len(times), -1), np.zeros(len(times), int)
        for i, t in enumerate(times):
            for p, top in enumerate(tops):
                if (t >= top).all():
                    break
            else:
                p = len(tops) if mode == "split" or not tops else -1
                if p >= 0:
                    tops.append(t)
                    count.append(0)
            if p >= 0:
                tops[p], part[i], rank[i] = t, p, count[p]
                count[p] += 1
        keep = np.repeat(part >= 0, size)
        out = pdf[keep].copy()
        out["rank"] = np.repeat(rank[part >= 0], size).astype(np.int32)
        if mode == "split":
            out["route_id"] = out.route_id * 1000 + np.repeat(part[part >= 0], size)
        return out

    cols = "trip_id long, route_id long, rank int, idx int, stop_id long, arr int, dep int"
    return events.select("trip_id", "route_id", "rank", "idx", "stop_id", "arr", "dep").groupBy("route_id").applyInPandas(one, cols)


def with_express(net: Network) -> DataFrame:
    """events of net and one more trip per route that starts 300 s after the third and needs half the
    time per leg: a timetable that overtakes. Ranks by times."""
    third = net.events.where("rank = 2")
    w = Window.partitionBy("route_id").orderBy("idx")
    first = F.first("arr").over(w)
    when = (first + 300 + F.floor((F.col("arr") - first) / 2)).cast("int")
    extra = third.select((F.col("route_id") * 1000 + 999).alias("trip_id"), "route_id", F.lit(0).alias("rank"), "idx", "stop_id", when.alias("arr"), when.alias("dep"))
    all_ = net.events.unionByName(extra)
    return all_.drop("rank").join(rank_trips(all_).select("trip_id", "rank"), "trip_id").select("trip_id", "route_id", "rank", "idx", "stop_id", "arr", "dep")


def from_events(name: str, events: DataFrame, walks: DataFrame | None = None) -> Network:
    """A network of an irregular timetable: stop times (trip_id, idx, stop_id, arr) with any number of
    routes; overtaking trips are split off, so that the routers' order by rank holds."""
    routed = events.join(derive_routes(events).select("trip_id", "route_id"), "trip_id")
    ranked = routed.join(rank_trips(routed).select("trip_id", "rank"), "trip_id").withColumn("dep", F.col("arr"))
    ev = enforce_fifo(ranked, "split")
    rs = ev.select("route_id", "idx", "stop_id").distinct()
    trips = ev.where("idx = 0").select("trip_id", "route_id", "rank", F.col("dep").alias("start"))
    stops = ev.select("stop_id").distinct().select("stop_id", F.lit(0).alias("region"), F.lit(0).alias("pos"), F.lit("").alias("poi"))
    none = stops.where("false").select(F.col("stop_id").alias("a"), F.col("stop_id").alias("b"), F.lit(0).alias("secs"))
    return Network(name, stops, rs, trips, ev, walks if walks is not None else none)


def validate(net: Network) -> DataFrame:
    """(rule, rows that break it) for walks, indices, times and precedence; zeros for a sound network."""
    w = net.walks
    closed = footpaths.close(w)
    parts = [
        ("walks closed and shortest", closed.join(w.withColumnRenamed("secs", "own"), ["a", "b"], "left").where("own is null or own > secs")),
        ("walks both ways", w.join(w.select(F.col("a").alias("b"), F.col("b").alias("a"), F.col("secs").alias("own")), ["a", "b"], "left").where("own is null or own <> secs")),
        ("indices dense", net.route_stops.groupBy("route_id").agg(F.max("idx").alias("m"), F.count("*").alias("k")).where("m + 1 <> k")),
        ("times rise along a trip", net.events.withColumn("p", F.lag("arr").over(Window.partitionBy("trip_id").orderBy("idx"))).where("arr < p")),
        ("no overtaking", fifo_violations(net.events)),
    ]
    out = None
    for name, bad in parts:
        row = bad.agg(F.lit(name).alias("rule"), F.count("*").alias("broken"))
        out = row if out is None else out.unionByName(row)
    return out
