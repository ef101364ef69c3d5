"""The fill-in: trips of best journeys between cut stops, at any time of day."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels
from .derive import DAY_END, DAY_START
from .range_router import as_pairs, fanout_segments
from .schema import Network


def compute(net: Network, transfers: DataFrame, pairs: DataFrame, k: int = 4, engine: str = "fanout", lo: int = DAY_START, hi: int = DAY_END) -> DataFrame:
    """(trip_id, src_stop, dst_stop) of the journeys of every non-dominated (departure, transfers,
    arrival) between the ordered stop pairs (src_stop, dst_stop). engine: fanout searches once per source
    for all its destinations; pairs once per pair, the baseline; arrays as fanout, one task per source
    against a broadcast timetable whose size is checked. Walking from the source is allowed. Of equally
    good journeys the engines may keep different ones; either set of trips answers every request."""
    groups = pairs.select(F.col("src_stop").alias("g"), F.col("src_stop").alias("source")).distinct()
    targets = pairs.select(F.col("src_stop").alias("g"), F.col("dst_stop").alias("target")).distinct()
    if engine == "arrays":
        found = kernels.fanout_blocks(net, transfers, groups, targets, lo, hi, k, with_trips=True)
        return found.select(F.explode("trips").alias("trip_id"), F.col("source").alias("src_stop"), F.col("target").alias("dst_stop")).distinct()
    if engine == "pairs":
        groups, targets = as_pairs(groups, targets)
    found = fanout_segments(net, transfers, groups, targets, lo, hi, k, with_legs=True).rows
    legs = found.select(F.col("source").alias("src_stop"), F.col("target").alias("dst_stop"), F.explode("legs").alias("leg"))
    return legs.select("leg.trip_id", "src_stop", "dst_stop").distinct()


def as_trips(net: Network, found: DataFrame, grain: str = "trip") -> DataFrame:
    """(trip_id, route_id, rank) of the fill-in: its trips, or all trips of its routes (the route
    router's grain, and what scanning whole routes gives)."""
    ids = found.select("trip_id").distinct()
    trips = net.trips.select("trip_id", "route_id", "rank")
    own = trips.join(ids, "trip_id", "left_semi")
    return own if grain == "trip" else trips.join(own.select("route_id").distinct(), "route_id", "left_semi")


def as_events(net: Network, trips: DataFrame) -> DataFrame:
    """The fill-in as marked stop events."""
    return net.events.join(trips.select("trip_id"), "trip_id", "left_semi")


def overlay(net: Network, trips: DataFrame, routes_by_cell: DataFrame, cells: list[int]) -> Network:
    """The sub-timetable of some cells and the fill-in, as a network of its own."""
    own = net.trips.join(routes_by_cell.where(F.col("cell").isin(cells)).select("route_id"), "route_id", "left_semi")
    keep = own.select("trip_id").union(trips.select("trip_id")).distinct()
    return net.with_(name=f"{net.name} overlay", trips=net.trips.join(keep, "trip_id", "left_semi"), events=net.events.join(keep, "trip_id", "left_semi"), headway=None, offsets=None)
