"""Routes and walks as nodes, shared stops as edges, with three weighting schemes and one of demand."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .schema import Network

#: Ids of walk nodes start here: node id = WALK_NODE + number of the undirected walk.
WALK_NODE = 1 << 50


@dataclass(frozen=True)
class Hypergraph:
    """nodes (node_id, kind, weight), pins (edge_id, node_id), edges (edge_id, weight, stops): edges with
    the same pins are one, their weights added, their stops listed, so a cut edge names its stops."""

    nodes: DataFrame
    pins: DataFrame
    edges: DataFrame


def walk_node(a: str, b: str):
    """The node id of the undirected walk between stops a < b."""
    return F.lit(WALK_NODE) + F.col(a) * 10**7 + F.col(b)


def incidence(net: Network) -> DataFrame:
    """(stop_id, node_id): every route at its stops, every undirected walk at its two ends."""
    route = net.route_stops.select("stop_id", F.col("route_id").alias("node_id")).distinct()
    walk = net.walks.where("a < b").select(walk_node("a", "b").alias("node_id"), "a", "b")
    ends = walk.select(F.col("a").alias("stop_id"), "node_id").union(walk.select(F.col("b").alias("stop_id"), "node_id"))
    return route.union(ends)


def _log(x):
    return F.when(x > 0, F.log(x.cast("double"))).otherwise(F.lit(0.0))


def build(net: Network, scheme: int | str = 3, demand: DataFrame | None = None) -> Hypergraph:
    """scheme 1: unit weights; 2: a route weighs its events (a walk 0), an edge the logarithm of its
    stop's events; 3: as 2 with the events of the stop's whole neighbourhood; "demand": as 3 with the
    journeys of demand (stop_id, trips) in place of events. No event at all: weight 0."""
    at = incidence(net)
    per_route = net.events.groupBy(F.col("route_id").alias("node_id")).agg(F.count("*").alias("events"))
    per_stop = demand.select("stop_id", F.col("trips").alias("events")) if scheme == "demand" else net.events.groupBy("stop_id").agg(F.count("*").alias("events"))
    if scheme in (3, "demand"):
        near = net.neighbourhood()
        per_stop = near.join(per_stop, near.b == per_stop.stop_id).groupBy(F.col("a").alias("stop_id")).agg(F.sum("events").alias("events"))
    kind = F.when(F.col("node_id") >= WALK_NODE, "walk").otherwise("route")
    nodes = at.select("node_id").distinct().join(per_route, "node_id", "left")
    nodes = nodes.select("node_id", kind.alias("kind"), (F.lit(1.0) if scheme == 1 else F.coalesce("events", F.lit(0)).cast("double")).alias("weight"))
    stops = at.groupBy("stop_id").agg(F.sort_array(F.collect_set("node_id")).alias("pins")).where(F.size("pins") > 1)
    weight = F.lit(1.0) if scheme == 1 else _log(F.coalesce("events", F.lit(0)))
    edges = stops.join(per_stop, "stop_id", "left").groupBy("pins").agg(F.sum(weight).alias("weight"), F.sort_array(F.collect_list("stop_id")).alias("stops"))
    edges = edges.withColumn("edge_id", F.element_at("stops", 1))
    return Hypergraph(nodes, edges.select("edge_id", F.explode("pins").alias("node_id")), edges.select("edge_id", "weight", "stops"))
