"""Network statistics, partition quality, fill-in figures, counters of work."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .hypergraph import Hypergraph, incidence
from .schema import Network


def network_stats(net: Network) -> DataFrame:
    """One row: stops, served stops, routes, trips, directed walks, stop events, hypernodes, hyperedges."""
    at = incidence(net)
    edges = at.groupBy("stop_id").agg(F.sort_array(F.collect_set("node_id")).alias("pins")).where(F.size("pins") > 1)
    one = lambda df, name: df.agg(F.count("*").alias(name))
    out = one(net.stops, "stops")
    for df, name in (
        (net.route_stops.select("stop_id").distinct(), "served"), (net.route_stops.select("route_id").distinct(), "routes"), (net.trips, "trips"),
        (net.walks, "walks"), (net.events, "stop_events"), (at.select("node_id").distinct(), "hypernodes"), (edges.select("pins").distinct(), "hyperedges"),
    ):
        out = out.join(F.broadcast(one(df, name)))  # one row each
    return out


def topology(net: Network) -> DataFrame:
    """One row: stops per route, routes per served stop, events per served stop (rounded to 6 places)."""
    r = net.route_stops
    per_route = r.groupBy("route_id").agg(F.count("*").alias("k")).agg(F.round(F.avg("k"), 6).alias("stops_per_route"))
    per_stop = r.groupBy("stop_id").agg(F.countDistinct("route_id").alias("k")).agg(F.round(F.avg("k"), 6).alias("routes_per_stop"))
    events = net.events.groupBy("stop_id").agg(F.count("*").alias("k")).agg(F.round(F.avg("k"), 6).alias("events_per_stop"))
    return per_route.join(F.broadcast(per_stop)).join(F.broadcast(events))


def partition_quality(h: Hypergraph, node_cells: DataFrame) -> DataFrame:
    """One row: cut edges, cut weight, all weight, heaviest cell over the mean."""
    per = h.pins.join(node_cells, "node_id").groupBy("edge_id").agg((F.min("cell") != F.max("cell")).alias("cut"))
    e = per.join(h.edges, "edge_id").agg(
        F.sum(F.col("cut").cast("int")).cast("long").alias("cut_edges"), F.round(F.sum(F.when(F.col("cut"), F.col("weight")).otherwise(0.0)), 6).alias("cut_weight"), F.round(F.sum("weight"), 6).alias("all_weight")
    )
    load = h.nodes.join(node_cells, "node_id").groupBy("cell").agg(F.sum("weight").alias("w"))
    return e.join(F.broadcast(load.agg(F.round(F.max("w") / F.avg("w"), 6).alias("imbalance"))))


def cut_share(cells_of_stops: DataFrame, net: Network) -> DataFrame:
    """One row: cut stops and their share of all stops in percent."""
    cut = cells_of_stops.where("cell = 0").agg(F.count("*").alias("cut_stops"))
    n = net.stops.agg(F.count("*").alias("n"))
    return cut.join(F.broadcast(n)).select("cut_stops", F.round(100.0 * F.col("cut_stops") / F.col("n"), 6).alias("cut_pct"))


def fillin_stats(net: Network, found: DataFrame, cells_of_stops: DataFrame) -> DataFrame:
    """One row: fill-in trips, their share of all trips, the routes they belong to, cut stops."""
    trips = net.trips.join(found.select("trip_id").distinct(), "trip_id", "left_semi")
    a = trips.agg(F.count("*").alias("fillin_trips"), F.countDistinct("route_id").alias("fillin_routes"))
    n = net.trips.agg(F.count("*").alias("n"), F.countDistinct("route_id").alias("m"))
    x = a.join(F.broadcast(n)).select("fillin_trips", (100.0 * F.col("fillin_trips") / F.col("n")).alias("fillin_pct"), (100.0 * F.col("fillin_routes") / F.col("m")).alias("fillin_route_pct"))
    return x.join(F.broadcast(cut_share(cells_of_stops, net)))


def profile_queries(flat_cuts: int, parent_cuts: list[int], child_cuts: list[int], top: int | None = None) -> dict:
    """Profile searches of a flat partition, C (C - 1), and of nested cells: top pairs and, both ways,
    every parent's top cut stops with the cut stops that only its children have."""
    flat = flat_cuts * (flat_cuts - 1)
    t = top if top is not None else len(parent_cuts)
    nested = t * (t - 1) + 2 * sum(a * b for a, b in zip(parent_cuts, child_cuts, strict=True))
    return {"flat": flat, "nested": nested, "saved_pct": round(100.0 * (flat - nested) / flat, 6) if flat else 0.0}


def gain(base: float, new: float) -> float:
    """Percent by which new is below base."""
    return 100.0 * (base - new) / base


def diff(a: DataFrame, b: DataFrame, keys: tuple[str, ...] = ("req_id", "n")) -> DataFrame:
    """Rows in which two answers differ (arr), missing rows included: empty for exact methods."""
    x, y = a.select(*keys, F.col("arr").alias("arr_a")), b.select(*keys, F.col("arr").alias("arr_b"))
    return x.join(y, list(keys), "full_outer").where(~F.col("arr_a").eqNullSafe(F.col("arr_b")))


def work_table(spark, rows: dict[str, list[dict]]) -> DataFrame:
    """(method, n, counter, value) of counters that routers returned."""
    flat = [(m, r["n"], c, int(v)) for m, rs in rows.items() for r in rs for c, v in r.items() if c != "n"]
    return spark.createDataFrame(flat, "method string, n int, counter string, value long")
