"""Cells of a partition: routes, stops, cut stops, and which trips a request may use."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .hypergraph import WALK_NODE, incidence
from .schema import Network


def natural(net: Network) -> DataFrame:
    """(node_id, cell): routes in the region that most of their stops lie in (ties: the least), walks in
    the region of their lesser end; cells count from 1."""
    at = incidence(net).join(net.stops.select("stop_id", "region"), "stop_id")
    votes = at.groupBy("node_id", "region").agg(F.count("*").alias("k"))
    return votes.groupBy("node_id").agg((F.max_by("region", F.struct("k", -F.col("region"))) + 1).cast("int").alias("cell"))


def route_cells(node_cells: DataFrame) -> DataFrame:
    return node_cells.where(F.col("node_id") < WALK_NODE).select(F.col("node_id").alias("route_id"), "cell")


def stop_cells(net: Network, node_cells: DataFrame) -> DataFrame:
    """(stop_id, cell): the one cell of all nodes at the stop, 0 if there are several (a cut stop)."""
    at = incidence(net).join(node_cells, "node_id")
    return at.groupBy("stop_id").agg(F.when(F.min("cell") == F.max("cell"), F.min("cell")).otherwise(0).cast("int").alias("cell"))


def cut_stops(cells_of_stops: DataFrame) -> DataFrame:
    return cells_of_stops.where("cell = 0").select("stop_id")


def label_requests(requests: DataFrame, cells_of_stops: DataFrame) -> DataFrame:
    """requests with src_cell and tgt_cell; a cut stop or unserved stop has none (null)."""
    c = cells_of_stops.where("cell > 0")
    s = c.select(F.col("stop_id").alias("source"), F.col("cell").alias("src_cell"))
    t = c.select(F.col("stop_id").alias("target"), F.col("cell").alias("tgt_cell"))
    return requests.join(s, "source", "left").join(t, "target", "left")


def trip_admission(labelled: DataFrame, routes: DataFrame, fillin: DataFrame):
    """A filter for the segment router: a candidate (req_id, route_id, rank) stays if its trip is in the
    fill-in (route_id, rank) or its route lies in the source's or target's cell."""
    req = labelled.select("req_id", "src_cell", "tgt_cell")
    flags = fillin.select("route_id", "rank", F.lit(True).alias("fill_"))

    def admit(candidates: DataFrame) -> DataFrame:
        names = candidates.columns
        c = candidates.join(routes.withColumnRenamed("cell", "cell_"), "route_id", "left").join(req, "req_id").join(flags, ["route_id", "rank"], "left")
        ok = F.coalesce("fill_", F.lit(False)) | F.coalesce(F.col("cell_") == F.col("src_cell"), F.lit(False)) | F.coalesce(F.col("cell_") == F.col("tgt_cell"), F.lit(False))
        return c.where(ok).select(*names)

    return admit


def route_admission(labelled: DataFrame, routes: DataFrame, fillin_routes: DataFrame):
    """As trip_admission for the round router: a row (req_id, route_id, ...) stays if its route is in the
    fill-in or lies in the source's or target's cell. Only rows that occur are looked up, never all
    pairs of requests and routes."""
    req = labelled.select("req_id", "src_cell", "tgt_cell")
    flags = fillin_routes.select("route_id").distinct().withColumn("fill_", F.lit(True))
    marks = routes.withColumnRenamed("cell", "cell_").join(flags, "route_id", "full")

    def admit(rows: DataFrame) -> DataFrame:
        c = rows.join(marks, "route_id", "left").join(req, "req_id")
        ok = F.coalesce("fill_", F.lit(False)) | F.coalesce(F.col("cell_") == F.col("src_cell"), F.lit(False)) | F.coalesce(F.col("cell_") == F.col("tgt_cell"), F.lit(False))
        return c.where(ok).select(*rows.columns)

    return admit


def advise(net: Network, cells_of_stops: DataFrame, most_cut: float = 0.1) -> bool:
    """Whether cells are worth their preprocessing: not if over most_cut of the stops are cut, as then
    nearly every trip ends up in the fill-in."""
    r = cells_of_stops.agg(F.avg((F.col("cell") == 0).cast("double")).alias("x")).first()
    return (r["x"] or 0.0) <= most_cut
