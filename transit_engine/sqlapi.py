"""Networks and searches from SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from . import journeys, kernels, segment_router
from .schema import Network


def register(net: Network, prefix: str = "transit") -> None:
    """Temporary views of a network's tables: <prefix>_stops, _route_stops, _trips, _events, _walks,
    _neighbourhood, _routes."""
    for part in ("stops", "route_stops", "trips", "events", "walks"):
        getattr(net, part).createOrReplaceTempView(f"{prefix}_{part}")
    net.neighbourhood().createOrReplaceTempView(f"{prefix}_neighbourhood")
    net.routes.createOrReplaceTempView(f"{prefix}_routes")


def register_answers(net: Network, requests: DataFrame, transfers: DataFrame, k: int = 4, name: str = "transit_journeys") -> None:
    """A view (req_id, n, arr) over a routed batch. Filter requests before routing: a condition on the
    view passes below the windows only for req_id."""
    journeys.pareto(segment_router.route(net, requests, transfers, k).labels).createOrReplaceTempView(name)


def register_function(spark: SparkSession, net: Network, name: str = "route", k: int = 4) -> None:
    """A table function route(source, target, dep) -> (n, arr) over a broadcast timetable, for lateral
    joins of a few requests; batches belong to the routers."""
    sent = spark.sparkContext.broadcast(kernels.Arrays(net))

    @udtf(returnType="n: int, arr: int")
    class Route:
        def eval(self, source: int, target: int, dep: int):
            a = sent.value
            s, t = a.of(np.array([source])), a.of(np.array([target]))
            best = 2**30
            for n, arr in enumerate(kernels.round_labels(a, s, t, np.array([dep], np.int32), k)[:, 0].tolist()):
                if arr < best:
                    best = arr
                    yield n, arr

    spark.udtf.register(name, Route)
