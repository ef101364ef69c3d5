"""The route-by-route router: rounds of riding and walking from improved stops."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .asof import earliest, times_at
from .schema import Network
from .storage import sorted_if_large, written


@dataclass
class Answer:
    """labels (req_id, n, arr): arrivals that improve on fewer transfers; state: best arrival per stop
    (with one-to-all); work: one row of counters per round."""

    labels: DataFrame
    state: DataFrame | None
    work: list[dict]


def route(net: Network, requests: DataFrame, k: int = 4, prune: bool = True, admit=None, to_all: bool = False, targets: DataFrame | None = None, count: bool = False) -> Answer:
    """Earliest arrivals with at most 0..k transfers for a batch of requests (req_id, source, target,
    dep), all at once: the request is part of every key.

    A round boards the earliest trip of every route at every stop improved in the round before (as-of),
    rides to all later stops, keeps the least arrival per (request, stop), walks, and keeps what beats
    the stop's best and, with prune, the target's label. admit: a function that filters boardings
    (req_id, route_id, ...), the cell-pruned variant. to_all: labels (req_id, stop_id, n, arr) of all stops, or of
    targets (req_id, target); then stops count only below the largest label once all targets have one.
    Each round's state is written, so lineage and failures stay short.
    """
    near = sorted_if_large(net.neighbourhood())
    lens = net.route_stops.groupBy("route_id").agg(F.max("idx").alias("last"))
    boards = net.route_stops.join(sorted_if_large(lens), "route_id").where("idx < last").select("route_id", "idx", "stop_id")
    rides = sorted_if_large(net.route_stops.select("route_id", F.col("idx").alias("off"), F.col("stop_id").alias("alight")))
    start = requests.join(near, requests.source == near.a).groupBy("req_id", F.col("b").alias("stop_id")).agg(F.min(F.col("dep") + F.col("secs")).cast("int").alias("t"))
    goals = requests.select("req_id", "target") if not to_all else None
    state = written(start.select("req_id", "stop_id", F.col("t").alias("best"), F.lit(True).alias("marked")))
    labels, work = None, []
    label_now = None
    for n in range(k + 1):
        probes = state.where("marked").join(boards, "stop_id").select("req_id", "route_id", "idx", F.col("best").alias("tau"))
        if admit:
            probes = admit(probes)
        on = earliest(probes, net).select("req_id", "route_id", "idx", "rank")
        rode = times_at(on.join(rides, "route_id").where("off > idx"), net, "off", "arr")
        rode = rode.groupBy("req_id", F.col("alight").alias("a")).agg(F.min("arr").alias("arr"))
        reached = rode.join(near, "a").groupBy("req_id", F.col("b").alias("stop_id")).agg(F.min(F.col("arr") + F.col("secs")).cast("int").alias("t"))
        both = state.select("req_id", "stop_id", "best", F.lit(None).cast("int").alias("t")).unionByName(reached.withColumn("best", F.lit(None).cast("int")), allowMissingColumns=True)
        merged = both.groupBy("req_id", "stop_id").agg(F.min("best").alias("old"), F.min("t").alias("t"))
        state_n = merged.select("req_id", "stop_id", F.least("old", "t").alias("best"), (F.col("t") < F.coalesce("old", F.lit(2**30))).alias("marked"), F.col("t").alias("t"))
        state_n = state_n.withColumn("marked", F.coalesce("marked", F.lit(False)))
        state_n = written(state_n)
        if count:
            work.append({"n": n, "routes_scanned": on.select("req_id", "route_id").distinct().count(), "stops_marked": state_n.where("marked").count()})
        if not to_all:
            found = state_n.join(goals, (state_n.req_id == goals.req_id) & (state_n.stop_id == goals.target)).where("t is not null").select(state_n.req_id, F.lit(n).alias("n"), F.col("t").alias("arr"))
            labels = found if labels is None else labels.unionByName(found)
            if prune:
                label_now = labels.groupBy("req_id").agg(F.min("arr").alias("label"))
                state_n = state_n.join(label_now, "req_id", "left").withColumn("marked", F.col("marked") & (F.col("label").isNull() | (F.col("best") < F.col("label"))))
        else:
            found = state_n.where("marked").select("req_id", "stop_id", F.lit(n).alias("n"), F.col("t").alias("arr"))
            if targets is not None:
                found = found.join(targets.select("req_id", F.col("target").alias("stop_id")), ["req_id", "stop_id"], "left_semi")
            labels = found if labels is None else labels.unionByName(found)
            if targets is not None and prune:
                wanted = targets.groupBy("req_id").agg(F.countDistinct("target").alias("wanted"))
                best = labels.groupBy("req_id", "stop_id").agg(F.min("arr").alias("arr")).groupBy("req_id").agg(F.count("*").alias("have"), F.max("arr").alias("label"))
                bound = best.join(wanted, "req_id").where("have = wanted").select("req_id", "label")
                state_n = state_n.join(bound, "req_id", "left").withColumn("marked", F.col("marked") & (F.col("label").isNull() | (F.col("best") < F.col("label"))))
        state = state_n.select("req_id", "stop_id", "best", "marked")
    return Answer(written(labels), state, work)
