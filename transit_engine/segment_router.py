"""The trip-segment router: rounds over segments of trips, joined by precomputed transfers."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .asof import earliest, times_at
from .round_router import Answer
from .schema import LEGS, Network
from .storage import written


def target_hits(net: Network, requests: DataFrame, keys: tuple[str, ...] = ("req_id",)) -> DataFrame:
    """(keys, route_id, at, walk): where routes come to the target's neighbourhood."""
    near = net.neighbourhood().select(F.col("a").alias("stop_id"), F.col("b").alias("target"), F.col("secs").alias("walk"))
    return requests.select(*keys, "target").distinct().join(near, "target").join(net.route_stops.where("idx > 0"), "stop_id").select(*dict.fromkeys([*keys, "target"]), "route_id", F.col("idx").alias("at"), "walk")


def first_boards(net: Network, requests: DataFrame, keep: list[str], walk_from_source: bool = True) -> DataFrame:
    """(keep, route_id, rank, idx): the first trip of every route from the source's neighbourhood."""
    near = net.neighbourhood() if walk_from_source else net.neighbourhood().where("a = b")
    lens = net.route_stops.groupBy("route_id").agg(F.max("idx").alias("last"))
    boards = net.route_stops.join(lens, "route_id").where("idx < last").select("route_id", "idx", F.col("stop_id").alias("b"))
    probes = requests.join(near, requests.source == near.a).join(boards, "b").select(*keep, "route_id", "idx", (F.col("dep") + F.col("secs")).alias("tau"))
    return earliest(probes, net).select(*keep, "route_id", "rank", "idx")


def enqueue(reached: DataFrame | None, candidates: DataFrame, lens: DataFrame, keys: list[str], lanes: bool = False) -> DataFrame:
    """Which candidate segments are new: per (keys, route), a trip entered at an index counts as
    reached from there for itself and all later trips. One running minimum over (rank, idx) of what was
    reached and what comes in decides all at once; a new segment ends where the trip was reached before.

    lanes: keys end in a departure, and what a later departure reached on the same trip counts too."""
    c = candidates.withColumn("new", F.lit(1))
    rows = c if reached is None else c.unionByName(reached.withColumn("new", F.lit(0)), allowMissingColumns=True)
    w = Window.partitionBy(*keys, "route_id").orderBy("rank", "idx", "new").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("run", F.min("idx").over(w))
    if lanes:
        *outer, dep = keys
        x = Window.partitionBy(*outer, "route_id", "rank").orderBy(F.desc(dep), "idx", "new").rowsBetween(Window.unboundedPreceding, -1)
        rows = rows.withColumn("run", F.least("run", F.min("idx").over(x)))
    out = rows.where("new = 1").join(lens, "route_id").withColumn("to_idx", F.coalesce("run", "last"))
    return out.where("idx < to_idx").drop("new", "run", "last")


def route(net: Network, requests: DataFrame, transfers: DataFrame, k: int = 4, prune: bool = True, with_legs: bool = False, admit=None, walk_from_source: bool = True, count: bool = False) -> Answer:
    """Earliest arrivals with at most 0..k transfers for a batch of requests.

    A round scores the frontier's segments against the target's routes, expands those whose next
    arrival still beats the label over the transfers of their trip, and enqueues what is new. admit:
    a function that filters candidates (req_id, route_id, rank, ...), the cell-pruned variants. The
    frontier is written each round. A label carries its legs if asked."""
    lens = net.route_stops.groupBy("route_id").agg(F.max("idx").alias("last"))
    hits = written(target_hits(net, requests)) if prune else target_hits(net, requests)
    ids = net.trips.select("route_id", "rank", "trip_id")
    keys = ["req_id"]
    c = first_boards(net, requests, keys, walk_from_source)
    if with_legs:
        c = c.withColumn("legs", F.expr(f"cast(array() as {LEGS})"))
    if admit:
        c = admit(c)
    reached, labels, work = None, None, []
    for n in range(k + 1):
        frontier = written(enqueue(reached, c, lens, keys).join(ids, ["route_id", "rank"]))
        reached_now = frontier.select("req_id", "route_id", "rank", "idx")
        reached = reached_now if reached is None else reached.unionByName(reached_now)
        scored = frontier.join(hits, ["req_id", "route_id"]).where("at > idx and at <= to_idx")
        scored = times_at(scored, net, "at", "t").withColumn("arr", (F.col("t") + F.col("walk")).cast("int"))
        if with_legs:
            ride = F.struct("trip_id", F.col("idx").alias("from_idx"), F.col("at").alias("to_idx"))
            scored = scored.withColumn("legs", F.concat("legs", F.array(ride)))
            best = scored.groupBy("req_id").agg(F.min("arr").alias("arr"), F.min_by("legs", F.struct("arr", "trip_id", "at", "idx")).alias("legs"))
        else:
            best = scored.groupBy("req_id").agg(F.min("arr").alias("arr"))
        best = written(best.withColumn("n", F.lit(n)))
        labels = best if labels is None else labels.unionByName(best)
        if count:
            work.append({"n": n, "segments": frontier.count(), "target_checks": scored.count()})
        if n == k:
            break
        nxt = times_at(frontier.withColumn("next", F.col("idx") + 1), net, "next", "soon")
        if prune:
            now = labels.groupBy("req_id").agg(F.min("arr").alias("label"))
            nxt = nxt.join(now, "req_id", "left").where("label is null or soon < label")
        go = nxt.join(transfers, nxt.trip_id == transfers.t1).where("i1 > idx and i1 <= to_idx")
        cols = ["req_id", F.col("route2").alias("route_id"), F.col("rank2").alias("rank"), F.col("i2").alias("idx")]
        if with_legs:
            ride = F.struct("trip_id", F.col("idx").alias("from_idx"), F.col("i1").alias("to_idx"))
            c = go.select(*cols, F.concat("legs", F.array(ride)).alias("legs")).groupBy("req_id", "route_id", "rank", "idx").agg(F.min("legs").alias("legs"))
        else:
            c = go.select(*cols).distinct()
        if admit:
            c = admit(c)
    names = ["req_id", "n", "arr"] + (["legs"] if with_legs else [])
    return Answer(labels.select(*names), None, work)
