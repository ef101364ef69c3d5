"""Range and fan-out searches: every departure of an interval, from one source to many targets."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import round_router
from .asof import times_at
from .schema import LEGS, Network
from .segment_router import enqueue, first_boards
from .storage import written


@dataclass
class Profile:
    """rows (g, source, target, dep, n, arr [, legs]): no other row departs as late, transfers as
    little and arrives as early; work: counters per round."""

    rows: DataFrame
    work: list[dict]


def departures(net: Network, sources: DataFrame, lo: int, hi: int, walk: bool = True) -> DataFrame:
    """(source, dep): distinct times in lo..hi at which leaving the source catches some departure."""
    near = net.neighbourhood() if walk else net.neighbourhood().where("a = b")
    lens = net.route_stops.groupBy("route_id").agg(F.max("idx").alias("last"))
    e = net.events.join(lens, "route_id").where("idx < last").select(F.col("stop_id").alias("b"), F.col("dep").alias("at"))
    s = sources.select("source").distinct()
    d = s.join(near, s.source == near.a).join(e, "b").select("source", (F.col("at") - F.col("secs")).cast("int").alias("dep"))
    return d.where((F.col("dep") >= lo) & (F.col("dep") <= hi)).distinct()


def compress(labels: DataFrame, by: tuple[str, ...] = ("g", "source", "target")) -> DataFrame:
    """Non-dominated (dep, n, arr): first over fewer transfers of the same departure; then every row
    also stands for the larger n that its pair has, and over later departures (and fewer transfers of
    the same one) a running minimum per n tells whether something as good left no earlier."""
    inside = Window.partitionBy(*by, "dep").orderBy("n", "arr").rowsBetween(Window.unboundedPreceding, -1)
    x = labels.withColumn("b1", F.min("arr").over(inside)).where("b1 is null or arr < b1").drop("b1")
    steps = x.select(*by, "n").distinct().withColumnRenamed("n", "m")
    spread = x.join(steps, list(by)).where("m >= n")
    w = Window.partitionBy(*by, "m").orderBy(F.desc("dep"), "n", "arr").rowsBetween(Window.unboundedPreceding, -1)
    return spread.withColumn("b2", F.min("arr").over(w)).where("m = n and (b2 is null or arr < b2)").drop("b2", "m")


def _lanes(net, groups, lo, hi):
    d = departures(net, groups, lo, hi)
    return groups.join(d, "source").select("g", "source", "dep")


def fanout_segments(net: Network, transfers: DataFrame, groups: DataFrame, targets: DataFrame, lo: int, hi: int, k: int = 4, scope: bool = True, with_legs: bool = False, count: bool = False) -> Profile:
    """All departures in lo..hi of every group (g, source) to its targets (g, target) in k + 1 rounds.

    The frontier is keyed by (g, departure) and has no target column, so a segment is scanned once for
    all targets; with one target per group this is the plain range search, run once per pair. Departures
    are lanes of one computation instead of a loop: later lanes' segments prune earlier ones of the
    same trip, labels pass from later to earlier departures. A lane expands what still arrives before
    the largest label of its targets; scope drops targets that no segment of the lane can improve."""
    keys = ["g", "dep"]
    lens = net.route_stops.groupBy("route_id").agg(F.max("idx").alias("last"))
    near = net.neighbourhood().select(F.col("a").alias("stop_id"), F.col("b").alias("target"), F.col("secs").alias("walk"))
    hits = written(targets.join(near, "target").join(net.route_stops.where("idx > 0"), "stop_id").select("g", "target", "route_id", F.col("idx").alias("at"), "walk"))
    wanted = targets.groupBy("g").agg(F.countDistinct("target").alias("wanted"))
    lanes = written(_lanes(net, groups, lo, hi))
    ids = net.trips.select("route_id", "rank", "trip_id")
    c = first_boards(net, lanes, keys)
    if with_legs:
        c = c.withColumn("legs", F.expr(f"cast(array() as {LEGS})"))
    reached, labels, active, work = None, None, None, []
    inherit = Window.partitionBy("g", "target").orderBy(F.desc("dep")).rowsBetween(Window.unboundedPreceding, 0)
    for n in range(k + 1):
        frontier = written(enqueue(reached, c, lens, keys, lanes=True).join(ids, ["route_id", "rank"]))
        now = frontier.select(*keys, "route_id", "rank", "idx")
        reached = now if reached is None else reached.unionByName(now)
        checks = frontier.join(hits, ["g", "route_id"]).where("at > idx and at <= to_idx")
        if active is not None and scope:
            checks = checks.join(active, ["g", "dep", "target"], "left_anti")
        scored = times_at(checks, net, "at", "t").withColumn("arr", (F.col("t") + F.col("walk")).cast("int"))
        if with_legs:
            ride = F.struct("trip_id", F.col("idx").alias("from_idx"), F.col("at").alias("to_idx"))
            best = scored.groupBy("g", "dep", "target").agg(F.min_by(F.concat("legs", F.array(ride)), F.struct("arr", "trip_id", "at", "idx")).alias("legs"), F.min("arr").alias("arr"))
        else:
            best = scored.groupBy("g", "dep", "target").agg(F.min("arr").alias("arr"))
        best = written(best.withColumn("n", F.lit(n)))
        labels = best if labels is None else labels.unionByName(best)
        if count:
            work.append({"n": n, "segments": frontier.count(), "target_checks": checks.count()})
        if n == k:
            break
        grid = lanes.select("g", "dep").join(targets, "g")
        least = labels.groupBy("g", "dep", "target").agg(F.min("arr").alias("arr"))
        full = grid.join(least, ["g", "dep", "target"], "left").withColumn("arr", F.min("arr").over(inherit))
        full = written(full)
        bound = full.groupBy("g", "dep").agg(F.count("arr").alias("have"), F.max("arr").alias("label")).join(wanted, "g").where("have = wanted").select("g", "dep", "label")
        nxt = times_at(frontier.withColumn("next", F.col("idx") + 1), net, "next", "soon").join(bound, keys, "left").where("label is null or soon < label")
        nxt = written(nxt)
        if scope:  # targets with a label that the lane's earliest next arrival can't beat are closed
            soonest = nxt.groupBy(*keys).agg(F.min("soon").alias("soon"))
            active = full.join(soonest, keys, "left").where("arr is not null and (soon is null or soon >= arr)").select("g", "dep", "target")
        go = nxt.join(transfers, nxt.trip_id == transfers.t1).where("i1 > idx and i1 <= to_idx")
        cols = [*keys, F.col("route2").alias("route_id"), F.col("rank2").alias("rank"), F.col("i2").alias("idx")]
        if with_legs:
            ride = F.struct("trip_id", F.col("idx").alias("from_idx"), F.col("i1").alias("to_idx"))
            c = go.select(*cols, F.concat("legs", F.array(ride)).alias("legs")).groupBy(*keys, "route_id", "rank", "idx").agg(F.min("legs").alias("legs"))
        else:
            c = go.select(*cols).distinct()
    rows = labels.join(groups, "g")
    return Profile(compress(rows).select("g", "source", "target", "dep", "n", "arr", *(["legs"] if with_legs else [])), work)


def fanout_rounds(net: Network, groups: DataFrame, targets: DataFrame, lo: int, hi: int, k: int = 4, prune: bool = True, count: bool = False) -> Profile:
    """As fanout_segments with the round router: one lane per (g, departure), all its targets at once."""
    lanes = _lanes(net, groups, lo, hi)
    lanes = written(lanes.withColumn("req_id", F.xxhash64("g", "dep")))
    goals = lanes.select("req_id", "g").join(targets, "g").select("req_id", "target")
    got = round_router.route(net, lanes.select("req_id", "source", F.lit(None).cast("long").alias("target"), "dep"), k, prune, to_all=True, targets=goals, count=count)
    rows = got.labels.withColumnRenamed("stop_id", "target").join(lanes, "req_id").select("g", "source", "target", "dep", "n", "arr")
    return Profile(compress(rows), got.work)


def as_pairs(groups: DataFrame, targets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Groups of one target each: the repeated one-to-one searches that the fan-out is measured against."""
    p = groups.join(targets, "g").withColumn("g2", F.xxhash64("g", "target"))
    return p.select(F.col("g2").alias("g"), "source").distinct(), p.select(F.col("g2").alias("g"), "target").distinct()


def groups_of(net: Network, sources: DataFrame, targets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """One group per source, all with the same short list of targets but those within a walk."""
    g = sources.select(F.col("source").alias("g"), "source").distinct()
    t = g.join(F.broadcast(targets.select("target").distinct())).select("g", "target")
    near = net.neighbourhood().select(F.col("a").alias("g"), F.col("b").alias("target"))
    return g, t.join(near, ["g", "target"], "left_anti")


def lookup(profile: DataFrame, requests: DataFrame) -> DataFrame:
    """(req_id, n, arr) of requests answered from a profile: the best of all later departures, with
    at most n transfers; improvements only."""
    p = profile.select("source", "target", F.col("dep").alias("leaves"), "n", "arr")
    got = requests.join(p, ["source", "target"]).where("leaves >= dep").groupBy("req_id", "n").agg(F.min("arr").alias("arr"))
    w = Window.partitionBy("req_id").orderBy("n").rowsBetween(Window.unboundedPreceding, -1)
    return got.withColumn("b", F.min("arr").over(w)).where("b is null or arr < b").drop("b")


def isochrone(net: Network, sources: DataFrame, budget: int, k: int = 4) -> DataFrame:
    """(req_id, stop_id, secs): stops that (req_id, source, dep) reaches within budget seconds, on foot or
    by transit."""
    least = round_router.route(net, sources.withColumn("target", F.lit(None).cast("long")), k, to_all=True).state
    least = least.join(sources.select("req_id", "dep"), "req_id")
    return least.select("req_id", "stop_id", (F.col("best") - F.col("dep")).cast("int").alias("secs")).where(F.col("secs") <= budget)


def nearest_poi(net: Network, sources: DataFrame, poi: str, most: int, k: int = 4) -> DataFrame:
    """The most stops of a class that are reached first: (req_id, place, stop_id, arr)."""
    least = round_router.route(net, sources.withColumn("target", F.lit(None).cast("long")), k, to_all=True).state
    least = least.select("req_id", "stop_id", F.col("best").alias("arr")).join(net.stops.where(F.col("poi") == poi).select("stop_id"), "stop_id")
    w = Window.partitionBy("req_id").orderBy("arr", "stop_id")
    return least.withColumn("place", F.row_number().over(w)).where(F.col("place") <= most).select("req_id", "place", "stop_id", "arr")


def location_pairs(net: Network, members: DataFrame, pairs: DataFrame, k: int = 4) -> DataFrame:
    """(req_id, arr): earliest arrival between locations, sets of stops (location, stop_id), for pairs
    (req_id, from_location, to_location, dep)."""
    froms = pairs.join(members.select(F.col("location").alias("from_location"), F.col("stop_id").alias("source")), "from_location")
    lanes = froms.select(F.xxhash64("req_id", "source").alias("lane"), "req_id", "source", "to_location", "dep")
    goals = lanes.join(members.select(F.col("location").alias("to_location"), F.col("stop_id").alias("target")), "to_location").select(F.col("lane").alias("req_id"), "target")
    got = round_router.route(net, lanes.select(F.col("lane").alias("req_id"), "source", F.lit(None).cast("long").alias("target"), "dep"), k, to_all=True, targets=goals).labels
    return got.join(lanes.select(F.col("lane").alias("l_"), F.col("req_id").alias("r_")), F.col("req_id") == F.col("l_")).groupBy(F.col("r_").alias("req_id")).agg(F.min("arr").alias("arr"))
