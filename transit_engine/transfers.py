"""Trip-to-trip transfers: all feasible ones, and those worth keeping."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .asof import earliest
from .kernels import MOST_EVENTS, Arrays
from .schema import Network
from .storage import once, written

_KINDS = (pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int32())
SCHEMA = "t1 bigint, i1 int, t2 bigint, i2 int, route2 bigint, rank2 int"


def generate(net: Network, change_secs: int = 0, events: DataFrame | None = None) -> DataFrame:
    """From every event but a trip's first, over every walk or on the spot, to the earliest trip of every
    route that leaves there; not to the same or a later trip of the route at the same or a later index.
    events: those of the trips to transfer from, where not all are asked for."""
    lens = net.route_stops.groupBy("route_id").agg(F.max("idx").alias("last"))
    boards = net.route_stops.join(lens, "route_id").where("idx < last").select(F.col("route_id").alias("r2"), F.col("idx").alias("i2"), F.col("stop_id").alias("b"))
    e = (net.events if events is None else events).where("idx > 0").select(F.col("trip_id").alias("t1"), F.col("route_id").alias("r1"), F.col("rank").alias("k1"), F.col("idx").alias("i1"), F.col("stop_id").alias("a"), "arr")
    probes = e.join(net.neighbourhood(), "a").join(boards, "b").select(
        "t1", "r1", "k1", "i1", F.col("r2").alias("route_id"), F.col("i2").alias("idx"), (F.col("arr") + F.col("secs") + change_secs).alias("tau")
    )
    got = earliest(probes, net).where("not (route_id = r1 and rank >= k1 and idx >= i1)")
    ids = net.trips.select("route_id", "rank", F.col("trip_id").alias("t2"))
    return got.join(ids, ["route_id", "rank"]).select("t1", "i1", "t2", F.col("idx").alias("i2"), F.col("route_id").alias("route2"), F.col("rank").alias("rank2")).distinct()


def weakly_reduced(net: Network, found: DataFrame) -> DataFrame:
    """Transfers that reach some stop of the new trip, or one near it, before staying aboard does: a
    relational superset of the full reduction."""
    e = net.events.select("trip_id", "idx", "stop_id", "arr")
    near = net.neighbourhood()
    stay = e.join(near, e.stop_id == near.a).select(F.col("trip_id").alias("t1"), F.col("idx").alias("j"), "b", (F.col("arr") + F.col("secs")).alias("stay"))
    gain = found.join(e.select(F.col("trip_id").alias("t2"), F.col("idx").alias("j2"), F.col("stop_id").alias("a"), "arr"), "t2").where("j2 > i2")
    gain = gain.join(near, "a").select("t1", "i1", "t2", "i2", "b", (F.col("arr") + F.col("secs")).alias("go"))
    # only what staying aboard reaches from here on counts
    best = gain.join(stay, ["t1", "b"], "left").groupBy("t1", "i1", "t2", "i2", "b", "go").agg(F.min(F.when(F.col("j") >= F.col("i1"), F.col("stay"))).alias("stay"))
    useful = best.where("stay is null or go < stay").select("t1", "i1", "t2", "i2").distinct()
    return found.join(useful, ["t1", "i1", "t2", "i2"], "left_semi")


def _useful(own: list, hops: list[tuple], drop_uturn: bool) -> list[int]:
    """Which of a trip's transfers (i1, route2, i2, t2, reach of t2) stay. own and reach: per index the
    stops met there, (stop, time) with the trip's own stop first and then those that it walks to."""
    state: dict[int, int] = {}

    def lower(met) -> bool:
        better = False
        for stop, t in met:
            if state.get(stop, 1 << 60) > t:
                state[stop] = t
                better = True
        return better

    keep, at = [], len(own)
    for k in sorted(range(len(hops)), key=lambda k: (-hops[k][0], *hops[k][1:4])):
        i1, _, i2, _, reach = hops[k]
        while at > i1:
            at -= 1
            lower(own[at])
        if drop_uturn and i1 and reach[i2 + 1][0][0] == own[i1 - 1][0][0] and reach[i2][0][0] == own[i1][0][0] and reach[i2 + 1][0][1] >= own[i1 - 1][0][1]:
            continue
        if sum([lower(reach[j]) for j in range(i2 + 1, len(reach))]):
            keep.append(k)
    return keep


def _by_trip(batches):
    """(t1, rows) of consecutive rows of one trip, through all batches; first column t1."""
    trip, rows = None, []
    for b in batches:
        for r in zip(*(c.to_pylist() for c in b.columns), strict=True):
            if r[0] != trip and rows:
                yield trip, rows
                rows = []
            trip = r[0]
            rows.append(r)
    if rows:
        yield trip, rows


_REACH = "array<array<struct<stop:bigint,t:int>>>"


def reduced(net: Network, found: DataFrame, drop_uturn: bool = True, most_events: int = MOST_EVENTS) -> DataFrame:
    """Keeps a transfer if it lowers the arrival at some stop below what staying aboard and the
    transfers kept before give. A trip is scanned from its last index; inside an index by route, index
    and trip; ties lose. Trips are independent, so each is one run of sorted rows, whatever the
    timetable. A timetable of most_events or less is broadcast (16 bytes an event); with a larger one
    every transfer brings along what its two trips reach, in shuffled joins, with the same result."""
    cols = ["t1", "i1", "t2", "i2", "route2", "rank2"]
    if net.events.count() <= most_events:
        a = Arrays(net)
        walks: dict[int, list] = {}
        for x, y, w in zip(a.ids[a.walk_a].tolist(), a.ids[a.walk_b].tolist(), a.walk_s.tolist(), strict=True):
            walks.setdefault(x, []).append((y, w))
        place = {int(t): (r, k) for r, (_, ids) in enumerate(a.trips) for k, t in enumerate(ids)}
        sent = found.sparkSession.sparkContext.broadcast((a, walks, place))

        def scan(batches):
            a, walks, place = sent.value
            seen: dict[int, list] = {}

            def reach(trip):
                if trip not in seen:
                    if len(seen) > 20_000:
                        seen.clear()
                    r, k = place[trip]
                    stops, times = a.routes[r]
                    seen[trip] = [[(s, t), *((b, t + w) for b, w in walks.get(s, ()))] for s, t in zip(a.ids[stops].tolist(), times[:, k].tolist(), strict=True)]
                return seen[trip]

            for trip, rows in _by_trip(batches):
                got = _useful(reach(trip), [(r[1], r[4], r[3], r[2], reach(r[2])) for r in rows], drop_uturn)
                if got:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*(rows[k] for k in got), strict=True), _KINDS, strict=True)], names=cols)

        return found.select(*cols).repartition("t1").sortWithinPartitions("t1").mapInArrow(scan, SCHEMA)

    near = net.neighbourhood()
    trips = found.select(F.col("t1").alias("trip_id")).union(found.select("t2")).distinct()
    met = net.events.join(trips, "trip_id", "left_semi").join(near, F.col("stop_id") == F.col("a")).groupBy("trip_id", "idx").agg(F.sort_array(F.collect_list(F.struct("secs", F.col("b").alias("stop"), (F.col("arr") + F.col("secs")).cast("int").alias("t")))).alias("m"))
    met = met.select("trip_id", "idx", F.transform("m", lambda x: F.struct(x["stop"].alias("stop"), x["t"].alias("t"))).alias("m"))
    full = written(met.groupBy("trip_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("idx", "m"))), lambda x: x["m"]).cast(_REACH).alias("reach")))
    rows = found.select(*cols).join(full.select(F.col("trip_id").alias("t2"), "reach"), "t2").select(*cols, "reach", F.lit(None).cast(_REACH).alias("own"))
    # a trip's own reach comes once, ahead of its transfers, not with each
    heads = found.select("t1").distinct().join(full.select(F.col("trip_id").alias("t1"), F.col("reach").alias("own")), "t1")
    rows = rows.unionByName(heads, allowMissingColumns=True)
    pairs = lambda reach: [[(x["stop"], x["t"]) for x in met] for met in reach]

    def scan_wide(batches):
        for _, (head, *rows) in _by_trip(batches):
            got = _useful(pairs(head[7]), [(r[1], r[4], r[3], r[2], pairs(r[6])) for r in rows], drop_uturn)
            if got:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*(rows[k][:6] for k in got), strict=True), _KINDS, strict=True)], names=cols)

    return rows.repartition("t1").sortWithinPartitions("t1", F.col("own").isNull()).mapInArrow(scan_wide, SCHEMA)


def of(net: Network, key: str, reduce: bool = True) -> DataFrame:
    """Written transfers of a network, built once per session; key names the network's data."""
    spark = net.events.sparkSession
    raw = once(spark, f"transfers all {key}", lambda: written(generate(net).repartition("t1").sortWithinPartitions("t1", "i1")))
    if not reduce:
        return raw
    return once(spark, f"transfers reduced {key}", lambda: written(reduced(net, raw).repartition("t1").sortWithinPartitions("t1", "i1")))


def sizes(raw: DataFrame, kept: DataFrame) -> DataFrame:
    return raw.agg(F.count("*").alias("transfers_all")).join(kept.agg(F.count("*").alias("transfers_kept")))


def per_event_rank(found: DataFrame) -> DataFrame:
    """How many transfers every (trip, index) offers, and their order by arrival index."""
    return found.withColumn("nth", F.row_number().over(Window.partitionBy("t1", "i1").orderBy("route2", "i2", "t2")))
