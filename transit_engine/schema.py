"""The relational timetable: what every network holds, and the schemas of its frames."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

STOPS = "stop_id bigint, region int, pos int, poi string"
ROUTES = "route_id bigint, len int, stops array<bigint>"
ROUTE_STOPS = "route_id bigint, idx int, stop_id bigint"
TRIPS = "trip_id bigint, route_id bigint, rank int, start int"
EVENTS = "trip_id bigint, route_id bigint, rank int, idx int, stop_id bigint, arr int, dep int"
WALKS = "a bigint, b bigint, secs int"
TRANSFERS = "t1 bigint, i1 int, t2 bigint, i2 int"
REQUESTS = "req_id bigint, source bigint, target bigint, dep int"
LEGS = "array<struct<trip_id:bigint,from_idx:int,to_idx:int>>"
LABELS = "req_id bigint, n int, arr int"
PROFILE = "source bigint, target bigint, dep int, n int, arr int"
#: Ids of a network in a batch of several are shifted by its number times this.
NETWORK_SPAN = 10**12


@dataclass(frozen=True)
class Network:
    """A timetable of one service day. walks are closed under composition, without self rows;
    headway (route_id, first, step, trips) is there only if every route runs at a constant one."""

    name: str
    stops: DataFrame
    route_stops: DataFrame
    trips: DataFrame
    events: DataFrame
    walks: DataFrame
    headway: DataFrame | None = None
    offsets: DataFrame | None = None

    @property
    def routes(self) -> DataFrame:
        listed = F.array_sort(F.collect_list(F.struct("idx", "stop_id")))
        return self.route_stops.groupBy("route_id").agg(F.count("*").cast("int").alias("len"), F.transform(listed, lambda s: s["stop_id"]).alias("stops"))

    def neighbourhood(self) -> DataFrame:
        """(a, b, secs): every stop with itself at 0 seconds, and its walks."""
        own = self.stops.select(F.col("stop_id").alias("a"), F.col("stop_id").alias("b"), F.lit(0).alias("secs"))
        return own.unionByName(self.walks.select("a", "b", "secs"))

    def with_(self, **frames) -> "Network":
        return replace(self, **frames)


def stack(networks: list[Network], name: str = "stack") -> Network:
    """Several networks (or service days) as one batch: ids are shifted apart, so no key needs a
    second column and nothing can join across networks."""
    ids = {"stop_id", "route_id", "trip_id", "a", "b"}

    def shifted(df: DataFrame | None, k: int):
        return df and df.select(*[(F.col(c) + F.lit(k * NETWORK_SPAN)).alias(c) if c in ids else F.col(c) for c in df.columns])

    out = {}
    for part in ("stops", "route_stops", "trips", "events", "walks", "headway", "offsets"):
        frames = [shifted(getattr(n, part), k) for k, n in enumerate(networks)]
        if any(f is None for f in frames):
            out[part] = None
            continue
        total = frames[0]
        for f in frames[1:]:
            total = total.unionByName(f)
        out[part] = total
    return Network(name, **out)


def struct(ddl: str) -> T.StructType:
    return T.StructType.fromDDL(ddl)
