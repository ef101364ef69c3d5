"""Networks and requests computed from the given tables, with integer arithmetic only."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import footpaths
from .hypergraph import walk_node
from .schema import EVENTS, ROUTE_STOPS, STOPS, TRIPS, WALKS, Network
from .storage import once, written

#: Seconds of the service day: first departures from, and the end.
DAY_START, DAY_END = 18000, 86400
#: Walking limits in seconds: friendly networks, hostile networks.
NEAR_LIMIT, FAR_LIMIT = 180, 120


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _in_region(spark, sf_dir, table, key, nation_key):
    nation = _table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias(nation_key), F.col("n_regionkey").cast("int").alias("region"))
    return _table(spark, sf_dir, table).join(nation, nation_key)


def stops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per region the customers of least key, three per supplier of the region and six more."""
    many = _in_region(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey").groupBy("region").agg((F.count("*") * 3 + 6).alias("most"))
    rank = F.row_number().over(Window.partitionBy("region").orderBy("c_custkey")) - 1
    c = _in_region(spark, sf_dir, "customer", "c_custkey", "c_nationkey").withColumn("pos", rank)
    return c.join(many, "region").where("pos < most").select(
        F.col("c_custkey").cast("long").alias("stop_id"), "region", F.col("pos").cast("int").alias("pos"), F.col("c_mktsegment").alias("poi")
    )


def _first_visits(visits: DataFrame) -> DataFrame:
    """(route_id, i, stop_id) with later visits to a stop dropped and indices made dense."""
    first = visits.groupBy("route_id", "stop_id").agg(F.min("i").alias("i"))
    idx = F.row_number().over(Window.partitionBy("route_id").orderBy("i")) - 1
    return first.select("route_id", idx.cast("int").alias("idx"), "stop_id")


def _both_ways(k_stops: DataFrame) -> DataFrame:
    """(k, i, n, stop_id) of suppliers as routes 2k and, backwards, 2k + 1."""
    there = k_stops.select((F.col("k") * 2).alias("route_id"), "i", "stop_id")
    back = k_stops.select((F.col("k") * 2 + 1).alias("route_id"), (F.col("n") - 1 - F.col("i")).alias("i"), "stop_id")
    return there.unionByName(back)


def _supplier_visits(spark, sf_dir, places: DataFrame, mesh: bool) -> DataFrame:
    s = _in_region(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey").select(F.col("s_suppkey").cast("long").alias("k"), F.col("region").alias("home"))
    s = s.withColumns({"step": 1 + F.col("k") % 3, "plain": (6 + F.col("k") % 5).cast("int"), "trunk": F.col("k") % 10 == 9})
    s = s.withColumn("n", F.col("plain") if mesh else F.when(F.col("trunk"), 5).otherwise(F.col("plain")))
    s = s.withColumn("i", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    if mesh:
        order = F.row_number().over(Window.orderBy("region", "pos")) - 1
        numbered = places.withColumn("g", order)
        total = numbered.agg(F.count("*").alias("total"))
        s = s.join(F.broadcast(total)).withColumn("g", (F.col("k") * 37 + F.col("i") * (F.col("step") * 17 + 1)) % F.col("total"))
        return s.join(numbered.select("g", "stop_id"), "g").select("k", "i", "n", "stop_id")
    size = places.groupBy("region").agg(F.count("*").alias("m"))
    s = s.withColumn("region", F.when(F.col("trunk"), (F.col("home") + F.col("i")) % 5).otherwise(F.col("home")).cast("int")).join(size, "region")
    pos = F.when(F.col("trunk") | ((F.col("i") == 0) & (F.col("k") % 3 == 0)), 0).otherwise(1 + (F.col("k") * 37 + F.col("i") * F.col("step")) % (F.col("m") - 1))
    return s.withColumn("pos", pos.cast("int")).join(places.select("region", "pos", "stop_id"), ["region", "pos"]).select("k", "i", "n", "stop_id")


def _timetabled(name: str, places: DataFrame, route_stops: DataFrame, walks: DataFrame) -> Network:
    """Trips at a constant headway over route_stops; a leg takes 2 to 6 minutes by its stops."""
    byr = Window.partitionBy("route_id").orderBy("idx")
    leg = 120 + 60 * ((F.lag("stop_id").over(byr) + F.col("stop_id")) % 5)
    offsets = route_stops.withColumn("leg", F.coalesce(leg, F.lit(0)))
    offsets = offsets.select("route_id", "idx", "stop_id", F.sum("leg").over(byr).cast("int").alias("offset"))
    k = F.floor(F.col("route_id") / 2)
    headway = route_stops.select("route_id").distinct().select(
        "route_id", (DAY_START + F.col("route_id") % 7 * 60).cast("int").alias("first"), (600 + 300 * (k % 4)).cast("int").alias("step")
    )
    headway = headway.withColumn("trips", F.ceil((DAY_END - F.col("first")) / F.col("step")).cast("int"))
    trips = headway.withColumn("rank", F.explode(F.sequence(F.lit(0), F.col("trips") - 1))).select(
        (F.col("route_id") * 1000 + F.col("rank")).alias("trip_id"), "route_id", "rank", (F.col("first") + F.col("rank") * F.col("step")).alias("start")
    )
    # trips spread out behind the join: the planner takes exploded rows for as few as the routes and would broadcast all trips
    runs = offsets.join(headway.hint("merge"), "route_id").withColumn("rank", F.explode(F.sequence(F.lit(0), F.col("trips") - 1)))
    when = (F.col("first") + F.col("rank") * F.col("step") + F.col("offset")).cast("int")
    events = runs.select((F.col("route_id") * 1000 + F.col("rank")).alias("trip_id"), "route_id", "rank", "idx", "stop_id", when.alias("arr"), when.alias("dep"))
    return Network(name, places, route_stops, trips, events, walks, headway, offsets.select("route_id", "idx", "stop_id", "offset"))


def raw_walks(places: DataFrame) -> DataFrame:
    """Undirected neighbours inside a region, by position (a < b is not implied)."""
    at = lambda p, n: places.select("region", F.col("pos").alias(p), F.col("stop_id").alias(n))
    q = F.floor(F.col("p") / 4)
    near = at("p", "a").join(at("p2", "b"), "region").where("p2 = p + 1")
    secs = F.when(F.col("p") % 4 == 0, 90 + 30 * (q % 4)).when((F.col("p") % 4 == 1) & (q % 3 == 0), 100 + 20 * (q % 6))
    return near.select("a", "b", secs.cast("int").alias("secs")).where("secs is not null")


def _build(spark, sf_dir, mesh: bool, limit: int | None = None) -> Network:
    places = written(stops(spark, sf_dir))
    rs = written(_first_visits(_both_ways(_supplier_visits(spark, sf_dir, places, mesh))))
    walks = written(footpaths.close(footpaths.from_distance(raw_walks(places), limit=limit or (FAR_LIMIT if mesh else NEAR_LIMIT))))
    net = _timetabled("mesh" if mesh else "regional", places, rs, walks)
    return net.with_(events=written(net.events), trips=written(net.trips), headway=written(net.headway), offsets=written(net.offsets))


def regional(spark: SparkSession, sf_dir: str) -> Network:
    """Routes stay in their region, joined by trunks: easy to split into cells."""
    return once(spark, f"regional {sf_dir}", lambda: _build(spark, sf_dir, False))


def mesh(spark: SparkSession, sf_dir: str) -> Network:
    """Routes spread over all regions: hard to split."""
    return once(spark, f"mesh {sf_dir}", lambda: _build(spark, sf_dir, True))


def line_groups(spark: SparkSession, sf_dir: str, net: Network) -> DataFrame:
    """(node_id, into): ten groups of routes and walks, by home region (a walk's: of its lesser end) and
    whether a trunk: 2 * region, + 1 for trunks."""
    s = _in_region(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey").select(F.col("s_suppkey").cast("long").alias("k"), "region")
    group = (F.col("region") * 2 + (F.col("k") % 10 == 9).cast("int")).cast("long")
    routes = s.select(F.explode(F.array(F.col("k") * 2, F.col("k") * 2 + 1)).alias("node_id"), group.alias("into"))
    walks = net.walks.where("a < b").join(net.stops.select(F.col("stop_id").alias("a"), "region"), "a")
    return routes.unionByName(walks.select(walk_node("a", "b").alias("node_id"), (F.col("region") * 2).cast("long").alias("into")))


#: The toy network (fixed values): stops of five routes, a start every 600 s from 08:00, legs of 600 s.
TOY_ROUTES = {1: (0, 2, 3), 2: (0, 5, 8), 3: (2, 6, 9), 4: (8, 9), 5: (9, 7, 100)}
TOY_WALK = (3, 100, 2400)
TOY_SLOTS = 8


def toy(spark: SparkSession) -> Network:
    """Five routes and one long walk; stop 100 is the destination."""

    def make():
        ids = sorted({s for r in TOY_ROUTES.values() for s in r})
        places = spark.createDataFrame([(s, 0, i, "toy") for i, s in enumerate(ids)], STOPS)
        rs = spark.createDataFrame([(r, i, s) for r, ss in TOY_ROUTES.items() for i, s in enumerate(ss)], ROUTE_STOPS)
        trips = spark.createDataFrame([(5 * k + r, r, k, 28800 + 600 * k) for r in TOY_ROUTES for k in range(TOY_SLOTS)], TRIPS)
        t = F.col("start") + 600 * F.col("idx")
        events = trips.join(rs, "route_id").select("trip_id", "route_id", "rank", "idx", "stop_id", t.alias("arr"), t.alias("dep"))
        a, b, secs = TOY_WALK
        walks = spark.createDataFrame([(a, b, secs), (b, a, secs)], WALKS)
        hw = spark.createDataFrame([(r, 28800, 600, TOY_SLOTS) for r in TOY_ROUTES], "route_id bigint, first int, step int, trips int")
        off = rs.withColumn("offset", (600 * F.col("idx")).cast("int"))
        return Network("toy", places, rs, trips, written(events.select(*[f.split()[0] for f in EVENTS.split(", ")])), walks, hw, off)

    return once(spark, "toy", make)


def chain_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as trips over suppliers, days as times: (trip_id, idx, stop_id, arr). The first line of a
    supplier counts; orders with one supplier only are no trips."""
    day = F.datediff(F.col("l_shipdate"), F.lit("1970-01-01"))
    l = _table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").cast("long").alias("trip_id"), F.col("l_suppkey").cast("long").alias("stop_id"), day.alias("arr"), F.struct("l_shipdate", "l_linenumber", "l_partkey").alias("o"))
    first = l.groupBy("trip_id", "stop_id").agg(F.min(F.struct("o", "arr")).alias("m")).select("trip_id", "stop_id", F.col("m.o").alias("o"), F.col("m.arr").alias("arr"))
    w = Window.partitionBy("trip_id")
    d = first.withColumns({"idx": F.row_number().over(w.orderBy("o")) - 1, "size": F.count("*").over(w)})
    return d.where("size > 1").select("trip_id", F.col("idx").cast("int").alias("idx"), "stop_id", "arr")


def log_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event log as an observed feed: (vehicle, ts, stop_id, event_id)."""
    stop = F.get_json_object("props", "$.k").cast("long")
    return _table(spark, sf_dir, "events").select(F.col("user_id").alias("vehicle"), "ts", stop.alias("stop_id"), "event_id", "value")


def requests(spark: SparkSession, sf_dir: str, net: Network, most: int | None = None) -> DataFrame:
    """Orders as travel requests between served stops; pairs within walking reach are no requests.
    most: only orders with keys below most + 1 (the workload's size)."""
    served = net.route_stops.select("stop_id").distinct()
    served = served.withColumn("at", F.row_number().over(Window.orderBy("stop_id")) - 1)
    n = served.agg(F.count("*").alias("n"))
    o = _table(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("long").alias("req_id"), F.col("o_custkey").cast("long").alias("c"))
    if most is not None:
        o = o.where(F.col("req_id") <= most)
    o = o.join(F.broadcast(n)).select(
        "req_id", (F.col("c") % F.col("n")).alias("sa"), ((F.col("req_id") * 7919 + 13) % F.col("n")).alias("ta"), (DAY_START + F.col("req_id") % 1200 * 30).cast("int").alias("dep")
    )
    pick = lambda k, name: served.select(F.col("at").alias(k), F.col("stop_id").alias(name))
    o = o.join(pick("sa", "source"), "sa").join(pick("ta", "target"), "ta")
    near = net.neighbourhood().select(F.col("a").alias("source"), F.col("b").alias("target"))
    return o.join(near, ["source", "target"], "left_anti").select("req_id", "source", "target", "dep")
