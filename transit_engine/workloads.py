"""The named queries: worked examples, network measures, searches, cells, fill-in, surrounding operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import cells, derive, event_graph, fillin, footpaths, hypergraph, journeys, kernels, metrics, nested, oracles, partition, range_router, round_router, segment_router, streaming, timetable, transfers
from .storage import once, written

#: Requests of the workload that SQL texts repeat, and of the timed one; the *_all queries take every order.
FEW, MANY = 200, 10_000
K = 4
RANGE = (25200, 28800)

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _r(spark, d):
    return derive.regional(spark, d)


def _m(spark, d):
    return derive.mesh(spark, d)


def _requests(spark, d, net=None) -> DataFrame:
    net = net or _r(spark, d)
    return once(spark, f"requests {net.name} {d}", lambda: written(derive.requests(spark, d, net, FEW)))


def _all_requests(spark, d, net=None) -> DataFrame:
    net = net or _r(spark, d)
    return once(spark, f"all requests {net.name} {d}", lambda: written(derive.requests(spark, d, net)))


def _transfers(spark, d, net=None, reduce=True):
    net = net or _r(spark, d)
    return transfers.of(net, f"{net.name} {d}", reduce)


def _events(spark, d):
    return spark.read.parquet(f"{d}/events.parquet")


# --- the toy network ----------------------------------------------------------------------------

def _toy_request(spark):
    return spark.createDataFrame([(1, 0, 100, 28800)], "req_id bigint, source bigint, target bigint, dep int")


@query("SELECT * FROM (VALUES (1::BIGINT, 0, 32400), (1, 2, 31800)) t(req_id, n, arr)")
def toy_pareto(spark: SparkSession, sf_dir: str) -> DataFrame:
    net = derive.toy(spark)
    return journeys.pareto(segment_router.route(net, _toy_request(spark), transfers.of(net, "toy"), K).labels)


#: Trips of routes 1 to 4 of ranks 0, 0, 1 and 2, as the toy's trips 1, 2, 8 and 14 were.
_WORKED = "(1000, 2000, 3001, 4002)"


# a transfer stays if it reaches some stop before its trip from there on and all transfers ahead of it do
@query(oracles.with_(oracles.XFER + f""",
fx AS MATERIALIZED (SELECT DISTINCT t1, i1, t2, i2, route2 FROM tf WHERE t1 IN {_WORKED} AND NOT (route2 = r1 AND rank2 >= k1 AND i2 >= i1)),
nu AS MATERIALIZED (SELECT fx.* FROM fx JOIN ev a ON a.trip_id = t1 AND a.idx = i1 - 1 JOIN ev b ON b.trip_id = t1 AND b.idx = i1 JOIN ev c ON c.trip_id = t2 AND c.idx = i2 JOIN ev d ON d.trip_id = t2 AND d.idx = i2 + 1
  WHERE NOT (d.stop_id = a.stop_id AND c.stop_id = b.stop_id AND d.arr >= a.arr)),
mt AS (SELECT t1, i1, 1 AS kind, route2, i2, t2, nb.b AS stop_id, min(e.arr + secs) AS t FROM nu JOIN ev e ON e.trip_id = t2 AND e.idx > i2 JOIN nb ON nb.a = e.stop_id GROUP BY ALL
  UNION ALL SELECT trip_id, idx, 0, 0, 0, 0, nb.b, arr + secs FROM ev JOIN nb ON nb.a = ev.stop_id WHERE trip_id IN {_WORKED}),
sn AS (SELECT *, min(t) OVER (PARTITION BY t1, stop_id ORDER BY -i1, kind, route2, i2, t2 ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS known FROM mt)
SELECT DISTINCT t1, i1::INT AS i1, t2, i2::INT AS i2 FROM sn WHERE kind = 1 AND (known IS NULL OR t < known)"""))
def toy_transfers(spark, sf_dir):
    """The transfers worth keeping of four trips of the regional network."""
    net = _r(spark, sf_dir)
    found = written(transfers.generate(net, events=net.events.where(f"trip_id in {_WORKED}")))
    return transfers.reduced(net, found).select("t1", "i1", "t2", "i2")


@query(oracles.with_(oracles.CELLS.strip() + "\nSELECT stop_id FROM sc WHERE cell = 0", mesh=True))
def toy_cut_stops(spark, sf_dir):
    net = _m(spark, sf_dir)
    return cells.cut_stops(cells.stop_cells(net, cells.natural(net)))


@query(oracles.with_(oracles.HYPER.strip() + "\nSELECT stop_id, count(DISTINCT node_id) AS pins FROM inc GROUP BY stop_id HAVING count(DISTINCT node_id) > 1", mesh=True))
def toy_hyperedges(spark, sf_dir):
    at = hypergraph.incidence(_m(spark, sf_dir))
    return at.groupBy("stop_id").agg(F.countDistinct("node_id").alias("pins")).where("pins > 1")


#: The mesh network's stops over its ten groups of routes and walks, every assignment to three cells tried.
_ALL_PARTITIONS = oracles.with_(oracles.HYPER.strip() + """,
gr AS (SELECT unnest([2 * k, 2 * k + 1]) AS node_id, 2 * home + trunk::INT AS g FROM sup UNION ALL SELECT node_id, 2 * region FROM wn JOIN st ON st.stop_id = a),
gw AS (SELECT g, count(*) AS w FROM gr WHERE node_id IN (SELECT node_id FROM inc) GROUP BY g),
e AS MATERIALIZED (SELECT m, count(*) AS w FROM (SELECT stop_id, bit_or(1 << g) AS m FROM inc JOIN gr USING (node_id) GROUP BY stop_id HAVING count(DISTINCT g) > 1) GROUP BY m),
a AS (SELECT i, g, (i // (3 ** g)::BIGINT) % 3 AS c, w FROM range(0, 59049) r(i), gw),
l AS (SELECT i, c, sum(w) AS w, sum(1 << g)::INT AS m FROM a GROUP BY i, c),
ok AS MATERIALIZED (SELECT i, max(m) FILTER (c = 0) AS m0, max(m) FILTER (c = 1) AS m1, max(m) FILTER (c = 2) AS m2 FROM l GROUP BY i HAVING count(*) = 3 AND 6 * min(w) >= sum(w) AND 2 * max(w) <= sum(w)),
u AS (SELECT i, coalesce(sum(w) FILTER ((m & m0) = m OR (m & m1) = m OR (m & m2) = m), 0) AS uncut FROM ok, e GROUP BY i)
SELECT 3::BIGINT AS cells, max(uncut)::DOUBLE AS uncut FROM u""", mesh=True)


def _line_groups(spark, d):
    """The hypergraph of unit weights over groups of routes and walks, and the least and greatest weight of one of three cells: half and one and a half of the mean."""

    def make():
        net = _m(spark, d)
        h = partition.grouped(_hyper(spark, d, 1, net), written(derive.line_groups(spark, d, net)))
        total = h.nodes.agg(F.sum("weight")).first()[0] or 0.0
        return h, total / 6, total / 2

    return once(spark, f"line groups {d}", make)


@query(_ALL_PARTITIONS)
def partition_exact_toy_quality(spark, sf_dir):
    """How many cells keep the bounds, and the weight of uncut edges, which is the greatest possible."""
    h, lo, hi = _line_groups(spark, sf_dir)
    c = written(partition.exact(spark, h, 3, lo, hi))
    load = c.join(h.nodes, "node_id").groupBy("cell").agg(F.sum("weight").alias("w")).where(F.col("w").between(lo, hi))
    q = metrics.partition_quality(h, c)
    return load.agg(F.count("*").alias("cells")).join(F.broadcast(q.select((F.col("all_weight") - F.col("cut_weight")).alias("uncut"))))


@query()
def partition_exact_toy(spark, sf_dir):
    h, lo, hi = _line_groups(spark, sf_dir)
    return partition.exact(spark, h, 3, lo, hi)


# --- networks -----------------------------------------------------------------------------------

@query(oracles.with_(oracles.HYPER.strip() + "\n" + oracles.STATS))
def net_stats_regional(spark, sf_dir):
    return metrics.network_stats(_r(spark, sf_dir))


@query(oracles.with_(oracles.HYPER.strip() + "\n" + oracles.STATS, mesh=True))
def net_stats_mesh(spark, sf_dir):
    return metrics.network_stats(_m(spark, sf_dir))


@query("WITH " + oracles.CHAINS.strip() + """,
s AS (SELECT trip_id, list(stop_id ORDER BY idx) AS stops FROM ce GROUP BY trip_id)
SELECT (SELECT count(*) FROM s) AS trips, (SELECT count(*) FROM ce) AS stop_events, (SELECT count(DISTINCT stops) FROM s) AS routes, (SELECT count(DISTINCT stop_id) FROM ce) AS served""")
def net_stats_chains(spark, sf_dir):
    e = derive.chain_events(spark, sf_dir)
    r = timetable.derive_routes(e)
    a = e.agg(F.count("*").alias("stop_events"), F.countDistinct("stop_id").alias("served"))
    return a.join(F.broadcast(r.agg(F.count("*").alias("trips"), F.countDistinct("route_id").alias("routes"))))


_TOPO = """SELECT {net} AS net, (SELECT round(avg(k), 6) FROM (SELECT count(*) AS k FROM rs GROUP BY route_id)) AS stops_per_route,
(SELECT round(avg(k), 6) FROM (SELECT count(DISTINCT route_id) AS k FROM rs GROUP BY stop_id)) AS routes_per_stop, (SELECT round(avg(k), 6) FROM (SELECT count(*) AS k FROM ev GROUP BY stop_id)) AS events_per_stop,
(SELECT count(*) FROM sc WHERE cell = 0) AS cut_stops, (SELECT round(100.0 * count(*) FILTER (cell = 0) / (SELECT count(*) FROM st), 6) FROM sc) AS cut_pct"""


@query("SELECT * FROM (" + oracles.with_(oracles.CELLS.strip() + "\n" + _TOPO.format(net="'regional'")) + ") UNION ALL SELECT * FROM (" + oracles.with_(oracles.CELLS.strip() + "\n" + _TOPO.format(net="'mesh'"), mesh=True) + ")")
def topology_contrast(spark, sf_dir):
    out = None
    for net in (_r(spark, sf_dir), _m(spark, sf_dir)):
        row = metrics.topology(net).join(F.broadcast(metrics.cut_share(cells.stop_cells(net, cells.natural(net)), net))).withColumn("net", F.lit(net.name))
        out = row if out is None else out.unionByName(row)
    return out


@query("WITH " + oracles.CHAINS.strip() + """,
s AS (SELECT trip_id, list(stop_id ORDER BY idx) AS stops FROM ce GROUP BY trip_id)
SELECT trip_id, dense_rank() OVER (ORDER BY stops) AS route_id, len(stops)::INT AS len FROM s""")
def routes_from_sequences(spark, sf_dir):
    return timetable.derive_routes(derive.chain_events(spark, sf_dir))


@query(oracles.with_("x AS (SELECT 1)\nSELECT trip_id, route_id, rank::INT AS rank FROM tr"))
def trip_ranks(spark, sf_dir):
    return timetable.rank_trips(_r(spark, sf_dir).events)


_EXPRESS = """third AS (SELECT route_id, idx, arr, first_value(arr) OVER (PARTITION BY route_id ORDER BY idx) AS f FROM ev WHERE rank = 2),
xe AS (SELECT trip_id, route_id, idx, arr FROM ev UNION ALL SELECT route_id * 1000 + 999, route_id, idx, (f + 300 + (arr - f) // 2)::INT FROM third),
vec AS (SELECT route_id, trip_id, list(arr ORDER BY idx) AS times FROM xe GROUP BY ALL),
rk AS (SELECT *, row_number() OVER (PARTITION BY route_id ORDER BY times, trip_id) - 1 AS rank FROM vec),
re AS (SELECT rk.route_id, rk.trip_id, rk.rank, xe.idx, xe.arr, max(xe.arr) OVER (PARTITION BY rk.route_id, xe.idx ORDER BY rk.rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM rk JOIN xe USING (route_id, trip_id))
"""


@query(oracles.with_(_EXPRESS + "SELECT DISTINCT route_id, trip_id FROM re WHERE arr < top"))
def fifo_violations(spark, sf_dir):
    return timetable.fifo_violations(timetable.with_express(_r(spark, sf_dir)))


@query()
def fifo_dropped(spark, sf_dir):
    x = timetable.with_express(_r(spark, sf_dir))
    kept = timetable.enforce_fifo(x, "drop").select("trip_id").distinct()
    return x.select("route_id", "trip_id").distinct().join(kept, "trip_id", "left_anti")


@query()
def fifo_split(spark, sf_dir):
    return timetable.enforce_fifo(timetable.with_express(_r(spark, sf_dir)), "split").groupBy("route_id").agg(F.countDistinct("trip_id").alias("trips"))


@query("SELECT * FROM (VALUES ('walks closed and shortest', 0::BIGINT), ('walks both ways', 0), ('indices dense', 0), ('times rise along a trip', 0), ('no overtaking', 0)) t(rule, broken)")
def network_checks(spark, sf_dir):
    return timetable.validate(_r(spark, sf_dir))


# --- walks --------------------------------------------------------------------------------------

@query(oracles.with_("x AS (SELECT 1)\nSELECT a, b, secs FROM nb"))
def walk_neighbourhood(spark, sf_dir):
    return _r(spark, sf_dir).neighbourhood()


@query(oracles.with_("x AS (SELECT 1)\nSELECT a, b, secs FROM wk"))
def walk_closure(spark, sf_dir):
    return _r(spark, sf_dir).walks


@query(" UNION ALL ".join("SELECT * FROM (" + oracles.with_(f"x AS (SELECT 1)\nSELECT {n} AS max_secs, (SELECT count(*) FROM w1) AS walks, (SELECT count(*) FROM wk) AS closed, (SELECT coalesce(max(secs), 0) FROM wk) AS longest", limit=n) + ")" for n in (60, 120, 180)))
def walk_closure_sweep(spark, sf_dir):
    raw, out = derive.raw_walks(_r(spark, sf_dir).stops), None
    for limit in (60, 120, 180):
        w = footpaths.from_distance(raw, limit=limit)
        row = w.agg(F.lit(limit).alias("max_secs"), F.count("*").alias("walks")).join(F.broadcast(footpaths.close(w).agg(F.count("*").alias("closed"), F.coalesce(F.max("secs"), F.lit(0)).alias("longest"))))
        out = row if out is None else out.unionByName(row)
    return out


# --- transfers ----------------------------------------------------------------------------------

@query(oracles.with_(oracles.XFER + "\nSELECT DISTINCT t1, i1::INT AS i1, t2, i2::INT AS i2 FROM tf WHERE NOT (route2 = r1 AND rank2 >= k1 AND i2 >= i1)"))
def transfers_all(spark, sf_dir):
    return _transfers(spark, sf_dir, reduce=False).select("t1", "i1", "t2", "i2")


@query()
def transfers_reduced_count(spark, sf_dir):
    return transfers.sizes(_transfers(spark, sf_dir, reduce=False), _transfers(spark, sf_dir))


@query("SELECT 0::BIGINT AS req_id, 0 AS n, 0 AS arr_a, 0 AS arr_b WHERE false")
def transfer_set_differences(spark, sf_dir):
    """Answers with all, the weakly and the fully reduced transfers that differ: none."""
    net, raw, q = _r(spark, sf_dir), _transfers(spark, sf_dir, reduce=False), _requests(spark, sf_dir)
    a = kernels.Arrays(net)
    full, weak, every = (written(kernels.segment_blocks(net, t, q, K, a)) for t in (_transfers(spark, sf_dir), transfers.weakly_reduced(net, raw), raw))
    return metrics.diff(every, full).unionByName(metrics.diff(every, weak))


@query()
def transfers_weakly_reduced_count(spark, sf_dir):
    net, raw = _r(spark, sf_dir), _transfers(spark, sf_dir, reduce=False)
    return transfers.sizes(raw, transfers.weakly_reduced(net, raw))


@query(oracles.od("SELECT req_id, route_id, idx::INT AS idx, rank::INT AS rank FROM b0", k=0))
def earliest_board(spark, sf_dir):
    net = _r(spark, sf_dir).with_(headway=None, offsets=None)  # the as-of window, not arithmetic
    q = _requests(spark, sf_dir)
    from .asof import earliest_by_window

    near = net.neighbourhood()
    lens = net.route_stops.groupBy("route_id").agg(F.max("idx").alias("last"))
    start = q.join(near, q.source == near.a).select("req_id", F.col("b").alias("stop_id"), (F.col("dep") + F.col("secs")).alias("tau"))
    probes = start.join(net.route_stops.join(lens, "route_id").where("idx < last"), "stop_id").select("req_id", "route_id", "idx", "tau")
    return earliest_by_window(probes, net).select("req_id", "route_id", "idx", "rank")


# --- one-to-one searches ------------------------------------------------------------------------

@query(oracles.with_(oracles.REQUESTS.format(most=FEW).strip() + "\nSELECT req_id, source, target, dep FROM rq"))
def od_requests(spark, sf_dir):
    return _requests(spark, sf_dir)


def _rounds(spark, d, net=None, **more):
    net = net or _r(spark, d)
    return round_router.route(net, _requests(spark, d, net), K, **more)


def _segments(spark, d, net=None, **more):
    net = net or _r(spark, d)
    return segment_router.route(net, _requests(spark, d, net), _transfers(spark, d, net), K, **more)


@query(oracles.od("SELECT req_id, min(arr) AS arr FROM lab GROUP BY req_id"))
def od_earliest_arrival(spark, sf_dir):
    return journeys.earliest_arrival(_segments(spark, sf_dir).labels)


@query(oracles.od())
def od_pareto_segments(spark, sf_dir):
    return journeys.pareto(_segments(spark, sf_dir).labels)


@query(oracles.od())
def od_pareto_rounds(spark, sf_dir):
    return journeys.pareto(_rounds(spark, sf_dir).labels)


@query(oracles.od())
def od_pareto_blocks(spark, sf_dir):
    return kernels.route_blocks(_r(spark, sf_dir), _requests(spark, sf_dir), K)


@query(oracles.od())
def od_segment_kernel(spark, sf_dir):
    return kernels.segment_blocks(_r(spark, sf_dir), _transfers(spark, sf_dir), _requests(spark, sf_dir), K)


@query(oracles.od())
def od_layered_graph(spark, sf_dir):
    return event_graph.layered(_r(spark, sf_dir), _requests(spark, sf_dir), K + 1)


@query(oracles.od(mesh=True))
def od_pareto_rounds_mesh(spark, sf_dir):
    return journeys.pareto(_rounds(spark, sf_dir, _m(spark, sf_dir)).labels)


@query(oracles.od("SELECT req_id, min(arr) AS arr FROM lab GROUP BY req_id", k=9))
def od_event_graph(spark, sf_dir):
    return event_graph.route(_r(spark, sf_dir), _requests(spark, sf_dir))


@query(oracles.od("SELECT req_id, min(arr) AS arr FROM lab GROUP BY req_id", k=9))
def od_connection_sweep(spark, sf_dir):
    return event_graph.sweep(_r(spark, sf_dir), _requests(spark, sf_dir))


@query(oracles.od("SELECT req_id, n::INT AS n, arr FROM lab"))
def od_labels_at_most(spark, sf_dir):
    return journeys.at_most(_segments(spark, sf_dir).labels, K)


@query()
def od_journey_legs(spark, sf_dir):
    return journeys.pareto(_segments(spark, sf_dir, with_legs=True).labels)


@query("SELECT 0::BIGINT AS req_id, 0 AS n WHERE false")
def od_journey_replay(spark, sf_dir):
    net = _r(spark, sf_dir)
    return journeys.replay(net, journeys.pareto(_segments(spark, sf_dir, with_legs=True).labels), _requests(spark, sf_dir))


@query("SELECT 0::BIGINT AS req_id, 0 AS n, 0 AS arr_a, 0 AS arr_b WHERE false")
def router_differences(spark, sf_dir):
    return metrics.diff(journeys.pareto(_segments(spark, sf_dir, prune=True).labels), journeys.pareto(_rounds(spark, sf_dir, prune=False).labels))


# Over all orders, without SQL texts, which are too slow there.

@query()
def od_requests_all(spark, sf_dir):
    return _all_requests(spark, sf_dir)


@query()
def od_pareto_blocks_all(spark, sf_dir):
    return kernels.route_blocks(_r(spark, sf_dir), _all_requests(spark, sf_dir), K)


@query()
def od_segment_kernel_all(spark, sf_dir):
    return kernels.segment_blocks(_r(spark, sf_dir), _transfers(spark, sf_dir), _all_requests(spark, sf_dir), K)


@query()
def od_pareto_rounds_all(spark, sf_dir):
    return journeys.pareto(round_router.route(_r(spark, sf_dir), _all_requests(spark, sf_dir), K).labels)


@query()
def od_pareto_segments_all(spark, sf_dir):
    return journeys.pareto(segment_router.route(_r(spark, sf_dir), _all_requests(spark, sf_dir), _transfers(spark, sf_dir), K).labels)


@query()
def od_event_graph_all(spark, sf_dir):
    return event_graph.route(_r(spark, sf_dir), _all_requests(spark, sf_dir))


@query()
def od_connection_sweep_all(spark, sf_dir):
    return event_graph.sweep(_r(spark, sf_dir), _all_requests(spark, sf_dir))


@query()
def request_cells_all(spark, sf_dir):
    return cells.label_requests(_all_requests(spark, sf_dir), _natural(spark, sf_dir)[1]).select("req_id", "src_cell", "tgt_cell")


# --- ranges -------------------------------------------------------------------------------------

def _few(spark, d, sources=5, targets=8):
    q, net = _requests(spark, d), _r(spark, d)
    s = q.select("source").distinct().orderBy("source").limit(sources)
    t = q.select("target").distinct().orderBy("target").limit(targets)
    return once(spark, f"range groups {d} {sources} {targets}", lambda: tuple(written(x) for x in range_router.groups_of(net, s, t)))


_FEW_SQL = """fs AS (SELECT DISTINCT source FROM rq ORDER BY source LIMIT 5), ft AS (SELECT DISTINCT target FROM rq ORDER BY target LIMIT 8),
lst AS (SELECT route_id, max(idx) AS last FROM rs GROUP BY route_id),
dps AS (SELECT DISTINCT source, (e.arr - secs)::INT AS dep FROM fs JOIN nb ON nb.a = source JOIN ev e ON e.stop_id = nb.b JOIN lst USING (route_id) WHERE e.idx < last AND e.arr - secs BETWEEN 25200 AND 28800)"""
_PROFILE = oracles.with_(",\n".join([
    oracles.REQUESTS.format(most=FEW).strip(), _FEW_SQL,
    "lanes AS (SELECT source * 100000 + dep AS req_id, source, dep FROM dps)", oracles.source_start("lanes"), oracles.rounds("s0", K),
    "lab AS (" + " UNION ALL ".join(f"SELECT source, stop_id AS target, dep, {n} AS n, t AS arr FROM l{n} JOIN lanes USING (req_id) JOIN ft ON ft.target = stop_id" for n in range(K + 1)) + ")",
    "ok AS (SELECT * FROM lab WHERE NOT EXISTS (SELECT 1 FROM nb WHERE nb.a = source AND nb.b = target))",
]) + """
SELECT source, target, dep, n::INT AS n, arr FROM ok x WHERE NOT EXISTS (SELECT 1 FROM ok y WHERE y.source = x.source AND y.target = x.target AND y.dep >= x.dep AND y.n <= x.n AND y.arr <= x.arr
  AND (y.dep > x.dep OR y.n < x.n OR y.arr < x.arr))""")


@query(oracles.with_(oracles.REQUESTS.format(most=FEW).strip() + ",\n" + _FEW_SQL + "\nSELECT source, dep FROM dps"))
def range_departures(spark, sf_dir):
    g, _ = _few(spark, sf_dir)
    return range_router.departures(_r(spark, sf_dir), g, *RANGE)


def _profile_rows(p):
    return p.rows.select("source", "target", "dep", "n", "arr")


@query(_PROFILE)
def profile_fanout_segments(spark, sf_dir):
    return _profile_rows(range_router.fanout_segments(_r(spark, sf_dir), _transfers(spark, sf_dir), *_few(spark, sf_dir), *RANGE))


@query(_PROFILE)
def profile_fanout_noscope(spark, sf_dir):
    return _profile_rows(range_router.fanout_segments(_r(spark, sf_dir), _transfers(spark, sf_dir), *_few(spark, sf_dir), *RANGE, scope=False))


@query(_PROFILE)
def profile_fanout_rounds(spark, sf_dir):
    return _profile_rows(range_router.fanout_rounds(_r(spark, sf_dir), *_few(spark, sf_dir), *RANGE))


@query(_PROFILE)
def profile_pairs_segments(spark, sf_dir):
    return _profile_rows(range_router.fanout_segments(_r(spark, sf_dir), _transfers(spark, sf_dir), *range_router.as_pairs(*_few(spark, sf_dir)), *RANGE))


@query(_PROFILE)
def profile_pairs_rounds(spark, sf_dir):
    return _profile_rows(range_router.fanout_rounds(_r(spark, sf_dir), *range_router.as_pairs(*_few(spark, sf_dir)), *RANGE))


@query(_PROFILE)
def profile_fanout_arrays(spark, sf_dir):
    return kernels.fanout_blocks(_r(spark, sf_dir), _transfers(spark, sf_dir), *_few(spark, sf_dir), *RANGE).select("source", "target", "dep", "n", "arr")


@query(f"""WITH prof AS ({_PROFILE}), lk AS (SELECT source, target, n, min(arr) AS arr FROM prof WHERE dep >= 26000 GROUP BY ALL)
SELECT source, target, n, arr FROM (SELECT *, min(arr) OVER (PARTITION BY source, target ORDER BY n ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS b FROM lk) WHERE b IS NULL OR arr < b""")
def profile_lookup(spark, sf_dir):
    p = range_router.fanout_segments(_r(spark, sf_dir), _transfers(spark, sf_dir), *_few(spark, sf_dir), *RANGE).rows
    g, t = _few(spark, sf_dir)
    q = t.select(F.xxhash64("g", "target").alias("req_id"), F.col("g").alias("source"), "target", F.lit(26000).alias("dep"))
    return range_router.lookup(p, q).join(q, "req_id").select("source", "target", "n", "arr")


@query()
def profile_day_70x70(spark, sf_dir):
    """A day's profiles between the 70 first sources and the 70 first targets of all requests."""
    q, net = _all_requests(spark, sf_dir), _r(spark, sf_dir)
    s, t = (q.select(c).distinct().orderBy(c).limit(70) for c in ("source", "target"))
    return kernels.fanout_blocks(net, _transfers(spark, sf_dir), *range_router.groups_of(net, s, t), derive.DAY_START, derive.DAY_END).select("source", "target", "dep", "n", "arr")


_TEN = "rq10 AS (SELECT * FROM rq WHERE req_id <= 10)"


def _all_sql(select: str) -> str:
    return oracles.with_(",\n".join([oracles.REQUESTS.format(most=FEW).strip(), _TEN, oracles.source_start("rq10"), oracles.rounds("s0", K)]) + "\n" + select)


def _ten(spark, d):
    return _requests(spark, d).where("req_id <= 10").select("req_id", "source", "dep")


@query(_all_sql("SELECT req_id, stop_id, (t - dep)::INT AS secs FROM (SELECT req_id, stop_id, min(t) AS t FROM (SELECT * FROM l4 UNION ALL SELECT * FROM s0) GROUP BY ALL) JOIN rq10 USING (req_id) WHERE t - dep <= 1800"))
def isochrone(spark, sf_dir):
    return range_router.isochrone(_r(spark, sf_dir), _ten(spark, sf_dir), 1800, K)


@query(_all_sql("SELECT req_id, place::INT AS place, stop_id, arr FROM (SELECT req_id, stop_id, t AS arr, row_number() OVER (PARTITION BY req_id ORDER BY t, stop_id) AS place FROM (SELECT req_id, stop_id, min(t)::INT AS t FROM (SELECT * FROM l4 UNION ALL SELECT * FROM s0) GROUP BY ALL) JOIN st USING (stop_id) WHERE poi = 'BUILDING') WHERE place <= 3"))
def nearest_poi(spark, sf_dir):
    return range_router.nearest_poi(_r(spark, sf_dir), _ten(spark, sf_dir), "BUILDING", 3, K)


def _locations(spark, d):
    c = spark.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").cast("long").alias("stop_id"), F.col("c_nationkey").alias("location"))
    return _r(spark, d).route_stops.select("stop_id").distinct().join(c, "stop_id").select("location", "stop_id")


@query(oracles.with_(",\n".join([
    "loc AS (SELECT DISTINCT rs.stop_id, c_nationkey AS location FROM rs JOIN customer ON c_custkey = rs.stop_id)",
    "pq AS (SELECT n_nationkey::BIGINT AS req_id, n_nationkey AS fl, (n_nationkey + 1) % 25 AS tl, 30000 AS dep FROM nation WHERE n_nationkey < 5)",
    "s0 AS (SELECT req_id, nb.b AS stop_id, min(dep + secs) AS t FROM pq JOIN loc ON location = fl JOIN nb ON nb.a = loc.stop_id GROUP BY ALL)", oracles.rounds("s0", K)])
    + "\nSELECT req_id, min(t)::INT AS arr FROM l4 JOIN pq USING (req_id) JOIN loc ON loc.stop_id = l4.stop_id AND loc.location = tl GROUP BY req_id"))
def location_pairs(spark, sf_dir):
    n = spark.read.parquet(f"{sf_dir}/nation.parquet").where("n_nationkey < 5")
    pairs = n.select(F.col("n_nationkey").cast("long").alias("req_id"), F.col("n_nationkey").alias("from_location"), ((F.col("n_nationkey") + 1) % 25).alias("to_location"), F.lit(30000).alias("dep"))
    return range_router.location_pairs(_r(spark, sf_dir), _locations(spark, sf_dir), pairs, K)


@query()
def demand_load(spark, sf_dir):
    """Riders per trip leg if every request takes its earliest journey."""
    legs = journeys.pareto(_segments(spark, sf_dir, with_legs=True).labels)
    last = legs.groupBy("req_id").agg(F.max_by("legs", "n").alias("legs"))
    leg = last.select(F.explode("legs").alias("leg")).select("leg.*")
    return leg.select("trip_id", F.explode(F.sequence("from_idx", F.col("to_idx") - 1)).alias("idx")).groupBy("trip_id", "idx").agg(F.count("*").alias("riders"))


# --- hypergraph, cells --------------------------------------------------------------------------

def _hyper(spark, d, scheme, net=None):
    net = net or _r(spark, d)
    return once(spark, f"hyper {net.name} {d} {scheme}", lambda: (lambda h: hypergraph.Hypergraph(written(h.nodes), written(h.pins), written(h.edges)))(hypergraph.build(net, scheme)))


@query(oracles.with_(oracles.HYPER.strip() + """
SELECT i.node_id, CASE WHEN i.node_id >= (1::BIGINT << 50) THEN 'walk' ELSE 'route' END AS kind, coalesce(e.k, 0)::DOUBLE AS weight FROM (SELECT DISTINCT node_id FROM inc) i LEFT JOIN (SELECT route_id, count(*) AS k FROM ev GROUP BY route_id) e ON e.route_id = i.node_id"""))
def hyper_nodes(spark, sf_dir):
    return _hyper(spark, sf_dir, 2).nodes


def _edge_sql(weight: str) -> str:
    return oracles.with_(oracles.HYPER.strip() + f""",
own AS (SELECT stop_id, count(*) AS k FROM ev GROUP BY stop_id), wide AS (SELECT nb.a AS stop_id, sum(k) AS k FROM nb JOIN own ON own.stop_id = nb.b GROUP BY nb.a),
pn AS (SELECT stop_id, list_sort(list(DISTINCT node_id)) AS pins FROM inc GROUP BY stop_id HAVING count(DISTINCT node_id) > 1)
SELECT min(stop_id) AS edge_id, any_value(len(pins))::INT AS pins, count(*) AS stops, round(sum({weight}), 6) AS weight FROM pn LEFT JOIN own USING (stop_id) LEFT JOIN wide USING (stop_id) GROUP BY pn.pins""")


def _edges(spark, d, scheme):
    h = _hyper(spark, d, scheme)
    k = h.pins.groupBy("edge_id").agg(F.count("*").cast("int").alias("pins"))
    return h.edges.join(k, "edge_id").select("edge_id", "pins", F.size("stops").cast("long").alias("stops"), F.round("weight", 6).alias("weight"))


@query(_edge_sql("1.0::DOUBLE"))
def hyper_edges_s1(spark, sf_dir):
    return _edges(spark, sf_dir, 1)


@query(_edge_sql("CASE WHEN own.k > 0 THEN ln(own.k) ELSE 0 END"))
def hyper_edges_s2(spark, sf_dir):
    return _edges(spark, sf_dir, 2)


@query(_edge_sql("CASE WHEN wide.k > 0 THEN ln(wide.k::DOUBLE) ELSE 0 END"))
def hyper_edges_s3(spark, sf_dir):
    return _edges(spark, sf_dir, 3)


def _natural(spark, d):
    net = _r(spark, d)
    return once(spark, f"natural cells {d}", lambda: (written(cells.natural(net)), written(cells.stop_cells(net, cells.natural(net)))))


@query(oracles.with_(oracles.CELLS.strip() + "\nSELECT stop_id, cell FROM sc"))
def stop_cells_region(spark, sf_dir):
    return _natural(spark, sf_dir)[1]


@query(oracles.with_(oracles.CELLS.strip() + "\nSELECT stop_id FROM sc WHERE cell = 0"))
def cut_stops_region(spark, sf_dir):
    return cells.cut_stops(_natural(spark, sf_dir)[1])


@query(oracles.with_(",\n".join([oracles.REQUESTS.format(most=FEW).strip(), oracles.CELLS.strip()]) + "\nSELECT req_id, a.cell AS src_cell, b.cell AS tgt_cell FROM rq LEFT JOIN sc a ON a.stop_id = source AND a.cell > 0 LEFT JOIN sc b ON b.stop_id = target AND b.cell > 0"))
def request_cells(spark, sf_dir):
    return cells.label_requests(_requests(spark, sf_dir), _natural(spark, sf_dir)[1]).select("req_id", "src_cell", "tgt_cell")


@query(oracles.with_(oracles.CELLS.strip() + """,
own AS (SELECT stop_id, count(*) AS k FROM ev GROUP BY stop_id), wide AS (SELECT nb.a AS stop_id, sum(k) AS k FROM nb JOIN own ON own.stop_id = nb.b GROUP BY nb.a),
es AS (SELECT stop_id, min(cell) <> max(cell) AS cut, list_sort(list(DISTINCT node_id)) AS pins FROM inc JOIN nc USING (node_id) GROUP BY stop_id HAVING count(DISTINCT node_id) > 1),
eg AS (SELECT pins, any_value(cut) AS cut, sum(ln(k::DOUBLE)) AS w FROM es JOIN wide USING (stop_id) GROUP BY pins),
ld AS (SELECT cell, sum(coalesce(k, 0)) AS w FROM nc LEFT JOIN (SELECT route_id, count(*) AS k FROM ev GROUP BY route_id) e ON e.route_id = node_id GROUP BY cell)
SELECT count(*) FILTER (cut) AS cut_edges, round(coalesce(sum(w) FILTER (cut), 0), 6) AS cut_weight, round(sum(w), 6) AS all_weight, (SELECT round(max(w) / avg(w), 6) FROM ld) AS imbalance FROM eg"""))
def partition_quality_region(spark, sf_dir):
    return metrics.partition_quality(_hyper(spark, sf_dir, 3), _natural(spark, sf_dir)[0])


def _parts(spark, d, p, coarsen="mutual", scheme=3, net=None):
    net = net or _r(spark, d)
    h = _hyper(spark, d, scheme, net)
    # a small driver limit makes even these networks go through contraction in Spark
    return once(spark, f"parts {net.name} {d} {p} {coarsen} {scheme}", lambda: partition.multilevel(h, p, coarsen=coarsen, driver_nodes=100))


@query()
def partition_multilevel(spark, sf_dir):
    return _parts(spark, sf_dir, 4)


@query()
def partition_first_choice(spark, sf_dir):
    return _parts(spark, sf_dir, 4, "first_choice")


@query()
def partition_community(spark, sf_dir):
    return _parts(spark, sf_dir, 4, "community")


@query()
def partitioner_ablation(spark, sf_dir):
    """Cut and balance of the ways to coarsen, and of natural cells."""
    h, out = _hyper(spark, sf_dir, 3), None
    for name, c in (("mutual", _parts(spark, sf_dir, 5)), ("first_choice", _parts(spark, sf_dir, 5, "first_choice")), ("community", _parts(spark, sf_dir, 5, "community")), ("natural", _natural(spark, sf_dir)[0])):
        row = metrics.partition_quality(h, c).withColumn("partitioner", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


@query()
def scheme_ablation(spark, sf_dir):
    """Cut stops of the partitions that each weighting scheme leads to."""
    net, out = _r(spark, sf_dir), None
    for s in (1, 2, 3):
        row = metrics.cut_share(cells.stop_cells(net, _parts(spark, sf_dir, 4, scheme=s)), net).withColumn("scheme", F.lit(s))
        out = row if out is None else out.unionByName(row)
    return out


# --- fill-in and pruned searches ----------------------------------------------------------------

def _fillin(spark, d):
    net = _r(spark, d)
    return once(spark, f"fillin natural {d}", lambda: written(fillin.compute(net, _transfers(spark, d), nested.flat_pairs(cells.cut_stops(_natural(spark, d)[1])))))


def _nested(spark, d):
    net, h = _r(spark, d), _hyper(spark, d, 3)
    return once(spark, f"nested 2-2 {d}", lambda: written(nested.split(h, 2, 2)))


def _nested_fillin(spark, d):
    net = _r(spark, d)
    return once(spark, f"nested fillin {d}", lambda: written(fillin.compute(net, _transfers(spark, d), nested.pairs(net, _nested(spark, d), "strict"))))


@query()
def fillin_fanout(spark, sf_dir):
    return _fillin(spark, sf_dir)


@query()
def fillin_pairs(spark, sf_dir):
    net = _r(spark, sf_dir)
    return fillin.compute(net, _transfers(spark, sf_dir), nested.flat_pairs(cells.cut_stops(_natural(spark, sf_dir)[1])), engine="pairs")


@query()
def fillin_events(spark, sf_dir):
    """The fill-in as marked stop events."""
    net = _r(spark, sf_dir)
    return fillin.as_events(net, fillin.as_trips(net, _fillin(spark, sf_dir))).select("trip_id", "idx", "stop_id", "arr")


@query()
def fillin_overlay(spark, sf_dir):
    """Trips and stop events of the sub-timetable of two cells and the fill-in, for every pair of cells."""
    net, (nodes, _) = _r(spark, sf_dir), _natural(spark, sf_dir)
    trips = net.trips.join(cells.route_cells(nodes), "route_id", "left").join(fillin.as_trips(net, _fillin(spark, sf_dir)).select("trip_id", F.lit(True).alias("fill")), "trip_id", "left")
    size = net.events.groupBy("trip_id").agg(F.count("*").alias("k")).join(trips, "trip_id")
    own = size.groupBy("cell").agg(F.count("*").alias("trips"), F.sum("k").alias("events"), F.count("fill").alias("fill_trips"), F.sum(F.when(F.col("fill"), F.col("k")).otherwise(0)).alias("fill_events")).where("cell is not null")
    own = written(own)  # one row per cell
    a, b = (own.select(*[F.col(c).alias(f"{c}_{s}") for c in own.columns]) for s in "ab")
    fill = own.agg(F.sum("fill_trips").alias("ft"), F.sum("fill_events").alias("fe"))
    both = a.join(b, F.col("cell_a") < F.col("cell_b")).join(F.broadcast(fill))
    sums = [(F.col(f"{n}_a") + F.col(f"{n}_b") + F.col(f) - F.col(f"fill_{n}_a") - F.col(f"fill_{n}_b")).alias(n) for n, f in (("trips", "ft"), ("events", "fe"))]
    return both.select("cell_a", "cell_b", *sums)


@query()
def nested_search_counts(spark, sf_dir):
    """Ordered stop pairs that nested cells search, by rule."""
    net, out = _r(spark, sf_dir), None
    for mode in ("paper", "siblings", "strict"):
        row = nested.pairs(net, _nested(spark, sf_dir), mode).agg(F.lit(mode).alias("rule"), F.count("*").alias("searches"))
        out = row if out is None else out.unionByName(row)
    return out


@query()
def fillin_share(spark, sf_dir):
    return metrics.fillin_stats(_r(spark, sf_dir), _fillin(spark, sf_dir), _natural(spark, sf_dir)[1])


@query(oracles.with_(oracles.CELLS.strip() + "\nSELECT 'flat' AS cells, (count(*) * (count(*) - 1))::BIGINT AS searches FROM sc WHERE cell = 0"))
def profile_query_counts(spark, sf_dir):
    return nested.flat_pairs(cells.cut_stops(_natural(spark, sf_dir)[1])).agg(F.lit("flat").alias("cells"), F.count("*").alias("searches"))


def _labelled(spark, d, stop_cells):
    return cells.label_requests(_requests(spark, d), stop_cells)


def _admitted(spark, d, nodes, fill):
    net = _r(spark, d)
    a = kernels.Arrays(net)
    return a, kernels.Admission(a, cells.route_cells(nodes), fillin.as_trips(net, fill))


@query(oracles.od())
def od_pruned_segment_arrays(spark, sf_dir):
    net, (nodes, stops) = _r(spark, sf_dir), _natural(spark, sf_dir)
    a, own = _admitted(spark, sf_dir, nodes, _fillin(spark, sf_dir))
    return kernels.segment_blocks(net, _transfers(spark, sf_dir), _labelled(spark, sf_dir, stops), K, a, cells=own)


@query(oracles.od())
def od_pruned_round_arrays(spark, sf_dir):
    net, (nodes, stops) = _r(spark, sf_dir), _natural(spark, sf_dir)
    a, own = _admitted(spark, sf_dir, nodes, _fillin(spark, sf_dir))
    return kernels.route_blocks(net, _labelled(spark, sf_dir, stops), K, arrays=a, cells=own)


@query("SELECT 0::BIGINT AS req_id, 0 AS n, 0 AS arr_a, 0 AS arr_b WHERE false")
def fillin_engine_differences(spark, sf_dir):
    """Pruned searches by the fill-ins of the engines that differ: none."""
    net, (nodes, stops) = _r(spark, sf_dir), _natural(spark, sf_dir)
    pairs, ask, got = nested.flat_pairs(cells.cut_stops(stops)), _labelled(spark, sf_dir, stops), []
    for engine in ("fanout", "arrays"):
        a, own = _admitted(spark, sf_dir, nodes, written(fillin.compute(net, _transfers(spark, sf_dir), pairs, engine=engine)))
        got.append(written(kernels.segment_blocks(net, _transfers(spark, sf_dir), ask, K, a, cells=own)))
    return metrics.diff(*got)


@query(oracles.od())
def od_pruned_segments(spark, sf_dir):
    net, (nodes, stops) = _r(spark, sf_dir), _natural(spark, sf_dir)
    admit = cells.trip_admission(_labelled(spark, sf_dir, stops), cells.route_cells(nodes), fillin.as_trips(net, _fillin(spark, sf_dir)))
    return journeys.pareto(_segments(spark, sf_dir, admit=admit).labels)


@query(oracles.od())
def od_pruned_rounds(spark, sf_dir):
    net, (nodes, stops) = _r(spark, sf_dir), _natural(spark, sf_dir)
    ok = cells.route_admission(_labelled(spark, sf_dir, stops), cells.route_cells(nodes), fillin.as_trips(net, _fillin(spark, sf_dir), "route"))
    return journeys.pareto(_rounds(spark, sf_dir, admit=ok).labels)


@query(oracles.od())
def od_nested_segments(spark, sf_dir):
    net, c = _r(spark, sf_dir), _nested(spark, sf_dir).select("node_id", "cell")
    stops = cells.stop_cells(net, c)
    admit = cells.trip_admission(_labelled(spark, sf_dir, stops), cells.route_cells(c), fillin.as_trips(net, _nested_fillin(spark, sf_dir)))
    return journeys.pareto(_segments(spark, sf_dir, admit=admit).labels)


@query(oracles.od())
def od_nested_rounds(spark, sf_dir):
    net, c = _r(spark, sf_dir), _nested(spark, sf_dir).select("node_id", "cell")
    stops = cells.stop_cells(net, c)
    ok = cells.route_admission(_labelled(spark, sf_dir, stops), cells.route_cells(c), fillin.as_trips(net, _nested_fillin(spark, sf_dir), "route"))
    return journeys.pareto(_rounds(spark, sf_dir, admit=ok).labels)


@query()
def preproc_sweep(spark, sf_dir):
    """Cut stops and profile searches, flat against nested, for 4, 6, 8 and 10 cells."""
    net, h, rows = _r(spark, sf_dir), _hyper(spark, sf_dir, 3), None
    for parents, children in ((2, 2), (3, 2), (4, 2), (5, 2)):
        p = parents * children
        flat = cells.stop_cells(net, _parts(spark, sf_dir, p))
        nest = once(spark, f"nested {parents} {sf_dir}", lambda a=parents, b=children: written(nested.split(h, a, b)))
        searches = nested.pairs(net, nest, "paper").agg(F.count("*").alias("nested_searches"))
        c = flat.where("cell = 0").agg(F.count("*").alias("flat_cuts"))
        row = c.join(F.broadcast(searches)).select(F.lit(p).alias("p"), F.lit(f"{parents}-{children}").alias("split"), "flat_cuts", (F.col("flat_cuts") * (F.col("flat_cuts") - 1)).alias("flat_searches"), "nested_searches")
        rows = row if rows is None else rows.unionByName(row)
    return rows


@query()
def work_counters(spark, sf_dir):
    """Segments and target checks of the plain and cell-pruned searches, and of the range searches."""
    net, (nodes, stops) = _r(spark, sf_dir), _natural(spark, sf_dir)
    admit = cells.trip_admission(_labelled(spark, sf_dir, stops), cells.route_cells(nodes), fillin.as_trips(net, _fillin(spark, sf_dir)))
    t, few = _transfers(spark, sf_dir), _few(spark, sf_dir)
    return metrics.work_table(spark, {
        "segments": _segments(spark, sf_dir, count=True).work,
        "segments, cell-pruned": _segments(spark, sf_dir, admit=admit, count=True).work,
        "rounds": _rounds(spark, sf_dir, count=True).work,
        "range, fan-out": range_router.fanout_segments(net, t, *few, *RANGE, count=True).work,
        "range, pairs": range_router.fanout_segments(net, t, *range_router.as_pairs(*few), *RANGE, count=True).work,
    })


# --- operators around the methods, on the given tables ------------------------------------------

_LOG = "lg AS (SELECT user_id AS vehicle, ts, (props::JSON ->> 'k')::BIGINT AS stop_id, event_id, value FROM events)"


@query(f"WITH {_LOG} SELECT stop_id, epoch(time_bucket(INTERVAL 1 hour, ts, TIMESTAMP '2024-01-01'))::BIGINT AS hour_start, count(*) AS n FROM lg GROUP BY ALL")
def board_events_per_hour(spark, sf_dir):
    return streaming.events_per_hour(derive.log_events(spark, sf_dir)).select("stop_id", F.unix_timestamp("window.start").alias("hour_start"), "n")


@query(f"""WITH {_LOG}, w AS (SELECT stop_id, floor(epoch(ts))::BIGINT // 1800 * 1800 - 1800 * unnest(generate_series(0, 3)) AS start FROM lg) SELECT stop_id, start AS win_start, count(*) AS n FROM w GROUP BY ALL""")
def load_sliding(spark, sf_dir):
    return streaming.sliding_load(derive.log_events(spark, sf_dir)).select("stop_id", F.unix_timestamp("window.start").alias("win_start"), "n")


@query(f"""WITH {_LOG}, g AS (SELECT vehicle, ts, CASE WHEN epoch(ts) - epoch(lag(ts) OVER w) < 21600 THEN 0 ELSE 1 END AS new FROM lg WINDOW w AS (PARTITION BY vehicle ORDER BY ts, event_id)),
s AS (SELECT vehicle, ts, sum(new) OVER (PARTITION BY vehicle ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM (SELECT vehicle, ts, new FROM g ORDER BY vehicle, ts))
SELECT vehicle, count(*) AS n, floor(epoch(min(ts)))::BIGINT AS began FROM s GROUP BY vehicle, k""")
def trip_sessions(spark, sf_dir):
    return streaming.sessions(derive.log_events(spark, sf_dir)).select("vehicle", "n", F.unix_timestamp("session.start").alias("began"))


@query(f"WITH {_LOG} SELECT vehicle, arg_max(stop_id, row(ts, event_id)) AS stop_id FROM lg GROUP BY vehicle")
def last_seen_stop(spark, sf_dir):
    e = derive.log_events(spark, sf_dir)
    return e.groupBy("vehicle").agg(F.max_by("stop_id", F.struct("ts", "event_id")).alias("stop_id"))


@query("WITH x AS (SELECT event_id, ts, max(ts) OVER (ORDER BY (event_id * 7919) % 10007, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM events) SELECT event_id FROM x WHERE ts < seen - INTERVAL 20 days")
def late_events(spark, sf_dir):
    """Events that come later than the watermark allows when the log arrives in a scrambled order. One
    running maximum over arrival order; bucketed first so that no single task sorts the log."""
    e = _events(spark, sf_dir).withColumn("o", (F.col("event_id") * 7919) % 10007)
    e = e.withColumn("b", F.floor(F.col("o") / 512))
    tops = e.groupBy("b").agg(F.max("ts").alias("top")).withColumn("before", F.max("top").over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)))
    w = Window.partitionBy("b").orderBy("o", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    x = e.join(F.broadcast(tops.select("b", "before")), "b").withColumn("seen", F.greatest("before", F.max("ts").over(w)))
    return x.where(F.col("ts") < F.col("seen") - F.expr("INTERVAL 20 DAYS")).select("event_id")


_BASE = "b AS (SELECT region, poi, trips FROM st JOIN (SELECT stop_id, count(*) AS trips FROM ev GROUP BY stop_id) USING (stop_id))"


def _busy(spark, d):
    net = _r(spark, d)
    return net.stops.join(net.events.groupBy("stop_id").agg(F.count("*").alias("trips")), "stop_id").select("stop_id", "region", "poi", "trips")


@query(oracles.with_(_BASE + "\nSELECT region, poi, sum(trips)::BIGINT AS trips FROM b GROUP BY ROLLUP (region, poi)"))
def stop_type_rollup(spark, sf_dir):
    return _busy(spark, sf_dir).rollup("region", "poi").agg(F.sum("trips").alias("trips"))


@query(oracles.with_(_BASE + "\nSELECT region, poi, sum(trips)::BIGINT AS trips FROM b GROUP BY CUBE (region, poi)"))
def stop_type_cube(spark, sf_dir):
    return _busy(spark, sf_dir).cube("region", "poi").agg(F.sum("trips").alias("trips"))


@query(oracles.with_(_BASE + "\nSELECT region, poi, count(*) AS stops FROM b GROUP BY GROUPING SETS ((region), (poi), ())"))
def metrics_grouping_sets(spark, sf_dir):
    b = _busy(spark, sf_dir)
    return b.groupingSets([["region"], ["poi"], []], "region", "poi").agg(F.count("*").alias("stops"))


@query(oracles.with_("b AS (SELECT stop_id, count(*) AS trips FROM ev GROUP BY stop_id)\nSELECT stop_id, trips FROM b ORDER BY trips DESC, stop_id LIMIT 20"))
def topk_busy_stops(spark, sf_dir):
    return _busy(spark, sf_dir).select("stop_id", "trips").orderBy(F.desc("trips"), "stop_id").limit(20)


@query(oracles.with_("g AS (SELECT route_id, start - lag(start) OVER (PARTITION BY route_id ORDER BY rank) AS gap FROM tr)\nSELECT route_id, min(gap)::INT AS least, max(gap)::INT AS most FROM g WHERE gap IS NOT NULL GROUP BY route_id"))
def headway_stats(spark, sf_dir):
    t = _r(spark, sf_dir).trips
    g = t.withColumn("gap", F.col("start") - F.lag("start").over(Window.partitionBy("route_id").orderBy("rank"))).where("gap is not null")
    return g.groupBy("route_id").agg(F.min("gap").cast("int").alias("least"), F.max("gap").cast("int").alias("most"))


@query(oracles.with_("x AS (SELECT trip_id, idx, stop_id, count(*) OVER (PARTITION BY stop_id ORDER BY arr RANGE BETWEEN 1800 PRECEDING AND CURRENT ROW) AS n FROM ev)\nSELECT trip_id, idx::INT AS idx, n FROM x"))
def arrivals_range_frame(spark, sf_dir):
    w = Window.partitionBy("stop_id").orderBy("arr").rangeBetween(-1800, 0)
    return _r(spark, sf_dir).events.select("trip_id", "idx", F.count("*").over(w).alias("n"))


@query(oracles.with_("x AS (SELECT 1)\nSELECT stop_id FROM st WHERE stop_id NOT IN (SELECT stop_id FROM rs)"))
def unserved_stops(spark, sf_dir):
    net = _r(spark, sf_dir)
    return net.stops.select("stop_id").join(net.route_stops.select("stop_id"), "stop_id", "left_anti")


_BOTH = "SELECT * FROM (" + oracles.with_("x AS (SELECT 1)\nSELECT DISTINCT stop_id FROM rs") + ") {op} SELECT * FROM (" + oracles.with_("x AS (SELECT 1)\nSELECT DISTINCT stop_id FROM rs", mesh=True) + ")"


@query(_BOTH.format(op="INTERSECT"))
def served_both(spark, sf_dir):
    return _r(spark, sf_dir).route_stops.select("stop_id").intersect(_m(spark, sf_dir).route_stops.select("stop_id"))


@query(_BOTH.format(op="EXCEPT"))
def only_regional_stops(spark, sf_dir):
    return _r(spark, sf_dir).route_stops.select("stop_id").subtract(_m(spark, sf_dir).route_stops.select("stop_id"))


@query(f"WITH {_LOG} SELECT stop_id, count(*) AS n, count(DISTINCT vehicle) AS vehicles FROM lg GROUP BY stop_id")
def props_json(spark, sf_dir):
    return derive.log_events(spark, sf_dir).groupBy("stop_id").agg(F.count("*").alias("n"), F.countDistinct("vehicle").alias("vehicles"))


@query(oracles.with_("x AS (SELECT 1)\nSELECT route_id, count(*)::INT AS len, array_to_string(list(stop_id ORDER BY idx), '>') AS path FROM rs GROUP BY route_id"))
def leg_arrays(spark, sf_dir):
    return _r(spark, sf_dir).routes.select("route_id", "len", F.array_join(F.transform("stops", lambda s: s.cast("string")), ">").alias("path"))


@query(oracles.with_("x AS (SELECT 1)\nSELECT trip_id, printf('%02d:%02d', start // 3600, start % 3600 // 60) AS label FROM tr"))
def hhmm_labels(spark, sf_dir):
    return _r(spark, sf_dir).trips.select("trip_id", journeys.hhmm(F.col("start")).alias("label"))
