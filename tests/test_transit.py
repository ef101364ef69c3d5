"""The engine: worked examples, agreement of all methods, invariants."""

import random

import numpy as np
import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from transit_engine import cells, derive, event_graph, fillin, footpaths, hypergraph, journeys, kernels, metrics, nested, partition, plans, range_router, round_router, segment_router, streaming, timetable, transfers, workloads
from transit_engine.asof import earliest, earliest_by_window
from transit_engine.schema import EVENTS, REQUESTS, ROUTE_STOPS, STOPS, TRIPS, WALKS, Network, stack
from transit_engine.storage import written

K = 4


def rows(df, *cols):
    return sorted(map(tuple, df.select(*cols).collect()))


@pytest.fixture(scope="module")
def toy(spark):
    return derive.toy(spark)


@pytest.fixture(scope="module")
def ask(spark):
    return spark.createDataFrame([(1, 0, 100, 28800)], REQUESTS)


def random_network(spark, seed):
    r = random.Random(seed)
    n = r.randint(6, 10)
    routes = {}
    for k in range(r.randint(3, 6)):
        stops = r.sample(range(n), r.randint(2, min(5, n)))
        times, t = [], 0
        for _ in stops:
            times.append(t)
            t += r.randint(1, 9) * 60
        routes[k] = (stops, times, sorted({r.randint(0, 90) * 60 for _ in range(r.randint(1, 6))}))
    ev = [(k * 100 + j, k, j, i, s, a + o, a + o) for k, (ss, oo, starts) in routes.items() for j, a in enumerate(starts) for i, (s, o) in enumerate(zip(ss, oo, strict=True))]
    walks = footpaths.close(spark.createDataFrame([(a, a + 1, 120) for a in range(0, n - 1, 3)] + [(a + 1, a, 120) for a in range(0, n - 1, 3)], WALKS))
    return Network(
        f"random {seed}", spark.createDataFrame([(s, s % 2, s, "x") for s in range(n)], STOPS), spark.createDataFrame([(k, i, s) for k, (ss, *_) in routes.items() for i, s in enumerate(ss)], ROUTE_STOPS),
        spark.createDataFrame([(k * 100 + j, k, j, a) for k, (_, _, starts) in routes.items() for j, a in enumerate(starts)], TRIPS), written(spark.createDataFrame(ev, EVENTS)), walks,
    )


def brute(net, source, target, dep, k):
    """Labels by enumerating rides round by round over plain Python lists."""
    ev = net.events.collect()
    near = {}
    for a, b, w in net.neighbourhood().collect():
        near.setdefault(a, []).append((b, w))
    trips = {}
    for e in ev:
        trips.setdefault(e.trip_id, []).append((e.idx, e.stop_id, e.arr))
    at = {b: dep + w for b, w in near[source]}
    best, out = 1 << 30, []
    for _ in range(k + 1):
        new = dict(at)
        for seq in trips.values():
            seq = sorted(seq)
            on = False
            for i, s, t in seq:
                if on:
                    for b, w in near[s]:
                        new[b] = min(new.get(b, 1 << 30), t + w)
                        if b == target:
                            best = min(best, t + w)
                on = on or at.get(s, 1 << 30) <= t
        at = new
        out.append(best)
    return [(n, a) for n, a in enumerate(out) if a < 1 << 30 and (n == 0 or a < out[n - 1])]


def test_worked_example(toy, ask):
    want = [(1, 0, 32400), (1, 2, 31800)]
    full, kept = transfers.of(toy, "toy", False), transfers.of(toy, "toy")
    for got in (round_router.route(toy, ask, K), segment_router.route(toy, ask, full, K), segment_router.route(toy, ask, kept, K, prune=False)):
        assert rows(journeys.pareto(got.labels), "req_id", "n", "arr") == want
    assert rows(kernels.route_blocks(toy, ask, K), "req_id", "n", "arr") == want
    assert rows(journeys.at_most(segment_router.route(toy, ask, full, K).labels, 2), "n", "arr") == [(0, 32400), (1, 32400), (2, 31800)]
    legs = journeys.pareto(segment_router.route(toy, ask, full, K, with_legs=True).labels)
    assert journeys.replay(toy, legs, ask).count() == 0


def test_worked_cells(spark, toy):
    node_cells = spark.createDataFrame([(4, 1), (2, 2), (3, 2), (1, 3), (5, 3), (hypergraph.WALK_NODE + 3 * 10**7 + 100, 3)], "node_id bigint, cell int")
    got = dict(rows(cells.stop_cells(toy, node_cells), "stop_id", "cell"))
    assert {s for s, c in got.items() if c == 0} == {0, 2, 8, 9}
    assert {s for s, c in got.items() if c == 2} == {5, 6} and {s for s, c in got.items() if c == 3} == {3, 7, 100}


def test_cut_stops_and_hyperedges_read_given_tables(spark, sf):
    """On the mesh network; on the toy network's own rows they read no table."""
    net = derive.mesh(spark, sf)
    pins = {}
    for r in hypergraph.incidence(net).collect():
        pins.setdefault(r.stop_id, set()).add(r.node_id)
    cell = dict(rows(cells.natural(net), "node_id", "cell"))
    edges, cuts = workloads.QUERIES["toy_hyperedges"](spark, sf), workloads.QUERIES["toy_cut_stops"](spark, sf)
    assert edges.inputFiles() and cuts.inputFiles()
    assert rows(edges, "stop_id", "pins") == sorted((s, len(p)) for s, p in pins.items() if len(p) > 1)
    assert rows(cuts, "stop_id") == sorted((s,) for s, p in pins.items() if len({cell[n] for n in p}) > 1)


def test_exact_partition_and_transfers_read_given_tables(spark, sf):
    """On the mesh and the regional network; on the toy network's own rows they read no table."""
    from itertools import product

    net, trunk = derive.mesh(spark, sf), lambda k: k % 10 == 9
    home = {r.s_suppkey: r.n_regionkey for r in spark.read.parquet(f"{sf}/supplier.parquet").join(spark.read.parquet(f"{sf}/nation.parquet"), F.col("s_nationkey") == F.col("n_nationkey")).collect()}
    region, group, at = dict(rows(net.stops, "stop_id", "region")), {}, {}
    for r in hypergraph.incidence(net).collect():
        walk = r.node_id >= hypergraph.WALK_NODE
        a = (r.node_id - hypergraph.WALK_NODE) // 10**7
        group[r.node_id] = 2 * region[a] if walk else 2 * home[r.node_id // 2] + trunk(r.node_id // 2)
        at.setdefault(r.stop_id, set()).add(group[r.node_id])
    weight = {g: list(group.values()).count(g) for g in set(group.values())}
    total, ids, edges = len(group), sorted(weight), [p for p in at.values() if len(p) > 1]

    def uncut(cell):
        load = [sum(weight[g] for g in ids if cell[g] == c) for c in (1, 2, 3)]
        return sum(len({cell[g] for g in p}) == 1 for p in edges) if min(load) >= total / 6 and max(load) <= total / 2 else -1

    best = max(uncut(dict(zip(ids, x, strict=True))) for x in product((1, 2, 3), repeat=len(ids)))
    assert best > 0 and rows(workloads.QUERIES["partition_exact_toy_quality"](spark, sf), "cells", "uncut") == [(3, float(best))]
    assert uncut(dict(rows(workloads.QUERIES["partition_exact_toy"](spark, sf), "node_id", "cell"))) == best

    got, reg = workloads.QUERIES["toy_transfers"](spark, sf), derive.regional(spark, sf)
    assert got.inputFiles()
    want = transfers.of(reg, f"regional {sf}").where("t1 in (1000, 2000, 3001, 4002)")
    assert rows(got, "t1", "i1", "t2", "i2") == rows(want, "t1", "i1", "t2", "i2") and len({r.t1 for r in got.collect()}) > 1


def test_worked_counts():
    assert metrics.profile_queries(7, [2, 4, 2], [1, 1, 1], top=4) == {"flat": 42, "nested": 28, "saved_pct": round(100 / 3, 6)}


@pytest.mark.parametrize("seed", range(3))
def test_irregular_networks_against_enumeration(spark, seed):
    net = random_network(spark, seed)
    stops = [r.stop_id for r in net.stops.collect()]
    near = {(a, b) for a, b, _ in net.neighbourhood().collect()}
    r = random.Random(seed)
    pairs = [(s, t) for s in stops for t in stops if (s, t) not in near]
    reqs = [(i, s, t, r.randint(0, 60) * 60) for i, (s, t) in enumerate(r.sample(pairs, 8))]
    df = spark.createDataFrame(reqs, REQUESTS)
    want = sorted((i, n, a) for i, s, t, d in reqs for n, a in brute(net, s, t, d, 3))
    tr = written(transfers.generate(net))
    assert rows(journeys.pareto(round_router.route(net, df, 3).labels), "req_id", "n", "arr") == want
    assert rows(journeys.pareto(segment_router.route(net, df, tr, 3).labels), "req_id", "n", "arr") == want
    assert rows(kernels.route_blocks(net, df, 3), "req_id", "n", "arr") == want
    slow = rows(journeys.earliest_arrival(kernels.route_blocks(net, df, 12)), "req_id", "arr")
    assert rows(event_graph.route(net, df), "req_id", "arr") == slow == rows(event_graph.sweep(net, df), "req_id", "arr")


def test_single_request_kernel(toy):
    a = kernels.Arrays(toy)
    number = {t: (r, j) for r, (_, trips) in enumerate(a.trips) for j, t in enumerate(trips.tolist())}
    hops = {}
    for x in transfers.of(toy, "toy").collect():
        hops.setdefault((*number[x.t1], x.i1), []).append((*number[x.t2], x.i2))
    s, t = (int(a.of([x])[0]) for x in (0, 100))
    assert kernels.segment_query(a, hops, s, t, 28800, 2, kernels._walks_by_stop(a)) == [32400, 32400, 31800]


@pytest.fixture(scope="module")
def net(spark, sf):
    return derive.regional(spark, sf)


def test_boarding_both_ways(net):
    probes = net.route_stops.where("idx = 0").select("route_id", "idx", (F.col("stop_id") * 997 % 60000 + 18000).cast("int").alias("tau"), F.col("stop_id").alias("tag"))
    cols = ("route_id", "idx", "tag", "tau", "rank")
    assert rows(earliest(probes, net), *cols) == rows(earliest_by_window(probes, net), *cols)


def test_pruned_and_ranges_agree(spark, sf, net):
    q = written(derive.requests(spark, sf, net, 30))
    tr = transfers.of(net, f"regional {sf}")
    plain = journeys.pareto(segment_router.route(net, q, tr, K).labels)
    nodes = written(cells.natural(net))
    stops = written(cells.stop_cells(net, nodes))
    pairs = nested.flat_pairs(cells.cut_stops(stops))
    fill = written(fillin.compute(net, tr, pairs))
    labelled = cells.label_requests(q, stops)
    admit = cells.trip_admission(labelled, cells.route_cells(nodes), fillin.as_trips(net, fill))
    assert metrics.diff(plain, journeys.pareto(segment_router.route(net, q, tr, K, admit=admit).labels)).count() == 0
    ok = cells.route_admission(labelled, cells.route_cells(nodes), fillin.as_trips(net, fill, "route"))
    assert metrics.diff(plain, journeys.pareto(round_router.route(net, q, K, admit=ok).labels)).count() == 0


def test_profiles(spark, sf, net):
    tr = transfers.of(net, f"regional {sf}")
    q = derive.requests(spark, sf, net, 30)
    s, t = q.select("source").distinct().orderBy("source").limit(2), q.select("target").distinct().orderBy("target").limit(3)
    g, goals = range_router.groups_of(net, s, t)
    cols = ("source", "target", "dep", "n", "arr")
    fan = range_router.fanout_segments(net, tr, g, goals, 25200, 27000, count=True)
    pairs = range_router.fanout_segments(net, tr, *range_router.as_pairs(g, goals), 25200, 27000, count=True)
    assert rows(fan.rows, *cols) == rows(pairs.rows, *cols) == rows(range_router.fanout_rounds(net, g, goals, 25200, 27000).rows, *cols)
    assert sum(w["segments"] for w in fan.work) <= sum(w["segments"] for w in pairs.work)
    ask = goals.select(F.xxhash64("g", "target").alias("req_id"), F.col("g").alias("source"), "target", F.lit(26000).alias("dep"))
    got = range_router.lookup(fan.rows, ask).where("arr <= 27000")
    direct = journeys.pareto(segment_router.route(net, ask, tr, K).labels).where("arr <= 27000")
    assert rows(got, "req_id", "n", "arr") == rows(direct, "req_id", "n", "arr")


def test_partitioners(spark, net, toy):
    h = hypergraph.build(net, 3)
    h = hypergraph.Hypergraph(written(h.nodes), written(h.pins), written(h.edges))
    for how in ("mutual", "first_choice", "community"):
        c = partition.multilevel(h, 3, coarsen=how, driver_nodes=10)
        assert c.count() == h.nodes.count() == c.select("node_id").distinct().count() and {r.cell for r in c.collect()} <= {1, 2, 3}
    small = hypergraph.build(toy, 1)
    best = metrics.partition_quality(small, partition.exact(spark, small, 3, 1, 3)).first()
    found = metrics.partition_quality(small, partition.multilevel(small, 3, imbalance=0.5)).first()
    assert best.cut_weight <= found.cut_weight
    two = nested.split(h, 2, 2)
    assert two.count() == h.nodes.count()
    strict, paper = nested.pairs(net, two, "strict"), nested.pairs(net, two, "paper")
    assert paper.exceptAll(strict).count() == 0


def test_moves_between_levels_cut_no_more(spark):
    """Two groups that one edge joins, one node put into the wrong cell: refinement moves it back, the bound on weight held."""
    edges = [(e, (a, b)) for e, (a, b) in enumerate([(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3)])]
    h = hypergraph.Hypergraph(
        spark.createDataFrame([(v, "route", 1.0) for v in range(6)], "node_id bigint, kind string, weight double"), spark.createDataFrame([(e, v) for e, p in edges for v in p], "edge_id bigint, node_id bigint"),
        spark.createDataFrame([(e, 1.0, [e]) for e, _ in edges], "edge_id bigint, weight double, stops array<bigint>"),
    )
    wrong = spark.createDataFrame([(v, 1 if v < 2 else 2) for v in range(6)], "node_id bigint, cell int")
    assert rows(partition.refined(h, wrong, 2, 3.0), "node_id", "cell") == [(v, 1 if v < 3 else 2) for v in range(6)]
    assert rows(partition.refined(h, wrong, 2, 2.5), "node_id", "cell") == rows(wrong, "node_id", "cell")


def test_stop_events_are_not_broadcast(spark, net):
    """All trips were, as the planner takes exploded rows for as few as the routes."""
    fresh = derive._timetabled("fresh", net.stops, net.route_stops, net.walks)
    plans.assert_no(fresh.events, "BroadcastExchange")
    assert rows(fresh.events, *net.events.columns) == rows(fresh.trips.join(fresh.offsets, "route_id").select("trip_id", "route_id", "rank", "idx", "stop_id", (F.col("start") + F.col("offset")).alias("arr"), (F.col("start") + F.col("offset")).alias("dep")), *net.events.columns)


def test_departures_stand_in_arrays(net):
    """As tuples and dictionaries they took ten times the memory; routes come to the driver as bytes."""
    a = kernels.Arrays(net)
    want = {}
    for e in net.events.collect():
        want.setdefault((e.route_id, e.rank), []).append((e.idx, e.stop_id, e.arr))
    got = {(rid, k): [(i, int(a.ids[s]), int(times[i, k])) for i, s in enumerate(stops)] for (stops, times), (rid, ids) in zip(a.routes, a.trips, strict=True) for k in range(len(ids))}
    assert got == {k: sorted(v) for k, v in want.items()}
    lists = kernels.departure_lists(a)
    for stop, (times, rides, place) in enumerate(lists):
        assert hasattr(rides, "nbytes") and rides.nbytes == 12 * len(times)
        rows_ = [(int(t), *r) for t, r in zip(times, rides.tolist(), strict=True)]
        assert rows_ == sorted((int(t), r, i, k) for r, i in a.calls[stop] if i < len(a.routes[r][0]) - 1 for k, t in enumerate(a.routes[r][1][i, :-1]))
        assert [place.get(r[1:]) for r in rows_] == list(range(len(rows_)))


def test_fifo(spark, net):
    x = written(timetable.with_express(net))
    assert timetable.fifo_violations(x).count() > 0
    for mode in ("drop", "split"):
        y = timetable.enforce_fifo(x, mode)
        assert timetable.fifo_violations(y).count() == 0
        assert (y.count() == x.count()) == (mode == "split")
    assert all(r.broken == 0 for r in timetable.validate(net).collect())


def test_stacked_networks_stay_apart(spark, toy, ask):
    both = stack([toy, toy])
    shift = 10**12
    q = ask.union(spark.createDataFrame([(2, shift, shift + 100, 28800), (3, 0, shift + 100, 28800)], REQUESTS))
    assert rows(journeys.pareto(round_router.route(both, q, K).labels), "req_id", "n", "arr") == [(1, 0, 32400), (1, 2, 31800), (2, 0, 32400), (2, 2, 31800)]


def test_edge_requests(spark, toy):
    q = spark.createDataFrame([(1, 0, 0, 28800), (2, 100, 0, 28800), (3, 0, 100, 90000)], REQUESTS)
    assert rows(journeys.pareto(round_router.route(toy, q, 0).labels), "req_id", "n", "arr") == []
    assert round_router.route(toy, q.where("false"), 1).labels.count() == 0


def test_stream_equals_batch(spark, sf, tmp_path):
    raw = spark.read.parquet(f"{sf}/events.parquet")
    raw.repartition(3).write.parquet(str(tmp_path / "in"))
    log = streaming.read_log(spark, str(tmp_path / "in"), raw.schema, 2)
    batch = derive.log_events(spark, sf)
    run = log.transform(streaming.last_seen).writeStream.outputMode("update").format("memory").queryName("seen").trigger(availableNow=True).start()
    run.awaitTermination()
    last = {}
    for r in spark.table("seen").collect():
        if r.seen >= last.get(r.vehicle, (0, 0))[1]:
            last[r.vehicle] = (r.stop_id, r.seen)
    want = batch.groupBy("vehicle").agg(F.max_by("stop_id", F.struct("ts", "event_id")).alias("s"), F.count("*").alias("n"))
    assert {v: x for v, x in last.items()} == {r.vehicle: (r.s, r.n) for r in want.collect()}
    run = streaming.events_per_hour(log, "40 days").writeStream.outputMode("complete").format("memory").queryName("hours").trigger(availableNow=True).start()
    run.awaitTermination()
    cols = (F.col("window.start").alias("w"), "stop_id", "n")
    assert rows(spark.table("hours"), *cols) == rows(streaming.events_per_hour(batch), *cols)


def test_sql_and_plans(spark, toy, ask):
    from transit_engine import plans, sqlapi

    sqlapi.register(toy)
    assert spark.sql("SELECT count(DISTINCT route_id) AS n FROM transit_events").first().n == 5
    sqlapi.register_function(spark, toy, "route_toy")
    got = spark.sql("SELECT t.n, t.arr FROM VALUES (0, 100, 28800) q(s, t, d), LATERAL route_toy(s, t, d) t")
    assert rows(got, "n", "arr") == [(0, 32400), (2, 31800)]
    ev = toy.events.where("trip_id = 1").select("arr")
    assert any("trip_id" in p for p in plans.pushed_filters(ev)) and plans.read_schemas(ev)
    plans.assert_no(transfers.generate(toy.with_(headway=None, offsets=None)), "CartesianProduct", "BroadcastNestedLoopJoin")


def test_feed_round_trip(spark, tmp_path, toy):
    from transit_engine import sources

    toy.events.select("trip_id", "idx", "stop_id", "arr").write.option("header", True).csv(str(tmp_path / "stop_times"))
    toy.walks.select("a", "b", "secs").write.option("header", True).csv(str(tmp_path / "walks"))
    net = sources.read_feed(spark, str(tmp_path), "csv")
    q = spark.createDataFrame([(1, 0, 100, 28800)], REQUESTS)
    assert rows(journeys.pareto(round_router.route(net, q, K).labels), "n", "arr") == [(0, 32400), (2, 31800)]


def test_all_orders_are_searched(spark, sf):
    from transit_engine import workloads

    asked = workloads.QUERIES["od_requests_all"](spark, sf)
    net, n = derive.regional(spark, sf), spark.read.parquet(f"{sf}/orders.parquet").count()
    assert 200 < asked.count() <= n and asked.agg({"req_id": "max"}).first()[0] > 200
    got = workloads.QUERIES["od_pareto_blocks_all"](spark, sf).groupBy("req_id").agg({"arr": "min"}).collect()
    best = {r.req_id: r[1] for r in kernels.route_blocks(net, asked, 9).groupBy("req_id").agg({"arr": "min"}).collect()}
    graph = {r.req_id: r.arr for r in workloads.QUERIES["od_event_graph_all"](spark, sf).collect()}
    assert best == graph and len(got) > 200 and all(r[1] >= graph[r.req_id] for r in got)


def test_layered_graph_and_cells_in_arrays(spark, sf, net):
    """The layered event graph, and the cell-pruned kernels, against the routers that they repeat."""
    q = written(derive.requests(spark, sf, net, 60))
    want = rows(kernels.route_blocks(net, q, K), "req_id", "n", "arr")
    assert rows(event_graph.layered(net, q, K + 1), "req_id", "n", "arr") == want and len(want) > 40
    tr = transfers.of(net, f"regional {sf}")
    nodes = written(cells.natural(net))
    stops = written(cells.stop_cells(net, nodes))
    cut = cells.cut_stops(stops)
    fill = written(fillin.compute(net, tr, nested.flat_pairs(cut), engine="arrays"))
    a = kernels.Arrays(net)
    own = kernels.Admission(a, cells.route_cells(nodes), fillin.as_trips(net, fill))
    ask = written(cells.label_requests(q, stops))
    assert rows(kernels.segment_blocks(net, tr, ask, K, a, cells=own), "req_id", "n", "arr") == want
    assert rows(kernels.route_blocks(net, ask, K, arrays=a, cells=own), "req_id", "n", "arr") == want
    some = written(cut.orderBy("stop_id").limit(4))
    g, goals = range_router.groups_of(net, some.withColumnRenamed("stop_id", "source"), some.withColumnRenamed("stop_id", "target"))
    cols = ("source", "target", "dep", "n", "arr")
    assert rows(kernels.fanout_blocks(net, tr, g, goals, 25200, 36000), *cols) == rows(range_router.fanout_segments(net, tr, g, goals, 25200, 36000).rows, *cols)


@pytest.mark.parametrize("seed", range(3))
def test_layers_and_reductions_on_irregular_networks(spark, seed):
    net = random_network(spark, seed)
    stops = [r.stop_id for r in net.stops.collect()]
    near = {(a, b) for a, b, _ in net.neighbourhood().collect()}
    r = random.Random(seed + 7)
    reqs = [(i, s, t, r.randint(0, 60) * 60) for i, (s, t) in enumerate(r.sample([(s, t) for s in stops for t in stops if (s, t) not in near], 10))]
    df = spark.createDataFrame(reqs, REQUESTS)
    want = sorted((i, n, a) for i, s, t, d in reqs for n, a in brute(net, s, t, d, 3))
    assert rows(event_graph.layered(net, df, 4), "req_id", "n", "arr") == want
    raw = written(transfers.generate(net))
    weak, full, dealt = (written(x) for x in (transfers.weakly_reduced(net, raw), transfers.reduced(net, raw), transfers.reduced(net, raw, most_events=0)))
    assert rows(full, *full.columns) == rows(dealt, *full.columns)
    assert full.exceptAll(raw).count() == full.join(weak, ["t1", "i1", "t2", "i2"], "left_anti").count() == 0
    for kept in (weak, full):
        assert rows(journeys.pareto(segment_router.route(net, df, kept, 3).labels), "req_id", "n", "arr") == want
        assert rows(kernels.segment_blocks(net, kept, df, 3), "req_id", "n", "arr") == want


@pytest.mark.parametrize("seed", range(4))
def test_one_search_serves_all_targets(spark, seed):
    """The event graph's search back through the day, against one search a request; also with rides and walks that take no time."""
    net = random_network(spark, seed)
    a = kernels.Arrays(net)
    if seed % 2:
        a.walk_s = a.walk_s * 0
        for _, times in a.routes:
            times[1] = times[0]
    lists, walks = kernels.departure_lists(a), kernels._walks_by_stop(a)
    graph, r = kernels.EventGraph(a), random.Random(seed)
    s, t, d = (np.array(x) for x in zip(*((r.randrange(len(a.ids)), r.randrange(len(a.ids)), r.randint(0, 100) * 60) for _ in range(300)), strict=True))
    want = [kernels.event_dijkstra(a, lists, int(x), int(y), int(z), walks) for x, y, z in zip(s, t, d, strict=True)]
    assert graph.earliest(s, t, d).tolist() == want and 0 < sum(x < 2**30 for x in want) < 300
    asked = spark.createDataFrame([(i, int(a.ids[x]), int(a.ids[y]), int(z)) for i, (x, y, z) in enumerate(zip(s, t, d, strict=True))], REQUESTS)
    if seed % 2 == 0:
        assert rows(event_graph.route(net, asked), "req_id", "arr") == [(i, x) for i, x in enumerate(want) if x < 2**30]


def test_searches_do_not_grow_with_requests(spark, net, monkeypatch):
    """One search a request took days over all orders."""
    count = []
    monkeypatch.setattr(kernels.EventGraph, "search", lambda self, s, t, d, until, f=kernels.EventGraph.search: count.append(len(s)) or f(self, s, t, d, until))
    a = kernels.Arrays(net)
    r, n = np.random.default_rng(3), len(a.ids)
    s, t, d = r.integers(0, n, 20_000), r.integers(0, n, 20_000), r.integers(18000, 54000, 20_000)
    arr = kernels.EventGraph(a).earliest(s, t, d)
    assert len(count) <= 5 and count[0] == 20_000 and (arr < 2**30).mean() > 0.5


@pytest.mark.parametrize("seed", range(3))
def test_sweeps_take_any_number_of_rides(spark, seed, monkeypatch):
    """Beyond the limit on broadcast events the sweep raised an error; rides are sorted by Spark there."""
    net = random_network(spark, seed)
    if seed == 1:  # first legs that take no time
        net = net.with_(events=written(net.events.withColumn("arr", F.when(F.col("idx") == 1, F.first("arr").over(Window.partitionBy("trip_id").orderBy("idx"))).otherwise(F.col("arr")).cast("int"))))
    a, r = kernels.Arrays(net), random.Random(seed)
    lists, walks = kernels.departure_lists(a), kernels._walks_by_stop(a)
    ask = [(i, r.randrange(len(a.ids)), r.randrange(len(a.ids)), r.randint(0, 100) * 60) for i in range(80)]
    df = spark.createDataFrame(ask, REQUESTS)
    want = [(i, x) for i, s, t, d in ask if (x := kernels.event_dijkstra(a, lists, int(a.of(s)), int(a.of(t)), d, walks)) < 2**30]
    assert 10 < len(want) < 80
    assert rows(event_graph.sweep(net, df), "req_id", "arr") == want
    monkeypatch.setattr(event_graph, "LABELS", 200)
    assert rows(event_graph.sweep(net, df, most_events=0), "req_id", "arr") == want
    assert event_graph.sweep(net, df.where("false"), most_events=0).count() == 0
