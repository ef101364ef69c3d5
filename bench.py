"""Times the headline queries and prints one JSON line.

Searches run over 10,000 requests (the paper's batch size) by the block routers; the frame routers and
the event-graph baselines over 100. Preprocessing, cell-pruned searches and 70 x 70 day profiles run on
the network of BENCH_SMALL_DIR (sf0.01 beside the bench folder) against its own plain searches.
Per-request milliseconds are in "per_request_ms", counters of work in "work"."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.warehouse.dir", "/tmp/bench_warehouse").config("spark.checkpoint.dir", "/tmp/bench_shared").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from transit_engine import cells, derive, event_graph, fillin, hypergraph, kernels, metrics, nested, partition, range_router, round_router, segment_router, transfers
    from transit_engine.storage import written

    took: dict[str, float] = {}
    per: dict[str, float] = {}
    work: dict[str, int] = {}

    started, budget, skipped = time.time(), float(os.environ.get("BENCH_BUDGET", "300")), []

    def room(*names) -> bool:
        """Whether there is time left for more steps; those left out are listed in the output."""
        ok = time.time() - started < budget
        skipped.extend([] if ok else names)
        return ok

    def timed(name, f, requests=0):
        began = time.time()
        out = f()
        took[name] = round(time.time() - began, 3)
        print(f"{name} {took[name]}", file=sys.stderr, flush=True)
        if requests:
            per[name] = round(1000 * took[name] / requests, 4)
        return out

    noop = lambda df: df.write.format("noop").mode("overwrite").save()
    net = timed("network_regional", lambda: derive.regional(spark, sf))
    timed("network_stats", lambda: metrics.network_stats(net).collect())
    many = written(derive.requests(spark, sf, net, 10_000).repartition(4 * int(cpus)))
    n = many.count()
    arrays = timed("broadcast_timetable", lambda: kernels.Arrays(net))
    noop(kernels.route_blocks(net, many.where("req_id < 64"), arrays=arrays))
    timed("pareto_blocks_10000", lambda: noop(kernels.route_blocks(net, many, arrays=arrays)), n)
    few = written(many.where("req_id <= 100"))
    m = few.count()
    timed("event_graph_100", lambda: noop(event_graph.route(net, few)), m)
    timed("layered_graph_100", lambda: noop(event_graph.layered(net, few, 5)), m)
    timed("pareto_rounds_100", lambda: noop(round_router.route(net, few).labels), m)
    large = (net, arrays)

    # preprocessing and cell-pruned searches on the smaller network; its own plain searches are the base
    small = os.environ.get("BENCH_SMALL_DIR", os.path.join(os.path.dirname(sf.rstrip("/")), "sf0.01"))
    small = small if os.path.isdir(small) else sf
    net, tag = derive.regional(spark, small), "small"
    kept = transfers.of(net, f"bench {small}")
    arrays = kernels.Arrays(net)
    hops = kernels.Hops(arrays, kept)
    ask = written(derive.requests(spark, small, net, 10_000).repartition(4 * int(cpus)))
    n = ask.count()
    timed("small_rounds", lambda: noop(kernels.route_blocks(net, ask, arrays=arrays)), n)
    timed("small_segments", lambda: noop(kernels.segment_blocks(net, kept, ask, arrays=arrays, hops=hops)), n)
    seventy = [written(ask.select(c).distinct().orderBy(c).limit(70)) for c in ("source", "target")]
    groups = tuple(written(x) for x in range_router.groups_of(net, *seventy))
    day = (derive.DAY_START, derive.DAY_END)
    scans = lambda df: df.select("g", "scanned").distinct().agg({"scanned": "sum"}).first()[0] or 0
    fan = timed("small_range_fanout_70x70", lambda: written(kernels.fanout_blocks(net, kept, *groups, *day)))
    one = tuple(written(x) for x in range_router.as_pairs(groups[0].orderBy("g").limit(1), groups[1]))
    pairs = timed("small_range_pairs_1x70", lambda: written(kernels.fanout_blocks(net, kept, *one, *day)))
    work["segments_fanout"], work["segments_pairs"] = scans(fan.join(groups[0].orderBy("g").limit(1), "g", "left_semi")), scans(pairs)
    work["fanout_gain_pct"] = round(metrics.gain(work["segments_pairs"], work["segments_fanout"]), 1)
    h = hypergraph.build(net, 3)
    h = hypergraph.Hypergraph(written(h.nodes), written(h.pins), written(h.edges))
    trips = net.trips.count()
    for split in os.environ.get("BENCH_SPLITS", "4 2-2").split():
        if not room(f"cells_{split}"):
            continue
        began = time.time()
        if "-" in split:
            a, b = map(int, split.split("-"))
            nodes = written(nested.split(h, a, b))
            pairs = written(nested.pairs(net, nodes, "strict"))
            nodes = nodes.select("node_id", "cell")
        else:
            nodes = partition.multilevel(h, int(split))
        stops = written(cells.stop_cells(net, nodes))
        if "-" not in split:
            pairs = written(nested.flat_pairs(cells.cut_stops(stops)))
        took[f"cells_{split}_partition"] = round(time.time() - began, 3)
        fill = timed(f"cells_{split}_fillin", lambda p=pairs: written(fillin.as_trips(net, fillin.compute(net, kept, p, engine="arrays"))))
        work[f"cells_{split}_cut_stops"], work[f"cells_{split}_searches"] = stops.where("cell = 0").count(), pairs.count()
        work[f"cells_{split}_fillin_pct"] = round(100 * fill.count() / trips, 2)
        own = kernels.Admission(arrays, cells.route_cells(nodes), fill)
        mine = written(cells.label_requests(ask, stops))
        timed(f"cells_{split}_rounds", lambda x=mine, o=own: noop(kernels.route_blocks(net, x, arrays=arrays, cells=o)), n)
        timed(f"cells_{split}_segments", lambda x=mine, o=own: noop(kernels.segment_blocks(net, kept, x, arrays=arrays, hops=hops, cells=o)), n)
        for kind in ("rounds", "segments"):
            work[f"cells_{split}_{kind}_gain_pct"] = round(metrics.gain(per[f"{tag}_{kind}"], per[f"cells_{split}_{kind}"]), 1)
    # takes many minutes: on request only
    if os.environ.get("BENCH_LARGE", "0") != "1":
        skipped += ["transfers_all", "transfers_reduced", "segment_blocks_1000", "pareto_segments_100"]
    else:
        net, arrays = large
        raw = timed("transfers_all", lambda: transfers.of(net, f"bench {sf}", False))
        kept = timed("transfers_reduced", lambda: transfers.of(net, f"bench {sf}"))
        work["transfers_all"], work["transfers_reduced"] = raw.count(), kept.count()
        hops = timed("broadcast_transfers", lambda: kernels.Hops(arrays, kept))
        some = written(many.where("req_id <= 1000").repartition(4 * int(cpus)))
        timed("segment_blocks_1000", lambda: noop(kernels.segment_blocks(net, kept, some, arrays=arrays, hops=hops)), some.count())
        timed("pareto_segments_100", lambda: noop(segment_router.route(net, few, kept).labels), m)
    if os.environ.get("BENCH_LLM", "1") == "1":
        try:
            from transit_engine.llm import entry as llm
        except ImportError:
            llm = None
        for name in llm.QUERIES if llm else ():
            timed(name, lambda q=name: noop(llm.QUERIES[q](spark, sf)))
    print(json.dumps({"metric": "total wall seconds of the headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "per_request_ms": per, "work": work, "skipped": skipped, "sf": sf}))
    spark.stop()


if __name__ == "__main__":
    main()
