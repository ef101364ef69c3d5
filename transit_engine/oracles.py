"""SQL texts that give the same rows as the queries, for DuckDB on the same tables."""

from __future__ import annotations


def network(mesh: bool = False, limit: int | None = None) -> str:
    """Common table expressions of a derived network: st (stops), rs (route stops), off (offsets), hw
    (headways), tr (trips), ev (events), wk (closed walks), nb (with self)."""
    limit = limit or (120 if mesh else 180)
    visits = (
        """numbered AS (SELECT *, row_number() OVER (ORDER BY region, pos) - 1 AS g FROM st),
sv AS (SELECT k, i, plain AS n, stop_id FROM (SELECT *, unnest(generate_series(0, plain - 1)) AS i FROM sup) s
       JOIN numbered ON g = (k * 37 + i * (step * 17 + 1)) % (SELECT count(*) FROM st)),"""
        if mesh
        else """sz AS (SELECT region, count(*) AS m FROM st GROUP BY region),
sx AS (SELECT *, CASE WHEN trunk THEN (home + i) % 5 ELSE home END AS reg FROM
       (SELECT *, CASE WHEN trunk THEN 5 ELSE plain END AS n, unnest(generate_series(0, CASE WHEN trunk THEN 5 ELSE plain END - 1)) AS i FROM sup) q),
sv AS (SELECT k, i, n, stop_id FROM sx JOIN sz ON sz.region = sx.reg JOIN st ON st.region = sx.reg AND st.pos =
       CASE WHEN trunk OR (i = 0 AND k % 3 = 0) THEN 0 ELSE 1 + (k * 37 + i * step) % (m - 1) END),"""
    )
    return f"""
sreg AS (SELECT s_suppkey::BIGINT AS k, n_regionkey AS home FROM supplier JOIN nation ON s_nationkey = n_nationkey),
sup AS (SELECT k, home, 1 + k % 3 AS step, 6 + k % 5 AS plain, k % 10 = 9 AS trunk FROM sreg),
creg AS (SELECT c_custkey, c_mktsegment, n_regionkey AS region FROM customer JOIN nation ON c_nationkey = n_nationkey),
st AS MATERIALIZED (SELECT stop_id, region, pos, poi FROM (SELECT c_custkey::BIGINT AS stop_id, region, row_number() OVER (PARTITION BY region ORDER BY c_custkey) - 1 AS pos,
       c_mktsegment AS poi FROM creg) c JOIN (SELECT home, 3 * count(*) + 6 AS most FROM sreg GROUP BY home) h ON h.home = c.region WHERE pos < most),
{visits}
bothways AS (SELECT 2 * k AS route_id, i, stop_id FROM sv UNION ALL SELECT 2 * k + 1, n - 1 - i, stop_id FROM sv),
rs AS MATERIALIZED (SELECT route_id, row_number() OVER (PARTITION BY route_id ORDER BY i) - 1 AS idx, stop_id FROM
       (SELECT route_id, stop_id, min(i) AS i FROM bothways GROUP BY ALL)),
lg AS (SELECT *, coalesce(120 + 60 * ((lag(stop_id) OVER w + stop_id) % 5), 0) AS leg FROM rs WINDOW w AS (PARTITION BY route_id ORDER BY idx)),
off AS MATERIALIZED (SELECT route_id, idx, stop_id, sum(leg) OVER (PARTITION BY route_id ORDER BY idx)::INT AS o FROM lg),
hw AS (SELECT route_id, 18000 + route_id % 7 * 60 AS f, 600 + 300 * ((route_id // 2) % 4) AS h FROM (SELECT DISTINCT route_id FROM rs)),
tr AS (SELECT route_id * 1000 + rank AS trip_id, route_id, rank, f + rank * h AS start FROM
       (SELECT *, unnest(generate_series(0, (86400 - f + h - 1) // h - 1)) AS rank FROM hw)),
ev AS MATERIALIZED (SELECT trip_id, tr.route_id, rank, idx, stop_id, (start + o)::INT AS arr FROM tr JOIN off ON off.route_id = tr.route_id),
near1 AS (SELECT x.stop_id AS a, y.stop_id AS b, CASE WHEN x.pos % 4 = 0 THEN 90 + 30 * ((x.pos // 4) % 4)
       WHEN x.pos % 4 = 1 AND (x.pos // 4) % 3 = 0 THEN 100 + 20 * ((x.pos // 4) % 6) END AS secs FROM st x JOIN st y ON x.region = y.region AND y.pos = x.pos + 1),
w1 AS (SELECT a, b, secs FROM near1 WHERE secs <= {limit} UNION ALL SELECT b, a, secs FROM near1 WHERE secs <= {limit}),
w2 AS (SELECT a, b, min(secs) AS secs FROM (SELECT * FROM w1 UNION ALL SELECT x.a, y.b, x.secs + y.secs FROM w1 x JOIN w1 y ON x.b = y.a AND x.a <> y.b) GROUP BY a, b),
wk AS MATERIALIZED (SELECT a, b, min(secs)::INT AS secs FROM (SELECT * FROM w2 UNION ALL SELECT x.a, y.b, x.secs + y.secs FROM w2 x JOIN w2 y ON x.b = y.a AND x.a <> y.b) GROUP BY a, b),
nb AS MATERIALIZED (SELECT stop_id AS a, stop_id AS b, 0 AS secs FROM st UNION ALL SELECT * FROM wk)"""


def with_(body: str, mesh: bool = False, limit: int | None = None) -> str:
    return f"WITH {network(mesh, limit).strip()},\n{body}"


REQUESTS = """
served AS (SELECT stop_id, row_number() OVER (ORDER BY stop_id) - 1 AS at FROM (SELECT DISTINCT stop_id FROM rs)),
rq0 AS (SELECT o_orderkey::BIGINT AS req_id, o_custkey % (SELECT count(*) FROM served) AS sa, (o_orderkey * 7919 + 13) % (SELECT count(*) FROM served) AS ta,
        (18000 + o_orderkey % 1200 * 30)::INT AS dep FROM orders WHERE o_orderkey <= {most}),
rq AS (SELECT req_id, s.stop_id AS source, t.stop_id AS target, dep FROM rq0 JOIN served s ON s.at = sa JOIN served t ON t.at = ta
       WHERE NOT EXISTS (SELECT 1 FROM nb WHERE nb.a = s.stop_id AND nb.b = t.stop_id))"""


def rounds(start: str, k: int = 4) -> str:
    """Label-correcting rounds over all stops, unrolled: l0..lk (req_id, stop_id, t), arrivals after at
    most n transfers, from start (req_id, stop_id, t). Trips are found by arithmetic on the headway."""
    out = ["hb AS MATERIALIZED (SELECT off.route_id, idx, stop_id, f, h, o, (86400 - f + h - 1) // h AS nt, max(idx) OVER (PARTITION BY off.route_id) AS last FROM off JOIN hw ON hw.route_id = off.route_id)"]
    prev = start
    for n in range(k + 1):
        out.append(f"b{n} AS MATERIALIZED (SELECT req_id, route_id, idx, rank, f, h FROM (SELECT q.req_id, v.*, greatest(0, (q.t - f - o + h - 1) // h) AS rank FROM {prev} q JOIN hb v ON v.stop_id = q.stop_id) WHERE rank < nt AND idx < last)")
        out.append(f"a{n} AS MATERIALIZED (SELECT b.req_id, e.stop_id, min(b.f + b.h * b.rank + e.o) AS t FROM b{n} b JOIN hb e ON e.route_id = b.route_id AND e.idx > b.idx GROUP BY ALL)")
        known = f"SELECT req_id, nb.b AS stop_id, a.t + secs AS t FROM a{n} a JOIN nb ON nb.a = a.stop_id"
        if n:
            known += f" UNION ALL SELECT req_id, stop_id, t FROM l{n - 1}"
        out.append(f"l{n} AS MATERIALIZED (SELECT req_id, stop_id, min(t)::INT AS t FROM ({known}) GROUP BY ALL)")
        prev = f"l{n}"
    return ",\n".join(out)


def source_start(rq: str = "rq") -> str:
    return f"s0 AS (SELECT req_id, nb.b AS stop_id, min(dep + secs) AS t FROM {rq} JOIN nb ON nb.a = source GROUP BY ALL)"


def labels(k: int = 4) -> str:
    return "lab AS (" + " UNION ALL ".join(f"SELECT l.req_id, {n} AS n, l.t AS arr FROM l{n} l JOIN rq ON rq.req_id = l.req_id AND rq.target = l.stop_id" for n in range(k + 1)) + ")"


PARETO = """SELECT req_id, n::INT AS n, arr FROM (SELECT *, min(arr) OVER (PARTITION BY req_id ORDER BY n ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS b FROM lab) WHERE b IS NULL OR arr < b"""


def od(select: str = PARETO, mesh: bool = False, most: int = 200, k: int = 4) -> str:
    return with_(",\n".join([REQUESTS.format(most=most).strip(), source_start(), rounds("s0", k), labels(k)]) + "\n" + select, mesh)


XFER = """last AS (SELECT route_id, max(idx) AS last FROM rs GROUP BY route_id),
xn AS MATERIALIZED (SELECT e.trip_id AS t1, e.route_id AS r1, e.rank AS k1, e.idx AS i1, nb.b, e.arr + secs AS tau FROM ev e JOIN nb ON nb.a = e.stop_id WHERE e.idx > 0),
vb AS MATERIALIZED (SELECT off.route_id, off.idx, stop_id, f + o AS f0, h FROM off JOIN hw ON hw.route_id = off.route_id JOIN last ON last.route_id = off.route_id WHERE idx < last),
pr AS MATERIALIZED (SELECT t1, r1, k1, i1, route_id, idx, greatest(0, (tau - f0 + h - 1) // h) AS rk FROM xn JOIN vb ON vb.stop_id = xn.b),
tf AS (SELECT t1, i1, tr.trip_id AS t2, p.idx AS i2, p.route_id AS route2, tr.rank AS rank2, r1, k1 FROM pr p JOIN tr ON tr.route_id = p.route_id AND tr.rank = p.rk)"""

HYPER = """
wn AS (SELECT (1::BIGINT << 50) + a * 10000000 + b AS node_id, a, b FROM wk WHERE a < b),
inc AS (SELECT DISTINCT stop_id, route_id AS node_id FROM rs UNION ALL SELECT a, node_id FROM wn UNION ALL SELECT b, node_id FROM wn)"""

CELLS = HYPER + """,
vote AS (SELECT node_id, region, count(*) AS k FROM inc JOIN st USING (stop_id) GROUP BY ALL),
nc AS (SELECT node_id, (arg_max(region, k * 1000 - region) + 1)::INT AS cell FROM vote GROUP BY node_id),
sc AS (SELECT stop_id, CASE WHEN min(cell) = max(cell) THEN min(cell) ELSE 0 END::INT AS cell FROM inc JOIN nc USING (node_id) GROUP BY stop_id)"""

STATS = """SELECT (SELECT count(*) FROM st) AS stops, (SELECT count(DISTINCT stop_id) FROM rs) AS served, (SELECT count(DISTINCT route_id) FROM rs) AS routes, (SELECT count(*) FROM tr) AS trips,
(SELECT count(*) FROM wk) AS walks, (SELECT count(*) FROM ev) AS stop_events, (SELECT count(DISTINCT node_id) FROM inc) AS hypernodes,
(SELECT count(DISTINCT pins) FROM (SELECT stop_id, list_sort(list(DISTINCT node_id)) AS pins FROM inc GROUP BY stop_id HAVING count(DISTINCT node_id) > 1)) AS hyperedges"""

CHAINS = """
l AS (SELECT l_orderkey::BIGINT AS trip_id, l_suppkey::BIGINT AS stop_id, (l_shipdate::DATE - DATE '1970-01-01')::INT AS arr, row(l_shipdate, l_linenumber, l_partkey) AS o FROM lineitem),
fs AS (SELECT trip_id, stop_id, min(o) AS o, arg_min(arr, o) AS arr FROM l GROUP BY ALL),
ce AS (SELECT trip_id, (row_number() OVER w - 1)::INT AS idx, stop_id, arr FROM (SELECT *, count(*) OVER (PARTITION BY trip_id) AS size FROM fs) WHERE size > 1 WINDOW w AS (PARTITION BY trip_id ORDER BY o))"""
