"""DuckDB SQL that derives the same answers: networks, searches and whole plans."""

from __future__ import annotations

from chargepath.config import TripOptions

G1 = """n AS (SELECT count(*) AS n, ceil(sqrt(1.5 * count(*)))::BIGINT AS w, count(*) // ceil(sqrt(1.5 * count(*)))::BIGINT AS h FROM customer),
nodes AS (SELECT c_custkey AS node, (c_custkey % w)::DOUBLE AS x, (c_custkey // w)::DOUBLE AS y, 300 + (round(100 * c_acctbal)::BIGINT + 100000) % 301 AS cost FROM customer, n),
steps AS (SELECT b.node + d AS src, b.node AS dst, b.cost AS weight FROM nodes b, n, (SELECT unnest([-1, 1, -w, w]) AS d FROM n) WHERE NOT (d = -1 AND b.x = 0) AND NOT (d = 1 AND b.x = w - 1)),
edges AS (SELECT src, dst, weight FROM steps, n WHERE src >= 0 AND src < n.n),
stations AS (SELECT s_suppkey AS station, ((v // h) % h) * w + v % w AS node, (v % w)::DOUBLE AS x, ((v // h) % h)::DOUBLE AS y, r_name AS plug
  FROM (SELECT *, round(100 * s_acctbal)::BIGINT + 100000 AS v FROM supplier), n, nation, region WHERE n_nationkey = s_nationkey AND r_regionkey = n_regionkey)"""
CORNER = "trips AS (SELECT 0::BIGINT AS trip, 0::BIGINT AS source, w * h - 1 AS target FROM n)"
BATCH = "trips AS (SELECT o_orderkey AS trip, o_custkey AS source, (31 * o_custkey + 17 * o_orderkey + 7) % n.n AS target FROM orders, n WHERE o_orderpriority = '1-URGENT' AND o_custkey <> (31 * o_custkey + 17 * o_orderkey + 7) % n.n)"
DEPOTS = "depots AS (SELECT c_nationkey AS nation, min(c_custkey) AS node FROM customer GROUP BY 1)"
PAIRS = f"{DEPOTS}, trips AS (SELECT (a.nation * 1000 + b.nation)::BIGINT AS trip, a.node AS source, b.node AS target FROM depots a JOIN depots b ON a.nation <> b.nation)"
DENSE = """stations2 AS (SELECT p_partkey AS station, ((v // h) % h) * w + v % w AS node, (v % w)::DOUBLE AS x, ((v // h) % h)::DOUBLE AS y FROM (SELECT p_partkey, p_partkey * 7919 + p_size * 104729 AS v FROM part), n)"""
G3 = """q AS (SELECT vec_id AS node, embedding[1]::DOUBLE AS x, embedding[2]::DOUBLE AS y FROM embeddings),
k AS (SELECT a.node AS a, b.node AS b, sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)) AS d, row_number() OVER (PARTITION BY a.node ORDER BY (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y), b.node) AS r FROM q a JOIN q b ON a.node <> b.node),
edges3 AS (SELECT DISTINCT src, dst, 1 + floor(100000 * d)::BIGINT AS weight FROM (SELECT a AS src, b AS dst, d FROM k WHERE r <= 6 UNION ALL SELECT b, a, d FROM k WHERE r <= 6))"""
G2 = """n2 AS (SELECT count(*) AS n, ceil(sqrt(1.5 * count(*)))::BIGINT AS w FROM orders),
segs AS (SELECT a, b, road_class, direction, weight FROM (SELECT l_orderkey AS a, CASE l_partkey % 4 WHEN 0 THEN l_orderkey + 1 WHEN 1 THEN l_orderkey + w WHEN 2 THEN l_orderkey - 1 ELSE l_orderkey - w END AS b,
  l_partkey % 4 AS side, l_returnflag AS road_class, l_linestatus AS direction, (60 + 10 * l_quantity)::BIGINT AS weight, n, w FROM lineitem, n2)
  WHERE b >= 0 AND b < n AND NOT (side = 0 AND a % w = w - 1) AND NOT (side = 2 AND a % w = 0)),
directed AS (SELECT a AS src, b AS dst, weight FROM segs WHERE road_class <> 'R' UNION ALL SELECT b, a, weight FROM segs WHERE road_class <> 'R' AND direction = 'F'),
edges2 AS (SELECT src, dst, min(weight) AS weight FROM directed WHERE src <> dst GROUP BY src, dst)"""


def reach(name: str, runs: str, edges: str = "edges") -> str:
    """A keyed recursion over runs(run, source, radius): name(run, node, dist)."""
    return f"""{name}(run, node, dist, radius) USING KEY (run, node) AS (
  SELECT run, source, 0::BIGINT, radius::BIGINT FROM {runs}
  UNION
  SELECT r.run, e.dst, min(r.dist + e.weight), any_value(r.radius) FROM {name} r JOIN {edges} e ON e.src = r.node LEFT JOIN recurring.{name} o ON o.run = r.run AND o.node = e.dst
  WHERE (o.dist IS NULL OR r.dist + e.weight < o.dist) AND (r.radius IS NULL OR r.dist + e.weight <= r.radius) GROUP BY r.run, e.dst)"""


def tight(name: str, found: str, edges: str = "edges") -> str:
    """name(run, node, dist, pred): the least predecessor on a shortest path."""
    return f"""{name} AS (SELECT t.run, t.node, t.dist, min(r.node) FILTER (r.dist + e.weight = t.dist) AS pred FROM {found} t LEFT JOIN {edges} e ON e.dst = t.node LEFT JOIN {found} r ON r.run = t.run AND r.node = e.src GROUP BY t.run, t.node, t.dist)"""


REVERSED = "rev AS (SELECT dst AS src, src AS dst, weight FROM edges)"


def plan(trips: str, opts: TripOptions, stations: str = "stations", extra: str = "") -> str:
    """WITH list of a whole plan; ends with chain(trip, layer, u, v, cost). Searches are shared by the node they start from."""
    radii = ", ".join(f"({k}, {opts.radius(k)})" for k in range(opts.max_widen + 1))
    tail = opts.capacity if opts.tail_rule == "capacity" else opts.step
    plugs = "" if opts.plugs is None else " WHERE plug IN ({})".format(", ".join(f"'{p}'" for p in opts.plugs))
    disk = {
        "out": reach("d1", "r1"),
        "in": reach("d1", "r1", "rev"),
        "both": f"{reach('da', 'r1')},\n{reach('db', 'r1', 'rev')},\nd1 AS (SELECT run, node, greatest(da.dist, db.dist) AS dist FROM da JOIN db USING (run, node))",
    }[opts.direction]
    order = "dist, station" if opts.order == "network" else "d2, station"
    return f"""WITH RECURSIVE {G1},
{extra}{trips},
{REVERSED},
places AS (SELECT station, node, x, y FROM {stations}{plugs}),
r0 AS (SELECT DISTINCT source AS run, source, NULL AS radius FROM trips),
{reach('d0', 'r0')},
{tight('p0', 'd0')},
way AS (SELECT t.trip, p.run, p.node, p.dist, p.pred FROM trips t JOIN p0 p ON p.run = t.source AND p.node = t.target
  UNION ALL SELECT q.trip, p.run, p.node, p.dist, p.pred FROM way q JOIN p0 p ON p.run = q.run AND p.node = q.pred),
total AS (SELECT t.trip, d.dist AS cost FROM trips t JOIN d0 d ON d.run = t.source AND d.node = t.target),
cuts AS (SELECT trip, 0 AS stop, -1::BIGINT AS node, 0::BIGINT AS cum, cost FROM total WHERE cost > {opts.capacity if opts.direct_if_within else 0}
  UNION ALL SELECT c.trip, c.stop + 1, arg_max(w.node, w.dist), max(w.dist), c.cost FROM cuts c JOIN way w ON w.trip = c.trip AND w.dist > c.cum AND w.dist <= c.cum + {opts.step} WHERE c.cost - c.cum > {tail} GROUP BY c.trip, c.stop, c.cost),
bases AS (SELECT trip, stop, node, cum FROM cuts WHERE stop > 0),
r1 AS (SELECT DISTINCT node AS run, node AS source, {opts.radius(opts.max_widen)} AS radius FROM bases),
{disk},
near AS (SELECT b.trip, b.stop, s.station, s.node, d.dist, (s.x - c.x) * (s.x - c.x) + (s.y - c.y) * (s.y - c.y) AS d2 FROM bases b JOIN nodes c ON c.node = b.node JOIN d1 d ON d.run = b.node JOIN places s ON s.node = d.node),
radii(k, radius) AS (VALUES {radii}),
found AS (SELECT trip, stop, k, radius, count(*) AS have FROM near, radii WHERE dist <= radius GROUP BY ALL),
picked AS (SELECT trip, stop, arg_min(radius, k) AS radius, min(k) AS k FROM found WHERE have >= CASE WHEN k < {opts.max_widen} THEN {opts.n} ELSE 1 END GROUP BY trip, stop),
cands AS (SELECT trip, stop, station, node, dist, k::INTEGER AS widen_round FROM (SELECT x.*, p.k, row_number() OVER (PARTITION BY x.trip, x.stop ORDER BY {order}) AS rk FROM near x JOIN picked p USING (trip, stop) WHERE x.dist <= p.radius) WHERE rk <= {opts.n}),
m AS (SELECT t.trip, coalesce(max(b.stop), 0) AS m FROM total t LEFT JOIN bases b USING (trip) GROUP BY t.trip),
have AS (SELECT trip, count(DISTINCT stop) AS c FROM cands GROUP BY trip),
good AS (SELECT m.trip, m.m FROM m LEFT JOIN have USING (trip) WHERE m.m = coalesce(have.c, 0)),
layers AS (SELECT t.trip, 0 AS layer, -1::BIGINT AS id, t.source AS node FROM trips t JOIN good USING (trip) UNION ALL SELECT c.trip, c.stop, c.station, c.node FROM cands c JOIN good USING (trip)
  UNION ALL SELECT t.trip, m + 1, -2, t.target FROM trips t JOIN good USING (trip)),
r2 AS (SELECT DISTINCT node AS run, node AS source, {opts.limit} AS radius FROM layers),
{reach('d2', 'r2')},
legs AS (SELECT a.trip, a.layer, a.id AS u, b.id AS v, a.node AS u_node, b.node AS v_node, d.dist AS cost FROM layers a JOIN layers b ON b.trip = a.trip AND b.layer = a.layer + 1 AND a.id <> b.id JOIN d2 d ON d.run = a.node AND d.node = b.node),
dp AS (SELECT trip, layer, v, cost * 1048576 + u + 2 AS enc FROM legs WHERE layer = 0
  UNION ALL SELECT l.trip, l.layer, l.v, min((d.enc // 1048576 + l.cost) * 1048576 + l.u + 2) FROM dp d JOIN legs l ON l.trip = d.trip AND l.layer = d.layer + 1 AND l.u = d.v GROUP BY l.trip, l.layer, l.v),
back AS (SELECT trip, layer, v, enc % 1048576 - 2 AS u FROM dp WHERE v = -2
  UNION ALL SELECT d.trip, d.layer, d.v, d.enc % 1048576 - 2 FROM back b JOIN dp d ON d.trip = b.trip AND d.layer = b.layer - 1 AND d.v = b.u),
chain AS (SELECT b.trip, b.layer, b.u, b.v, l.cost FROM back b JOIN legs l USING (trip, layer, u, v))
"""


#: Status of each trip, after ``plan``.
STATUS = """SELECT t.trip, CASE WHEN c.trip IS NOT NULL THEN 'ok' WHEN g.trip IS NOT NULL THEN 'no_leg_chain' WHEN w.trip IS NOT NULL THEN 'no_candidate' ELSE 'no_path' END AS status{more}
FROM trips t LEFT JOIN total w USING (trip) LEFT JOIN good g USING (trip) LEFT JOIN (SELECT trip, sum(cost)::BIGINT AS cost FROM chain GROUP BY trip) c USING (trip)"""


def paths_of_legs(more: str = "") -> str:
    """Walks each leg of the chain back along the least predecessors; walk(trip, layer, node, dist)."""
    return f"""r3 AS (SELECT DISTINCT u_node AS run, u_node AS source, NULL AS radius FROM legs JOIN chain USING (trip, layer, u, v)),
{reach('d3', 'r3')},
{tight('p3', 'd3')},
walk AS (SELECT l.trip, l.layer, p.run, p.node, p.dist, p.pred FROM chain c JOIN legs l USING (trip, layer, u, v) JOIN p3 p ON p.run = l.u_node AND p.node = l.v_node
  UNION ALL SELECT q.trip, q.layer, p.run, p.node, p.dist, p.pred FROM walk q JOIN p3 p ON p.run = q.run AND p.node = q.pred){more}"""


def exact(trips: str, capacity: int) -> str:
    """The cheapest chain over all stations with no leg over the capacity: trip, cost."""
    return f"""WITH RECURSIVE {G1}, {trips}, places AS (SELECT node FROM stations UNION SELECT source FROM trips UNION SELECT target FROM trips),
rp AS (SELECT node AS run, node AS source, {capacity} AS radius FROM places), {reach('dp', 'rp')},
sites AS (SELECT DISTINCT node FROM stations),
arcs AS (SELECT run AS src, node AS dst, dist AS weight FROM dp WHERE run <> node AND run IN (FROM sites) AND node IN (FROM sites)),
rs AS (SELECT t.trip, d.node, d.dist FROM trips t JOIN dp d ON d.run = t.source WHERE d.node IN (FROM sites)),
de(run, node, dist) USING KEY (run, node) AS (SELECT trip, node, dist FROM rs UNION
  SELECT r.run, a.dst, min(r.dist + a.weight) FROM de r JOIN arcs a ON a.src = r.node LEFT JOIN recurring.de o ON o.run = r.run AND o.node = a.dst WHERE o.dist IS NULL OR r.dist + a.weight < o.dist GROUP BY r.run, a.dst),
ways AS (SELECT t.trip, d.dist AS cost FROM trips t JOIN dp d ON d.run = t.source AND d.node = t.target UNION ALL
  SELECT t.trip, e.dist + d.dist FROM trips t JOIN de e ON e.run = t.trip JOIN dp d ON d.run = e.node AND d.node = t.target),
best AS (SELECT trip, min(cost) AS cost FROM ways GROUP BY trip)
"""


def greedy(trips: str, capacity: int) -> str:
    """Always on to the reachable station nearest to the target, while that comes nearer: trip, cost, stops."""
    return f"""WITH RECURSIVE {G1}, {trips}, {REVERSED},
rp AS (SELECT node AS run, node AS source, {capacity} AS radius FROM (SELECT node FROM stations UNION SELECT source FROM trips)), {reach('dp', 'rp')},
rt AS (SELECT DISTINCT target AS run, target AS source, NULL AS radius FROM trips), {reach('dt', 'rt', 'rev')},
sites AS (SELECT node, min(station) AS station FROM stations GROUP BY node),
hops AS (SELECT run AS at, d.node AS to_node, dist, station FROM dp d JOIN sites s ON s.node = d.node),
g AS (SELECT t.trip, t.target, t.source AS at, 0::BIGINT AS cost, 0 AS stops, d.dist AS rest FROM trips t JOIN dt d ON d.run = t.target AND d.node = t.source
  UNION ALL SELECT trip, target, m.n, m.c, stops + 1, m.a FROM (SELECT g.trip, g.target, g.stops, min({{'a': d.dist, 's': h.station, 'n': h.to_node, 'c': g.cost + h.dist}}) AS m
    FROM g JOIN hops h ON h.at = g.at JOIN dt d ON d.run = g.target AND d.node = h.to_node WHERE g.rest > {capacity} AND d.dist < g.rest GROUP BY g.trip, g.target, g.stops))
SELECT trip, cost + rest AS cost, stops FROM g WHERE rest <= {capacity}"""


def sweep(settings: list[TripOptions], penalties: tuple[int, ...]) -> str:
    """Plans between depots under several settings, summed up by a cube."""
    parts = [f"SELECT {o.capacity} AS capacity, {o.n} AS n, {o.alpha}::DOUBLE AS alpha, cost FROM ({plan(PAIRS, o)} SELECT trip, sum(cost)::BIGINT AS cost FROM chain GROUP BY trip)" for o in settings]
    return f"""SELECT capacity, n, alpha, penalty, count(*) AS trips, round(avg(cost * (capacity + penalty) / capacity), 4) AS mean_cost_adj
FROM ({' UNION ALL '.join(parts)}), (SELECT unnest({list(penalties)}) AS penalty) GROUP BY CUBE (capacity, n, alpha, penalty)"""
