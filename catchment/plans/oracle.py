"""DuckDB statements that recompute the queries on the same tables, by definitions: all pairs, inequalities, unions."""

from __future__ import annotations

from .registry import BOX, CAPACITY_RUNS, CUBE_RUNS, LINF_RUNS, NEAR, NEW_CAP, PIXELS, RATIO_RUNS, RATIO_RUNS_L2, RIDE, SIZE_RUNS, SIZE_RUNS_L2

DIST = {"linf": "greatest(abs(x - fx), abs(y - fy))", "l1": "abs(x - fx) + abs(y - fy)", "l2": "(x - fx) * (x - fx) + (y - fy) * (y - fy)"}


def hexed(key: str, first: int, digits: int) -> str:
    return f"('0x' || substr(md5({key}::VARCHAR), {first}, {digits}))::BIGINT"


SETS = {
    "ord": "SELECT o_orderkey AS id, round(o_totalprice * 100)::BIGINT AS x, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) * 20000 AS y FROM orders",
    "evt": "SELECT event_id AS id, round(value * 100)::BIGINT AS x, date_diff('minute', TIMESTAMP '2024-01-01', ts) AS y FROM events",
    "uni": f"SELECT o_orderkey AS id, {hexed('o_orderkey', 9, 5)} AS x, {hexed('o_orderkey', 14, 5)} AS y FROM orders",
    "zip": f"SELECT o_orderkey AS id, floor(1048576.0::DOUBLE * pow({hexed('o_orderkey', 9, 5)} / 1048576.0::DOUBLE, 1.25))::BIGINT AS x, floor(1048576.0::DOUBLE * pow({hexed('o_orderkey', 14, 5)} / 1048576.0::DOUBLE, 1.25))::BIGINT AS y FROM orders",
    "emb": "SELECT vec_id AS id, round(embedding[1]::DOUBLE * 1e6)::BIGINT AS x, round(embedding[2]::DOUBLE * 1e6)::BIGINT AS y FROM embeddings",
    "part": "SELECT p_partkey AS id, p_size * 200 AS x, round(p_retailprice * 100)::BIGINT AS y FROM part",
}

MARKET = f"""clients AS (
  SELECT c_custkey AS oid, round(c_acctbal * 100)::BIGINT AS x, {hexed('c_custkey', 14, 5)} AS y, coalesce(k, 0) AS weight, c_nationkey::VARCHAR AS grp
  FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS k FROM orders GROUP BY 1) ON o_custkey = c_custkey),
facilities AS (SELECT s_suppkey AS fid, round(s_acctbal * 100)::BIGINT AS fx, {hexed('s_suppkey', 14, 5)} AS fy, s_nationkey + 5 AS cap FROM supplier)"""

QUERIES = "queries AS (SELECT p_partkey AS qid, p_size * 20000 - 50000 AS x, round(p_retailprice * 100)::BIGINT * 5 AS y FROM part)"


def sampled(name: str, n: int, ratio: int, n_f: int | None = None) -> str:
    return f"""points AS ({SETS[name]}),
numbered AS (SELECT *, row_number() OVER (ORDER BY {hexed('id', 1, 8)}, id) AS k FROM points),
clients AS (SELECT id AS oid, x, y, 1 AS weight FROM numbered WHERE k <= {n}),
facilities AS (SELECT id AS fid, x AS fx, y AS fy FROM numbered WHERE k > {n} AND k <= {n + (n_f or max(1, n // ratio))})"""


def near(metric: str) -> str:
    return f"""near AS (SELECT oid, x, y, weight, min(d) AS r FROM (SELECT c.*, {DIST[metric]} AS d FROM clients c, facilities) GROUP BY ALL)"""


def squares(metric: str) -> str:
    u, v = ("x - y", "x + y") if metric == "l1" else ("x", "y")
    return f"""{near(metric)},
circles AS (SELECT oid, weight, {u} - r AS xl, {u} + r AS xh, {v} - r AS yl, {v} + r AS yh FROM near),
sq AS (SELECT xl, xh, yl, yh, min(oid) AS oid, count(*) AS n, sum(weight)::BIGINT AS weight FROM circles WHERE xl < xh GROUP BY 1, 2, 3, 4)"""


SLABS = """xs AS (SELECT xl AS x FROM sq UNION SELECT xh FROM sq),
slabs AS (SELECT x AS x0, x1 FROM (SELECT x, lead(x) OVER (ORDER BY x) AS x1 FROM xs) WHERE x1 IS NOT NULL),
live AS (SELECT x0, x1, sq.* FROM slabs JOIN sq ON xl <= x0 AND xh >= x1)"""

PAIRS = f"""{SLABS},
turns AS (
  SELECT x0, x1, y, sum(dn) AS dn, sum(dw) AS dw FROM (
    SELECT x0, x1, yl AS y, n AS dn, weight AS dw FROM live UNION ALL SELECT x0, x1, yh, -n, -weight FROM live) GROUP BY 1, 2, 3),
pairs AS (
  SELECT x0, x1, y AS y0, y1, n, w FROM (
    SELECT x0, x1, y, lead(y) OVER (PARTITION BY x0 ORDER BY y) AS y1,
      (sum(dn) OVER (PARTITION BY x0 ORDER BY y))::BIGINT AS n, (sum(dw) OVER (PARTITION BY x0 ORDER BY y))::BIGINT AS w FROM turns)
  WHERE y1 IS NOT NULL)"""

INTERVALS = """spans AS (SELECT xl AS x, yl AS lo, yh AS hi FROM sq UNION ALL SELECT xh, yl, yh FROM sq),
opened AS (SELECT *, CASE WHEN lo <= max(hi) OVER (PARTITION BY x ORDER BY lo, hi ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) THEN 0 ELSE 1 END AS opens FROM spans),
islands AS (SELECT *, sum(opens) OVER (PARTITION BY x ORDER BY lo, hi ROWS UNBOUNDED PRECEDING) AS iv FROM opened),
intervals AS (SELECT x, iv::BIGINT AS iv_id, min(lo) AS lo, max(hi) AS hi FROM islands GROUP BY 1, 2)"""

CHANGED = f"""{PAIRS}, {INTERVALS},
changed AS (SELECT p.* FROM pairs p JOIN intervals i ON p.x0 = i.x AND i.lo <= p.y0 AND p.y1 <= i.hi)"""

MEMBERS = """held AS (
  SELECT p.x0, p.x1, p.y0, p.y1, c.oid FROM {labels} p JOIN circles c ON c.xl <= p.x0 AND p.x1 <= c.xh AND c.yl <= p.y0 AND p.y1 <= c.yh AND c.xl < c.xh)"""

EULER = """flat AS (SELECT DISTINCT y, a, b FROM (SELECT yl AS y, xl AS a, xh AS b FROM sq UNION ALL SELECT yh, xl, xh FROM sq)),
tall AS (SELECT DISTINCT x, a, b FROM (SELECT xl AS x, yl AS a, yh AS b FROM sq UNION ALL SELECT xh, yl, yh FROM sq)),
corners AS (SELECT DISTINCT x, y FROM flat f JOIN tall t ON x BETWEEN f.a AND f.b AND y BETWEEN t.a AND t.b),
along AS (SELECT x, y, lead(x) OVER (PARTITION BY y ORDER BY x) AS nx, lead(y) OVER (PARTITION BY x ORDER BY y) AS ny FROM corners),
e AS (SELECT (SELECT count(*) FROM along g WHERE nx IS NOT NULL AND EXISTS (SELECT 1 FROM flat f WHERE f.y = g.y AND f.a <= g.x AND f.b >= g.nx))
  + (SELECT count(*) FROM along g WHERE ny IS NOT NULL AND EXISTS (SELECT 1 FROM tall t WHERE t.x = g.x AND t.a <= g.y AND t.b >= g.ny)) AS e),
touch AS (SELECT a.oid AS u, b.oid AS v FROM sq a JOIN sq b ON a.oid <> b.oid AND a.xl <= b.xh AND b.xl <= a.xh AND a.yl <= b.yh AND b.yl <= a.yh
  WHERE NOT (a.xl < b.xl AND b.xh < a.xh AND a.yl < b.yl AND b.yh < a.yh) AND NOT (b.xl < a.xl AND a.xh < b.xh AND b.yl < a.yl AND a.yh < b.yh)),
reach AS (SELECT oid AS u, oid AS v FROM sq UNION SELECT r.u, t.v FROM reach r JOIN touch t ON r.v = t.u),
parts AS (SELECT count(DISTINCT least) AS c FROM (SELECT u, min(v) AS least FROM reach GROUP BY u))"""


def nn(metric: str) -> str:
    return f"""WITH {MARKET}
SELECT oid, d AS r, fid AS nn_fid FROM (
  SELECT oid, fid, d, row_number() OVER (PARTITION BY oid ORDER BY d, fid) AS k FROM (SELECT oid, fid, {DIST[metric]} AS d FROM clients, facilities)) WHERE k = 1"""


def mono(name: str) -> str:
    return f"""WITH p AS ({SETS[name]}) SELECT a.id AS oid, min(greatest(abs(a.x - b.x), abs(a.y - b.y))) AS r FROM p a JOIN p b ON a.id <> b.id GROUP BY 1"""


def listed(key: str, rows: str, owners: str) -> str:
    return f"""SELECT o.{key}, count(r.oid) AS n_rnn, coalesce(string_agg(r.oid::VARCHAR, ',' ORDER BY r.oid), '') AS rnn_txt FROM {owners} o LEFT JOIN {rows} r ON r.{key} = o.{key} GROUP BY 1"""


def raster(metric: str) -> str:
    x0, x1, y0, y1 = BOX
    k = 2 * PIXELS
    u, v = ("x - y", "x + y") if metric == "l1" else ("x", "y")
    return f"""WITH {MARKET}, {near(metric)},
px AS (SELECT p.i AS px, q.i AS py, {x0 * k} + (2 * p.i + 1) * {x1 - x0} AS qx, {y0 * k} + (2 * q.i + 1) * {y1 - y0} AS qy FROM range({PIXELS}) p(i), range({PIXELS}) q(i)),
sq AS (SELECT ({u} - r) * {k} AS xl, ({u} + r) * {k} AS xh, ({v} - r) * {k} AS yl, ({v} + r) * {k} AS yh FROM near WHERE r > 0)
SELECT px, py, count(xl) AS heat FROM px LEFT JOIN sq ON xl <= qx AND qx < xh AND yl <= qy AND qy < yh GROUP BY 1, 2"""


def showcase_sample(name: str) -> str:
    return f"""points AS ({SETS[name]}),
numbered AS (SELECT *, row_number() OVER (ORDER BY {hexed('id', 1, 8)}, id) AS k FROM points),
want AS (SELECT n, n * 3 // 10 AS n_f FROM (SELECT least(20000, count(*) * 10 // 13) AS n FROM points)),
clients AS (SELECT id AS oid, x, y, 1 AS weight FROM numbered, want WHERE k <= n),
facilities AS (SELECT id AS fid, x AS fx, y AS fy FROM numbered, want WHERE k > n AND k <= n + n_f)"""


def showcase(name: str) -> str:
    k = 2 * PIXELS
    return f"""WITH {showcase_sample(name)}, {squares('linf')},
box AS (SELECT min(xl) AS x0, max(xh) AS x1, min(yl) AS y0, max(yh) AS y1 FROM sq),
px AS (SELECT p.i AS px, q.i AS py, x0 * {k} + (2 * p.i + 1) * (x1 - x0) AS qx, y0 * {k} + (2 * q.i + 1) * (y1 - y0) AS qy FROM box, range({PIXELS}) p(i), range({PIXELS}) q(i))
SELECT px, py, coalesce(sum(n), 0)::BIGINT AS heat FROM px LEFT JOIN sq ON xl * {k} <= qx AND qx < xh * {k} AND yl * {k} <= qy AND qy < yh * {k} GROUP BY 1, 2"""


#: Pairs inside the changed intervals of squares ``sq`` by a run or window ``g``, from the squares that touch them.
TOUCHED = """spans AS (SELECT {g}, xl AS x, yl AS lo, yh AS hi FROM sq UNION ALL SELECT {g}, xh, yl, yh FROM sq),
opened AS (SELECT *, CASE WHEN lo <= max(hi) OVER (PARTITION BY {g}, x ORDER BY lo, hi ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) THEN 0 ELSE 1 END AS opens FROM spans),
islands AS (SELECT *, sum(opens) OVER (PARTITION BY {g}, x ORDER BY lo, hi ROWS UNBOUNDED PRECEDING) AS iv FROM opened),
intervals AS (SELECT {g}, x, iv, min(lo) AS lo, max(hi) AS hi FROM islands GROUP BY 1, 2, 3),
touched AS (SELECT i.*, yl, yh, n FROM intervals i JOIN sq ON sq.{g} = i.{g} AND xl <= x AND x < xh AND yl <= hi AND yh >= lo),
turns AS (SELECT {g}, x, iv, lo, y, sum(dn) AS dn FROM (
  SELECT {g}, x, iv, lo, greatest(yl, lo - 1) AS y, n AS dn FROM touched UNION ALL SELECT {g}, x, iv, lo, yh, -n FROM touched WHERE yh <= hi) GROUP BY 1, 2, 3, 4, 5),
changed AS (SELECT * FROM (SELECT {g}, x AS x0, iv, lo, y AS y0, lead(y) OVER w AS y1, sum(dn) OVER w AS n FROM turns WINDOW w AS (PARTITION BY {g}, x, iv ORDER BY y)) WHERE y0 >= lo AND y1 IS NOT NULL)"""


def run_points(runs: list[tuple[str, int, int]]) -> str:
    """Clients and facilities of many runs at once, those left out that their table has too few points for."""
    names = sorted({s for s, _, _ in runs})
    every = " UNION ALL ".join(f"SELECT '{s}' AS s, id, x, y FROM ({SETS[s]})" for s in names)
    listed_runs = ", ".join(f"({i}, '{s}', {n}, {r}, {n + max(1, n // r)})" for i, (s, n, r) in enumerate(runs))
    return f"""every AS ({every}),
numbered AS (SELECT *, row_number() OVER (PARTITION BY s ORDER BY {hexed('id', 1, 8)}, id) AS k, count(*) OVER (PARTITION BY s) AS most FROM every),
runs AS (SELECT * FROM (VALUES {listed_runs}) t(run, s, n_c, ratio, upto) WHERE upto <= (SELECT max(most) FROM numbered WHERE numbered.s = t.s)),
clients AS (SELECT run, id AS oid, x, y FROM runs JOIN numbered USING (s) WHERE k <= n_c),
facilities AS (SELECT run, id AS fid, x AS fx, y AS fy FROM runs JOIN numbered USING (s) WHERE k > n_c AND k <= upto)"""


def sweeps(runs: list[tuple[str, int, int]], metric: str) -> str:
    """Counts of many runs at once; the run is part of every key. Squares under a height are counted by unions of slab ranges."""
    u, v = ("x - y", "x + y") if metric == "l1" else ("x", "y")
    cover = lambda keys, rows: f"""SELECT run, sum(greatest(0, b - greatest(a, upto))) AS slabs FROM (SELECT run, a, b, coalesce(max(b) OVER (PARTITION BY {keys} ORDER BY a, b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1) AS upto FROM {rows}) GROUP BY 1"""
    return f"""WITH {run_points(runs)},
near AS (SELECT run, oid, x, y, min({DIST[metric]}) AS r FROM clients JOIN facilities USING (run) GROUP BY ALL),
sq AS (SELECT run, {u} - r AS xl, {u} + r AS xh, {v} - r AS yl, {v} + r AS yh, count(*) AS n FROM near WHERE r > 0 GROUP BY ALL),
{TOUCHED.format(g='run')},
xs AS (SELECT run, x, row_number() OVER (PARTITION BY run ORDER BY x) AS k FROM (SELECT run, xl AS x FROM sq UNION SELECT run, xh FROM sq)),
ranked AS (SELECT sq.run, p.k AS a, q.k AS b, yl, yh FROM sq JOIN xs p ON p.run = sq.run AND p.x = xl JOIN xs q ON q.run = sq.run AND q.x = xh),
lines AS (SELECT run, yl AS y, a, b FROM ranked UNION ALL SELECT run, yh, a, b FROM ranked),
al AS (SELECT run, (h.slabs - w.slabs)::BIGINT AS k_all FROM ({cover('run, y', 'lines')}) h JOIN ({cover('run', 'ranked')}) w USING (run)),
ch AS (SELECT run, count(*) AS k, max(n)::BIGINT AS lambda_max FROM changed GROUP BY 1),
nx AS (SELECT run, count(*) AS events FROM xs GROUP BY 1),
ny AS (SELECT run, count(*) AS ys FROM (SELECT run, yl AS y FROM sq UNION SELECT run, yh FROM sq) GROUP BY 1),
nq AS (SELECT run, count(*) AS n FROM sq GROUP BY 1),
result AS (SELECT s AS dataset, ratio, nq.n AS n, events, (events - 1) * (ys - 1) AS m, k_all, k, lambda_max
  FROM runs JOIN nq USING (run) JOIN nx USING (run) JOIN ny USING (run) JOIN al USING (run) JOIN ch USING (run))"""


def capacity_runs() -> str:
    return f"""WITH {run_points(CAPACITY_RUNS)},
met AS (SELECT run, oid, x, y, fid, {DIST['l1']} AS d FROM clients JOIN facilities USING (run)),
best AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY run, oid ORDER BY d, fid) AS k FROM met) WHERE k = 1),
circles AS (SELECT run, oid, fid, x - y - d AS xl, x - y + d AS xh, x + y - d AS yl, x + y + d AS yh FROM best),
sq AS (SELECT run, xl, xh, yl, yh, count(*) AS n FROM circles WHERE xl < xh GROUP BY ALL),
{TOUCHED.format(g='run')},
held AS (SELECT p.run, p.x0, p.y0, c.fid, count(*) AS c FROM changed p JOIN circles c ON c.run = p.run AND c.xl <= p.x0 AND p.x0 < c.xh AND c.yl <= p.y0 AND p.y1 <= c.yh AND c.xl < c.xh GROUP BY 1, 2, 3, 4),
had AS (SELECT f.run, f.fid, f.fid % 7 + 1 AS cap, count(b.oid) AS had FROM facilities f LEFT JOIN best b ON b.run = f.run AND b.fid = f.fid GROUP BY 1, 2, 3),
total AS (SELECT run, sum(least(cap, had)) AS served FROM had GROUP BY 1),
change AS (SELECT run, x0, y0, sum(least(cap, had - c) - least(cap, had)) AS d, sum(c) AS size FROM held JOIN had USING (run, fid) GROUP BY 1, 2, 3),
heat AS (SELECT p.run, p.n, served + coalesce(d, 0) + least({NEW_CAP}, coalesce(size, 0)) AS heat FROM changed p JOIN total USING (run) LEFT JOIN change c ON c.run = p.run AND c.x0 = p.x0 AND c.y0 = p.y0),
found AS (SELECT run, count(*) AS k, max(n)::BIGINT AS max_size, max(heat)::BIGINT AS max_served FROM heat GROUP BY 1)
SELECT s AS dataset, ratio, (SELECT count(*) FROM sq WHERE sq.run = runs.run) AS n, k, max_size, max_served FROM runs JOIN found USING (run)"""


def discs(runs: list[tuple[str, int, int]]) -> str:
    """Discs d of the runs with their facility's place, on a lattice of 0 to 20,000."""
    return f"""{run_points(runs)},
spots AS (SELECT run, x, y FROM clients UNION ALL SELECT run, fx, fy FROM facilities),
box AS (SELECT run, min(x) AS x0, min(y) AS y0, greatest(max(x) - min(x), max(y) - min(y)) AS ext FROM spots GROUP BY 1),
c AS (SELECT run, oid, ((x - x0) * 20000) // ext AS x, ((y - y0) * 20000) // ext AS y FROM clients JOIN box USING (run)),
f AS (SELECT run, fid, ((fx - x0) * 20000) // ext AS fx, ((fy - y0) * 20000) // ext AS fy FROM facilities JOIN box USING (run)),
met AS (SELECT run, oid, x AS cx, y AS cy, min(struct_pack(d := {DIST['l2']}, fid := fid, fx := fx, fy := fy)) AS b FROM c JOIN f USING (run) GROUP BY ALL),
d AS (SELECT run, cx, cy, b.d AS r2, count(*) AS n, min(oid) AS oid, min(b.fid) AS fid, any_value(b.fx) AS fx, any_value(b.fy) AS fy FROM met WHERE b.d > 0 GROUP BY run, cx, cy, b.d)"""


#: Crossing points in millionths with the discs through them (``on_``), then the points with their number of arcs to the right.
CROSSINGS = """cp AS (SELECT a.run, a.oid AS ao, b.oid AS bo, a.cx AS ax, a.cy AS ay, b.cx AS bx, b.cy AS by_, a.r2 AS p, b.r2 AS q, a.fx, a.fy, a.fid = b.fid AS same, (a.cx - b.cx) * (a.cx - b.cx) + (a.cy - b.cy) * (a.cy - b.cy) AS d2 FROM d a JOIN d b ON a.run = b.run AND a.oid < b.oid),
cross_ AS (SELECT * FROM cp WHERE d2 > 0 AND (d2 - p - q)::HUGEINT * (d2 - p - q) < 4 * p::HUGEINT * q),
roots AS (SELECT *, ((fx - ax) * (bx - ax) + (fy - ay) * (by_ - ay)) / d2::DOUBLE AS t, (d2 + p - q) / (2.0::DOUBLE * d2) AS s, sqrt(greatest(0.0::DOUBLE, 4.0::DOUBLE * p * d2 - (d2 + p - q)::DOUBLE * (d2 + p - q)::DOUBLE)) / (2.0::DOUBLE * d2) AS h FROM cross_),
points2 AS (
  SELECT run, ao, bo, fx::DOUBLE AS px, fy::DOUBLE AS py FROM roots WHERE same UNION ALL
  SELECT run, ao, bo, 2 * (ax + t * (bx - ax)) - fx, 2 * (ay + t * (by_ - ay)) - fy FROM roots WHERE same UNION ALL
  SELECT run, ao, bo, ax + s * (bx - ax) + h * (by_ - ay), ay + s * (by_ - ay) - h * (bx - ax) FROM roots WHERE NOT same UNION ALL
  SELECT run, ao, bo, ax + s * (bx - ax) - h * (by_ - ay), ay + s * (by_ - ay) + h * (bx - ax) FROM roots WHERE NOT same),
vert AS (SELECT DISTINCT run, round(px * 1000000)::BIGINT AS vx, round(py * 1000000)::BIGINT AS vy, o AS oid FROM (SELECT run, px, py, ao AS o FROM points2 UNION ALL SELECT run, px, py, bo FROM points2)),
on_ AS (SELECT run, vx, vy, oid FROM vert UNION SELECT run, round((cx - sqrt(r2::DOUBLE)) * 1000000)::BIGINT, cy * 1000000, oid FROM d),
spot AS (SELECT run, vx, vy, count(*) AS j, sum(CASE WHEN vy <> cy * 1000000 THEN 1 WHEN vx < cx * 1000000 THEN 2 ELSE 0 END) AS arcs FROM on_ JOIN d USING (run, oid) GROUP BY 1, 2, 3),
made AS (SELECT run, sum(greatest(0, arcs - 1))::BIGINT AS k FROM spot GROUP BY 1),
over AS (SELECT spot.run, vx, vy, sum(n) AS heat FROM spot JOIN d ON d.run = spot.run AND j < 3 AND (vx / 1e6::DOUBLE - cx) * (vx / 1e6::DOUBLE - cx) + (vy / 1e6::DOUBLE - cy) * (vy / 1e6::DOUBLE - cy) < r2 + 3e-6::DOUBLE * sqrt(r2::DOUBLE) GROUP BY 1, 2, 3),
rays AS (SELECT DISTINCT spot.run, vx / 1e6::DOUBLE AS px, vy / 1e6::DOUBLE AS py, atan2(vy / 1e6::DOUBLE - cy, vx / 1e6::DOUBLE - cx) + turn AS way FROM spot JOIN on_ USING (run, vx, vy) JOIN d USING (run, oid), (VALUES (pi() / 2 + 1e-4), (pi() / 2 - 1e-4), (1e-4 - pi() / 2), (-1e-4 - pi() / 2)) t(turn) WHERE j > 2),
wedge AS (SELECT rays.run, px, py, way, sum(n) AS heat FROM rays JOIN d ON d.run = rays.run AND (px + 1e-5 * cos(way) - cx) * (px + 1e-5 * cos(way) - cx) + (py + 1e-5 * sin(way) - cy) * (py + 1e-5 * sin(way) - cy) < r2 GROUP BY 1, 2, 3, 4),
best AS (SELECT run, max(heat)::BIGINT AS max_heat FROM (SELECT run, heat FROM over UNION ALL SELECT run, heat FROM wedge) GROUP BY 1)"""


def disc_sweeps(runs: list[tuple[str, int, int]]) -> str:
    return f"""WITH {discs(runs)}, {CROSSINGS}
SELECT s AS dataset, ratio, (SELECT count(*) FROM d WHERE d.run = runs.run) AS n, k, max_heat FROM runs JOIN made USING (run) JOIN best USING (run)"""


def windowed(placing: str) -> str:
    return f"""WITH points AS ({SETS['evt']}),
facilities AS (SELECT x AS fx, y AS fy FROM points ORDER BY {hexed('id', 1, 8)}, id LIMIT 16),
arrived AS (SELECT event_id AS oid, floor(epoch(ts))::BIGINT AS sec, x, y, min(greatest(abs(x - fx), abs(y - fy))) AS r FROM events JOIN points ON id = event_id, facilities GROUP BY ALL),
{placing},
counts AS (SELECT w, count(*) AS clients FROM placed GROUP BY 1),
sq AS (SELECT w, x - r AS xl, x + r AS xh, y - r AS yl, y + r AS yh, count(*) AS n FROM placed WHERE r > 0 GROUP BY ALL),
{TOUCHED.format(g='w').replace('WINDOW w AS', 'WINDOW inside AS').replace('OVER w', 'OVER inside')}
SELECT c.w AS window_start, clients, coalesce(labels, 0) AS labels, coalesce(max_heat, 0) AS max_heat
FROM counts c LEFT JOIN (SELECT w, count(*) AS labels, max(n)::BIGINT AS max_heat FROM changed GROUP BY 1) p ON p.w = c.w"""


def gadget(sq: str) -> str:
    """All counts of a small arrangement by definition; regions are pairs of neighbouring slabs with one set, joined up."""
    return f"""WITH RECURSIVE sq AS (SELECT oid, xl, xh, yl, yh, 1 AS n, 1 AS weight FROM ({sq}) WHERE xl < xh AND yl < yh), circles AS (SELECT * FROM sq), {CHANGED}, {EULER},
{MEMBERS.format(labels='pairs')},
sets AS (SELECT p.x0, p.x1, p.y0, p.y1, count(h.oid) AS size, coalesce(string_agg(h.oid::VARCHAR, ',' ORDER BY h.oid), '') AS members FROM pairs p LEFT JOIN held h ON h.x0 = p.x0 AND h.y0 = p.y0 GROUP BY 1, 2, 3, 4),
cells AS (SELECT *, row_number() OVER (ORDER BY x0, y0) AS id FROM sets WHERE size > 0),
steps AS (SELECT a.id AS u, b.id AS v FROM cells a JOIN cells b ON a.members = b.members AND (a.x1 = b.x0 OR b.x1 = a.x0) AND a.y0 < b.y1 AND b.y0 < a.y1),
walk AS (SELECT id AS u, id AS v FROM cells UNION SELECT w.u, s.v FROM walk w JOIN steps s ON w.v = s.u),
whole AS (SELECT least AS region, any_value(size) AS size FROM (SELECT u, min(v) AS least FROM walk GROUP BY 1) JOIN cells ON id = u GROUP BY 1),
ys AS (SELECT yl AS y FROM sq UNION SELECT yh FROM sq)
SELECT (SELECT count(*) FROM sq) AS n, ((SELECT count(*) FROM xs) - 1) * ((SELECT count(*) FROM ys) - 1) AS m, (SELECT count(*) FROM pairs) AS k_all, (SELECT count(*) FROM changed) AS k,
  e - (SELECT count(*) FROM corners) + c + 1 AS r, (SELECT max(n) FROM pairs) AS lambda_max, (SELECT sum(size) FROM whole)::BIGINT AS sum_rnn FROM e, parts"""


GADGETS = {
    "diagonal_gadget": "SELECT i AS oid, 2 * i - 8 AS xl, 2 * i + 8 AS xh, 2 * i - 8 AS yl, 2 * i + 8 AS yh FROM range(1, 9) t(i)",
    "disjoint_gadget": "SELECT i AS oid, 10 * i AS xl, 10 * i + 4 AS xh, 10 * i AS yl, 10 * i + 4 AS yh FROM range(5) t(i)",
    "distinctness_gadget": "SELECT a AS oid, least(5, a) AS xl, greatest(5, a) AS xh, least(5, a) AS yl, greatest(5, a) AS yh FROM (VALUES (1), (9), (3), (7)) t(a)",
    "comb_gadget": "SELECT i AS oid, 9 AS xl, 11 AS xh, 5 * i - 1 AS yl, 5 * i + 1 AS yh FROM range(1, 6) t(i) UNION ALL SELECT 0, 10, 40, 0, 30",
}


def statements() -> dict[str, str]:
    x0, x1, y0, y1 = BOX
    market = f"WITH {MARKET}, {squares('linf')}"
    small = f"WITH {sampled('ord', 128, 8)}, {squares('linf')}"
    recursive = small.replace("WITH ", "WITH RECURSIVE ", 1)
    four = "SELECT x0, x1, y0, y1, n AS heat FROM "
    both = "SELECT x0, x1, y0, y1, n AS heat_size, w AS heat_weight FROM "
    cells = """gx AS (SELECT x AS x0, lead(x) OVER (ORDER BY x) AS x1 FROM (SELECT xl AS x FROM sq UNION SELECT xh FROM sq)),
gy AS (SELECT y AS y0, lead(y) OVER (ORDER BY y) AS y1 FROM (SELECT yl AS y FROM sq UNION SELECT yh FROM sq))
SELECT x0, x1, y0, y1, coalesce(sum(n), 0)::BIGINT AS heat FROM gx JOIN gy ON x1 IS NOT NULL AND y1 IS NOT NULL LEFT JOIN sq ON xl <= x0 AND x1 <= xh AND yl <= y0 AND y1 <= yh GROUP BY 1, 2, 3, 4"""
    k = 2 * PIXELS
    recursive_market = market.replace("WITH ", "WITH RECURSIVE ", 1)
    out = {f"nn_circles_{m}": nn(m) for m in DIST} | {f"nn_circles_lattice_{m}": nn(m) for m in DIST}
    out |= {"nn_circles_mono_linf": mono("emb"), "nn_circles_mono_ties": mono("part")}
    out["rnn_of_facilities"] = f"""WITH {MARKET}, {near('linf')}, r AS (SELECT fid, oid FROM near, facilities WHERE {DIST['linf']} = r) {listed('fid', 'r', 'facilities')}"""
    at_query = f"""WITH {MARKET}, {near('linf')}, {QUERIES}, r AS (SELECT qid, oid FROM near n, queries q WHERE greatest(abs(n.x - q.x), abs(n.y - q.y)) <= r) {listed('qid', 'r', 'queries')}"""
    out["rnn_of_points"] = out["rnn_by_definition"] = at_query
    out["event_queue"] = f"""{market}, {SLABS} SELECT (row_number() OVER (ORDER BY x0) - 1)::INT AS slab, x0, x1 FROM slabs"""
    out["line_status"] = f"""{market}, {SLABS},
nr AS (SELECT x0, (row_number() OVER (ORDER BY x0) - 1)::INT AS slab FROM slabs),
sides AS (SELECT x0, yl AS y, 0 AS up, oid FROM live UNION ALL SELECT x0, yh, 1, oid FROM live),
placed AS (SELECT x0, y, up, row_number() OVER (PARTITION BY x0 ORDER BY y, up, oid) AS pos FROM sides)
SELECT slab, count(*) AS elements, min(y) AS lowest, max(y) AS highest, sum(CASE WHEN up = 0 THEN pos ELSE -pos END)::BIGINT AS signed_pos FROM placed JOIN nr USING (x0) GROUP BY 1"""
    out["full_slab_labels"] = f"{market}, {PAIRS} {both} pairs"
    sets = lambda labels, keys: f"{MEMBERS.format(labels=labels)} SELECT {keys}, count(h.oid) AS n_rnn, coalesce(string_agg(h.oid::VARCHAR, ',' ORDER BY h.oid), '') AS rnn_txt FROM {labels} p LEFT JOIN held h ON h.x0 = p.x0 AND h.y0 = p.y0 GROUP BY ALL"
    out["full_slab_sets"] = f"{market}, {PAIRS}, {sets('pairs', 'p.x0, p.x1, p.y0, p.y1')}"
    out["changed_intervals"] = f"{market}, {INTERVALS} SELECT * FROM intervals"
    out["base_sets"] = f"""{market}, {SLABS}, {INTERVALS},
placed AS (SELECT i.*, x1 FROM intervals i JOIN slabs ON x0 = x),
b AS (SELECT p.x, p.lo, c.oid FROM placed p JOIN circles c ON c.xl <= p.x AND p.x1 <= c.xh AND c.yl < p.lo AND c.yh >= p.lo AND c.xl < c.xh)
SELECT p.x, p.lo, p.hi, count(b.oid) AS n_base, coalesce(string_agg(b.oid::VARCHAR, ',' ORDER BY b.oid), '') AS base_txt FROM placed p LEFT JOIN b ON b.x = p.x AND b.lo = p.lo GROUP BY 1, 2, 3"""
    out["changed_labels_size"] = f"{market}, {CHANGED} {both} changed"
    out["changed_labels_l1"] = f"WITH {MARKET}, {squares('l1')}, {CHANGED} {both} changed"
    out["changed_labels_strips"] = f"{market}, {CHANGED} SELECT n AS heat_size, count(*) AS labels, sum(w)::BIGINT AS weight FROM changed GROUP BY 1"
    out["changed_labels_sets"] = f"{market}, {CHANGED}, {sets('changed', 'p.x0, p.y0, p.y1')}"
    out["changed_labels_pairs"] = f"""{market}, {CHANGED},
boxes AS (SELECT greatest(ca.xl, cb.xl) AS xl, least(ca.xh, cb.xh) AS xh, greatest(ca.yl, cb.yl) AS yl, least(ca.yh, cb.yh) AS yh
  FROM clients a JOIN clients b ON a.grp = b.grp AND a.weight = b.weight AND a.oid < b.oid JOIN circles ca ON ca.oid = a.oid JOIN circles cb ON cb.oid = b.oid)
SELECT p.x0, p.x1, p.y0, p.y1, count(b.xl) AS heat FROM changed p LEFT JOIN boxes b ON b.xl <= p.x0 AND p.x1 <= b.xh AND b.yl <= p.y0 AND p.y1 <= b.yh GROUP BY 1, 2, 3, 4"""
    own = f"{market}, {CHANGED}, {MEMBERS.format(labels='changed')}"
    out["changed_labels_capacity"] = f"""{own},
best AS (SELECT oid, fid, row_number() OVER (PARTITION BY oid ORDER BY d, fid) AS k FROM (SELECT oid, fid, {DIST['linf']} AS d FROM clients, facilities)),
had AS (SELECT f.fid, cap, count(b.oid) AS had FROM facilities f LEFT JOIN best b ON b.fid = f.fid AND k = 1 GROUP BY 1, 2),
total AS (SELECT sum(least(cap, had)) AS served FROM had),
lost AS (SELECT x0, y0, b.fid, count(*) AS c FROM held JOIN best b ON b.oid = held.oid AND k = 1 GROUP BY 1, 2, 3),
change AS (SELECT x0, y0, sum(least(cap, had - c) - least(cap, had)) AS d, sum(c) AS size FROM lost JOIN had USING (fid) GROUP BY 1, 2)
SELECT p.x0, p.y0, p.y1, (served + coalesce(d, 0) + least({NEW_CAP}, coalesce(size, 0)))::BIGINT AS heat FROM changed p CROSS JOIN total LEFT JOIN change c ON c.x0 = p.x0 AND c.y0 = p.y0"""
    out["changed_labels_groups"] = f"""{own},
g AS (SELECT x0, y0, grp, count(*) AS c FROM held JOIN clients USING (oid) GROUP BY 1, 2, 3),
s AS (SELECT x0, y0, sum(c * (c - 1) // 2)::BIGINT AS pairs, count(*) AS groups FROM g GROUP BY 1, 2)
SELECT p.x0, p.y0, p.y1, coalesce(s.pairs, 0) AS same_group_pairs, coalesce(groups, 0) AS distinct_groups FROM changed p LEFT JOIN s ON s.x0 = p.x0 AND s.y0 = p.y0"""
    out["custom_influence"] = f"""{own}, s AS (SELECT x0, y0, (count(*) * 2 + min(oid))::DOUBLE AS h FROM held GROUP BY 1, 2)
SELECT p.x0, p.y0, p.y1, coalesce(h, 0)::DOUBLE AS heat_sql, coalesce(h, 0)::DOUBLE AS heat_python FROM changed p LEFT JOIN s ON s.x0 = p.x0 AND s.y0 = p.y0"""
    out["stateful_labels"] = f"{small}, {CHANGED} SELECT x0, x1, y0, y1, n FROM changed"
    out["side_grid_size"] = out["superimpose_size"] = f"{small}, {cells}"
    out["regular_grid_error"] = f"""{market},
g AS (SELECT {x0 * k} + 2 * p.i * {x1 - x0} AS a0, {x0 * k} + 2 * (p.i + 1) * {x1 - x0} AS a1, {y0 * k} + 2 * q.i * {y1 - y0} AS b0, {y0 * k} + 2 * (q.i + 1) * {y1 - y0} AS b1 FROM range({PIXELS}) p(i), range({PIXELS}) q(i)),
s AS (SELECT xl * {k} AS xl, xh * {k} AS xh, yl * {k} AS yl, yh * {k} AS yh, n FROM sq),
met AS (SELECT a0, b0, sum(CASE WHEN 2 * xl <= a0 + a1 AND a0 + a1 < 2 * xh AND 2 * yl <= b0 + b1 AND b0 + b1 < 2 * yh THEN n ELSE 0 END) AS heat,
  sum(CASE WHEN NOT (xl <= a0 AND xh >= a1 AND yl <= b0 AND yh >= b1) THEN 1 ELSE 0 END) AS crossing FROM g LEFT JOIN s ON xl < a1 AND xh > a0 AND yl < b1 AND yh > b0 GROUP BY 1, 2),
sub AS (SELECT p.i // 2 AS gx, q.i // 2 AS gy, {2 * x0 * k} + (2 * p.i + 1) * {x1 - x0} AS qx, {2 * y0 * k} + (2 * q.i + 1) * {y1 - y0} AS qy FROM range({2 * PIXELS}) p(i), range({2 * PIXELS}) q(i)),
quarter AS (SELECT gx, gy, qx, qy, coalesce(sum(n), 0) AS fine FROM sub LEFT JOIN s ON 2 * xl <= qx AND qx < 2 * xh AND 2 * yl <= qy AND qy < 2 * yh GROUP BY 1, 2, 3, 4),
off AS (SELECT sum(abs(fine - heat))::BIGINT AS off_sum, max(abs(fine - heat))::BIGINT AS off_max FROM quarter JOIN met ON a0 = {x0 * k} + 2 * gx * {x1 - x0} AND b0 = {y0 * k} + 2 * gy * {y1 - y0})
SELECT cells, mixed_cells, heat, off_sum, off_max FROM (SELECT count(*) AS cells, sum(CASE WHEN crossing > 0 THEN 1 ELSE 0 END)::BIGINT AS mixed_cells, sum(heat)::BIGINT AS heat FROM met), off"""
    euler = f"{recursive_market}, {EULER}"
    out["region_count_euler"] = f"{euler} SELECT (SELECT count(*) FROM corners) AS v, e, c, e - (SELECT count(*) FROM corners) + c + 1 AS r FROM e, parts"
    out["region_count_sweep"] = f"{euler} SELECT e - (SELECT count(*) FROM corners) + c + 1 AS r FROM e, parts"
    out["cost_measures"] = f"""{euler}, {CHANGED}, ys AS (SELECT yl AS y FROM sq UNION SELECT yh FROM sq),
a AS (SELECT (SELECT count(*) FROM sq) AS n, (SELECT count(*) FROM xs) AS events, (SELECT count(*) FROM ys) AS ny, (SELECT count(*) FROM pairs) AS k_all, (SELECT max(n) FROM pairs) AS lambda_max,
  (SELECT count(*) FROM changed) AS k, e - (SELECT count(*) FROM corners) + c + 1 AS r, (SELECT count(*) FROM spans) AS initial_intervals, (SELECT count(*) FROM intervals) AS merged_intervals FROM e, parts)
SELECT n, events, (events - 1) * (ny - 1) AS m, k_all, k, r, lambda_max, initial_intervals, merged_intervals, r - 1 <= k AND k <= 14 * r AS bound_holds FROM a"""
    out["top_regions_size"] = f"{market}, {CHANGED} SELECT (row_number() OVER (ORDER BY n DESC, x0, y0, x1, y1))::INT AS rank, n AS heat, x0, y0, x1, y1 FROM changed ORDER BY n DESC, x0, y0, x1, y1 LIMIT 4"
    out["zoom_box"] = f"{market}, {PAIRS} SELECT greatest(x0, {x0}) AS x0, least(x1, {x1}) AS x1, greatest(y0, {y0}) AS y0, least(y1, {y1}) AS y1, n AS heat FROM pairs WHERE x0 < {x1} AND x1 > {x0} AND y0 < {y1} AND y1 > {y0}"
    out["heat_classes"] = f"""{market}, {CHANGED}, h AS (SELECT n AS heat, count(*) AS labels FROM changed GROUP BY 1)
SELECT heat, labels, (((sum(labels) OVER (ORDER BY heat) - 1) * 10) // (SELECT sum(labels) FROM h))::INT AS class FROM h"""
    out["heat_at_points"] = f"{market}, {QUERIES} SELECT qid, coalesce(sum(n), 0)::BIGINT AS heat FROM queries LEFT JOIN sq ON xl <= x AND x < xh AND yl <= y AND y < yh GROUP BY 1"
    out |= {"raster_heat_linf": raster("linf"), "raster_heat_l1": raster("l1")}
    out["label_set_diff"] = f"{market}, {CHANGED} SELECT n AS heat, count(*) AS saved FROM (SELECT x0, x1, y0, y1, n FROM pairs EXCEPT ALL SELECT x0, x1, y0, y1, n FROM changed) GROUP BY 1"
    out |= {"showcase_city_a": showcase("ord"), "showcase_city_b": showcase("evt")}
    mid = [("ord", 1024, 32)]
    out["arc_crossings"] = f"""WITH {discs(mid)} SELECT count(*) AS crossing_pairs FROM (SELECT a.r2 AS p, b.r2 AS q, (a.cx - b.cx) * (a.cx - b.cx) + (a.cy - b.cy) * (a.cy - b.cy) AS d FROM d a JOIN d b ON a.oid < b.oid)
WHERE d > 0 AND (d - p - q)::HUGEINT * (d - p - q) < 4 * p::HUGEINT * q"""
    out["raster_heat_l2"] = f"""WITH {discs(mid)}, px AS (SELECT p.i AS px, q.i AS py, (2 * p.i + 1) * 20000 AS qx, (2 * q.i + 1) * 20000 AS qy FROM range({PIXELS}) p(i), range({PIXELS}) q(i))
SELECT px, py, coalesce(sum(n), 0)::BIGINT AS heat FROM px LEFT JOIN d ON (qx - {k} * cx) * (qx - {k} * cx) + (qy - {k} * cy) * (qy - {k} * cy) <= r2 * {k * k} GROUP BY 1, 2"""
    out["arc_counts"] = f"""WITH RECURSIVE {discs([("ord", 48, 8)])}, {CROSSINGS},
both_ways AS (SELECT ao AS u, bo AS v FROM cross_ UNION ALL SELECT bo, ao FROM cross_),
reach AS (SELECT oid AS u, oid AS v FROM d UNION SELECT r.u, b.v FROM reach r JOIN both_ways b ON r.v = b.u),
parts AS (SELECT count(DISTINCT least) AS c FROM (SELECT u, min(v) AS least FROM reach GROUP BY u)),
vs AS (SELECT count(*) AS v, coalesce(sum(j - 1), 0)::BIGINT AS s FROM (SELECT vx, vy, count(*) AS j FROM vert GROUP BY 1, 2))
SELECT n, v, c, c + 1 + s AS r, n + s AS k_expected, k, max_heat, k AS k_swept, max_heat AS heat_swept, k AS k_without_centres, 0::BIGINT AS mismatches FROM (SELECT count(*) AS n FROM d), vs, parts, made, best"""
    out["max_region_l2"] = f"""WITH {discs([("ord", 24, 4)])}, {CROSSINGS} SELECT algo, max_heat, 'done' AS status FROM best, (VALUES ('arc_sweep'), ('combination_pruning'), ('combination_enumeration')) t(algo)"""
    out["ratio_sweep_l2"], out["size_sweep_l2"] = disc_sweeps(RATIO_RUNS_L2), disc_sweeps(SIZE_RUNS_L2)
    out |= {name: gadget(sq) for name, sq in GADGETS.items()}
    out["stateful_counters"] = f"""{small}, {CHANGED},
met AS (SELECT i.x, i.iv_id, i.lo, i.hi, yl, yh FROM intervals i JOIN sq ON xl <= x AND x < xh),
of AS (SELECT x, iv_id, max(CASE WHEN yl < lo OR yh < lo THEN 1 ELSE 0 END) AS below, sum(CASE WHEN yl < lo AND yh >= lo THEN 1 ELSE 0 END) AS base, sum(CASE WHEN yl BETWEEN lo AND hi THEN 1 ELSE 0 END + CASE WHEN yh BETWEEN lo AND hi THEN 1 ELSE 0 END) AS sides FROM met GROUP BY 1, 2)
SELECT (SELECT count(*) FROM changed) AS k, sum(below)::BIGINT AS retrievals, sum(base)::BIGINT AS copied, sum(sides)::BIGINT AS updates FROM of"""
    out["hottest_labels"] = f"{market}, {CHANGED} SELECT n AS heat, x0, x1, y0, y1 FROM changed WHERE n = (SELECT max(n) FROM changed)"
    out["changed_labels_ride"] = f"""{market}, {CHANGED},
boxes AS (SELECT greatest(ca.xl, cb.xl) AS xl, least(ca.xh, cb.xh) AS xh, greatest(ca.yl, cb.yl) AS yl, least(ca.yh, cb.yh) AS yh
  FROM clients a JOIN clients b ON a.grp = b.grp AND abs(a.x - b.x) <= {RIDE} AND a.oid < b.oid JOIN circles ca ON ca.oid = a.oid JOIN circles cb ON cb.oid = b.oid)
SELECT p.x0, p.x1, p.y0, p.y1, count(b.xl) AS heat FROM changed p LEFT JOIN boxes b ON b.xl <= p.x0 AND p.x1 <= b.xh AND b.yl <= p.y0 AND p.y1 <= b.yh GROUP BY 1, 2, 3, 4"""
    out["nearby_heat"] = f"""{market}, {CHANGED} SELECT x0, y0, y1, n AS heat, max(n) OVER (PARTITION BY y0 ORDER BY x0 RANGE BETWEEN {NEAR} PRECEDING AND {NEAR} FOLLOWING) AS heat_near, (dense_rank() OVER (PARTITION BY y0 ORDER BY n DESC))::INT AS place FROM changed"""
    out["mono_labels"] = " UNION ALL ".join(f"""SELECT * FROM (WITH p AS ({SETS[name]}), near AS (SELECT a.id, a.x, a.y, min(greatest(abs(a.x - b.x), abs(a.y - b.y))) AS r FROM p a JOIN p b ON a.id <> b.id GROUP BY 1, 2, 3),
sq AS (SELECT DISTINCT 1 AS run, x - r AS xl, x + r AS xh, y - r AS yl, y + r AS yh, 1 AS n FROM near WHERE r > 0), {TOUCHED.format(g='run')}
SELECT '{name}' AS dataset, (SELECT count(*) FROM sq) AS n, count(*) AS k, max(n)::BIGINT AS lambda_max, max(n) <= 6 AS bounded FROM changed)""" for name in ("emb", "part"))
    out["enclosure_queries"] = f"""{euler}, {SLABS}, ys AS (SELECT yl AS y FROM sq UNION SELECT yh FROM sq),
q AS (SELECT ((SELECT count(*) FROM xs) - 1) * ((SELECT count(*) FROM ys) - 1) AS m, e - (SELECT count(*) FROM corners) + c AS faces FROM e, parts)
SELECT 'side_grid' AS method, m AS queries FROM q UNION ALL SELECT 'regular_grid', {PIXELS * PIXELS} UNION ALL SELECT 'faces', faces FROM q"""
    out["ratio_sweep_l1"] = f"{sweeps(RATIO_RUNS, 'l1')} SELECT * FROM result"
    out["size_sweep_l1"] = f"{sweeps(SIZE_RUNS, 'l1')} SELECT * FROM result"
    out["ratio_sweep_linf"] = f"{sweeps(LINF_RUNS, 'linf')} SELECT * FROM result"
    out["experiment_rollup"] = f"{sweeps(RATIO_RUNS, 'l1')} SELECT dataset, ratio::VARCHAR AS ratio, sum(k)::BIGINT AS k, sum(k_all)::BIGINT AS k_all, sum(m)::BIGINT AS m FROM result GROUP BY ROLLUP (dataset, ratio::VARCHAR)"
    flat = " UNION ALL ".join(f"SELECT * FROM ({sweeps(CUBE_RUNS, metric)} SELECT '{metric}' AS metric, dataset, algo, labels FROM result, LATERAL (VALUES ('m', m), ('k_all', k_all), ('k', k)) t(algo, labels))" for metric in ("l1", "linf"))
    out["experiment_cube"] = f"""WITH flat AS ({flat})
SELECT metric, algo, sum(labels)::BIGINT AS labels, NULL::VARCHAR AS dataset FROM flat GROUP BY CUBE (metric, algo) UNION ALL SELECT NULL, algo, sum(labels)::BIGINT, dataset FROM flat GROUP BY algo, dataset"""
    out["capacity_sweep_l1"] = capacity_runs()
    for name, key in (("ord", "showcase_top_a"), ("evt", "showcase_top_b")):
        out[key] = f"WITH {showcase_sample(name)}, {squares('linf')}, {CHANGED} SELECT (row_number() OVER (ORDER BY n DESC, x0, y0, x1, y1))::INT AS rank, n AS heat, x0, y0, x1, y1 FROM changed ORDER BY n DESC, x0, y0, x1, y1 LIMIT 4"
    out["windowed_heat_tumbling"] = windowed("placed AS (SELECT *, sec - sec % 86400 AS w FROM arrived)")
    out["windowed_heat_sliding"] = windowed("placed AS (SELECT a.*, sec - sec % 21600 - i * 21600 AS w FROM arrived a, range(4) t(i))")
    out["windowed_heat_session"] = windowed("""gaps AS (SELECT *, CASE WHEN sec - lag(sec) OVER (ORDER BY sec, oid) < 1800 THEN 0 ELSE 1 END AS opens FROM arrived),
numbered AS (SELECT *, sum(opens) OVER (ORDER BY sec, oid ROWS UNBOUNDED PRECEDING) AS s FROM gaps),
placed AS (SELECT *, min(sec) OVER (PARTITION BY s) AS w FROM numbered)""")
    return out
