"""DuckDB SQL for the registered queries: the same relations by recursive common table expressions."""

from __future__ import annotations

from saferoads.queries import DC, K, RHO, SMAX

FAR = 1000003


def net(smax: int = SMAX, clustered: bool = False, rho: float = RHO, edges_only: bool = False) -> str:
    keep = "AND (l_orderkey * 31 + l_linenumber) % 10 < (((l_partkey % z.w) // 8) * 3 + ((l_partkey // z.w) // 8) * 7) % 10 + 1" if clustered else ""
    return f"""
z AS (SELECT count(*) AS n, CAST(floor(sqrt(count(*))) AS BIGINT) AS w FROM part),
v AS (SELECT p_partkey AS vid, (p_partkey % w) * 10 AS x, (p_partkey // w) * 10 AS y, p_size FROM part, z),
base AS (
  SELECT a.vid * 2 AS eid, a.vid AS u, b.vid AS w, 10 + (a.p_size + 3 * b.p_size) % 11 AS len, a.x AS xu, a.y AS yu, b.x AS xw, b.y AS yw
  FROM v a JOIN v b ON b.vid = a.vid + 1, z WHERE a.vid % z.w <> z.w - 1 AND (a.p_size + b.p_size) % 8 <> 0
  UNION ALL
  SELECT a.vid * 2 + 1, a.vid, b.vid, 10 + (a.p_size + 7 * b.p_size) % 11, a.x, a.y, b.x, b.y
  FROM v a CROSS JOIN z JOIN v b ON b.vid = a.vid + z.w WHERE (a.p_size + b.p_size) % 8 <> 1),
inc AS (SELECT (l_partkey % z.w) * 10 + l_suppkey % 10 AS x, (l_partkey // z.w) * 10 + l_orderkey % 10 AS y FROM lineitem, z WHERE l_returnflag = 'R' {keep}),
boxes AS (SELECT eid, xu, yu, xw, yw, gx, unnest(generate_series(CAST(floor((yu - 10) / 10.0) AS BIGINT), CAST(floor((yw + 10) / 10.0) AS BIGINT))) AS gy
  FROM (SELECT *, unnest(generate_series(CAST(floor((xu - 10) / 10.0) AS BIGINT), CAST(floor((xw + 10) / 10.0) AS BIGINT))) AS gx FROM base)),
hits AS (SELECT eid, count(*) AS n FROM boxes JOIN inc ON gx = x // 10 AND gy = y // 10
  WHERE greatest(xu - x, 0, x - xw) * greatest(xu - x, 0, x - xw) + greatest(yu - y, 0, y - yw) * greatest(yu - y, 0, y - yw) <= 100 GROUP BY eid),
counted AS (SELECT b.*, coalesce(h.n, 0) AS n FROM base b LEFT JOIN hits h USING (eid)),
edges AS (SELECT eid, u, w, CAST(len AS BIGINT) AS len, CAST({smax} + 1 - (1 + (n - lo) * {smax} // (hi - lo + 1)) AS INTEGER) AS ess FROM counted, (SELECT min(n) AS lo, max(n) AS hi FROM counted)),
{rest(rho)}"""


def rest(rho: float = RHO) -> str:
    return f"""arcs AS (SELECT u AS src, w AS dst, len, ess FROM edges UNION ALL SELECT w, u, len, ess FROM edges),
pois AS (SELECT vid AS poi FROM (SELECT vid, row_number() OVER (ORDER BY vid * 611953 % {FAR}, vid) AS r FROM v), z WHERE r <= greatest(1, round_even({rho} * z.n, 0))),
q AS (SELECT qid, vid AS src FROM (SELECT vid, row_number() OVER (ORDER BY (vid * 514229 + 77) % {FAR}, vid) - 1 AS qid FROM v) WHERE qid < 100)"""


def zeros(smax: int) -> str:
    return "[" + ", ".join(["CAST(0 AS BIGINT)"] * smax) + "]"


def added(sd: str, smax: int) -> str:
    return f"[{', '.join(f'{sd}[{s}] + CASE WHEN a.ess = {s} THEN a.len ELSE 0 END' for s in range(1, smax + 1))}]"


def labels(smax: int = SMAX, dc: str = str(DC), start: str | None = None, grow: str | None = None) -> str:
    """Labels by hops; within a hop only those that no other beats."""
    return f"""lab AS (
  SELECT qid, src AS vid, {start or zeros(smax)} AS sd, CAST(0 AS BIGINT) AS dist FROM q
  UNION ALL
  SELECT qid, vid, sd, dist FROM (
    SELECT *, min(dist) OVER (PARTITION BY qid, vid ORDER BY sd, dist ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS least
    FROM (SELECT l.qid, a.dst AS vid, {grow or added('l.sd', smax)} AS sd, l.dist + a.len AS dist FROM lab l JOIN arcs a ON a.src = l.vid WHERE l.dist + a.len < {dc})
  ) WHERE least IS NULL OR dist < least
)"""


def top(k: int = K) -> str:
    return f"""best AS (SELECT qid, vid AS poi, min(sd) AS sd FROM lab JOIN pois ON vid = poi GROUP BY qid, vid),
dists AS (SELECT l.qid, l.vid AS poi, l.sd, min(l.dist) AS dist FROM lab l JOIN best b ON b.qid = l.qid AND b.poi = l.vid AND b.sd = l.sd GROUP BY ALL),
ranked AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY sd, dist, poi) AS rnk FROM dists),
ans AS (SELECT qid, CAST(rnk AS INTEGER) AS rnk, poi, dist, sd FROM ranked WHERE rnk <= {k})"""


SHOW = "SELECT qid, rnk, poi, dist, array_to_string(sd, ',') AS sd FROM ans"


def safest(smax: int = SMAX, dc: float = DC, k: int = K, clustered: bool = False, few: int = 100) -> str:
    return f"WITH RECURSIVE {net(smax, clustered)}, {labels(smax, str(dc))}, {top(k)} {SHOW} WHERE qid < {few}"


CHAIN = f"""lev AS (SELECT unnest(generate_series(0, {SMAX - 1})) AS lvl),
reach AS (SELECT lvl, vid, vid AS root FROM lev, v UNION SELECT r.lvl, a.dst, r.root FROM reach r JOIN arcs a ON a.src = r.vid AND a.ess > r.lvl AND r.root < a.dst),
chain AS (SELECT vid, CAST(lvl AS INTEGER) AS lvl, min(root) AS comp FROM reach GROUP BY ALL)"""

NEAR = f"""near AS (SELECT poi AS vid, poi AS source, CAST(0 AS BIGINT) AS dist FROM pois
  UNION ALL SELECT vid, source, dist FROM (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY dist, source) AS r FROM (SELECT a.dst AS vid, n.source, min(n.dist + a.len) AS dist FROM near n JOIN arcs a ON a.src = n.vid WHERE n.dist + a.len < {{reach}} GROUP BY ALL)) WHERE r <= {K}),
nn AS (SELECT q.qid, m.source AS poi, min(m.dist) AS dist FROM q JOIN near m ON m.vid = q.src GROUP BY ALL),
knn AS (SELECT qid, CAST(r AS INTEGER) AS rnk, poi, dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, poi) AS r FROM nn) WHERE r <= {K})"""
NEAREST, NEAREST_DC = NEAR.format(reach=600), NEAR.format(reach=DC)

# Safest unconstrained POI: improvements of a vertex go on, so each round keeps what beats all found before.
USN = f"""usn(vid, cell, sd, hop) USING KEY (vid) AS (
  SELECT poi, poi, {zeros(SMAX)}, 0 FROM pois
  UNION
  SELECT c.vid, c.cell, c.sd, c.hop FROM (
    SELECT a.dst AS vid, arg_min(u.cell, (({added('u.sd', SMAX)}), u.cell)) AS cell, min(({added('u.sd', SMAX)})) AS sd, max(u.hop) + 1 AS hop FROM usn u JOIN arcs a ON a.src = u.vid GROUP BY a.dst
  ) c LEFT JOIN recurring.usn o ON o.vid = c.vid WHERE o.vid IS NULL OR c.sd < o.sd OR (c.sd = o.sd AND c.cell < o.cell)
)"""
BORDERS = """b AS (SELECT e.u, e.w, x.cell AS cell_u, y.cell AS cell_w, e.ess, e.len, y.sd[e.ess] - x.sd[e.ess] + e.len AS pos2 FROM edges e JOIN usn x ON x.vid = e.u JOIN usn y ON y.vid = e.w WHERE x.cell <> y.cell)"""

PATHS = """paths AS (SELECT u // z.w AS path_id, u % z.w AS at, len, ess FROM (SELECT *, row_number() OVER (PARTITION BY u // z2.w ORDER BY u) - 1 AS i FROM edges, z z2 WHERE edges.w = u + 1), z WHERE i = u % z.w)"""
PATH_SD = "[" + ", ".join(f"CAST(sum(CASE WHEN ess = {s} THEN len ELSE 0 END) AS BIGINT)" for s in range(1, SMAX + 1)) + "]"
PATH5 = "[" + ", ".join(f"CAST(sum(CASE WHEN least(ess, 5) = {s} THEN len ELSE 0 END) AS BIGINT)" for s in range(1, 6)) + "]"

ZONES = f"""z AS (SELECT count(*) AS n, CAST(floor(sqrt(count(*))) AS BIGINT) AS w FROM part),
v AS (SELECT p_partkey AS vid, p_size, n_regionkey IN (0, 2) AS bad FROM part JOIN nation ON n_nationkey = p_partkey % 25),
edges AS (
  SELECT a.vid * 2 AS eid, a.vid AS u, b.vid AS w, CAST(10 + (a.p_size + 3 * b.p_size) % 11 AS BIGINT) AS len, CASE WHEN a.bad OR b.bad THEN 1 ELSE 2 END AS ess
  FROM v a JOIN v b ON b.vid = a.vid + 1, z WHERE a.vid % z.w <> z.w - 1 AND (a.p_size + b.p_size) % 8 <> 0
  UNION ALL
  SELECT a.vid * 2 + 1, a.vid, b.vid, CAST(10 + (a.p_size + 7 * b.p_size) % 11 AS BIGINT), CASE WHEN a.bad OR b.bad THEN 1 ELSE 2 END
  FROM v a CROSS JOIN z JOIN v b ON b.vid = a.vid + z.w WHERE (a.p_size + b.p_size) % 8 <> 1),
{rest()}"""

NODES = f"""WITH RECURSIVE {net()}, {CHAIN},
held AS (SELECT lvl, comp, count(*) AS n_vertices, count(poi) AS n_pois FROM chain LEFT JOIN pois ON poi = vid GROUP BY ALL),
inside AS (SELECT c.lvl, c.comp, count(*) AS n_edges, min(ess) AS lo, max(ess) AS hi FROM edges e JOIN chain c ON c.vid = e.u AND e.ess > c.lvl GROUP BY ALL)
SELECT a.lvl, a.comp, p.comp AS parent, n_vertices, coalesce(n_edges, 0) AS n_edges, n_pois, coalesce(n_edges, 0) = 0 OR lo = hi AS is_leaf
FROM held a LEFT JOIN inside i ON i.lvl = a.lvl AND i.comp = a.comp LEFT JOIN chain p ON p.vid = a.comp AND p.lvl = a.lvl - 1"""

BORDER_SET = "bord AS (SELECT c.lvl, c.comp, c.vid FROM chain c JOIN (SELECT src, min(ess) AS least FROM arcs GROUP BY src) m ON m.src = c.vid WHERE least <= lvl)"
BORDER_DISTANCE = f"""WITH RECURSIVE {net()}, {CHAIN}, {BORDER_SET},
walk AS (SELECT lvl, vid AS source, vid, CAST(0 AS BIGINT) AS dist FROM bord
  UNION SELECT lvl, source, vid, min(dist) FROM (SELECT w.lvl, w.source, a.dst AS vid, w.dist + a.len AS dist FROM walk w JOIN arcs a ON a.src = w.vid AND a.ess > w.lvl WHERE w.dist + a.len < {DC}) GROUP BY ALL),
db AS (SELECT w.lvl, w.source AS vid, min(w.dist) AS d FROM walk w JOIN bord b ON b.lvl = w.lvl AND b.vid = w.vid WHERE w.vid <> w.source GROUP BY ALL),
dp AS (SELECT w.lvl, w.source AS vid, min(w.dist) AS d FROM walk w JOIN pois ON poi = w.vid GROUP BY ALL)
SELECT b.lvl, b.comp, b.vid, db.d AS d_border, dp.d AS d_poi FROM bord b LEFT JOIN db ON db.lvl = b.lvl AND db.vid = b.vid LEFT JOIN dp ON dp.lvl = b.lvl AND dp.vid = b.vid"""

# The bound of each query comes from its own nearest POIs; the nearest paths are the safest among the shortest.
def effect(delta: float) -> str:
    def grown(name: str) -> str:
        return f"""(SELECT q.qid, src AS vid, dc, {zeros(SMAX)} AS sd, CAST(0 AS BIGINT) AS dist FROM q JOIN far USING (qid)
  UNION ALL
  SELECT qid, vid, dc, sd, dist FROM (
    SELECT *, min(dist) OVER (PARTITION BY qid, vid ORDER BY sd, dist ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS least
    FROM (SELECT l.qid, a.dst AS vid, l.dc, {added('l.sd', SMAX)} AS sd, l.dist + a.len AS dist FROM {name} l JOIN arcs a ON a.src = l.vid WHERE l.dist + a.len < l.dc)
  ) WHERE least IS NULL OR dist < least)"""

    cost = "CASE WHEN list_sum({0}) > 0 THEN 1 / list_reduce(CAST({0} AS DOUBLE[]), lambda s, x: s * 1000 + x) END"
    return f"""WITH RECURSIVE {net()}, {NEAREST},
far AS (SELECT qid, {delta} * max(dist) AS dc FROM knn GROUP BY qid),
lab AS {grown('lab')}, {top()},
far1 AS (SELECT qid, max(dist) + 1 AS dc FROM knn GROUP BY qid),
lab1 AS {grown('lab1').replace('JOIN far USING', 'JOIN far1 USING')},
shortest AS (SELECT k.qid, k.rnk, k.poi, k.dist, min(l.sd) AS sd FROM knn k JOIN lab1 l ON l.qid = k.qid AND l.vid = k.poi AND l.dist = k.dist WHERE k.qid IN (SELECT qid FROM ans) GROUP BY ALL),
per AS (SELECT qid, count(*) FILTER (a.poi IS NOT NULL AND n.poi IS NOT NULL) AS common, max(CASE WHEN a.rnk = 1 AND n.poi IS NOT NULL THEN 1 ELSE 0 END) AS top, avg(a.dist) AS ds, avg(n.dist) AS dn, avg({cost.format('a.sd')}) AS ps, avg({cost.format('n.sd')}) AS pn
  FROM ans a FULL JOIN shortest n USING (qid, poi) GROUP BY qid)
SELECT CAST({delta} AS DOUBLE) AS delta, round(avg(common), 6) AS common, round(avg(top), 6) AS p_safest_in_knn, round(avg(dn), 6) AS length_knn, round(avg(ds), 6) AS length_safest, round(avg(ds) / avg(dn), 6) AS length_ratio,
  round(log10(avg(pn)), 6) AS log_pss_knn, round(log10(avg(ps)), 6) AS log_pss_safest, round(log10(avg(ps) / avg(pn)), 6) AS log_pss_ratio FROM per"""


EFFECT = " UNION ALL ".join(f"({effect(d)})" for d in (1.25, 1.5, 1.75, 2.0))

DAYNIGHT = """WITH z AS (SELECT count(*) AS n, CAST(floor(sqrt(count(*))) AS BIGINT) AS w FROM part),
v AS (SELECT p_partkey AS vid, p_size FROM part),
e AS (
  SELECT a.vid * 2 AS eid, a.vid AS u, b.vid AS w FROM v a JOIN v b ON b.vid = a.vid + 1, z WHERE a.vid % z.w <> z.w - 1 AND (a.p_size + b.p_size) % 8 <> 0
  UNION ALL SELECT a.vid * 2 + 1, a.vid, b.vid FROM v a CROSS JOIN z JOIN v b ON b.vid = a.vid + z.w WHERE (a.p_size + b.p_size) % 8 <> 1),
ev AS (SELECT event_id * 611953 % z.n AS vid, sum(CASE WHEN hour(ts) BETWEEN 6 AND 17 THEN k ELSE 0 END) AS d, sum(CASE WHEN hour(ts) BETWEEN 6 AND 17 THEN 0 ELSE k END) AS g
  FROM (SELECT *, coalesce(CAST(json_extract_string(props, '$.k') AS BIGINT), 1) AS k FROM events WHERE event_type = 'error'), z GROUP BY ALL),
c AS (SELECT eid, coalesce(x.d, 0) + coalesce(y.d, 0) AS d, coalesce(x.g, 0) + coalesce(y.g, 0) AS g FROM e LEFT JOIN ev x ON x.vid = u LEFT JOIN ev y ON y.vid = e.w),
m AS (SELECT min(d) AS d0, max(d) AS d1, min(g) AS g0, max(g) AS g1 FROM c)
SELECT eid, CAST(5 - (d - d0) * 5 // (d1 - d0 + 1) AS INTEGER) AS day, CAST(5 - (g - g0) * 5 // (g1 - g0 + 1) AS INTEGER) AS night FROM c, m"""

DAY_EDGES = DAYNIGHT.removeprefix("WITH ").replace("a.vid AS u, b.vid AS w FROM v a JOIN", "a.vid AS u, b.vid AS w, 10 + (a.p_size + 3 * b.p_size) % 11 AS len FROM v a JOIN").replace("a.vid, b.vid FROM v a CROSS", "a.vid, b.vid, 10 + (a.p_size + 7 * b.p_size) % 11 FROM v a CROSS")
DAY_EDGES = DAY_EDGES[: DAY_EDGES.index("SELECT eid, CAST(5")] + ", levels AS (" + DAY_EDGES[DAY_EDGES.index("SELECT eid, CAST(5") :] + ")"


def daytime(key: str) -> str:
    edges = f"edges AS (SELECT eid, u, w, CAST(len AS BIGINT) AS len, {key} AS ess FROM e JOIN levels USING (eid))"
    return f"(WITH RECURSIVE {DAY_EDGES}, {edges}, {rest()}, {labels(5)}, {top()} SELECT '{key}' AS daytime, qid, rnk, poi, dist, array_to_string(sd, ',') AS sd FROM ans)"


TRADE = """t AS (SELECT o_custkey * 2 AS a, l_suppkey * 2 + 1 AS b, count(*) AS n, count(*) FILTER (l_returnflag = 'R') AS back FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY ALL),
edges AS (SELECT least(a, b) AS u, greatest(a, b) AS w, 1 + n % 5 AS len, CAST(5 - back * 4 // n AS INTEGER) AS ess FROM t)"""

PROXIMITY = """WITH v AS (SELECT vec_id, embedding AS e, label FROM embeddings WHERE embedding IS NOT NULL AND label IS NOT NULL),
p AS (SELECT a.vec_id AS i, b.vec_id AS j, a.label AS la, b.label AS lb, sqrt(list_sum(list_transform(list_zip(a.e, b.e), lambda x: CAST((x[1] - x[2]) * (x[1] - x[2]) AS DOUBLE)))) AS gap
  FROM v a JOIN v b ON a.vec_id <> b.vec_id AND (b.label = a.label OR (b.label + 9) % 10 = a.label)),
r AS (SELECT *, row_number() OVER (PARTITION BY i ORDER BY gap, j) AS r FROM p),
d AS (SELECT least(i, j) AS u, greatest(i, j) AS w, min(CAST(1 + ceil(gap * 100) AS BIGINT)) AS len, max(CASE WHEN la = lb THEN 5 ELSE CAST(1 + (la + lb) % 4 AS INTEGER) END) AS ess FROM r WHERE r <= 4 GROUP BY ALL)
SELECT ess, count(*) AS n, min(len) AS shortest FROM d GROUP BY ess"""

SQL: dict[str, str] = {
    "edges_lattice": f"WITH {net()} SELECT eid, u, w, len, ess FROM edges",
    "incidents_per_edge": f"WITH {net()} SELECT eid, u, w, n FROM counted",
    "incidents_clustered": f"WITH {net(clustered=True)} SELECT eid, u, w, n FROM counted",
    "ess_histogram": " UNION ALL ".join(f"(WITH {net(s)} SELECT {s} AS smax, ess, count(*) AS n FROM edges GROUP BY ess)" for s in (5, 10, 15)),
    "poi_sample": f"WITH {net()} SELECT poi FROM pois",
    "level_weights": f"WITH {net(5)} SELECT ess AS s, CAST(pow(10, 5 - ess) AS DOUBLE) AS weight, count(*) AS n FROM edges GROUP BY ess",
    "s_vector_paths": f"WITH {net()}, {PATHS} SELECT path_id, CAST(sum(len) AS BIGINT) AS dist, array_to_string({PATH_SD}, ',') AS sd, min(ess) AS bottleneck FROM paths GROUP BY path_id",
    "s_distance_paths": f"WITH {net()}, {PATHS} SELECT path_id, CAST(sum(CASE WHEN ess = 4 THEN len ELSE 0 END) AS BIGINT) AS d_s FROM paths GROUP BY path_id",
    "pss_paths": f"WITH {net()}, {PATHS}, s AS (SELECT path_id, {PATH5} AS sd FROM paths GROUP BY path_id) SELECT path_id, CAST(sd[1] * 1000000000000 + sd[2] * 1000000000 + sd[3] * 1000000 + sd[4] * 1000 + sd[5] AS BIGINT) AS cost, CAST(rank() OVER (ORDER BY sd) AS INTEGER) AS rnk FROM s",
    "safest_expand": safest(),
    "safest_expand_clustered": safest(clustered=True),
    "safest_expand_smax5": safest(5, 80.0, 1),
    "safest_brute": safest(dc=40.0),
    "safest_euclid": safest(),
    "safest_comptree": safest(),
    "safest_comptree_height5": safest(),
    "safest_safevor": safest(),
    "kernel_expand": safest(),
    "kernel_comptree": safest(),
    "kernel_safevor": safest(),
    "kernel_euclid": safest(),
    "safest_pairs": f"WITH RECURSIVE {net()}, {labels()} SELECT l.qid, l.vid AS poi, list_sum(min(l.sd)) AS dist, array_to_string(min(l.sd), ',') AS sd FROM lab l JOIN q ON q.qid = l.qid AND l.vid = q.src + 2 GROUP BY ALL".replace("list_sum(min(l.sd))", "CAST(list_sum(min(l.sd)) AS BIGINT)"),
    "safest_frontier": f"WITH RECURSIVE {net()}, {labels()} SELECT qid, vid AS poi, dist, array_to_string(sd, ',') AS sd FROM (SELECT *, min(dist) OVER (PARTITION BY qid, vid ORDER BY sd, dist ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS least FROM lab JOIN pois ON poi = vid) WHERE least IS NULL OR dist < least",
    "euclid_candidates": f"WITH {net()} SELECT qid, poi FROM q JOIN v a ON a.vid = q.src CROSS JOIN pois JOIN v b ON b.vid = poi WHERE (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) < {DC * DC}",
    "knn_topk": f"WITH RECURSIVE {net()}, {NEAREST} SELECT qid, rnk, poi, dist FROM knn",
    "dc_by_delta": f"WITH RECURSIVE {net()}, {NEAREST}, far AS (SELECT qid, max(dist) AS far, count(*) AS n FROM knn GROUP BY qid) SELECT CAST(delta AS DOUBLE) AS delta, qid, CAST(delta * far AS DOUBLE) AS dc, n < {K} AS few FROM far, (SELECT unnest([1.25, 1.5, 1.75, 2.0]) AS delta)",
    "comptree_pointers": f"WITH RECURSIVE {net()}, {CHAIN} SELECT vid, lvl, comp FROM chain",
    "comptree_nodes": NODES,
    "comptree_borders": f"WITH RECURSIVE {net()}, {CHAIN}, {BORDER_SET} SELECT lvl, comp, vid FROM bord",
    "border_distance": BORDER_DISTANCE,
    "usn_assignment": f"WITH RECURSIVE {net()}, {USN} SELECT vid, cell, CAST(list_sum(sd) AS BIGINT) AS dist, array_to_string(sd, ',') AS sd FROM usn",
    "cell_borders": f"WITH RECURSIVE {net()}, {USN}, {BORDERS} SELECT * FROM b",
    "cell_adjacency": f"WITH RECURSIVE {net()}, {USN}, {BORDERS} SELECT cell_u AS cell, cell_w AS other FROM b UNION SELECT cell_w, cell_u FROM b",
    "cell_sizes": f"WITH RECURSIVE {net()}, {USN} SELECT cell, count(*) AS n, CAST(max(list_sum(sd)) AS BIGINT) AS farthest FROM usn GROUP BY cell",
    "effectiveness": EFFECT,
    "zone_safest": f"WITH RECURSIVE {ZONES}, {labels(2)}, {top()} {SHOW}",
    "min_ess_safest": f"WITH RECURSIVE {net()}, {labels(start='[CAST(0 AS BIGINT)]', grow=f'[greatest(l.sd[1], CAST({SMAX + 1} - a.ess AS BIGINT))]')}, {top()} SELECT qid, rnk, poi, dist, sd[1] AS badness FROM ans",
    "product_ess_safest": f"WITH RECURSIVE {net()}, {labels(start='[CAST(0 AS BIGINT)]', grow=f'[l.sd[1] + CAST(round(ln({float(SMAX)} / a.ess) * 1000000) AS BIGINT)]')}, {top()} SELECT qid, rnk, poi, dist, sd[1] AS badness FROM ans",
    "daynight_ess": DAYNIGHT,
    "trade_edges": f"WITH {TRADE} SELECT u, w, len, ess FROM edges",
    "trade_components": f"WITH RECURSIVE {TRADE}, e AS (SELECT u AS a, w AS b FROM edges WHERE ess > 4 UNION ALL SELECT w, u FROM edges WHERE ess > 4), r(vid, root) USING KEY (vid) AS (SELECT a, min(least(a, b)) FROM e GROUP BY a UNION SELECT e.b, min(r.root) FROM r JOIN e ON e.a = r.vid LEFT JOIN recurring.r o ON o.vid = e.b WHERE r.root < o.root GROUP BY e.b) SELECT root AS comp, count(*) AS n FROM r GROUP BY root",
    "proximity_edges": PROXIMITY,
    "ess_asof": "WITH h AS (SELECT event_id * 611953 % 500 AS eid, ts, max(CAST(1 + user_id % 10 AS INTEGER)) AS ess FROM events WHERE event_type = 'error' GROUP BY ALL), a AS (SELECT event_id * 611953 % 500 AS eid, ts FROM events WHERE event_type = 'purchase') SELECT a.eid, count(*) AS asked, CAST(sum(h.ess) AS BIGINT) AS ess_sum FROM a ASOF LEFT JOIN h ON h.eid = a.eid AND h.ts <= a.ts GROUP BY a.eid",
    "ess_weekly_windows": "SELECT CAST(CAST(date_trunc('week', ts) AS DATE) AS VARCHAR) AS week, event_id * 611953 % 500 AS eid, count(*) AS n FROM events WHERE event_type = 'error' GROUP BY ALL",
    "incident_cube": "SELECT event_type, part, count(*) AS n, CAST(grouping_id(event_type, part) AS INTEGER) AS grp FROM (SELECT event_type, CASE WHEN hour(ts) BETWEEN 6 AND 17 THEN 'day' ELSE 'night' END AS part FROM events) GROUP BY CUBE (event_type, part)",
    "answers_setops": f"WITH RECURSIVE {net()}, {labels()}, {top()}, {NEAREST_DC} SELECT coalesce(a.qid, n.qid) AS qid, coalesce(a.poi, n.poi) AS poi, CASE WHEN n.poi IS NULL THEN 'safest' WHEN a.poi IS NULL THEN 'nearest' ELSE 'both' END AS side FROM ans a FULL JOIN knn n ON a.qid = n.qid AND a.poi = n.poi",
}
SQL["daynight_safest"] = daytime("day") + " UNION ALL " + daytime("night")
SQL["weight_choice_safest"] = safest().replace("CAST(len AS BIGINT) AS len, CAST", "CAST(ceil(len * 6.0 / (CAST(11 - (1 + (n - lo) * 10 // (hi - lo + 1)) AS INTEGER) + 2)) AS BIGINT) AS len, CAST")
SQL["incidents_of_kinds"] = "SELECT event_id * 611953 % 500 AS eid, count(*) AS n FROM events WHERE event_type IN ('error', 'signup') GROUP BY ALL"
SQL["cells_kernel"] = f"WITH RECURSIVE {net()}, {USN} SELECT vid, cell FROM usn"
SQL["cell_poi_paths"] = f"WITH RECURSIVE {net()}, {USN}, {BORDERS} SELECT cell, vid AS b1, CAST(list_sum(sd) AS BIGINT) AS dist, array_to_string(sd, ',') AS sd FROM usn WHERE vid <> cell AND vid IN (SELECT u FROM b UNION SELECT w FROM b)"
SETS = {"expand": ("1", "1,2"), "comptree": ("1", "1,2", "1,3", "1,4", "1,2,3,4"), "safevor": ("1", "1,2", "1,5,6", "1,7", "1,2,5,6,7")}
SQL["ablation_answers"] = f"WITH RECURSIVE {net()}, {labels()}, {top()}, t AS (SELECT count(*) AS answers, CAST(sum(dist) AS BIGINT) AS length, CAST(sum(rnk * poi) AS BIGINT) AS ranks FROM ans) SELECT * FROM (VALUES {', '.join(f"('{m}', '{r}')" for m, rs in SETS.items() for r in rs)}) s(method, rules), t"
SQL["stream_window_counts"] = SQL["ess_weekly_windows"]
SQL["stream_level_changes"] = "SELECT eid, ess FROM (SELECT event_id * 611953 % 500 AS eid, CAST(greatest(1, 10 - count(*) // 2) AS INTEGER) AS ess FROM events WHERE event_type = 'error' GROUP BY ALL) WHERE ess < 10"
SQL["knn_kernel"], SQL["border_distance_local"], SQL["comptree_nodes_local"] = SQL["knn_topk"], SQL["border_distance"], SQL["comptree_nodes"]
