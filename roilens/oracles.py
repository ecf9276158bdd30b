"""DuckDB SQL for the named queries, by other formulations than the plans where there are any.

Hulls come from directed edges with all points on one side, clusters from a recursive closure, regions
from a separating-edge test, matches from containment in both hulls; nothing is clipped or grown.
The common tables are listed once, in order; a query takes those up to the last it needs.
"""

from __future__ import annotations

import re

from .relational.ops import SQL as OPS_SQL

_AX, _AY = "[-500, -250, 0, 250, 500]", "[-200, 150, -100, 200, 0]"


def _moves(name: str, kind: str = "hover", users: int = 8) -> str:
    ty = "CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END"
    if kind != "hover":
        ty = "least(4, t_ms // 6000)::INT"
    jx, jy = ("(k % 10 - 5) * 8 + session_id % 4 * 7", "(k // 10 - 5) * 8 + session_id % 3 * 5") if kind != "still" else ("0", "0")
    noisy = "value >= 120" if kind != "still" else "false"
    return f"""{name} AS MATERIALIZED (SELECT session_id, event_id, t_ms, (CASE WHEN {noisy} THEN event_id * 7919 % 1600 - 800 ELSE {_AX}[ty + 1] + {jx} END)::BIGINT AS x,
  (CASE WHEN {noisy} THEN event_id * 104729 % 900 - 450 ELSE {_AY}[ty + 1] + {jy} END)::BIGINT AS y, ty AS true_spot, value >= 120 AS true_noise
  FROM (SELECT *, {ty} AS ty FROM (SELECT *, (epoch_us(ts) - 1704067200000000) // 86400000 AS t_ms, user_id // {users} AS session_id, (props->>'$.k')::BIGINT AS k FROM events)))"""


def _kept(name: str, of: str, eps: int = 100) -> str:
    return f"""{name} AS MATERIALIZED (SELECT session_id, event_id, t_ms, x, y FROM (SELECT *, row_number() OVER (PARTITION BY session_id, t_ms // {eps} ORDER BY t_ms, event_id) AS rn FROM {of}) WHERE rn = 1)"""


_PLACE = f"""CASE WHEN key % 8 < 5 THEN {_AX}[key % 8 + 1] + key * 48271 % 121 - 60 ELSE key * 48271 % 1601 - 800 END AS mx,
  CASE WHEN key % 8 < 5 THEN {_AY}[key % 8 + 1] + key * 16807 % 113 - 56 ELSE key * 16807 % 901 - 450 END AS my"""

#: Common tables in order of need.
TABLES: list[tuple[str, str]] = [
    ("m", _moves("m")),
    ("ms", _moves("ms", "still")),
    ("md", _moves("md", "drift")),
    ("k", _kept("k", "m")),
    ("ks", _kept("ks", "ms")),
    ("kd", _kept("kd", "md")),
    ("seg", "seg AS MATERIALIZED (SELECT *, dense_rank() OVER (PARTITION BY session_id ORDER BY least(2, t_ms * 3 // 30000))::INT AS seg FROM k)"),
    ("near", """near AS MATERIALIZED (SELECT a.session_id, a.seg, a.event_id AS a, b.event_id AS b, (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS d2
  FROM seg a JOIN seg b ON a.session_id = b.session_id AND a.seg = b.seg WHERE (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) < 900)"""),
    ("core", "core AS MATERIALIZED (SELECT a AS e FROM near GROUP BY a HAVING count(*) >= 5)"),
    ("reach", """reach AS (SELECT e AS a, e AS b FROM core UNION SELECT r.a, n.b FROM reach r JOIN near n ON n.a = r.b JOIN core c ON c.e = n.b)"""),
    ("named", "named AS MATERIALIZED (SELECT a AS e, min(b) AS cluster_id FROM reach GROUP BY a)"),
    ("clus", """clus AS MATERIALIZED (SELECT s.*, coalesce(c.cluster_id, b.cluster_id) AS cluster_id, CASE WHEN c.e IS NOT NULL THEN 'core' WHEN b.cluster_id IS NOT NULL THEN 'border' ELSE 'noise' END AS role
  FROM seg s LEFT JOIN named c ON c.e = s.event_id LEFT JOIN (SELECT a, arg_min(cluster_id, d2 * 1000000000 + cluster_id) AS cluster_id FROM near JOIN named ON named.e = near.b GROUP BY a) b ON b.a = s.event_id)"""),
    ("px", "px AS MATERIALIZED (SELECT DISTINCT session_id, seg, cluster_id, x, y FROM clus WHERE cluster_id IS NOT NULL)"),
    ("edge", """edge AS MATERIALIZED (SELECT p.session_id, p.seg, p.cluster_id, p.x AS ax, p.y AS ay, q.x AS bx, q.y AS ey FROM px p JOIN px q ON p.cluster_id = q.cluster_id AND p.session_id = q.session_id AND (p.x <> q.x OR p.y <> q.y)
  JOIN px r ON r.cluster_id = p.cluster_id AND r.session_id = p.session_id GROUP BY ALL
  HAVING bool_and((q.x - p.x) * (r.y - p.y) - (q.y - p.y) * (r.x - p.x) > 0 OR ((q.x - p.x) * (r.y - p.y) - (q.y - p.y) * (r.x - p.x) = 0
    AND (q.x - p.x) * (r.x - p.x) + (q.y - p.y) * (r.y - p.y) BETWEEN 0 AND (q.x - p.x) * (q.x - p.x) + (q.y - p.y) * (q.y - p.y))))"""),
    ("hullm", "hullm AS MATERIALIZED (SELECT session_id, seg, cluster_id, sum(ax * ey - bx * ay) / 2.0 AS area, sum(sqrt(((bx - ax) * (bx - ax) + (ey - ay) * (ey - ay))::DOUBLE)) AS perimeter, count(*) AS vertices FROM edge GROUP BY ALL)"),
    ("parted", """parted AS MATERIALIZED (SELECT DISTINCT e.session_id, e.cluster_id AS a, o.cluster_id AS b FROM (
    SELECT e.session_id, e.cluster_id, o.cluster_id AS oc, e.ax, e.ay, e.bx, e.ey FROM edge e JOIN edge o ON e.session_id = o.session_id AND e.cluster_id <> o.cluster_id
    GROUP BY ALL HAVING max((e.bx - e.ax) * (o.ay - e.ay) - (e.ey - e.ay) * (o.ax - e.ax)) <= 0) e JOIN hullm o ON o.cluster_id = e.oc AND o.session_id = e.session_id)"""),
    ("roi", """roi AS MATERIALIZED (SELECT a.session_id, (row_number() OVER (PARTITION BY a.session_id ORDER BY a.cluster_id, b.cluster_id))::INT AS roi_id, a.cluster_id AS src_a, b.cluster_id AS src_b, a.seg AS seg_a, b.seg AS seg_b
  FROM hullm a JOIN hullm b ON a.session_id = b.session_id AND a.cluster_id < b.cluster_id WHERE a.area > 0 AND b.area > 0
  AND NOT EXISTS (SELECT 1 FROM parted p WHERE p.session_id = a.session_id AND ((p.a = a.cluster_id AND p.b = b.cluster_id) OR (p.a = b.cluster_id AND p.b = a.cluster_id))))"""),
    ("corner", """corner AS MATERIALIZED (SELECT DISTINCT r.session_id, r.roi_id, round(v.x, 9) AS x, round(v.y, 9) AS y FROM roi r JOIN (
    SELECT o.session_id, e.cluster_id AS of, o.cluster_id AS within, e.ax::DOUBLE AS x, e.ay::DOUBLE AS y FROM edge e JOIN edge o ON o.session_id = e.session_id AND o.cluster_id <> e.cluster_id
    GROUP BY ALL HAVING bool_and((o.bx - o.ax) * (e.ay - o.ay) - (o.ey - o.ay) * (e.ax - o.ax) >= 0)) v
    ON v.session_id = r.session_id AND ((v.of = r.src_a AND v.within = r.src_b) OR (v.of = r.src_b AND v.within = r.src_a))
  UNION SELECT session_id, roi_id, round(ax + t * dx, 9), round(ay + t * dy, 9) FROM (
    SELECT r.session_id, r.roi_id, e.ax, e.ay, e.bx - e.ax AS dx, e.ey - e.ay AS dy, (e.bx - e.ax) * (f.ey - f.ay) - (e.ey - e.ay) * (f.bx - f.ax) AS det,
      ((f.ax - e.ax) * (f.ey - f.ay) - (f.ay - e.ay) * (f.bx - f.ax)) / nullif(det, 0)::DOUBLE AS t, ((f.ax - e.ax) * (e.ey - e.ay) - (f.ay - e.ay) * (e.bx - e.ax)) / nullif(det, 0)::DOUBLE AS u
    FROM roi r JOIN edge e ON e.session_id = r.session_id AND e.cluster_id = r.src_a JOIN edge f ON f.session_id = r.session_id AND f.cluster_id = r.src_b) WHERE t BETWEEN 0 AND 1 AND u BETWEEN 0 AND 1)"""),
    ("ring", """ring AS (SELECT *, coalesce(lead(x) OVER v, first_value(x) OVER v) AS nx, coalesce(lead(y) OVER v, first_value(y) OVER v) AS ny FROM (
    SELECT *, atan2(y - avg(y) OVER g, x - avg(x) OVER g) AS angle FROM corner WINDOW g AS (PARTITION BY session_id, roi_id)) WINDOW v AS (PARTITION BY session_id, roi_id ORDER BY angle))"""),
    ("region", """region AS MATERIALIZED (SELECT session_id, roi_id, sum(x * ny - nx * y) / 2 AS area, sum((x + nx) * (x * ny - nx * y)) / (3 * sum(x * ny - nx * y)) AS cx, sum((y + ny) * (x * ny - nx * y)) / (3 * sum(x * ny - nx * y)) AS cy FROM ring GROUP BY ALL)"""),
    ("poi", f"""poi AS MATERIALIZED (SELECT key AS poi_id, {_PLACE}, p_brand AS brand, p_type AS type, ((p_size - 1) // 10)::VARCHAR AS size_decade, split_part(p_name, ' ', 1) AS colour, split_part(p_name, ' ', 2) AS noun
  FROM (SELECT *, p_partkey AS key FROM part))"""),
    ("facet", """facet AS MATERIALIZED (SELECT poi_id, 'brand' AS attr, brand AS val FROM poi UNION ALL SELECT poi_id, 'type', type FROM poi UNION ALL SELECT poi_id, 'size_decade', size_decade FROM poi
  UNION ALL SELECT poi_id, 'colour', colour FROM poi UNION ALL SELECT poi_id, 'noun', noun FROM poi)"""),
    ("inhull", """inhull AS MATERIALIZED (SELECT e.session_id, e.cluster_id, p.poi_id FROM edge e JOIN poi p ON true GROUP BY ALL HAVING bool_and((e.bx - e.ax) * (p.my - e.ay) - (e.ey - e.ay) * (p.mx - e.ax) > 0))"""),
    ("match", """match AS MATERIALIZED (SELECT r.session_id, r.roi_id, i.poi_id FROM roi r JOIN inhull i ON i.session_id = r.session_id AND i.cluster_id = r.src_a JOIN inhull j ON j.session_id = r.session_id AND j.cluster_id = r.src_b AND j.poi_id = i.poi_id)"""),
    ("inc", "inc AS MATERIALIZED (SELECT m.session_id, m.roi_id, f.attr, f.val, count(*) * 0.05::DOUBLE AS inc FROM match m JOIN facet f USING (poi_id) GROUP BY ALL)"),
    ("fb", "fb AS MATERIALIZED (SELECT session_id, attr, val, sum(inc) AS raw FROM inc GROUP BY ALL)"),
    ("cells", "cells AS (SELECT count(*) AS f FROM (SELECT DISTINCT attr, val FROM facet))"),
    ("z", "z AS MATERIALIZED (SELECT session_id, sum(exp(raw)) + (any_value(f) - count(*)) AS z, any_value(f) - count(*) AS rest FROM fb, cells GROUP BY session_id)"),
    ("w", "w AS MATERIALIZED (SELECT fb.session_id, attr, val, exp(raw) / z.z AS weight, 1 / z.z AS w0 FROM fb JOIN z USING (session_id))"),
    ("norm", "norm AS MATERIALIZED (SELECT session_id, sqrt(sum(weight * weight) + any_value(rest) * any_value(w0) * any_value(w0)) AS norm, any_value(w0) AS w0 FROM w JOIN z USING (session_id) GROUP BY session_id)"),
    ("rel", """rel AS MATERIALIZED (SELECT m.session_id, m.roi_id, m.poi_id, sum(w.weight) / (any_value(n.norm) * sqrt(5)) AS relevance FROM match m JOIN facet f USING (poi_id)
  JOIN w ON w.session_id = m.session_id AND w.attr = f.attr AND w.val = f.val JOIN norm n ON n.session_id = m.session_id GROUP BY ALL)"""),
    ("vec", "vec AS MATERIALIZED (SELECT DISTINCT m.session_id, m.roi_id, f.attr, f.val FROM match m JOIN facet f USING (poi_id))"),
    ("pec", """pec AS MATERIALIZED (SELECT v.session_id, v.roi_id, sum(w.weight) / (any_value(n.norm) * sqrt(count(*))) AS printed FROM vec v JOIN w ON w.session_id = v.session_id AND w.attr = v.attr AND w.val = v.val
  JOIN norm n ON n.session_id = v.session_id GROUP BY ALL)"""),
    ("rnd", "rnd AS MATERIALIZED (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY session_id, roi_id ORDER BY (poi_id * 2654435761 + 1) % 4294967296, poi_id) AS rank FROM match) WHERE rank <= 5)"),
    ("clk", "clk AS MATERIALIZED (SELECT o_custkey // 8 AS session_id, l_partkey AS poi_id FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"),
    ("track", "track AS MATERIALIZED (SELECT e.user_id AS track_id, m.event_id, m.t_ms, m.x, m.y, e.value AS alt FROM events e JOIN m USING (event_id))"),
]
_NEEDS = {
    "m": "", "ms": "", "md": "", "k": "m", "ks": "ms", "kd": "md", "seg": "k", "near": "seg", "core": "near", "reach": "core near", "named": "reach", "clus": "named near seg", "px": "clus", "edge": "px",
    "hullm": "edge", "parted": "edge hullm", "roi": "hullm parted", "corner": "roi edge", "ring": "corner", "region": "ring", "poi": "", "facet": "poi", "inhull": "edge poi", "match": "roi inhull", "inc": "match facet", "fb": "inc", "cells": "facet", "z": "fb cells",
    "w": "fb z", "norm": "w z", "rel": "match facet w norm", "vec": "match facet", "pec": "vec w norm", "rnd": "match", "clk": "", "track": "m",
}


def _with(needs: str, select: str, more: str = "") -> str:
    """A query over the common tables it names, those they need included."""
    want: set[str] = set()

    def add(n: str) -> None:
        if n not in want:
            want.add(n)
            for x in _NEEDS[n].split():
                add(x)

    for n in needs.split():
        add(n)
    ctes = [sql for n, sql in TABLES if n in want] + ([more] if more else [])
    return f"WITH RECURSIVE {', '.join(ctes)} {select}"


def _summary(of: str, boundary: str, needs: str) -> str:
    """Segments from a boundary flag: one more than the flags strictly before a row."""
    return _with(
        needs,
        "SELECT session_id, seg, min(t_ms) AS t_start, max(t_ms) AS t_end, count(*) AS n FROM numbered GROUP BY ALL",
        f"""flagged AS (SELECT *, {boundary} AS f FROM {of}),
numbered AS (SELECT *, (1 + coalesce(sum(f::INT) OVER (PARTITION BY session_id ORDER BY t_ms, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::INT AS seg FROM flagged)""",
    )


_W = "OVER (PARTITION BY session_id ORDER BY t_ms, event_id)"
_STINT = f"""(SELECT *, max(CASE WHEN moved THEN t_ms END) OVER (PARTITION BY session_id ORDER BY t_ms, event_id ROWS UNBOUNDED PRECEDING) AS stint FROM
  (SELECT *, coalesce(lag(x) {_W} <> x OR lag(y) {_W} <> y, true) AS moved FROM {{0}}))"""
_STILL = f"(t_ms - stint >= 300 AND NOT (coalesce(lag(t_ms - stint) {_W} >= 300, false) AND NOT moved))"
_GAP = f"coalesce(lead(t_ms) {_W} - t_ms >= 300, false)"


def _tier(w: int) -> str:
    back = f"OVER (PARTITION BY session_id ORDER BY t_ms, event_id ROWS BETWEEN {w} PRECEDING AND 1 PRECEDING)"
    ahead = f"OVER (PARTITION BY session_id ORDER BY t_ms, event_id ROWS BETWEEN CURRENT ROW AND {w - 1} FOLLOWING)"
    spread = " + ".join(f"coalesce(var_pop({c}) {f}, 0)" for c in ("x", "y") for f in (back, ahead))
    return f"CASE WHEN count(x) {back} = {w} AND count(x) {ahead} = {w} THEN round(sqrt(pow(avg(x) {ahead} - avg(x) {back}, 2) + pow(avg(y) {ahead} - avg(y) {back}, 2)) / sqrt(({spread}) / 2 + 1), 9) ELSE 0 END"


_DRIFT = _with(
    "kd",
    "SELECT session_id, seg, min(t_ms) AS t_start, max(t_ms) AS t_end, count(*) AS n FROM numbered GROUP BY ALL",
    f"""scored AS (SELECT *, least({_tier(4)}, {_tier(8)}, {_tier(16)}) AS s FROM kd),
begins AS (SELECT *, s >= 1 AND s = max(s) OVER (PARTITION BY session_id ORDER BY t_ms, event_id ROWS BETWEEN 4 PRECEDING AND 4 FOLLOWING)
  AND coalesce(max(s) OVER (PARTITION BY session_id ORDER BY t_ms, event_id ROWS BETWEEN 4 PRECEDING AND 1 PRECEDING), -1) < s AS b FROM scored),
flagged AS (SELECT *, coalesce(lead(b) {_W}, false) AS f FROM begins),
numbered AS (SELECT *, (1 + coalesce(sum(f::INT) OVER (PARTITION BY session_id ORDER BY t_ms, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::INT AS seg FROM flagged)""",
)

_COS = "cos(radians(48.86))"


def _stretched(factor: str) -> str:
    return _with("hullm", f"SELECT session_id, cluster_id, round(area * ({factor}), 4) AS area FROM hullm WHERE area > 0")


_LEAVES = """cell AS (SELECT mx + 1024 AS cx, my + 1024 AS cy FROM poi),
code AS MATERIALIZED (SELECT (SELECT sum((((cx >> i) & 1) << (2 * i)) + (((cy >> i) & 1) << (2 * i + 1))) FROM range(11) t(i))::BIGINT AS code FROM cell),
lv AS MATERIALIZED (SELECT d AS depth, code >> (2 * (11 - d)) AS code, count(*) AS n FROM code, range(12) t(d) GROUP BY ALL),
leaf AS (SELECT a.depth::INT AS depth, a.code, a.n FROM lv a LEFT JOIN lv b ON b.depth = a.depth - 1 AND b.code = a.code >> 2 WHERE (a.n <= 64 OR a.depth = 11) AND (a.depth = 0 OR b.n > 64))"""

def _sides(sql: str) -> str:
    """``side(ax, ay, bx, by, x, y)`` written out: whether (x, y) lies left of the edge."""
    return re.sub(r"side\((\w+), (\w+), (\w+), (\w+), (\w+), (\w+)\)", r"((\3 - \1) * (\6 - \2) - (\4 - \2) * (\5 - \1) > 0)", sql)


ORACLES: dict[str, str] = {
    "q_signal_kinds": _with("m", "SELECT signal, count(*) AS n, sum(x + dx)::BIGINT AS sx, sum(y + CASE WHEN signal = 'scroll' THEN t_ms % 50 ELSE dy END)::BIGINT AS sy FROM m, (VALUES ('hover', 0, 0), ('gaze', 0, 1), ('scroll', 0, 0), ('pinch', 0, 0), ('zoom', 0, 0), ('voice', 0, 0), ('detail', 2, -2)) kind(signal, dx, dy) GROUP BY signal"),
    "q_eps_profile": _with("m", "SELECT profile, count(DISTINCT (session_id, t_ms // eps)) AS kept FROM m, (VALUES ('novice', 250), ('regular', 100), ('expert', 50), ('delivery', 50), ('tourism', 100), ('transportation', 100)) p(profile, eps) GROUP BY profile"),
    "q_reachable_chains": _with("named", "SELECT e AS event_id, cluster_id AS root FROM named"),
    "q_stretch_report": _with("hullm", "SELECT DISTINCT session_id, round((session_id % 5) / 4.0::DOUBLE, 6) AS confidence, round(1 + (session_id % 5) / 4.0::DOUBLE, 6) AS ratio FROM hullm WHERE area > 0"),
    "q_project_roundtrip": _with("m", f"SELECT event_id, round(y / 10000.0::DOUBLE + 48.86::DOUBLE, 6) AS lat, round(x / 10000.0::DOUBLE / {_COS} + 2.3::DOUBLE, 6) AS lon, round(x::DOUBLE, 3) AS bx, round(y::DOUBLE, 3) AS by FROM m"),
    "q_recentre": _with("m", "SELECT event_id, round(y / 10000.0::DOUBLE + 48 + 0.5 * i, 6) AS lat, round(x / 10000.0::DOUBLE / cos(radians(48 + 0.5 * i)) + 2 + i, 6) AS lon FROM (SELECT *, least(2, t_ms // 10000) AS i FROM m)"),
    "q_thin_grid": _with("k", "SELECT * FROM k"),
    "q_thin_refractory": _with(
        "m",
        "SELECT session_id, event_id, t_ms FROM kept",
        """one AS MATERIALIZED (SELECT session_id, event_id, t_ms FROM (SELECT *, row_number() OVER (PARTITION BY session_id, t_ms ORDER BY event_id) AS rn FROM m) WHERE rn = 1),
kept AS (SELECT session_id, arg_min(event_id, t_ms) AS event_id, min(t_ms) AS t_ms FROM one GROUP BY session_id
  UNION ALL SELECT k.session_id, arg_min(o.event_id, o.t_ms), min(o.t_ms) FROM kept k JOIN one o ON o.session_id = k.session_id AND o.t_ms >= k.t_ms + 100 GROUP BY k.session_id)""",
    ),
    "q_drop_repeats": _with("ms", f"SELECT session_id, event_id FROM (SELECT *, coalesce(lag(x) {_W} = x AND lag(y) {_W} = y, false) AS same FROM ms) WHERE NOT same"),
    "q_kinematics": _with("k", f"""SELECT session_id, event_id, t_ms - lag(t_ms) {_W} AS dt_ms, round(sqrt((pow(x - lag(x) {_W}, 2) + pow(y - lag(y) {_W}, 2))), 6) AS dist,
  round(sqrt((pow(x - lag(x) {_W}, 2) + pow(y - lag(y) {_W}, 2))) * 1000 / nullif(t_ms - lag(t_ms) {_W}, 0), 6) AS speed, lead(t_ms) {_W} - t_ms AS dwell_ms FROM k"""),
    "q_dwell": _with("m", f"SELECT session_id, true_spot, sum(d)::BIGINT AS dwell_ms, count(*) AS looks FROM (SELECT *, lead(t_ms) {_W} - t_ms AS d FROM m) GROUP BY ALL"),
    "q_seg_fixed": _with("seg", "SELECT session_id, seg, min(t_ms) AS t_start, max(t_ms) AS t_end, count(*) AS n FROM seg GROUP BY ALL"),
    "q_seg_fixed_length": _with("k", "SELECT session_id, seg, min(t_ms) AS t_start, max(t_ms) AS t_end, count(*) AS n FROM (SELECT *, dense_rank() OVER (PARTITION BY session_id ORDER BY t_ms // 7000)::INT AS seg FROM k) GROUP BY ALL"),
    "q_seg_closed_only": _with("seg", "SELECT session_id, seg, min(t_ms) AS t_start, max(t_ms) AS t_end, count(*) AS n FROM (SELECT *, max(seg) OVER (PARTITION BY session_id) AS top FROM seg) WHERE seg < top GROUP BY session_id, seg"),
    "q_seg_idle_gap": _summary("k", _GAP, "k"),
    "q_seg_idle_still": _summary(_STINT.format("ks"), _STILL, "ks"),
    "q_seg_idle_either": _summary(_STINT.format("k"), f"{_GAP} OR {_STILL}", "k"),
    "q_seg_drift_tiered": _DRIFT,
    "q_density_surface": _with("k", "SELECT session_id, floor(x / 50)::BIGINT AS gx, floor(y / 50)::BIGINT AS gy, count(*) AS n FROM k GROUP BY ALL"),
    "q_dbscan_roles": _with("clus", "SELECT session_id, seg, count(*) FILTER (role = 'core') AS cores, count(*) FILTER (role = 'border') AS borders, count(*) FILTER (role = 'noise') AS noise, count(DISTINCT cluster_id) AS clusters FROM clus GROUP BY ALL"),
    "q_dbscan_clusters": _with("clus", "SELECT session_id, seg, event_id, cluster_id, role FROM clus"),
    "q_dbscan_distributed": _with("clus", "SELECT session_id, seg, event_id, cluster_id, role FROM clus"),
    "q_dbscan_temporal": _with("clus", "SELECT session_id, seg, event_id, cluster_id, role FROM clus").replace("< 900)", "< 900 AND abs(a.t_ms - b.t_ms) <= 2000)"),
    "q_hull_angular": _with("hullm", """SELECT session_id, cluster_id, round(area::DOUBLE, 6) AS area FROM hullm
  UNION ALL SELECT session_id, cluster_id, 0.0::DOUBLE FROM px GROUP BY session_id, seg, cluster_id HAVING count(*) = 1"""),
    "q_hull_prune": _with("clus", """SELECT session_id, seg, cluster_id, count(*) AS "left" FROM clus JOIN far USING (session_id, seg, cluster_id) WHERE NOT (
    (wx, wy) <> (ex, ey) AND (side(wx, wy, sx, sy, x, y) OR (wx, wy) = (sx, sy)) AND (side(sx, sy, ex, ey, x, y) OR (sx, sy) = (ex, ey)) AND (side(ex, ey, nx, ny, x, y) OR (ex, ey) = (nx, ny)) AND (side(nx, ny, wx, wy, x, y) OR (nx, ny) = (wx, wy)))
  GROUP BY ALL""", """far AS MATERIALIZED (SELECT session_id, seg, cluster_id, min(x) AS wx, arg_min(y, x * 100000 - y) AS wy, arg_min(x, y * 100000 + x) AS sx, min(y) AS sy,
  max(x) AS ex, arg_min(y, y - x * 100000) AS ey, arg_min(x, -x - y * 100000) AS nx, max(y) AS ny FROM clus WHERE cluster_id IS NOT NULL GROUP BY ALL)"""),
    "q_roi_area": _with("region", "SELECT session_id, roi_id, round(area, 4) AS area FROM region"),
    "q_roi_printed_stretch": _with("region", "SELECT session_id, roi_id, round(area, 4) AS area FROM region"),
    "q_representativeness": _with("region", "SELECT a.session_id, round(coalesce(sum(sqrt(pow(a.cx - b.cx, 2) + pow(a.cy - b.cy, 2))), 0), 4) AS representativeness FROM region a LEFT JOIN region b ON a.session_id = b.session_id AND a.roi_id < b.roi_id GROUP BY ALL"),
    "q_nearest_k": _with("region match poi", """SELECT session_id, roi_id, rank, poi_id FROM (SELECT m.*, row_number() OVER (PARTITION BY m.session_id, m.roi_id ORDER BY round(sqrt(pow(mx - cx, 2) + pow(my - cy, 2)), 6), m.poi_id) AS rank
  FROM match m JOIN region USING (session_id, roi_id) JOIN poi p ON p.poi_id = m.poi_id) WHERE rank <= 5"""),
    "q_replace_poi": _with("poi", """SELECT noun, old_id, new_id FROM (SELECT o.noun, o.poi_id AS old_id, r.poi_id AS new_id, row_number() OVER (PARTITION BY o.poi_id ORDER BY (o.brand = r.brand)::INT + (o.type = r.type)::INT + (o.size_decade = r.size_decade)::INT + (o.colour = r.colour)::INT DESC, r.poi_id) AS n
  FROM plan o JOIN there r ON r.noun = o.noun WHERE r.poi_id NOT IN (SELECT poi_id FROM plan)) WHERE n = 1""", """there AS MATERIALIZED (SELECT poi.*, p_retailprice AS price FROM poi JOIN part ON p_partkey = poi_id WHERE mx BETWEEN -320 AND -180 AND my BETWEEN 80 AND 220),
plan AS MATERIALIZED (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY noun ORDER BY price, poi_id) AS n FROM there) WHERE n = 1)"""),
    "q_known_facet": _with("poi", """SELECT kind AS roi_kind, round(printed, 6) AS printed, round(1 - printed, 6) AS intent FROM (SELECT exp(10) AS e, count(DISTINCT size_decade) - 1 AS others, sqrt(e * e + others) AS norm FROM poi),
  LATERAL (VALUES ('known', e / norm), ('mixed', (e + others) / (norm * sqrt(others + 1)))) v(kind, printed)"""),
    "q_reachable": _with("near", "SELECT session_id, seg, a, b FROM near WHERE a < b"),
    "q_hull_vertices": _with("edge", """SELECT session_id, seg, cluster_id, ax::DOUBLE AS x, ay::DOUBLE AS y FROM edge
  UNION ALL SELECT session_id, seg, cluster_id, any_value(x)::DOUBLE, any_value(y)::DOUBLE FROM px GROUP BY session_id, seg, cluster_id HAVING count(*) = 1"""),
    "q_hull_area": _with("hullm", """SELECT session_id, cluster_id, round(area::DOUBLE, 6) AS area, round(perimeter, 6) AS perimeter FROM hullm
  UNION ALL SELECT session_id, cluster_id, 0.0::DOUBLE, 0.0::DOUBLE FROM px GROUP BY session_id, seg, cluster_id HAVING count(*) = 1"""),
    "q_confidence": "SELECT nnz, t, round(CASE WHEN nnz = 0 THEN 0 WHEN t = 0 THEN 1 ELSE least(1, nnz / (7.0::DOUBLE * t)) END, 6) AS confidence FROM (SELECT DISTINCT (SELECT count(DISTINCT o_orderstatus) + count(DISTINCT o_orderpriority) FROM orders WHERE o_custkey = c_custkey) AS nnz FROM customer), (VALUES (0), (1), (2), (5), (10), (20)) v(t)",
    "q_stretch_area_printed": _stretched("1 + (session_id % 5) / 4.0"),
    "q_stretch_area_intent": _stretched("2 - (session_id % 5) / 4.0"),
    "q_roi_pairs": _with("roi", "SELECT session_id, roi_id, src_a, src_b FROM roi"),
    "q_roi_cross_segment": _with("roi", "SELECT session_id, src_a, src_b FROM roi WHERE seg_a <> seg_b"),
    "q_mine_report": _with("clus", "SELECT session_id, count(*) AS segments, sum(c)::BIGINT AS clusters, round(sum(z) / sum(n), 6) AS noise_share FROM (SELECT session_id, seg, count(DISTINCT cluster_id) AS c, count(*) AS n, count(*) FILTER (cluster_id IS NULL) AS z FROM clus GROUP BY ALL) GROUP BY session_id"),
    "q_quadtree_leaves": _with("poi", "SELECT * FROM leaf", _LEAVES),
    "q_match": _with("match", "SELECT * FROM match"),
    "q_match_scan": _with("match", "SELECT * FROM match"),
    "q_out_of_sight": _with("match k", "SELECT m.* FROM match m JOIN poi p USING (poi_id) WHERE NOT EXISTS (SELECT 1 FROM k WHERE k.session_id = m.session_id AND (mx - x) * (mx - x) + (my - y) * (my - y) <= 400)"),
    "q_roi_vector": _with("vec", "SELECT * FROM vec"),
    "q_feedback_batch": _with("fb", "SELECT session_id, attr, val, round(raw, 6) AS raw FROM fb"),
    "q_feedback_per_value": _with("vec", "SELECT session_id, attr, val, round(count(*) * 0.05::DOUBLE, 6) AS raw FROM vec GROUP BY ALL"),
    "q_feedback_sequential": _with("inc", """SELECT s.session_id, s.roi_id, i.attr, i.val, round(sum(i.inc), 6) AS raw FROM (SELECT DISTINCT session_id, roi_id FROM match) s JOIN inc i ON i.session_id = s.session_id AND i.roi_id <= s.roi_id GROUP BY ALL"""),
    "q_softmax": _with("norm", "SELECT w.session_id, attr, val, round(weight, 6) AS weight, round(w.w0, 6) AS w0, round(norm, 6) AS norm FROM w JOIN norm USING (session_id)"),
    "q_feedback_explain": _with("fb", "SELECT session_id, rank, attr, val, value FROM (SELECT session_id, attr, val, round(raw, 6) AS value, row_number() OVER (PARTITION BY session_id ORDER BY round(raw, 6) DESC, attr, val) AS rank FROM fb) WHERE rank <= 5"),
    "q_feedback_clicks": _with("fb clk facet", """SELECT session_id, attr, val, round(sum(raw), 6) AS raw FROM (SELECT * FROM fb UNION ALL
  SELECT c.session_id, f.attr, f.val, count(*) * 0.1::DOUBLE FROM clk c JOIN facet f USING (poi_id) WHERE c.session_id IN (SELECT session_id FROM fb) GROUP BY ALL) GROUP BY ALL"""),
    "q_feedback_decay": _with("inc", "SELECT session_id, attr, val, round(sum(inc * exp(-0.1::DOUBLE * (30 - roi_id))), 6) AS raw FROM inc GROUP BY ALL"),
    "q_relevance": _with("rel", "SELECT session_id, roi_id, poi_id, round(relevance, 6) AS relevance FROM rel"),
    "q_peculiarity_printed": _with("pec", "SELECT session_id, roi_id, round(printed, 6) AS printed FROM pec"),
    "q_peculiarity_intent": _with("pec", "SELECT session_id, roi_id, round(1 - printed, 6) AS intent FROM pec"),
    "q_roi_alignment": _with("pec", "SELECT session_id, roi_id, round(printed, 6) AS alignment FROM pec"),
    "q_kprime": _with("pec", "SELECT session_id, roi_id, floor(5 * printed + 1e-9)::INT AS k_prime FROM pec"),
    "q_greedy_seed": _with("rel pec", """SELECT r.session_id, r.roi_id, rank, poi_id FROM (SELECT *, row_number() OVER (PARTITION BY session_id, roi_id ORDER BY round(relevance, 9) DESC, poi_id) AS rank FROM rel) r
  JOIN pec p ON p.session_id = r.session_id AND p.roi_id = r.roi_id WHERE rank <= floor(5 * printed + 1e-9)"""),
    "q_random_k": _with("rnd", "SELECT session_id, roi_id, rank, poi_id FROM rnd"),
    "q_diversity": _with("rnd facet", """SELECT s.session_id, s.roi_id, round(coalesce(d.diversity, 0), 6) AS diversity FROM (SELECT DISTINCT session_id, roi_id FROM rnd) s LEFT JOIN (
  SELECT a.session_id, a.roi_id, avg(1 - ((p.brand = q.brand)::INT + (p.type = q.type)::INT + (p.size_decade = q.size_decade)::INT + (p.colour = q.colour)::INT + (p.noun = q.noun)::INT) / 5.0::DOUBLE) AS diversity
  FROM rnd a JOIN rnd b ON a.session_id = b.session_id AND a.roi_id = b.roi_id AND a.poi_id < b.poi_id JOIN poi p ON p.poi_id = a.poi_id JOIN poi q ON q.poi_id = b.poi_id GROUP BY ALL) d USING (session_id, roi_id)"""),
    "q_precision": _with("rnd clk", "SELECT r.session_id, round(avg(CASE WHEN c.poi_id IS NULL THEN 0.0 ELSE 1.0 END::DOUBLE), 6) AS precision FROM rnd r LEFT JOIN (SELECT DISTINCT * FROM clk) c ON c.session_id = r.session_id AND c.poi_id = r.poi_id GROUP BY ALL"),
    "q_accumulated": _with("rnd clk", """SELECT session_id, round, round(p, 6) AS precision, round(avg(p) OVER v, 6) AS running_mean, round(sum(p) OVER v, 6) AS running_sum FROM (
  SELECT r.session_id, r.roi_id AS round, avg(CASE WHEN c.poi_id IS NULL THEN 0.0 ELSE 1.0 END::DOUBLE) AS p FROM rnd r LEFT JOIN (SELECT DISTINCT * FROM clk) c ON c.session_id = r.session_id AND c.poi_id = r.poi_id GROUP BY ALL)
  WINDOW v AS (PARTITION BY session_id ORDER BY round ROWS UNBOUNDED PRECEDING)"""),
    "q_hit_ratio": _with("rnd clk", "SELECT round(avg(h::DOUBLE), 6) AS hit_ratio FROM (SELECT r.session_id, max(CASE WHEN c.poi_id IS NULL THEN 0 ELSE 1 END) AS h FROM rnd r LEFT JOIN (SELECT DISTINCT * FROM clk) c ON c.session_id = r.session_id AND c.poi_id = r.poi_id GROUP BY ALL)"),
    "q_coverage": _with("rnd roi", "SELECT r.session_id, round(avg((h.roi_id IS NOT NULL)::INT::DOUBLE), 6) AS coverage FROM roi r LEFT JOIN (SELECT DISTINCT session_id, roi_id FROM rnd) h USING (session_id, roi_id) GROUP BY ALL"),
    "q_cohesiveness": _with("match facet", """SELECT session_id, roi_id, round(avg(((p.brand = q.brand)::INT + (p.type = q.type)::INT + (p.size_decade = q.size_decade)::INT + (p.colour = q.colour)::INT + (p.noun = q.noun)::INT) / 5.0::DOUBLE), 6) AS cohesiveness
  FROM match a JOIN match b USING (session_id, roi_id) JOIN poi p ON p.poi_id = a.poi_id JOIN poi q ON q.poi_id = b.poi_id GROUP BY ALL"""),
    "q_thinning_ratio": _with("m k", "SELECT a.session_id, a.raw, b.kept, round(b.kept / a.raw, 6) AS ratio FROM (SELECT session_id, count(*) AS raw FROM m GROUP BY 1) a JOIN (SELECT session_id, count(*) AS kept FROM k GROUP BY 1) b USING (session_id)"),
    "q_click_only": _with("clk facet cells", """SELECT session_id, rank, poi_id, round(relevance, 6) AS relevance FROM (SELECT *, row_number() OVER (PARTITION BY session_id ORDER BY round(relevance, 9) DESC, poi_id) AS rank FROM scored) WHERE rank <= 5""",
        """cf AS MATERIALIZED (SELECT c.session_id, f.attr, f.val, count(*) * 0.05::DOUBLE AS raw FROM clk c JOIN facet f USING (poi_id) GROUP BY ALL),
cz AS MATERIALIZED (SELECT session_id, sum(exp(raw)) + any_value(f) - count(*) AS z, any_value(f) - count(*) AS rest FROM cf, cells GROUP BY session_id),
cn AS MATERIALIZED (SELECT session_id, sqrt(sum(pow(exp(raw) / z, 2)) + any_value(rest) / pow(any_value(z), 2)) AS norm FROM cf JOIN cz USING (session_id) GROUP BY session_id),
scored AS (SELECT z.session_id, f.poi_id, sum(exp(coalesce(c.raw, 0)) / z.z) / (any_value(n.norm) * sqrt(5)) AS relevance FROM cz z JOIN cn n USING (session_id) CROSS JOIN facet f
  LEFT JOIN cf c ON c.session_id = z.session_id AND c.attr = f.attr AND c.val = f.val GROUP BY z.session_id, f.poi_id)"""),
    "q_popular_k": _with("clk", "SELECT row_number() OVER (ORDER BY n DESC, poi_id) AS rank, poi_id, n FROM (SELECT poi_id, count(*) AS n FROM clk GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 5)"),
    "q_worked_regions": """WITH h(s, c, x0, x1, y0, y1) AS (VALUES (0, 1, 0, 10, 0, 10), (0, 2, 40, 50, 0, 10), (1, 3, 5, 15, -5, 5), (1, 4, 45, 55, 5, 15), (2, 5, 12, 22, -10, 0), (2, 6, 52, 60, 12, 20))
SELECT a.c::BIGINT AS src_a, b.c::BIGINT AS src_b, ((least(a.x1, b.x1) - greatest(a.x0, b.x0)) * (least(a.y1, b.y1) - greatest(a.y0, b.y0)))::DOUBLE AS area FROM h a JOIN h b ON a.c < b.c
WHERE least(a.x1, b.x1) > greatest(a.x0, b.x0) AND least(a.y1, b.y1) > greatest(a.y0, b.y0)""",
    "q_cohort_compare": """SELECT c_mktsegment AS segment, round(count(*) FILTER (c_nationkey = 7) / sum(count(*) FILTER (c_nationkey = 7)) OVER (), 6) AS share_region, round(count(*) / sum(count(*)) OVER (), 6) AS share_all,
  round(avg(c_acctbal) FILTER (c_nationkey = 7), 4) AS balance_region, round(avg(c_acctbal), 4) AS balance_all FROM customer GROUP BY 1""",
    "q_layer_corr": "SELECT round(corr(a, b), 6) AS corr FROM (SELECT c_nationkey AS k, avg(c_acctbal) AS a FROM customer GROUP BY 1) JOIN (SELECT s_nationkey AS k, avg(s_acctbal) AS b FROM supplier GROUP BY 1) USING (k)",
    "q_track_summary": _with("track", """SELECT track_id, arg_min(event_id, t_ms * 100000000 + event_id) AS first_id, arg_max(event_id, t_ms * 100000000 + event_id) AS last_id, count(*) AS points, round(coalesce(sum(d), 0), 4) AS length
  FROM (SELECT *, sqrt(pow(x - lag(x) OVER v, 2) + pow(y - lag(y) OVER v, 2)) AS d FROM track WINDOW v AS (PARTITION BY track_id ORDER BY t_ms, event_id)) GROUP BY track_id"""),
    "q_track_focus": _with("track", "SELECT event_id, t_ms, x, y, row_number() OVER (ORDER BY t_ms, event_id) AS step FROM track WHERE track_id = 3"),
    "q_brush": _with("track", "SELECT track_id, count(*) AS n FROM track WHERE t_ms BETWEEN 5000 AND 20000 AND x BETWEEN -300 AND 300 AND y BETWEEN -200 AND 200 GROUP BY 1"),
    "q_band_dwell": _with("track", "SELECT floor(alt / 50)::BIGINT AS band, sum(d)::BIGINT AS dwell_ms, count(*) AS looks FROM (SELECT *, lead(t_ms) OVER (PARTITION BY track_id ORDER BY t_ms, event_id) - t_ms AS d FROM track) GROUP BY 1"),
    "q_day_plan": _with("poi", "SELECT noun, arg_min(poi_id, p_retailprice * 1000000 + poi_id) AS poi_id FROM poi JOIN part ON p_partkey = poi_id WHERE mx BETWEEN -320 AND -180 AND my BETWEEN 80 AND 220 GROUP BY noun"),
}


def oracle_sql() -> dict[str, str]:
    from .oracles_highlights import HIGHLIGHTS  # it builds on the tables of this module

    return HIGHLIGHTS | {name: _sides(sql) for name, sql in ORACLES.items()} | OPS_SQL
