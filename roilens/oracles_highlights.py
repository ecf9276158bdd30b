"""DuckDB SQL of the greedy highlights and of what is derived from them.

Relevance and peculiarity come from sums of exponentials, as the softmax's denominator cancels; the swap
scan is a recursion over ranks whose state is the list of chosen points.
"""

from __future__ import annotations

from .eval.workloads import SWEEPS
from .oracles import _LEAVES, _PLACE, TABLES, _kept, _moves, _with

_SQL = dict(TABLES)
PART = ("brand", "type", "size_decade", "colour", "noun")
_FOUND = "SELECT session_id, roi_id, rank, poi_id, round(relevance, 6) AS relevance FROM found"
_SPLIT = "least(2, t_ms * 3 // 30000)"
_HULLS = """roi AS MATERIALIZED (SELECT session_id, (row_number() OVER (PARTITION BY session_id ORDER BY cluster_id))::INT AS roi_id, cluster_id AS src_a, cluster_id AS src_b, seg AS seg_a, seg AS seg_b FROM hullm WHERE area > 0)"""


def _like(a: str, b: str, n: int) -> str:
    """Number of attributes that two lists of values share."""
    return "(" + " + ".join(f"coalesce({a}[{i}] = {b}[{i}], false)::INT" for i in range(1, n + 1)) + ")"


def _carrier(of: str, key: str, attrs: dict[str, str]) -> tuple[tuple[str, str], ...]:
    """Edits that put another table in the place of the POIs."""
    poi = f"poi AS MATERIALIZED (SELECT key AS poi_id, {_PLACE}, {', '.join(f'({e})::VARCHAR AS {a}' for a, e in attrs.items())} FROM (SELECT *, {key} AS key FROM {of}))"
    rows = " UNION ALL ".join(f"SELECT poi_id, '{a}' AS attr, {a} AS val FROM poi WHERE {a} IS NOT NULL" for a in attrs)
    return (_SQL["poi"], poi), (_SQL["facet"], f"facet AS MATERIALIZED ({rows})")


def _greedy(
    select: str = _FOUND, k: int = 5, guard: str = "intent", threshold: float = 0.3, swap: str = "first", scan: bool = True, batch: bool = False,
    plain: bool = False, attrs: tuple[str, ...] = PART, needs: str = "", more: str = "", edits: tuple[tuple[str, str], ...] = (),
) -> str:
    """A query over ``found``, the highlights; ``edits`` change the text of common tables."""
    n = len(attrs)
    like = _like("i.a", "b.a", n)
    goes_on = f"{like} / {n}.0::DOUBLE >= {threshold} - 1e-12" if guard == "intent" else f"{like} / {n}.0::DOUBLE <= {threshold} + 1e-12"
    each = f"CASE WHEN p = q THEN 0 ELSE {_like('s.ch[q].a', 's.ch[p].a', n)} - {_like('s.ch[q].a', 'i.a', n)} END"
    gains = f"list_transform(range(1, len(s.ch) + 1), lambda p: list_sum(list_transform(range(1, len(s.ch) + 1), lambda q: {each})))"
    hit = "list_position(list_transform(gains, lambda g: g > 0), true)" if swap == "first" else "CASE WHEN list_max(gains) > 0 THEN list_position(gains, list_max(gains)) END"
    cum = "SELECT r.session_id, r.roi_id, b.attr, b.val, b.raw FROM asked r JOIN fb b USING (session_id)" if batch else (
        "SELECT r.session_id, r.roi_id, i.attr, i.val, sum(i.inc) AS raw FROM asked r JOIN inc i ON i.session_id = r.session_id AND i.roi_id <= r.roi_id GROUP BY ALL"
    )
    tables = f"""asked AS MATERIALIZED (SELECT DISTINCT session_id, roi_id FROM match),
cum AS MATERIALIZED ({cum}),
len2 AS MATERIALIZED (SELECT session_id, roi_id, sqrt(sum(exp(2 * raw)) + any_value(f) - count(*)) AS norm FROM cum, cells GROUP BY ALL),
scored AS MATERIALIZED (SELECT m.session_id, m.roi_id, m.poi_id, sum(exp(c.raw)) / (any_value(l.norm) * sqrt({n})) AS relevance FROM match m JOIN facet f ON f.poi_id = m.poi_id
  JOIN cum c ON c.session_id = m.session_id AND c.roi_id = m.roi_id AND c.attr = f.attr AND c.val = f.val JOIN len2 l ON l.session_id = m.session_id AND l.roi_id = m.roi_id GROUP BY ALL),
grants AS MATERIALIZED (SELECT v.session_id, v.roi_id, sum(exp(c.raw)) / (any_value(l.norm) * sqrt(count(*))) AS peculiarity, {k if plain else f"floor({k} * peculiarity + 1e-9)"}::INT AS kp FROM vec v
  JOIN cum c ON c.session_id = v.session_id AND c.roi_id = v.roi_id AND c.attr = v.attr AND c.val = v.val JOIN len2 l ON l.session_id = v.session_id AND l.roi_id = v.roi_id GROUP BY v.session_id, v.roi_id),
item AS MATERIALIZED (SELECT s.session_id, s.roi_id, s.poi_id, s.relevance, g.kp, [{', '.join(f'p.{a}' for a in attrs)}] AS a, count(*) OVER (PARTITION BY s.session_id, s.roi_id) AS n,
  row_number() OVER (PARTITION BY s.session_id, s.roi_id ORDER BY round(s.relevance, 9) DESC, s.poi_id) AS pos FROM scored s JOIN grants g ON g.session_id = s.session_id AND g.roi_id = s.roi_id JOIN poi p ON p.poi_id = s.poi_id),
scan AS (SELECT session_id, roi_id, max(pos) AS upto, list({{'pos': pos, 'a': a}} ORDER BY pos) AS ch FROM item WHERE pos <= kp GROUP BY ALL
  UNION ALL SELECT session_id, roi_id, pos, CASE WHEN coalesce(hit, 0) = 0 THEN ch ELSE list_transform(range(1, len(ch) + 1), lambda p: CASE WHEN p = hit THEN {{'pos': pos, 'a': a}} ELSE ch[p] END) END FROM (
    SELECT *, {hit} AS hit FROM (SELECT s.session_id, s.roi_id, s.ch, i.pos, i.a, {gains} AS gains FROM scan s JOIN item i ON i.session_id = s.session_id AND i.roi_id = s.roi_id AND i.pos = s.upto + 1
      JOIN item b ON b.session_id = s.session_id AND b.roi_id = s.roi_id AND b.pos = 1 WHERE {goes_on if scan else 'false'}))),
done AS (SELECT session_id, roi_id, max(upto) AS upto, arg_max(ch, upto) AS ch FROM scan GROUP BY ALL),
chosen AS (SELECT session_id, roi_id, upto, unnest(ch).pos AS pos FROM done),
found AS MATERIALIZED (SELECT c.session_id, c.roi_id, (row_number() OVER (PARTITION BY c.session_id, c.roi_id ORDER BY c.pos))::INT AS rank, i.poi_id, i.relevance, i.kp AS k_prime, i.a,
  (c.upto - least(i.kp, i.n))::INT AS scanned, CASE WHEN c.upto = i.n THEN 'end' ELSE 'guard' END AS stop_reason FROM chosen c JOIN item i ON i.session_id = c.session_id AND i.roi_id = c.roi_id AND i.pos = c.pos)"""
    sql = _with(f"match facet cells vec inc fb poi roi {needs}", select, tables + (", " + more if more else ""))
    for old, new in edits:
        if old not in sql:
            raise ValueError(f"no such text: {old}")
        sql = sql.replace(old, new)
    return sql


def _row(parameter: str, value: str, **how) -> str:
    """One row of a sweep."""
    pairs = f"avg(CASE WHEN x.poi_id < y.poi_id THEN 1 - {_like('x.a', 'y.a', len(PART))} / {len(PART)}.0::DOUBLE END)"
    return _greedy(
        f"""SELECT '{parameter}' AS parameter, '{value}' AS value, (SELECT count(*) FROM roi) AS rois, (SELECT count(*) FROM found) AS highlights, (SELECT round(avg(relevance), 6) FROM found) AS relevance,
  (SELECT round(avg(d), 6) FROM (SELECT x.session_id, x.roi_id, coalesce({pairs}, 0) AS d FROM found x JOIN found y ON y.session_id = x.session_id AND y.roi_id = x.roi_id GROUP BY ALL)) AS diversity""",
        **how,
    )


def _sweep(name: str) -> str:
    how = {
        "k": lambda v: {"k": v},
        "threshold": lambda v: {"threshold": v},
        "delta": lambda v: {"edits": (("count(*) * 0.05::DOUBLE AS inc", f"count(*) * {v}::DOUBLE AS inc"),)},
        "eps_ms": lambda v: {"edits": ((_kept("k", "m"), _kept("k", "m", v)),)},
        "g": lambda v: {"edits": ((_SPLIT, f"least({v - 1}, t_ms * {v} // 30000)"),)},
        "radius": lambda v: {"edits": (("< 900)", f"< {int(v * v)})"),)},
        "min_pts": lambda v: {"edits": (("HAVING count(*) >= 5)", f"HAVING count(*) >= {v})"),)},
    }
    if name not in how:  # the index and, without earlier feedback, the confidence change nothing
        first = _row(name, "?")
        return f"SELECT r.parameter, v.value, r.rois, r.highlights, r.relevance, r.diversity FROM ({first}) r, (VALUES {', '.join(f"('{v}')" for v in SWEEPS[name])}) v(value)"
    return " UNION ALL ".join(f"SELECT * FROM ({_row(name, str(v), **how[name](v))})" for v in SWEEPS[name])


def _eps_row(eps: int) -> str:
    sql = _with("region m k", f"SELECT {eps} AS eps_ms, (SELECT count(*) FROM k) AS kept, (SELECT round(a.n / b.n, 6) FROM (SELECT count(*) AS n FROM k) a, (SELECT count(*) AS n FROM m) b) AS ratio, (SELECT count(*) FROM region) AS rois, (SELECT round(sum(area), 3) FROM region) AS roi_area")
    return "SELECT * FROM (" + sql.replace(_SQL["m"], _moves("m", "hover", 128)).replace(_SQL["k"], _kept("k", "m", eps)) + ")"


_SPREAD = "coalesce(avg(sqrt(pow(a.cx - b.cx, 2) + pow(a.cy - b.cy, 2))) / sqrt(3370000), 0)"
_ALL_MOVES = ((_kept("k", "m"), _kept("k", "m", 1)),)
_CUSTOMER = {"segment": "c_mktsegment", "nation": "c_nationkey", "c_acctbal_bin": "least(greatest(floor((c_acctbal::DOUBLE + 1000) / 1100), 0), 9)::BIGINT"}
_PLACED = {
    "supplier": ("supplier", "s_suppkey", {"nation": "s_nationkey", "s_acctbal_bin": "least(greatest(floor((s_acctbal::DOUBLE + 1000) / 1100), 0), 9)::BIGINT"}),
    "orders": ("orders", "o_orderkey", {"status": "o_orderstatus", "priority": "o_orderpriority"}),
    "pages": ("pages", "page_id", {"host": "split_part(split_part(url, '//', 2), '/', 1)"}),
    "benchmark": ("benchmark", "item_id", {"length": "length(text) // 50"}),
}
_DOCUMENTS = {"lang": "lang", "source": "source", "length": "least(9, n_chars // 1000)"}

HIGHLIGHTS: dict[str, str] = {
    "single_shot": _greedy("SELECT session_id, roi_id, rank, poi_id, round(relevance, 6) AS relevance, k_prime, scanned, stop_reason FROM found"),
    "q_greedy_intent": _greedy(),
    "q_greedy_printed": _greedy(guard="printed"),
    "q_greedy_best": _greedy(swap="best"),
    "q_base_all_moves": _greedy(edits=_ALL_MOVES),
    "q_base_no_segmentation": _greedy(edits=((_SPLIT, "0"), (_SQL["roi"], _HULLS))),
    "q_base_hulls_as_rois": _greedy(edits=((_SQL["roi"], _HULLS),)),
    "q_base_tight_rois": _greedy(),
    "q_base_textbook_hull": _greedy(),
    "q_base_scan": _greedy(),
    "q_base_plain_k": _greedy(plain=True),
    "q_base_relevance_only": _greedy(scan=False),
    "q_base_diversity_only": _greedy(threshold=0.0),
    "q_base_per_value": _greedy(edits=(("count(*) * 0.05::DOUBLE AS inc", "0.05::DOUBLE AS inc"),)),
    "q_base_batch_update": _greedy(batch=True),
    "q_preliminary_query": _greedy(edits=(("p_partkey AS key FROM part", "p_partkey AS key FROM part WHERE p_size <= 30 AND p_retailprice < 1500"),)),
    "q_scenario": _greedy(
        "SELECT f.session_id, count(*) AS n, round(avg((sqrt(pow(p.mx + 500, 2) + pow(p.my + 200, 2)) <= 200)::INT::DOUBLE), 6) AS near_share FROM found f JOIN poi p ON p.poi_id = f.poi_id GROUP BY f.session_id",
        edits=(("p_partkey AS key FROM part", "p_partkey AS key FROM part WHERE p_partkey < 1500"), ("AS rn FROM m)", "AS rn FROM m WHERE true_spot = 0 AND NOT true_noise)")),
    ),
    "q_generic_customer": _greedy(attrs=tuple(_CUSTOMER), edits=_carrier("customer", "c_custkey", _CUSTOMER)),
    "q_greedy_stops": _greedy("SELECT DISTINCT session_id, roi_id, k_prime, scanned, stop_reason FROM found"),
    "q_perception": _greedy(
        "SELECT f.session_id, round(avg(l.quality), 6) AS perception FROM found f JOIN labels l ON l.doc_id = f.poi_id GROUP BY f.session_id",
        attrs=tuple(_DOCUMENTS), edits=_carrier("documents", "doc_id", _DOCUMENTS),
    ),
    "q_peculiarity_report": _greedy("""SELECT count(*) AS rois, round(quantile_cont(peculiarity, 0.1), 6) AS p10, round(quantile_cont(peculiarity, 0.5), 6) AS p50, round(quantile_cont(peculiarity, 0.9), 6) AS p90,
  round(avg(kp), 6) AS mean_k, min(kp) AS min_k, max(kp) AS max_k FROM grants"""),
    "q_sequence": _greedy(
        "SELECT session_id, step, poi_id, round(leg, 6) AS leg FROM tour",
        more="""stop AS MATERIALIZED (SELECT f.session_id, f.poi_id, max(f.relevance) AS relevance, any_value(p.mx)::BIGINT AS mx, any_value(p.my)::BIGINT AS my FROM found f JOIN poi p ON p.poi_id = f.poi_id GROUP BY ALL),
tour AS (SELECT session_id, 1 AS step, poi_id, 0.0::DOUBLE AS leg, mx, my, [poi_id] AS seen FROM (SELECT *, row_number() OVER (PARTITION BY session_id ORDER BY round(relevance, 9) DESC, poi_id) AS o FROM stop) WHERE o = 1
  UNION ALL SELECT session_id, step + 1, best.poi_id, sqrt(best.d2::DOUBLE), best.mx, best.my, list_append(seen, best.poi_id) FROM (
    SELECT t.session_id, t.step, any_value(t.seen) AS seen, min({'d2': (s.mx - t.mx) * (s.mx - t.mx) + (s.my - t.my) * (s.my - t.my), 'poi_id': s.poi_id, 'mx': s.mx, 'my': s.my}) AS best
    FROM tour t JOIN stop s ON s.session_id = t.session_id AND NOT list_contains(t.seen, s.poi_id) GROUP BY t.session_id, t.step))""",
    ),
    "q_choose": _with("region", f"SELECT a.session_id, round({_SPREAD}, 6) AS dispersion, CASE WHEN {_SPREAD} >= 0.25 THEN 'greedy' ELSE 'fuzzy' END AS approach FROM region a LEFT JOIN region b ON a.session_id = b.session_id AND a.roi_id < b.roi_id GROUP BY a.session_id"),
    "q_signal_fusion": "SELECT 'hover' AS signal, count(*) AS n, count(*)::DOUBLE AS weight FROM events GROUP BY 1 UNION ALL SELECT 'voice' AS signal, count(*) AS n, 3 * count(*)::DOUBLE AS weight FROM conversations WHERE role = 'user' GROUP BY 1",
    "q_seg_auto": _with("k poi", "SELECT session_id, seg, min(t_ms) AS t_start, max(t_ms) AS t_end, count(*) AS n FROM split GROUP BY ALL", _LEAVES + """,
auto AS (SELECT least(12, greatest(2, round(sqrt(avg(n)))))::BIGINT AS g FROM leaf),
split AS (SELECT *, dense_rank() OVER (PARTITION BY session_id ORDER BY least(g - 1, t_ms * g // 30000))::INT AS seg FROM k, auto)"""),
    "q_eps_sweep": " UNION ALL ".join(_eps_row(eps) for eps in (1, 10, 50, 100, 250, 1000)),
} | {f"q_sweep{'' if name == 'k' else '_' + name}": _sweep(name) for name in SWEEPS if name != "weights"} | {f"q_generic_{name}": _greedy(attrs=tuple(attrs), edits=_carrier(of, key, attrs)) for name, (of, key, attrs) in _PLACED.items()}
