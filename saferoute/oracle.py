"""DuckDB twins: the same recipes and definitions in SQL, built from parts.

A twin finds optima by a recursion over all labels (query, vertex, minute), without any pruning."""

from __future__ import annotations

GRID = (20, 30, 40, 50, 60, 70, 80, 90)
_SOURCE = {
    "uni": "SELECT c_custkey AS v, CAST(floor((c_acctbal + 1000.0) * 400.0 / 11.0) AS BIGINT) AS x_mm, c_custkey * 247213 % 400000 AS y_mm FROM customer",
    "gau": "SELECT vec_id AS v, CAST(round((CAST(embedding[1] AS DOUBLE) + 1.0) * 200000.0) AS BIGINT) AS x_mm, CAST(round((CAST(embedding[2] AS DOUBLE) + 1.0) * 200000.0) AS BIGINT) AS y_mm FROM embeddings",
    "sparse": "SELECT p_partkey AS v, p_partkey * 247213 % 400000 AS x_mm, (CAST(p_size AS BIGINT) - 1) * 8000 + p_partkey * 7919 % 8000 AS y_mm FROM part",
}
_KEY = {"uni": "c_custkey", "gau": "vec_id", "sparse": "p_partkey"}
_PERIOD = {"uni": 3, "gau": 3, "sparse": 32}


def network(kind: str, quarters: int = 4) -> str:
    """CTEs vtx, edg and arc of one network, of the first quarters of its vertices."""
    source = _SOURCE[kind] + ("" if quarters == 4 else f" WHERE {_KEY[kind]} < (SELECT count(*) FROM {_SOURCE[kind].split()[-1]}) * {quarters} // 4")
    mph = "50" if kind == "sparse" else "(30 + 10 * (eid % 5))"
    return f"""
vp AS MATERIALIZED ({source}),
vy AS (SELECT *, row_number() OVER (ORDER BY y_mm, v) - 1 AS p, count(*) OVER () AS n FROM vp),
vs AS (SELECT v, x_mm, y_mm, p // greatest(2, n // greatest(1, CAST(floor(sqrt(n)) AS BIGINT))) AS strip FROM vy),
vtx AS MATERIALIZED (SELECT v, x_mm, y_mm, CAST(least(4, x_mm // 80000) + 5 * least(4, y_mm // 80000) AS INTEGER) AS cell, strip,
  row_number() OVER (PARTITION BY strip ORDER BY x_mm, v) - 1 AS r FROM vs),
ep AS (SELECT s.v AS v1, t.v AS v2, s.x_mm - t.x_mm AS dx, s.y_mm - t.y_mm AS dy FROM vtx s JOIN vtx t ON s.strip = t.strip AND t.r = s.r + 1
  UNION ALL SELECT s.v, t.v, s.x_mm - t.x_mm, s.y_mm - t.y_mm FROM vtx s JOIN vtx t ON t.strip = s.strip + 1 AND t.r = s.r WHERE s.r % {_PERIOD[kind]} = 0),
e0 AS (SELECT least(v1, v2) AS a, greatest(v1, v2) AS b, CAST(round(sqrt(CAST(dx * dx + dy * dy AS DOUBLE))) AS BIGINT) AS len_mm FROM ep),
e1 AS (SELECT row_number() OVER (ORDER BY a, b) - 1 AS eid, a, b, len_mm FROM e0),
pn AS (SELECT count(*) AS n FROM part),
edg AS MATERIALIZED (SELECT eid, a, b, len_mm, CAST(greatest(1, (len_mm * 60 + 1000 * {mph} - 1) // (1000 * {mph})) AS BIGINT) AS w_min,
  CASE WHEN eid % 6 = 0 THEN list_sort(list_distinct([p1.p_size, p2.p_size])) WHEN eid % 2 = 0 THEN [p1.p_size] ELSE [] END AS kw
  FROM e1, pn JOIN part p1 ON p1.p_partkey = 31 * eid % pn.n JOIN part p2 ON p2.p_partkey = (17 * eid + 7) % pn.n),
arc AS MATERIALIZED (SELECT a AS tail, b AS head, eid, len_mm, w_min, kw FROM edg UNION ALL SELECT b, a, eid, len_mm, w_min, kw FROM edg)"""


RING = """
ev AS (SELECT event_id, CAST(user_id % 25 AS INTEGER) AS cell, event_type AS wtype, CAST(hour(ts) AS INTEGER) AS slot, value,
  CAST(json_extract(props, '$.k') AS INTEGER) + 1 AS conf_pct, ts AS issued FROM events),
ev2 AS (SELECT * FROM ev UNION ALL SELECT event_id, cell, 'ANY', slot, value, conf_pct, issued FROM ev),
ring AS MATERIALIZED (SELECT cell, wtype, slot, value, conf_pct, issued, event_id FROM
  (SELECT *, row_number() OVER (PARTITION BY cell, wtype, slot ORDER BY issued DESC, event_id DESC) AS k FROM ev2) WHERE k = 1),
st AS MATERIALIZED (SELECT c.cell, list(coalesce(value, 0.0) ORDER BY s.slot) AS wv, list(coalesce(conf_pct, 0) ORDER BY s.slot) AS wp
  FROM (SELECT unnest(range(25)) AS cell) c, (SELECT unnest(range(24)) AS slot) s
  LEFT JOIN ring ON ring.cell = c.cell AND ring.slot = s.slot AND ring.wtype = 'ANY' GROUP BY c.cell),
warc AS MATERIALIZED (SELECT arc.*, s1.wv AS tw, s1.wp AS tp, s2.wv AS hw, s2.wp AS hp, x1.cell AS c1, x2.cell AS c2
  FROM arc JOIN vtx x1 ON x1.v = tail JOIN vtx x2 ON x2.v = head JOIN st s1 ON s1.cell = x1.cell JOIN st s2 ON s2.cell = x2.cell)"""


def blocked(t0: str, w: str, eps: str, alpha: str) -> str:
    """Whether the trip meets an obstacle; over columns tw, tp, hw, hp of warc."""
    i = "[CAST(s % 24 AS INTEGER) + 1]"

    def at(t: str) -> str:
        x = f"CASE WHEN ({w} - ({t} - {t0})) * tw{i} + ({t} - {t0}) * hw{i} > {eps} * {w} THEN tp{i} * hp{i} ELSE 0 END"
        y = f"CASE WHEN hw{i} > {eps} THEN (100 - tp{i}) * hp{i} ELSE 0 END + CASE WHEN tw{i} > {eps} THEN tp{i} * (100 - hp{i}) ELSE 0 END"
        return f"({x} + {y} >= 100 * {alpha})"

    first, last = f"greatest({t0}, s * 60)", f"least({t0} + {w}, (s + 1) * 60)"
    return f"len(list_filter(range({t0} // 60, ({t0} + {w}) // 60 + 1), lambda s: {at(first)} OR {at(last)})) > 0"


def query_set(n: int = 20, sigma: int = 10, s_size: int = 5, eps: float = 50.0, alpha: int = 50, name: str = "q", tag: str = "") -> str:
    """CTEs of a query set; ``tag`` keeps the names of several sets apart."""
    s = ", ".join(f"CAST((7 * x.qid + 11 * {j}) % 50 + 1 AS INTEGER)" for j in range(s_size))
    return f"""
src{tag} AS (SELECT i AS qid, i * 7919 % (SELECT count(*) FROM vtx) AS src FROM (SELECT unnest(range({n})) AS i)),
hop{tag}(qid, v, hops) AS (SELECT qid, src, 0 FROM src{tag} UNION SELECT h.qid, arc.head, h.hops + 1 FROM hop{tag} h JOIN arc ON arc.tail = h.v WHERE h.hops < {sigma}),
far{tag} AS (SELECT qid, v FROM hop{tag} GROUP BY qid, v HAVING min(hops) = {sigma}),
{name} AS MATERIALIZED (SELECT CAST(x.qid AS INTEGER) AS qid, src, dst, 480 + 37 * x.qid % 720 AS dep_min, CAST({eps} AS DOUBLE) AS eps, {alpha} AS alpha_pct, [{s}] AS s
  FROM src{tag} x JOIN (SELECT qid, min(v) AS dst FROM far{tag} GROUP BY qid) d ON d.qid = x.qid)"""


def labels(horizon: int = 360, q: str = "q") -> str:
    return f"""
lab(qid, v, arr) AS (SELECT qid, src, dep_min FROM {q} UNION
  SELECT l.qid, a.head, l.arr + a.w_min FROM lab l JOIN {q} q ON q.qid = l.qid JOIN warc a ON a.tail = l.v
  WHERE l.v <> q.dst AND l.arr + a.w_min <= q.dep_min + {horizon} AND NOT list_has_any(a.kw, q.s) AND NOT ({blocked("l.arr", "a.w_min", "q.eps", "q.alpha_pct")})),
opt AS (SELECT q.qid, min(lab.arr) - any_value(q.dep_min) AS total_min FROM {q} q JOIN lab ON lab.qid = q.qid AND lab.v = q.dst GROUP BY q.qid)"""


ANSWERS = "SELECT q.qid, opt.total_min IS NOT NULL AS answered, CAST(opt.total_min AS BIGINT) AS total_min FROM q LEFT JOIN opt ON opt.qid = q.qid"


def routes(kind: str = "uni", horizon: int = 360, quarters: int = 4, **options) -> str:
    return f"WITH RECURSIVE {network(kind, quarters)}, {RING}, {query_set(**options)}, {labels(horizon)} {ANSWERS}"


def sweep(sets: list[tuple], horizon: int = 360, kind: str = "uni") -> str:
    """(param, qid, total_min) over several query sets; each is (param, options)."""
    parts = ", ".join(query_set(**o, name=f"q{i}", tag=str(i)) for i, (_, o) in enumerate(sets))
    union = " UNION ALL ".join(f"SELECT CAST({1000 * i} + qid AS INTEGER) AS qid, src, dst, dep_min, eps, alpha_pct, s FROM q{i}" for i in range(len(sets)))
    param = "CASE q.qid // 1000 " + " ".join(f"WHEN {i} THEN {p}" for i, (p, _) in enumerate(sets)) + " END"
    return f"WITH RECURSIVE {network(kind)}, {RING}, {parts}, q AS MATERIALIZED ({union}), {labels(horizon)} SELECT CAST({param} AS INTEGER) AS param, CAST(q.qid % 1000 AS INTEGER) AS qid, CAST(opt.total_min AS BIGINT) AS total_min FROM q LEFT JOIN opt ON opt.qid = q.qid"


def sssp(pivots_sql: str, weight: str = "len_mm") -> str:
    """CTE sp(src, v, dist), all relaxations kept by key."""
    return f"""
pv AS MATERIALIZED ({pivots_sql}),
sp(src, v, dist) USING KEY (src, v) AS (SELECT src, src, CAST(0 AS BIGINT) FROM pv UNION
  SELECT f.src, arc.head, min(f.dist + arc.{weight}) FROM sp f JOIN arc ON arc.tail = f.v
  LEFT JOIN recurring.sp k ON k.src = f.src AND k.v = arc.head WHERE k.dist IS NULL OR f.dist + arc.{weight} < k.dist GROUP BY f.src, arc.head)"""


def fixed_pivots(d: int = 5) -> str:
    return f"SELECT DISTINCT i * n // {d} AS src, i FROM (SELECT unnest(range({d})) AS i), (SELECT count(*) AS n FROM vtx)"


def slot_bounds() -> str:
    """CTE sb: every edge and slot with the ends' forecasts, oriented a to b."""
    return """
sb AS MATERIALIZED (SELECT eid, CAST(s AS INTEGER) AS slot, tw[s + 1] AS wj, tp[s + 1] AS pj, hw[s + 1] AS wk, hp[s + 1] AS pk
  FROM warc, (SELECT unnest(range(24)) AS s) WHERE tail < head)"""


def ub(eps: str) -> str:
    return f"CASE WHEN wj <= {eps} AND wk <= {eps} THEN 10000 WHEN wj <= {eps} THEN 10000 - pk * (100 - pj) WHEN wk <= {eps} THEN 10000 - pj * (100 - pk) ELSE (100 - pj) * (100 - pk) END"


def case_of(eps: str) -> str:
    return f"CASE WHEN wj <= {eps} AND wk <= {eps} THEN '1' WHEN wj <= {eps} THEN '2.1' WHEN wk <= {eps} THEN '2.2' ELSE '3' END"


def index(fanout: int) -> str:
    """CTEs pos (eid, pos, rectangle, word), lvl (all levels up to the root) and nod: the Z-order packing."""
    z = " | ".join(f"(((mx >> {i}) & 1) << {2 * i}) | (((my >> {i}) & 1) << {2 * i + 1})" for i in range(19))
    return f"""
rect AS (SELECT edg.*, least(p.x_mm, t.x_mm) AS xmin, least(p.y_mm, t.y_mm) AS ymin, greatest(p.x_mm, t.x_mm) AS xmax, greatest(p.y_mm, t.y_mm) AS ymax,
  (p.x_mm + t.x_mm) // 2 AS mx, (p.y_mm + t.y_mm) // 2 AS my FROM edg JOIN vtx p ON p.v = a JOIN vtx t ON t.v = b),
zed AS (SELECT *, {z} AS z FROM rect),
pos AS MATERIALIZED (SELECT *, row_number() OVER (ORDER BY z, eid) - 1 AS pos, coalesce(list_aggregate(list_transform(kw, lambda k: CAST(1 AS BIGINT) << k), 'bit_or'), 0) AS word FROM zed),
lvl AS (SELECT level FROM (SELECT unnest(range(1, 40)) AS level), (SELECT count(*) AS n FROM edg) WHERE level = 1 OR power({fanout}, level - 1) < n),
nod AS MATERIALIZED (SELECT CAST(level AS INTEGER) AS level, pos // CAST({fanout} ** level AS BIGINT) AS node, pos // CAST({fanout} ** (level + 1) AS BIGINT) AS parent,
  min(xmin) AS xmin, min(ymin) AS ymin, max(xmax) AS xmax, max(ymax) AS ymax, min(w_min) AS lb_t, max(w_min) AS ub_t, bit_and(word) AS kw_and, bit_or(word) AS kw_or, count(*) AS n_edges
  FROM pos, lvl GROUP BY ALL)"""
