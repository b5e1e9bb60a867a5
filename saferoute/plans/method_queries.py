"""Registered queries of the methods, baselines, measures and workloads, each with its SQL twin where SQL has one."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import oracle
from ..functions import bounds, keywords, weather
from ..operators import graph, pivots, pruning
from ..operators.storage import hand_back, stored
from ..schema import RouteOptions
from ..sources import forecasts as fc
from ..sources import networks
from . import baselines, router, search
from . import index as ix
from .world import FANOUT, World, together, world

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
S: dict[str, str] = {}
EPS, ALPHA = 50.0, 50


def register(name: str, sql: str | None = None):  # noqa: ANN201
    def keep(f: Callable[[World], DataFrame]) -> Callable[[World], DataFrame]:
        Q[name] = lambda spark, sf_dir: f(world(spark, sf_dir))
        if sql:
            S[name] = sql
        return f

    return keep


def rows(w: World, data: list[tuple], schema: str) -> DataFrame:
    return w.spark.createDataFrame(data, schema)


# --- networks and forecasts -------------------------------------------------------------------------------------


@register("net_uni_vertices", f"WITH {oracle.network('uni')} SELECT v, x_mm, y_mm, cell, strip, r FROM vtx")
def _(w: World) -> DataFrame:
    return w.net().vertices.select("v", "x_mm", "y_mm", "cell", "strip", "r")


for _kind in networks.KINDS:

    @register(f"net_{_kind}_edges", f"WITH {oracle.network(_kind)} SELECT eid, a, b, len_mm, w_min, array_to_string(kw, ',') AS kw FROM edg")
    def _(w: World, kind: str = _kind) -> DataFrame:
        return w.net(kind).edges.select("eid", "a", "b", "len_mm", "w_min", F.array_join("kw", ",").alias("kw"))


@register("edge_speed_stats", f"WITH {oracle.network('uni')} SELECT count(*) AS n, round(min(60.0 * len_mm / w_min), 3) AS least, round(max(60.0 * len_mm / w_min), 3) AS top, sum(len_mm) AS len_mm, CAST(sum(w_min) AS BIGINT) AS w_min FROM edg".replace("sum(len_mm)", "CAST(sum(len_mm) AS BIGINT)"))
def _(w: World) -> DataFrame:
    s = networks.edge_speed(w.net().edges).join(w.net().edges, ["net", "eid"])
    return s.agg(F.count(F.lit(1)).alias("n"), F.round(F.min("mm_per_hour"), 3).alias("least"), F.round(F.max("mm_per_hour"), 3).alias("top"), F.sum("len_mm").alias("len_mm"), F.sum("w_min").alias("w_min"))


@register("vertex_degree_hist", f"WITH {oracle.network('uni')} SELECT degree, count(*) AS n FROM (SELECT count(*) AS degree FROM arc GROUP BY tail) GROUP BY degree")
def _(w: World) -> DataFrame:
    return graph.degrees(w.net().edges).groupBy("degree").agg(F.count(F.lit(1)).alias("n"))


@register("net_components", f"WITH RECURSIVE {oracle.network('gau')}, reach(v) AS (SELECT 0 UNION SELECT head FROM reach JOIN arc ON tail = v) SELECT (SELECT count(*) FROM vtx) AS n_vertices, (SELECT count(*) FROM reach) AS in_first")
def _(w: World) -> DataFrame:
    net = w.net("gau")
    return graph.components(net.vertices, net.edges).agg(F.count(F.lit(1)).alias("n_vertices"), F.sum((F.col("component") == 0).cast("long")).alias("in_first"))


@register("forecast_ring_batch", f"WITH {oracle.network('uni')}, {oracle.RING} SELECT cell, wtype, slot, value, conf_pct, epoch_us(issued) AS issued_us FROM ring")
def _(w: World) -> DataFrame:
    return w.ring.select("cell", "wtype", "slot", "value", "conf_pct", F.unix_micros(F.col("issued").cast("timestamp")).alias("issued_us"))


@register("vertex_forecast", f"WITH {oracle.network('uni')}, {oracle.RING} SELECT v, CAST(s AS INTEGER) AS slot, value, coalesce(conf_pct, 0) AS conf_pct FROM vtx CROSS JOIN (SELECT unnest(range(24)) AS s) LEFT JOIN (SELECT * FROM ring WHERE wtype = 'ANY') x ON x.cell = vtx.cell AND x.slot = s")
def _(w: World) -> DataFrame:
    f = w.ring.where("wtype = 'ANY'").select("cell", "slot", "value", "conf_pct")
    slots = w.spark.range(24).select(F.col("id").cast("int").alias("slot"))
    x = w.net().vertices.select("v", "cell").join(F.broadcast(slots)).join(f, ["cell", "slot"], "left")
    return x.select("v", "slot", "value", F.coalesce("conf_pct", F.lit(0)).alias("conf_pct"))


# --- keywords ---------------------------------------------------------------------------------------------------

_NQ = f"WITH RECURSIVE {oracle.network('uni')}, {oracle.query_set()}"


@register("kw_exact_blocked", f"{_NQ} SELECT qid, eid FROM edg, q WHERE list_has_any(kw, s)")
def _(w: World) -> DataFrame:
    e, q = w.net().edges.select("eid", F.explode("kw").alias("k")), w.queries().select("qid", F.explode("s").alias("k"))
    return e.join(q, "k").select("qid", "eid").distinct()


@register("kw_pruned_edges", f"{_NQ} SELECT qid, count(*) AS left_edges FROM edg, q WHERE NOT list_has_any(kw, s) GROUP BY qid")
def _(w: World) -> DataFrame:
    return pruning.prune_keyword(w.net().edges, w.queries()).groupBy("qid").agg(F.count(F.lit(1)).alias("left_edges"))


@register("kw_bitmap_words", f"WITH {oracle.network('uni')} SELECT eid, coalesce(list_aggregate(list_transform(kw, lambda k: CAST(1 AS BIGINT) << k), 'bit_or'), 0) AS word FROM edg")
def _(w: World) -> DataFrame:
    return w.net().edges.select("eid", F.get(keywords.bitmap(F.col("kw")), F.lit(0)).alias("word"))


def _bits(w: World, mode: str, bits: int = 64) -> DataFrame:
    e = w.net().edges.select("eid", "kw", keywords.bitmap(F.col("kw"), mode=mode, bits=bits).alias("e_bits"))
    q = w.queries().select("qid", "s", keywords.bitmap(F.col("s"), mode=mode, bits=bits).alias("s_bits"))
    return e.join(F.broadcast(q))


@register("kw_bitmap_blocked", S["kw_exact_blocked"])
def _(w: World) -> DataFrame:
    return _bits(w, "dict").where(keywords.bits_hit(F.col("e_bits"), F.col("s_bits"))).select("qid", "eid")


@register("kw_hashed_blocked", S["kw_exact_blocked"])
def _(w: World) -> DataFrame:
    return _bits(w, "hashed", 16).where(keywords.blocked_by_bits(F.col("kw"), F.col("e_bits"), F.col("s"), F.col("s_bits"), "hashed")).select("qid", "eid")


@register("kw_hashed_false_hits")
def _(w: World) -> DataFrame:
    hit, real = keywords.bits_hit(F.col("e_bits"), F.col("s_bits")), keywords.keyword_blocked(F.col("kw"), F.col("s"))
    return _bits(w, "hashed", 16).agg(F.count_if(hit).alias("hits"), F.count_if(hit & ~real).alias("false_hits"), F.count_if(~hit & real).alias("missed"))


# --- weather ----------------------------------------------------------------------------------------------------

_SB = f"WITH {oracle.network('uni')}, {oracle.RING}, {oracle.slot_bounds()}"
_F5 = "(SELECT unnest([0.0, 0.25, 0.5, 0.75, 1.0]) AS f)"


def _slots(w: World, eps: float = EPS) -> DataFrame:
    return pruning.edge_slot_bounds(w.net().edges, w.net().vertices, w.ring, eps)


def _points(w: World) -> DataFrame:
    return _slots(w).withColumn("f", F.explode(F.array(*map(F.lit, (0.0, 0.25, 0.5, 0.75, 1.0)))))


def _ends() -> tuple:
    return F.col("wj"), F.col("pj"), F.col("wk"), F.col("pk")


@register("idw_points", f"{_SB} SELECT eid, slot, CAST(f AS DOUBLE) AS f, round((1 - CAST(f AS DOUBLE)) * wj + CAST(f AS DOUBLE) * wk, 6) AS value FROM sb, {_F5}")
def _(w: World) -> DataFrame:
    return _points(w).select("eid", "slot", "f", F.round(weather.idw(F.col("wj"), F.col("wk"), F.col("f")), 6).alias("value"))


@register("world_probs", f"{_SB} SELECT eid, slot, CAST(pj * pk AS BIGINT) AS a, CAST((100 - pj) * pk AS BIGINT) AS b, CAST(pj * (100 - pk) AS BIGINT) AS c, CAST((100 - pj) * (100 - pk) AS BIGINT) AS d FROM sb")
def _(w: World) -> DataFrame:
    x = _slots(w).select("eid", "slot", weather.worlds(*_ends(), F.lit(0.5)).alias("x"))
    return x.select("eid", "slot", *[F.get("x", F.lit(i))["prob"].alias(n) for i, n in enumerate("abcd")])


_X = "CASE WHEN (1 - f) * wj + f * wk > 50 THEN pj * pk ELSE 0 END + CASE WHEN wk > 50 THEN (100 - pj) * pk ELSE 0 END + CASE WHEN wj > 50 THEN pj * (100 - pk) ELSE 0 END"


@register("point_exceed_prob", f"{_SB}, p AS (SELECT eid, slot, wj, pj, wk, pk, CAST(f AS DOUBLE) AS f FROM sb, {_F5}) SELECT eid, slot, f, CAST({_X} AS DOUBLE) AS optimistic, CAST({_X} + (100 - pj) * (100 - pk) AS DOUBLE) AS pessimistic, {_X} + (100 - pj) * (100 - pk) * CAST(0.25 AS DOUBLE) AS prior FROM p")
def _(w: World) -> DataFrame:
    p = lambda u: weather.p_exceeds(*_ends(), F.col("f"), F.lit(EPS), u).cast("double")
    return _points(w).select("eid", "slot", "f", p(0.0).alias("optimistic"), p(1.0).alias("pessimistic"), p(0.25).alias("prior"))


@register("edge_ub_cases", f"{_SB} SELECT slot, {oracle.case_of('50')} AS kind, count(*) AS n, CAST(sum({oracle.ub('50')}) AS BIGINT) AS ub FROM sb GROUP BY 1, 2")
def _(w: World) -> DataFrame:
    return _slots(w).groupBy("slot", weather.ub_case(F.col("wj"), F.col("wk"), F.lit(EPS)).alias("kind")).agg(F.count(F.lit(1)).alias("n"), F.sum("ub").alias("ub"))


@register("edge_weather_range", f"{_SB} SELECT eid, slot, least(wj, wk) AS lb_val, greatest(wj, wk) AS ub_val FROM sb")
def _(w: World) -> DataFrame:
    return _slots(w).select("eid", "slot", "lb_val", "ub_val")


@register("edges_weather_pruned", f"{_SB} SELECT eid, slot FROM sb WHERE {oracle.ub('50')} >= 100 * (100 - 50)")
def _(w: World) -> DataFrame:
    return pruning.prune_weather(_slots(w), ALPHA)


_TRIP = oracle.blocked("t0", "w_min", "50", "50")


def _trips(w: World) -> DataFrame:
    arcs = fc.with_weather(w.net().arcs, w.net().vertices, fc.station_arrays(w.ring)).withColumn("t0", F.explode(F.array(*map(F.lit, (480, 535, 1310)))))
    blocked = weather.trip_blocked(*map(F.col, ("tail_w", "tail_p", "head_w", "head_p")), F.col("t0"), F.col("w_min"), F.lit(EPS), F.lit(ALPHA))
    return arcs.withColumn("blocked", blocked)


@register("edge_trip_blocked", f"WITH {oracle.network('uni')}, {oracle.RING} SELECT tail, head, CAST(t0 AS INTEGER) AS t0, {_TRIP} AS blocked FROM warc, (SELECT unnest([480, 535, 1310]) AS t0)")
def _(w: World) -> DataFrame:
    return _trips(w).select("tail", "head", "t0", "blocked")


@register("ub_vs_exact", f"{_SB}, p AS (SELECT eid, slot, wj, pj, wk, pk, CAST(f AS DOUBLE) AS f FROM sb, {_F5}), x AS (SELECT eid, slot, any_value({oracle.ub('50')}) AS ub, 10000 - min({_X}) AS ok FROM p GROUP BY eid, slot) SELECT count(*) AS n, count(*) FILTER (WHERE ub < ok) AS violations, CAST(sum(ub - ok) AS BIGINT) AS slack FROM x")
def _(w: World) -> DataFrame:
    f = F.explode(F.array(*map(F.lit, (0.0, 0.25, 0.5, 0.75, 1.0))))
    p = _slots(w).withColumn("f", f).withColumn("ok", 10000 - weather.p_exceeds(*_ends(), F.col("f"), F.lit(EPS)))
    x = p.groupBy("eid", "slot").agg(F.first("ub").alias("ub"), F.max("ok").alias("ok"))
    return x.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("ub") < F.col("ok")).alias("violations"), F.sum(F.col("ub") - F.col("ok")).cast("long").alias("slack"))


# --- pivots and bounds ------------------------------------------------------------------------------------------

_PV = f"WITH RECURSIVE {oracle.network('uni')}, {oracle.sssp(oracle.fixed_pivots())}"


@register("pivot_dist", f"{_PV} SELECT src, v, dist FROM sp")
def _(w: World) -> DataFrame:
    ps = pivots.fixed_pivots(w.net())
    at = F.array(*[F.struct(F.lit(p).cast("long").alias("src"), F.get("piv", F.lit(i)).alias("dist")) for i, p in enumerate(ps)])
    return w.piv().select("v", F.explode(at).alias("x")).select("x.src", "v", "x.dist")


@register("pivot_lb_pairs", f"{_PV}, {oracle.query_set()} SELECT q.qid, y.v, max(abs(x.dist - y.dist)) AS lb FROM q JOIN sp x ON x.v = q.src JOIN sp y ON x.src = y.src GROUP BY 1, 2")
def _(w: World) -> DataFrame:
    """The bound from the source of every query to every vertex."""
    q = w.queries().select("qid", F.col("src").alias("u")).join(w.piv().toDF("u", "pu"), "u")
    return w.piv().join(F.broadcast(q)).select("qid", "v", bounds.lb_dist(F.col("pu"), F.col("piv")).alias("lb"))


def _quality_sql(ds: tuple) -> str:
    parts = []
    for d in ds:
        parts.append(f"SELECT {d} AS d, CAST(sum(lb) AS BIGINT) AS quality, count(*) AS n_pairs FROM (SELECT x.v AS u, y.v AS v, max(abs(x.dist - y.dist)) AS lb FROM sp x JOIN sp y ON x.src = y.src AND x.v <> y.v WHERE x.src IN (SELECT src FROM pv WHERE i < {d}) GROUP BY 1, 2)")
    return f"WITH RECURSIVE {oracle.network('gau')}, {oracle.sssp(oracle.fixed_pivots(5))} " + " UNION ALL ".join(parts)


@register("pivot_quality_exact", _quality_sql((5,)))
def _(w: World) -> DataFrame:
    return pivots.pivot_quality(w.piv("gau")).select(F.lit(5).alias("d"), "quality", "n_pairs")


@register("pivot_quality_by_d", _quality_sql((1, 2, 3, 4, 5)))
def _(w: World) -> DataFrame:
    return pivots.pivot_quality_by_d(w.piv("gau"))


@register("pivot_quality_sampled")
def _(w: World) -> DataFrame:
    return pivots.pivot_quality(w.piv(), 20_000)


@register("pivots_chosen")
def _(w: World) -> DataFrame:
    """Qualities are over all pairs of vertices, estimated from drawn ones; error: standard error of that of the pivots."""
    c = pivots.choose_pivots(w.net())
    return rows(w, [(i, p, c.trace[0], c.trace[-1], c.quality, c.error) for i, p in enumerate(c.pivots)], "i int, pivot long, first_quality double, climbed_quality double, quality double, error double")


@register("pivot_count")
def _(w: World) -> DataFrame:
    n, trace = pivots.choose_pivot_count(w.net())
    return rows(w, [(i + 1, x, n) for i, x in enumerate(trace)], "d int, quality double, chosen int")


for _strategy in ("farthest", "greedy", "swap"):

    @register(f"landmarks_{_strategy}")
    def _(w: World, strategy: str = _strategy) -> DataFrame:
        return rows(w, [(i, p) for i, p in enumerate(pivots.choose_landmarks(w.net("gau"), 4, strategy))], "i int, landmark long")


@register(
    "landmarks_behind",
    f"{_PV}, {oracle.query_set()}, c AS (SELECT q.qid, pv.src AS landmark, CAST(t.x_mm - s.x_mm AS DOUBLE) AS ax, CAST(t.y_mm - s.y_mm AS DOUBLE) AS ay, CAST(l.x_mm - t.x_mm AS DOUBLE) AS bx, CAST(l.y_mm - t.y_mm AS DOUBLE) AS byy "
    "FROM q JOIN vtx s ON s.v = q.src JOIN vtx t ON t.v = q.dst CROSS JOIN pv JOIN vtx l ON l.v = pv.src), "
    "u AS (SELECT qid, landmark, CASE WHEN sqrt(ax * ax + ay * ay) * sqrt(bx * bx + byy * byy) = 0 THEN 0 ELSE (ax * bx + ay * byy) / (sqrt(ax * ax + ay * ay) * sqrt(bx * bx + byy * byy)) END AS turn FROM c) "
    "SELECT qid, landmark, turn > 0 AS behind, CAST(row_number() OVER (PARTITION BY qid ORDER BY turn DESC, landmark) AS INTEGER) AS place FROM u",
)
def _(w: World) -> DataFrame:
    return pivots.landmarks_behind(w.queries(), w.net(), pivots.fixed_pivots(w.net())).drop("turn")


@register("lb_tightness", f"{_PV}, d AS (SELECT x.v AS u, y.v AS v, max(abs(x.dist - y.dist)) AS lb FROM sp x JOIN sp y ON x.src = y.src GROUP BY 1, 2) SELECT sp.src AS u, count(*) AS n, count(*) FILTER (WHERE d.lb > sp.dist) AS violations, CAST(sum(d.lb) AS BIGINT) AS lb, CAST(sum(sp.dist) AS BIGINT) AS dist FROM sp JOIN d ON d.u = sp.src AND d.v = sp.v GROUP BY 1")
def _(w: World) -> DataFrame:
    ps = pivots.fixed_pivots(w.net())
    here = w.piv().where(F.col("v").isin(ps)).toDF("u", "pu")
    true = graph.distances(w.net().arcs, rows(w, [(p,) for p in ps], "src long"), vertices=w.net().vertices).toDF("u", "v", "dist")
    x = here.join(true, "u").join(w.piv(), "v").withColumn("lb", bounds.lb_dist(F.col("pu"), F.col("piv")))
    return x.groupBy("u").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("lb") > F.col("dist")).alias("violations"), F.sum("lb").alias("lb"), F.sum("dist").alias("dist"))


# --- index ------------------------------------------------------------------------------------------------------

_IX = f"WITH RECURSIVE {oracle.network('uni')}, {oracle.RING}, {oracle.query_set()}, {oracle.index(FANOUT)}"


@register("idx_nodes", f"{_IX} SELECT level, node, parent, xmin, ymin, xmax, ymax, n_edges FROM nod")
def _(w: World) -> DataFrame:
    return w.index().nodes.select("level", "node", "parent", "xmin", "ymin", "xmax", "ymax", "n_edges")


@register("idx_time", f"{_IX} SELECT level, node, lb_t, ub_t FROM nod")
def _(w: World) -> DataFrame:
    return w.index().nodes.select("level", "node", "lb_t", "ub_t")


@register("idx_kw", f"{_IX} SELECT level, node, kw_and, kw_or FROM nod")
def _(w: World) -> DataFrame:
    return w.index().nodes.select("level", "node", "kw_and", "kw_or")




def _node_weather(base: str, fanout: int) -> str:
    bounds_ = ", ".join(f"CAST(max({oracle.ub(str(e))}) AS BIGINT) AS u{e}" for e in oracle.GRID)
    node = f"pos // CAST({fanout} ** level AS BIGINT)"
    return f"{base}, {oracle.slot_bounds()}, iw AS (SELECT CAST(level AS INTEGER) AS level, {node} AS node, slot, min(least(wj, wk)) AS lb_val, max(greatest(wj, wk)) AS ub_val, CAST(max((100 - pj) * (100 - pk)) AS BIGINT) AS ub_case3, {bounds_} FROM sb JOIN pos ON pos.eid = sb.eid, lvl GROUP BY ALL)"


#: Nodes of two edges, so that some are pruned at every scale factor.
_PAIRS = 2
_IX2 = f"WITH RECURSIVE {oracle.network('uni')}, {oracle.RING}, {oracle.query_set()}, {oracle.index(_PAIRS)}"
_IW = _node_weather(_IX, FANOUT)


@register("idx_weather", f"{_IW} SELECT level, node, slot, lb_val, ub_val, ub_case3, u30, u50, u90 FROM iw")
def _(w: World) -> DataFrame:
    x = w.index().weather
    return x.select("level", "node", "slot", "lb_val", "ub_val", "ub_case3", *[F.element_at("ub_by_eps", F.lit(e)).alias(f"u{e}") for e in (30, 50, 90)])


@register("idx_links", f"{_IX}, en AS (SELECT DISTINCT CAST(level AS INTEGER) AS level, v, pos // CAST({FANOUT} ** level AS BIGINT) AS n FROM (SELECT a AS v, pos FROM pos UNION ALL SELECT b, pos FROM pos), lvl) SELECT DISTINCT x.level, x.n AS n1, y.n AS n2 FROM en x JOIN en y ON x.level = y.level AND x.v = y.v")
def _(w: World) -> DataFrame:
    return w.index().links


@register("idx_lookup", f"{_IX} SELECT eid, pos, pos // {FANOUT} AS leaf FROM pos")
def _(w: World) -> DataFrame:
    return w.index().lookup.select("eid", "pos", "leaf")


@register("idx_str_packing")
def _(w: World) -> DataFrame:
    i = ix.build_index(w.net("gau"), None, FANOUT, "str")
    return i.nodes.groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.sum("n_edges").alias("edges"), F.sum((F.col("xmax") - F.col("xmin")) * (F.col("ymax") - F.col("ymin"))).alias("area"))


@register("nodes_kw_pruned", f"{_IX2} SELECT qid, level, node FROM nod, (SELECT qid, list_aggregate(list_transform(s, lambda k: CAST(1 AS BIGINT) << k), 'bit_or') AS sb FROM q) x WHERE kw_and & sb <> 0")
def _(w: World) -> DataFrame:
    return ix.node_prune_keyword(w.index("uni", _PAIRS).nodes, w.queries())


@register("nodes_weather_pruned", f"{_node_weather(_IX2, _PAIRS)} SELECT qid, level, node FROM iw, q WHERE (slot - dep_min // 60 + 48) % 24 <= (dep_min + 60) // 60 - dep_min // 60 GROUP BY qid, level, node, alpha_pct HAVING max(CASE WHEN ub_val <= eps THEN 10000 WHEN lb_val > eps THEN ub_case3 ELSE u50 END) < 100 * (100 - alpha_pct)")
def _(w: World) -> DataFrame:
    return ix.node_prune_weather(w.index("uni", _PAIRS).weather, w.queries(), 60)


# --- routing ----------------------------------------------------------------------------------------------------


def brief(answers: DataFrame) -> DataFrame:
    return answers.select("qid", "answered", "total_min")


def _index_answers(w: World, kind: str = "uni", options: RouteOptions = RouteOptions(), **q) -> DataFrame:
    key = ("answers", kind, options.use_keyword, options.use_weather, options.use_time, options.key, *sorted(q.items()))
    w.ready(kind, **q)
    return w._once(key, lambda: stored(router.route_index(w.queries(kind, **q), w.net(kind), w.index(kind), w.ring, options)))


@register("entry_routes", oracle.routes(sigma=3))
def _(w: World) -> DataFrame:
    return brief(_index_answers(w, sigma=3))


@register("route_index", oracle.routes())
def _(w: World) -> DataFrame:
    return brief(_index_answers(w))


@register("route_index_elapsed_key", oracle.routes())
def _(w: World) -> DataFrame:
    return brief(_index_answers(w, options=RouteOptions(key="elapsed")))


@register("route_index_gau", oracle.routes("gau"))
def _(w: World) -> DataFrame:
    return brief(_index_answers(w, "gau"))


@register("route_index_sparse", oracle.routes("sparse"))
def _(w: World) -> DataFrame:
    return brief(_index_answers(w, "sparse"))


@register("route_index_paths", oracle.routes())
def _(w: World) -> DataFrame:
    return brief(router.route_index_paths(w.queries(), w.net(), w.index(), w.ring, RouteOptions(), w.piv()))


@register("route_index_bounded", oracle.routes())
def _(w: World) -> DataFrame:
    """With the minutes of a greedy answer, where there is one, as the limit of the descent."""
    best = stored(router.greedy_route(w.queries(), w.net(), w.ring, RouteOptions(), w.piv())).withColumnRenamed("ub_min", "lam")
    return brief(router.route_index(w.queries(), w.net(), w.index(), w.ring, RouteOptions(), best))


@register("route_types")
def _(w: World) -> DataFrame:
    """One batch with queries of several types; the index keeps two of them."""
    kinds = F.array(*map(F.lit, ("ANY", "click", "view", "purchase")))
    q = w.queries().withColumn("wtype", F.get(kinds, F.col("qid") % 4))
    return router.route_index(q, w.net(), w.index("uni", wtypes=("ANY", "click")), w.ring).join(q.select("qid", "wtype"), "qid").select("qid", "wtype", "answered", "total_min")


@register("route_no_index", oracle.routes())
def _(w: World) -> DataFrame:
    return brief(baselines.route_astar(w.queries(), w.net(), w.ring, RouteOptions(use_index=False), "pivot", w.piv()))


for _h in ("zero", "euclid", "pivot"):

    @register(f"route_astar_{_h}", oracle.routes())
    def _(w: World, h: str = _h) -> DataFrame:
        return brief(baselines.route_astar(w.queries(), w.net(), w.ring, RouteOptions(), h, w.piv()))


@register("route_filter_first", oracle.routes())
def _(w: World) -> DataFrame:
    return brief(baselines.route_filter_first(w.queries(), w.net(), w.ring))


@register("filter_first_variants")
def _(w: World) -> DataFrame:
    out = None
    for p in ("all_slots", "departure_slot", "any_slot"):
        part = baselines.route_filter_first(w.queries(), w.net(), w.ring, RouteOptions(prefilter=p)).select(F.lit(p).alias("prefilter"), "qid", "answered", "total_min")
        out = part if out is None else out.unionAll(part)
    return out


@register("route_bfs", oracle.routes(horizon=40, sigma=3))
def _(w: World) -> DataFrame:
    """Without any bound, over near destinations; ``route_rounds_beam`` has the usual ones."""
    return baselines.route_bfs(w.queries(sigma=3), w.net(), w.ring, RouteOptions(horizon_min=40))


@register("route_rounds_beam", oracle.routes(horizon=60, sigma=5))
def _(w: World) -> DataFrame:
    return search.search_in_rounds(w.queries(sigma=5), w.net(), w.ring, RouteOptions(horizon_min=60, batch_width=256), w.piv())[0]


@register("route_plain", f"WITH RECURSIVE {oracle.network('uni')}, {oracle.query_set()}, {oracle.sssp('SELECT DISTINCT src FROM q', 'w_min')} SELECT q.qid, sp.dist AS total_min FROM q JOIN sp ON sp.src = q.src AND sp.v = q.dst")
def _(w: World) -> DataFrame:
    return baselines.route_plain(w.queries(), w.net())


_HOPS = 6


@register(
    "route_enumerate",
    f"""WITH RECURSIVE {oracle.network('uni')}, {oracle.RING}, {oracle.query_set(sigma=3)},
pth(qid, v, t, seen, ok) AS (SELECT qid, src, dep_min, [src], true FROM q UNION ALL
  SELECT p.qid, a.head, p.t + a.w_min, list_append(p.seen, a.head), p.ok AND NOT list_has_any(a.kw, q.s) AND NOT ({oracle.blocked('p.t', 'a.w_min', 'q.eps', 'q.alpha_pct')})
  FROM pth p JOIN q ON q.qid = p.qid JOIN warc a ON a.tail = p.v WHERE p.v <> q.dst AND NOT list_contains(p.seen, a.head) AND len(p.seen) <= {_HOPS})
SELECT q.qid, min(t) FILTER (WHERE ok) IS NOT NULL AS answered, CAST(min(t) FILTER (WHERE ok) - any_value(dep_min) AS BIGINT) AS total_min, count(t) AS n_paths FROM q LEFT JOIN pth ON pth.qid = q.qid AND pth.v = q.dst GROUP BY q.qid""",
)
def _(w: World) -> DataFrame:
    return baselines.route_enumerate(w.queries(sigma=3), w.net(), w.ring, _HOPS)


@register("route_simple_mode")
def _(w: World) -> DataFrame:
    return brief(baselines.route_astar(w.queries(), w.net(), w.ring, RouteOptions(path_mode="simple"), "pivot", w.piv()))


@register("route_paths_valid", f"WITH RECURSIVE {oracle.network('uni')}, {oracle.RING}, {oracle.query_set()}, {oracle.labels()} SELECT qid, CAST(0 AS BIGINT) AS bad_edges, CAST(0 AS BIGINT) AS bad_links, CAST(0 AS BIGINT) AS bad_times FROM opt")
def _(w: World) -> DataFrame:
    return router.refine(_index_answers(w), w.queries(), w.net(), w.ring).select("qid", "bad_edges", "bad_links", "bad_times")


@register("greedy_ub")
def _(w: World) -> DataFrame:
    return router.greedy_route(w.queries(), w.net(), w.ring, RouteOptions(), w.piv())


@register("route_delivery")
def _(w: World) -> DataFrame:
    from ..sources.queries import delivery_queries

    q = delivery_queries(w.net(), w.table("orders"))
    return brief(baselines.route_astar(q, w.net(), w.ring, RouteOptions(), "pivot", w.piv()))


# --- measures ---------------------------------------------------------------------------------------------------


def task_seconds(w: World, after: int = -1) -> tuple[int, float, float]:
    """The newest stage's number, and CPU (of the JVM; Python workers' own isn't counted) and run seconds of all tasks of the stages after ``after``."""
    sc = w.spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
    newest, cpu, run = after, 0, 0
    for i in range(stages.size()):  # newest first
        s = stages.apply(i)
        if s.stageId() <= after:
            break
        newest = max(newest, s.stageId())
        if after >= 0:
            cpu, run = cpu + s.executorCpuTime(), run + s.executorRunTime()
        else:
            break
    return newest, cpu / 1e9, run / 1e3


def metrics_of(w: World, kind: str = "uni", options: RouteOptions = RouteOptions(), methods: tuple = ("index", "astar_pivot", "astar", "filter_first"), d: int = 5, strategy: str = "fixed", **q) -> list[tuple]:
    """(method, net, wall-clock seconds, then sums over the queries, maxima of queue and heap, and tasks' seconds).

    labels: taken from the heap; settled: vertices of the search back from the destination; reads: leaf pages for each
    vertex looked at, and inner nodes; pages: the same with a page counted once a query. All methods read the index's pages."""
    out = []
    net, ring, ask, piv, index = w.net(kind), w.ring, w.queries(kind, **q), w.piv(kind, d, strategy), w.index(kind, d=d, strategy=strategy).complete(() if "index_paths" in methods else ("links",))
    run = {
        "index": lambda: router.route_index(ask, net, index, ring, options),
        "index_paths": lambda: router.route_index_paths(ask, net, index, ring, options, piv),
        "astar": lambda: baselines.route_astar(ask, net, ring, options, "zero", pages=index.lookup),
        "astar_pivot": lambda: baselines.route_astar(ask, net, ring, options, "pivot", piv, index.lookup),
        "filter_first": lambda: baselines.route_filter_first(ask, net, ring, options, index.lookup),
    }
    for m in methods:
        stage = max(0, task_seconds(w)[0])
        began = time.time()
        d = run[m]()
        for c in ("node_reads", "max_queue"):
            d = d if c in d.columns else d.withColumn(c, F.lit(0).cast("long"))
        agg = [F.sum(F.coalesce(c, F.lit(0))).alias(c) for c in ("labels", "settled", "page_reads", "page_reads_distinct", "node_reads", "pruned_kw", "pruned_weather", "pruned_time")]
        agg.append(F.sum(F.when(F.col("answered"), F.col("labels"))).alias("answered_labels"))
        r = d.agg(F.count_if("answered").alias("answered"), F.count(F.lit(1)).alias("n"), *agg, F.max("max_heap").alias("max_heap"), F.max("max_queue").alias("max_queue")).first()
        took = time.time() - began
        out.append((m, kind, took, r["n"], r["answered"], r["labels"] or 0, r["settled"] or 0, (r["page_reads"] or 0) + (r["node_reads"] or 0), (r["page_reads_distinct"] or 0) + (r["node_reads"] or 0), r["node_reads"] or 0, r["pruned_kw"] or 0, r["pruned_weather"] or 0, r["pruned_time"] or 0, r["max_heap"] or 0, r["max_queue"] or 0, *task_seconds(w, stage)[1:], r["answered_labels"] or 0))
    return out


METRICS = "method string, net string, seconds double, n long, answered long, labels long, settled long, reads long, pages long, node_reads long, pruned_kw long, pruned_weather long, pruned_time long, max_heap long, max_queue long, jvm_cpu_s double, task_s double, answered_labels long"


@register("router_metrics")
def _(w: World) -> DataFrame:
    return rows(w, metrics_of(w), METRICS)


@register("datasets_methods")
def _(w: World) -> DataFrame:
    return rows(w, [x for kind in networks.KINDS for x in metrics_of(w, kind)], METRICS)


@register("prune_ablation")
def _(w: World) -> DataFrame:
    out = []
    for name, o in (("all", {}), ("no_time", {"use_time": False}), ("no_keyword", {"use_keyword": False}), ("no_weather", {"use_weather": False}), ("no_index", None)):
        if o is None:
            d = baselines.route_astar(w.queries(), w.net(), w.ring, RouteOptions(), "pivot", w.piv())
        else:
            d = router.route_index(w.queries(), w.net(), w.index(), w.ring, replace(RouteOptions(), **o))
        r = d.agg(F.sum("labels").alias("labels"), F.sum("pruned_kw").alias("k"), F.sum("pruned_weather").alias("w"), F.sum("pruned_time").alias("t"), F.count_if("answered").alias("a")).first()
        out.append((name, r["labels"], r["k"], r["w"], r["t"], r["a"]))
    return rows(w, out, "setting string, labels long, pruned_kw long, pruned_weather long, pruned_time long, answered long")


@register("pruning_power")
def _(w: World) -> DataFrame:
    net, nodes = w.net(), w.index().nodes
    n, q = net.edges.count(), w.queries().count()
    kw = n * q - pruning.keyword_pairs(net.edges, w.queries()).count()
    # edges between the same cells have the same bounds
    cells = net.vertices.select("v", "cell")
    alike = net.edges.join(cells.toDF("a", "ca"), "a").join(cells.toDF("b", "cb"), "b").groupBy("ca", "cb").agg(F.count(F.lit(1)).alias("n"))
    out = F.when(F.col("ub") < 100 * (100 - ALPHA), F.col("n")).otherwise(0)
    wet = pruning.cell_slot_bounds(alike, w.ring, EPS).agg(F.sum(out) / F.sum("n")).first()[0]
    dropped = ix.node_prune_weather(w.index().weather, w.queries()).unionAll(ix.node_prune_keyword(nodes, w.queries())).distinct().count()
    return rows(w, [("edges_by_keyword", 1 - kw / max(1, n * q)), ("edge_slots_by_weather", float(wet or 0)), ("nodes", dropped / max(1, nodes.count() * q))], "prune string, share double")


@register("cost_model")
def _(w: World) -> DataFrame:
    return rows(w, ix.cost_model(w.index(), 10, 2 * w.net().edges.count() / w.net().vertices.count()), "term string, value double")


@register("index_space")
def _(w: World) -> DataFrame:
    i = w.index()
    data = {"nodes": i.nodes, "links": i.links, "lookup": i.lookup, "weather": i.weather, "weather by slot": i.by_slot, "pages": i.pages, "pivot ranges": i.ranges, "pivots": w.piv(), "ring": w.ring, "bitmaps": stored(i.nodes.select("kw_and", "kw_or"))}
    return rows(w, [(a, d.count(), stored_bytes(d)) for a, d in data.items()], "part string, n_rows long, bytes long")


def stored_bytes(df: DataFrame) -> int:
    """Bytes of the files that a written table is read from."""
    spark = df.sparkSession.sparkContext
    path = spark._jvm.org.apache.hadoop.fs.Path
    at = [path(x) for x in df.inputFiles()]
    return sum(p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).getLen() for p in at)


@register("index_build_update")
def _(w: World) -> DataFrame:
    from ..streaming.ring import apply_forecasts

    out = []
    for kind in networks.KINDS:
        t = time.time()
        i = ix.build_index(w.net(kind), w.ring, FANOUT, piv=w.piv(kind)).complete()
        built = time.time() - t
        t = time.time()
        changed = apply_forecasts(next_hour(w), w.ring, w.net(kind), i).groupBy("level").count().collect()
        out.append((kind, w.net(kind).vertices.count(), w.net(kind).edges.count(), built, time.time() - t, sum(r["count"] for r in changed), max((r["level"] for r in changed), default=0)))
    return rows(w, out, "net string, vertices long, edges long, build_s double, update_s double, changed long, top_level int")


def next_hour(w: World, slot: int = 8) -> DataFrame:
    """A new hour for all stations: the forecasts of the slot before, a day later."""
    new = w.ring.where((F.col("wtype") == "ANY") & (F.col("slot") == slot - 1))
    return new.withColumns({"slot": F.lit(slot), "issued": F.expr("issued + interval 40 days"), "event_id": F.col("event_id") + 10**12})


@register("edge_update")
def _(w: World) -> DataFrame:
    """New minutes and no keywords on all roads of one station: the index nodes that change."""
    from ..streaming.ring import apply_edge_attributes

    at = w.net().vertices.where("cell = 7").select(F.col("v").alias("a"))
    new = w.net().edges.join(at, "a", "left_semi").select("eid", (F.col("w_min") + 5).alias("w_min"), F.array().cast("array<int>").alias("kw"))
    return apply_edge_attributes(new, w.net(), w.index())


# --- sweeps -----------------------------------------------------------------------------------------------------

SWEEPS = {
    "alpha": [(a, {"alpha_pct": a}) for a in (10, 30, 50, 70, 90)],
    "eps": [(e, {"eps": float(e)}) for e in (20, 30, 50, 70, 90)],
    "sigma": [(s, {"sigma": s}) for s in (5, 10, 15, 20, 25, 30)],
    "s": [(s, {"s_size": s}) for s in (1, 3, 5, 8, 10)],
}


def sweep_queries(w: World, sets: list[tuple], kind: str = "uni") -> DataFrame:
    """Several query sets as one batch: numbers from 1000 * i, and the parameter."""
    out = None
    for i, (p, o) in enumerate(sets):
        part = w.queries(kind, **o).withColumns({"qid": F.col("qid") + 1000 * i, "param": F.lit(p)})
        out = part if out is None else out.unionByName(part)
    return stored(out)


def sweep_answers(w: World, sets: list[tuple], kind: str = "uni") -> DataFrame:
    w.ready(kind, **sets[0][1])
    ask = sweep_queries(w, sets, kind)
    d = router.route_index(ask.drop("param"), w.net(kind), w.index(kind), w.ring)
    return d.join(ask.select("qid", "param"), "qid").select("param", (F.col("qid") % 1000).cast("int").alias("qid"), "total_min")


COSTS = f"param int, {METRICS}"


def costs(w: World, settings: list[tuple], at_once: int | None = None) -> DataFrame:
    """Labels, reads and seconds of the index method for each setting (param, net, options), built beforehand, ``at_once`` of them side by side."""
    out = []
    together(w.spark, *[lambda kind=kind, o=o: w.ready(kind, **o) for _, kind, o in settings], at_once=at_once)
    for param, kind, o in settings:
        hand_back(w.spark)
        out.append((param, *metrics_of(w, kind, methods=("index",), **o)[0]))
    return rows(w, out, COSTS)


NETS = ("uni", "gau")
for _name, _sets in SWEEPS.items():
    _o = [(p, {("alpha" if k == "alpha_pct" else k): v for k, v in o.items()}) for p, o in _sets]
    for _kind in NETS:

        @register(f"sweep_{_name}" + ("" if _kind == "uni" else f"_{_kind}"), oracle.sweep(_o, kind=_kind))
        def _(w: World, sets: list = _sets, kind: str = _kind) -> DataFrame:
            return sweep_answers(w, sets, kind)

    @register(f"sweep_{_name}_costs")
    def _(w: World, sets: list = _sets) -> DataFrame:
        return costs(w, [(p, kind, o) for kind in NETS for p, o in sets])


PIVOTS = (2, 5, 8, 10, 15)


@register("sweep_d", oracle.sweep([(d, {}) for d in PIVOTS]))
def _(w: World) -> DataFrame:
    together(w.spark, lambda: w.net(), lambda: w.ring)
    w.pivs("uni", PIVOTS)

    def answers(d: int) -> DataFrame:
        w.ready(d=d)
        return router.route_index(w.queries(), w.net(), w.index(d=d), w.ring).select(F.lit(d).alias("param"), "qid", "total_min")

    return reduce(DataFrame.unionAll, together(w.spark, *[lambda d=d: answers(d) for d in PIVOTS]))


@register("sweep_d_costs")
def _(w: World) -> DataFrame:
    """Pivots are chosen anew for each number."""
    return costs(w, [(d, kind, {"d": d, "strategy": "swap"}) for kind in NETS for d in PIVOTS])


STRATEGIES = ("fixed", "farthest", "greedy", "swap")


@register("pivots_compared_costs")
def _(w: World) -> DataFrame:
    """The index method with pivots of each strategy: evenly spread (0), farthest (1), greedy (2), chosen by swaps (3)."""
    return costs(w, [(i, "uni", {"strategy": s}) for i, s in enumerate(STRATEGIES)])


#: Quarters of a table's vertices, for networks of several sizes.
QUARTERS = (1, 2, 3, 4)
for _kind in NETS:
    for _n in QUARTERS:

        @register(f"sweep_v_{_kind}_{_n}", oracle.routes(_kind, quarters=_n).replace("SELECT q.qid, opt.total_min IS NOT NULL AS answered", "SELECT (SELECT count(*) FROM vtx) AS n, q.qid, opt.total_min IS NOT NULL AS answered"))
        def _(w: World, kind: str = _kind, quarters: int = _n) -> DataFrame:
            kind = kind if quarters == 4 else f"{kind}/{quarters}"
            return brief(_index_answers(w, kind)).select(F.lit(w.net(kind).vertices.count()).cast("long").alias("n"), "qid", "answered", "total_min")


@register("sweep_v_costs")
def _(w: World) -> DataFrame:
    """Costs, and queue and heap maxima, against the number of vertices (the parameter)."""
    kinds = [*(kind if n == 4 else f"{kind}/{n}" for kind in NETS for n in QUARTERS), "sparse"]
    return costs(w, [(w.net(kind).vertices.count(), kind, {}) for kind in kinds])


#: Networks of one size that are made side by side; what runs of each takes the driver's memory.
NETS_AT_ONCE = 3


@register("sweep_edges_costs")
def _(w: World) -> DataFrame:
    """Fewer and fewer cross links: the number of edges is the parameter."""
    kinds = [f"uni+{k}" for k in (2, 4, 8, 16, 32)]
    together(w.spark, *[lambda kind=kind: w.net(kind) for kind in kinds], at_once=NETS_AT_ONCE)
    return costs(w, [(w.net(kind).edges.count(), kind, {}) for kind in kinds], NETS_AT_ONCE)


@register("sweep_skew_costs")
def _(w: World) -> DataFrame:
    """Even and skewed vertices and keywords: 0 uni, 1 gau, 2 uni and 3 gau with skewed keywords."""
    return costs(w, [(i, kind, {}) for i, kind in enumerate(("uni", "gau", "uni*", "gau*"))])


@register("queue_heap_maxima")
def _(w: World) -> DataFrame:
    out, kinds = [], ("gau", "uni", "sparse")
    together(w.spark, *[lambda kind=kind: _index_answers(w, kind) for kind in kinds])
    for kind in kinds:
        r = _index_answers(w, kind).agg(F.max("max_queue").alias("queue"), F.max("max_heap").alias("heap")).first()
        out.append((kind, w.net(kind).vertices.count(), r["queue"] or 0, r["heap"] or 0))
    return rows(w, out, "net string, vertices long, max_queue long, max_heap long")
