"""What the router is compared with. All share the label search, so differences come from pruning and order."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.keywords import keyword_blocked
from ..functions.weather import trip_blocked
from ..operators.graph import distances
from ..operators.pruning import edge_slot_bounds
from ..operators.storage import stored
from ..schema import RouteOptions
from ..sources.forecasts import station_arrays, with_weather
from ..sources.networks import Network
from . import search


def route_astar(queries: DataFrame, net: Network, forecasts: DataFrame, options: RouteOptions = RouteOptions(), h: str = "zero", piv: DataFrame | None = None, pages: DataFrame | None = None) -> DataFrame:
    """Outward search from the source, obstacles tested where they are met. h: 'zero', 'euclid' or 'pivot'.

    ``pages``: eid and leaf, for reads of the same pages as the index has."""
    o = replace(options, heuristic=h, use_time=options.use_time and h != "zero", key="elapsed" if h == "zero" else options.key)

    def run(ask: DataFrame, o: RouteOptions) -> DataFrame:
        ends = piv if h == "pivot" else None
        arcs = search.bound_arcs(ask, net, o, ends, pages)
        if o.extra.get("far") is not None:
            arcs, ask = stored(arcs), search.source_bounds(ask, net, o, ends)
        found = search.search_in_tasks(ask, arcs, search.plain_seeds(ask), forecasts, o)
        return ask.select("qid").join(found, "qid", "left").withColumn("answered", F.coalesce("answered", F.lit(False)))

    return search.by_growing_horizons(queries, net, o, run)


def blocked_edges(queries: DataFrame, net: Network, forecasts: DataFrame, prefilter: str = "all_slots") -> DataFrame:
    """qid, eid deleted before the search: by keyword, and by weather in all slots, at departure, or in any.

    Edges are tested once for each type, limit, share and, where it matters, departure slot that queries ask for."""
    from ..functions.weather import ub_prob_ok

    kw = net.edges.select("eid", F.explode("kw").alias("k")).join(queries.select("qid", F.explode("s").alias("k")), "k").select("qid", "eid")
    asked = ["wtype", "eps", "alpha_pct", *(["dep_slot"] if prefilter == "departure_slot" else [])]
    q = queries.withColumn("dep_slot", F.floor(F.col("dep_min") / 60 % 24))
    kinds, slots = q.select(*asked).distinct(), None
    for wtype in [r[0] for r in queries.select("wtype").distinct().collect()]:
        part = edge_slot_bounds(net.edges, net.vertices, forecasts, 0.0, wtype).select(F.lit(wtype).alias("wtype"), "eid", "slot", "wj", "pj", "wk", "pk")
        slots = part if slots is None else slots.unionAll(part)
    if slots is None:
        return kw
    ub = ub_prob_ok(F.col("wj"), F.col("pj"), F.col("wk"), F.col("pk"), F.col("eps"))
    rows = slots.join(F.broadcast(kinds), "wtype").withColumn("out", ub < 100 * (100 - F.col("alpha_pct")))
    if prefilter == "departure_slot":
        rows = rows.where("slot = dep_slot")
    verdict = F.bool_or("out") if prefilter == "any_slot" else F.bool_and("out")
    weather = rows.groupBy(*asked, "eid").agg(verdict.alias("out")).where("out").join(q.select("qid", *asked), asked).select("qid", "eid")
    return kw.unionAll(weather).distinct()


def route_filter_first(queries: DataFrame, net: Network, forecasts: DataFrame, options: RouteOptions = RouteOptions(), pages: DataFrame | None = None) -> DataFrame:
    """Obstacle edges deleted for every query first, then plain search on the rest.

    'all_slots' is exact (trips are checked again); 'departure_slot' takes the weather as it is at departure;
    'any_slot' deletes too much and may lose answers."""
    gone = stored(blocked_edges(queries, net, forecasts, options.prefilter))
    o = replace(options, heuristic="zero", use_time=False, key="elapsed", use_weather=options.prefilter != "departure_slot")

    def run(ask: DataFrame, o: RouteOptions) -> DataFrame:
        arcs = stored(search.bound_arcs(ask, net, o, None, pages).join(gone, ["qid", "eid"], "left_anti"))
        found = search.search_in_tasks(search.source_bounds(ask, net, o), arcs, search.plain_seeds(ask), forecasts, o)
        return ask.select("qid").join(found, "qid", "left").withColumn("answered", F.coalesce("answered", F.lit(False)))

    found = search.by_growing_horizons(queries, net, o, run)
    n = gone.groupBy("qid").agg(F.count(F.lit(1)).alias("filtered_edges"))
    return queries.select("qid").join(found, "qid", "left").join(n, "qid", "left").withColumn("answered", F.coalesce("answered", F.lit(False)))


def route_bfs(queries: DataFrame, net: Network, forecasts: DataFrame, options: RouteOptions = RouteOptions()) -> DataFrame:
    """Breadth first: rounds of joins over all labels of a hop, without a heuristic."""
    o = replace(options, heuristic="zero", key="elapsed", batch_width=None)
    return search.search_in_rounds(queries, net, forecasts, o)[0]


def route_plain(queries: DataFrame, net: Network) -> DataFrame:
    """qid, total_min without obstacles: a lower bound for every answer."""
    dist = distances(net.arcs, queries.select("src").distinct(), "w_min", net.vertices).toDF("src", "dst", "total_min")
    return queries.join(dist, ["src", "dst"]).select("qid", "total_min")


def route_enumerate(queries: DataFrame, net: Network, forecasts: DataFrame, max_hops: int = 7, options: RouteOptions = RouteOptions()) -> DataFrame:
    """qid, answered, total_min, n_paths over all simple paths of at most max_hops hops: every path is checked."""
    kinds = queries.select("wtype").distinct()  # one set of arcs for each type asked for
    arcs = stored(with_weather(net.arcs.join(F.broadcast(kinds)), net.vertices, station_arrays(forecasts, None)).withColumnRenamed("wtype", "kind"))
    q = queries.select("qid", "src", "dst", "dep_min", "wtype", "eps", "alpha_pct", "s")
    front = q.select("*", F.col("src").alias("v"), F.col("dep_min").alias("t"), F.array("src").alias("seen"), F.lit(True).alias("valid"))
    done = None
    for _ in range(max_hops):
        step = front.join(arcs, (front["v"] == arcs["tail"]) & (front["wtype"] == arcs["kind"])).where(~F.array_contains("seen", F.col("head")))
        bad = trip_blocked(F.col("tail_w"), F.col("tail_p"), F.col("head_w"), F.col("head_p"), F.col("t"), F.col("w_min"), F.col("eps"), F.col("alpha_pct"), options.unknown)
        # on its own: beside an alias t, a lambda's t would be the new one
        step = step.withColumn("still", F.col("valid") & ~bad & ~keyword_blocked(F.col("kw"), F.col("s")))
        new = stored(step.select(*q.columns, F.col("head").alias("v"), (F.col("t") + F.col("w_min")).alias("t"), F.concat("seen", F.array("head")).alias("seen"), F.col("still").alias("valid")))
        arrived = new.where("v = dst").select("qid", "t", "valid")
        done = arrived if done is None else done.unionAll(arrived)
        front = new.where("v <> dst")
    best = done.groupBy("qid").agg(F.min(F.when(F.col("valid"), F.col("t"))).alias("t"), F.count(F.lit(1)).alias("n_paths"))
    return q.join(best, "qid", "left").select("qid", F.col("t").isNotNull().alias("answered"), (F.col("t") - F.col("dep_min")).alias("total_min"), F.coalesce("n_paths", F.lit(0)).alias("n_paths"))
