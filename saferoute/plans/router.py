"""The index-guided router, and its form by node paths.

``route_index`` goes down the index once for the whole batch and searches over the arcs of the leaf pages that are left.

``route_index_paths`` follows node paths: one stands for walks whose i-th edge lies in its i-th node. That descent starts with the pair of
the root, goes down level by level (each entry replaced by linked children, one linked entry appended), and
prunes entries by keywords, weather and time. Paths that reach a node with an edge at the destination also
stay unextended, so that near destinations are not overshot. At the edge level, walks are followed head to
tail through the surviving node paths; what arrives is a candidate, the rest seeds the search."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bounds import lb_dist, lb_time
from ..functions.keywords import bitmap, keyword_blocked
from ..functions.weather import trip_blocked
from ..operators.pruning import prune_time
from ..operators.storage import stored
from ..schema import RouteOptions
from ..sources.forecasts import station_arrays, with_weather
from ..sources.networks import Network
from . import search
from .index import Index, bound_at

METRICS = ["qid", "node_reads", "node_reads_distinct", "max_queue"]


@dataclass
class Descent:
    paths: DataFrame  #: qid, nodes (leaf ids), stopped
    metrics: DataFrame  #: qid, node_reads, node_reads_distinct, max_queue
    history: list[dict]


def bind_queries(queries: DataFrame) -> DataFrame:
    """Queries with the bitmap of their keywords."""
    return queries.withColumn("s_bits", F.get(bitmap(F.col("s")), F.lit(0)))


PIVOTED = ["src_piv", "dst_piv"]


def seen_from_pivots(queries: DataFrame, index: Index) -> DataFrame:
    """Queries with the distances of their ends to the index's pivots, if it has any and they are not there already."""
    if index.pivots is None or PIVOTED[0] in queries.columns:
        return queries
    # the ends are few: what is kept of the vertices is theirs
    ends = queries.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    at = index.pivots.join(F.broadcast(ends), "v")
    return stored(queries.join(at.toDF("src", "src_piv"), "src", "left").join(at.toDF("dst", "dst_piv"), "dst", "left"))


def reachable_nodes(queries: DataFrame, index: Index, options: RouteOptions, best: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(qid, level, node, lb_t of the nodes that no prune rules out; qid and counters of the descent).

    From the root down, a level's nodes meet the surviving queries of their parents by an equi-join; no query meets
    a node whose parent is out. Out go nodes whose edges all carry a keyword of the query, whose bound on the
    weather is too low in every slot that the trip can touch, and that no way within the horizon can touch, nor within
    ``best`` (qid, lam: minutes of a known answer): bound from the source, the shortest edge, bound to the destination."""
    timed = options.use_time and index.ranges is not None
    if timed:
        queries = seen_from_pivots(queries, index)
    q = bind_queries(queries).select("qid", "src", "dst", "dep_min", "wtype", "eps", "alpha_pct", "s_bits", *(PIVOTED if timed else []))
    rows = index.nodes.select("level", "node", "parent", "lb_t", "kw_and")
    if timed:
        rows = rows.join(index.ranges, ["level", "node"])
    wet = options.use_weather and index.by_slot is not None

    def gap(at: str) -> Column:
        """Minutes at top speed from a vertex to any end of the node's edges, at least."""
        part = F.zip_with(F.col(at), F.zip_with("piv_lo", "piv_hi", lambda a, b: F.struct(a.alias("a"), b.alias("b"))), lambda p, r: F.greatest(r["a"] - p, p - r["b"], F.lit(0).cast("long")))
        return lb_time(F.array_max(part), F.lit(index.vmax))

    first, last = F.floor(F.col("dep_min") / 60), F.floor((F.col("dep_min") + options.horizon_min) / 60)
    some_slot = F.exists(F.sequence(first, F.least(last, first + 23)), lambda s: F.coalesce(bound_at(F.col("eps"), F.element_at("slots", F.pmod(s, F.lit(24)).cast("int"))) >= 100 * (100 - F.col("alpha_pct")), F.lit(True)))
    above, out = q.withColumn("parent", F.lit(0).cast("long")), None
    for level in range(index.height, 0, -1):
        here = above.join(rows.where(F.col("level") == level).drop("level"), "parent")
        if options.use_keyword:
            here = here.where(F.col("kw_and").bitwiseAND(F.col("s_bits")) == 0)
        if timed:
            here = here.withColumn("lb", gap("src_piv") + F.col("lb_t") + gap("dst_piv")).where(F.col("lb") <= options.horizon_min)
            if best is not None:
                here = prune_time(here, best)
        if wet:
            slots = index.by_slot.where(F.col("level") == level).drop("level")
            here = here.join(slots, ["wtype", "node"], "left").where(F.col("slots").isNull() | some_slot)
        here = stored(here.select("qid", F.lit(level).alias("level"), "node", "lb_t"))
        out = here if out is None else out.unionAll(here)
        above = here.select("qid", F.col("node").alias("parent")).join(q, "qid")
    # the entries tested at a level are the children of the nodes that were left above it
    children = index.nodes.groupBy((F.col("level") + 1).alias("level"), F.col("parent").alias("node")).agg(F.count(F.lit(1)).alias("n"))
    root = q.select("qid", F.lit(index.height + 1).alias("level"), F.lit(0).cast("long").alias("node"))
    tested = out.where("level > 1").select("qid", "level", "node").unionAll(root).join(children, ["level", "node"]).groupBy("qid").agg(F.sum("n").alias("node_reads_distinct"))
    # a surviving inner node is a page that is read for the entries of its children; leaf pages count in the search
    opened = out.groupBy("qid", "level").agg(F.count(F.lit(1)).alias("n")).groupBy("qid").agg(F.sum(F.when(F.col("level") > 1, F.col("n")).otherwise(0)).alias("node_reads"), F.max("n").alias("max_queue"))
    zero = lambda c: F.coalesce(c, F.lit(0).cast("long")).alias(c)
    return out, tested.join(opened, "qid", "left").select("qid", zero("node_reads"), "node_reads_distinct", zero("max_queue"))


def page_bounds(queries: DataFrame, index: Index, leaves: DataFrame, options: RouteOptions, best: DataFrame | None = None) -> DataFrame:
    """``search.bound_arcs`` from the surviving leaf pages alone."""
    q = seen_from_pivots(queries, index)
    q = q.select("qid", "src", "dst", "wtype", "s", *[c for c in PIVOTED if c in q.columns])
    if index.pivots is not None:
        q = q.dropna(subset=PIVOTED)
    arcs = leaves.join(index.pages, "leaf").join(q, "qid")
    h, g = F.lit(0).cast("long"), F.lit(0.0)
    if index.pivots is not None:
        h = lb_time(lb_dist(F.col("head_piv"), F.col("dst_piv")), F.lit(index.vmax))
        g = (60 * lb_dist(F.col("src_piv"), F.col("tail_piv")) / F.lit(index.vmax)).cast("double")
    arcs = arcs.withColumns({"h": h, "g": g})
    if options.use_time:
        arcs = arcs.withColumn("lb", F.floor("g") + F.col("w_min") + F.col("h")).where(F.col("lb") <= options.horizon_min)
        if best is not None:
            arcs = prune_time(arcs, best)
    kwb = keyword_blocked(F.col("kw"), F.col("s")) if options.use_keyword else F.lit(False)
    return arcs.select("qid", "wtype", "tail", "head", "eid", F.col("w_min").alias("w"), "tail_cell", "head_cell", "h", "g", kwb.alias("kwb"), F.col("leaf").alias("page"))


def descend(queries: DataFrame, net: Network, index: Index, options: RouteOptions) -> Descent:
    """All surviving node paths of the leaf level. One round per level; the driver sees counts only."""
    ends = index.lookup.join(net.edges.select("eid", "a", "b"), "eid")
    ends = stored(ends.select(F.explode(F.array("a", "b")).alias("v"), "pos"))
    good = stored(reachable_nodes(queries, index, options)[0])
    links = index.links
    q = queries.select("qid", "src", "dst")
    src, dst = (q.join(ends, q[c] == ends["v"]).select("qid", "pos").distinct() for c in ("src", "dst"))
    paths = reads = None
    history = []

    def at(rows: DataFrame, level: int) -> DataFrame:
        return rows.select("qid", F.floor(F.col("pos") / (index.fanout**level)).alias("node")).distinct()

    for level in range(index.height, 0, -1):
        ok = good.where(F.col("level") == level).select("qid", "node", "lb_t")
        near = links.where(F.col("level") == level).select("n1", "n2")
        goal = at(dst, level).withColumn("goal", F.lit(True))
        start = at(src, level).join(ok, ["qid", "node"])
        touched = at(src, level).select("qid", "node")
        if paths is None:
            grown = start.select("qid", F.array("node").alias("nodes"), F.col("lb_t").alias("lb"), F.lit(False).alias("stopped"), F.lit(1).alias("old"))
            old_max = 1
        else:
            up = paths.select("qid", F.col("nodes").alias("up"), "stopped", F.size("nodes").alias("old"))
            old_max = level_length
            grown = up.join(start, "qid").where(F.floor(F.col("node") / index.fanout) == F.get("up", F.lit(0))).select("qid", "up", "stopped", "old", F.array("node").alias("nodes"), F.col("lb_t").alias("lb"))
            for i in range(1, old_max):
                step = grown.where((F.col("old") > i)).join(near, F.element_at("nodes", -1) == near["n1"]).where(F.floor(F.col("n2") / index.fanout) == F.get("up", F.lit(i)))
                touched = touched.unionAll(step.select("qid", F.col("n2").alias("node")))
                step = step.join(ok.withColumnRenamed("node", "n2"), ["qid", "n2"])
                step = step.select("qid", "up", "stopped", "old", F.concat("nodes", F.array("n2")).alias("nodes"), (F.col("lb") + F.col("lb_t")).alias("lb"))
                if options.use_time:
                    step = step.where(F.col("lb") <= options.horizon_min)
                grown = step.unionByName(grown.where(F.col("old") <= i))
            grown = grown.drop("up").distinct()
        grown = stored(grown)
        arrived = grown.join(goal, (grown["nodes"][F.size(grown["nodes"]) - 1] == goal["node"]) & (grown["qid"] == goal["qid"]), "left_semi").withColumn("stopped", F.lit(True))
        more = grown.where(~F.col("stopped")).join(near, F.element_at("nodes", -1) == near["n1"])
        touched = touched.unionAll(more.select("qid", F.col("n2").alias("node")))
        more = more.join(ok.withColumnRenamed("node", "n2"), ["qid", "n2"]).select(
            "qid", F.concat("nodes", F.array("n2")).alias("nodes"), (F.col("lb") + F.col("lb_t")).alias("lb"), F.lit(False).alias("stopped"))
        if options.use_time:
            more = more.where(F.col("lb") <= options.horizon_min)
        paths = stored(more.unionByName(arrived.select("qid", "nodes", "lb", "stopped")).distinct())
        level_length = old_max + 1
        seen = touched.groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("node").alias("d"))
        size = paths.groupBy("qid").agg(F.count(F.lit(1)).alias("queue"))
        now = seen.join(size, "qid", "left").select("qid", "n", "d", F.coalesce("queue", F.lit(0)).alias("queue"))
        reads = now if reads is None else reads.unionAll(now)
        history.append({"level": level, "paths": paths.count()})
    metrics = reads.groupBy("qid").agg(F.sum("n").alias("node_reads"), F.sum("d").alias("node_reads_distinct"), F.max("queue").alias("max_queue"))
    return Descent(paths.select("qid", "nodes", "stopped"), stored(metrics), history)


def seed_labels(queries: DataFrame, net: Network, index: Index, forecasts: DataFrame, descent: Descent, options: RouteOptions) -> DataFrame:
    """Labels at the ends of the surviving node paths, and labels that have arrived (``done``).

    Prefixes are followed together: a step keeps the labels whose leaves so far begin a surviving path."""
    kinds = queries.select("wtype").distinct()  # one set of arcs for each type asked for
    arcs = net.arcs.join(index.lookup.select("eid", "leaf"), "eid").join(F.broadcast(kinds))
    arcs = with_weather(arcs, net.vertices, station_arrays(forecasts, None)).withColumnRenamed("wtype", "kind")
    q = queries.select("qid", "src", "dst", "dep_min", "wtype", "eps", "alpha_pct", "s")
    paths = stored(descent.paths.withColumn("n", F.size("nodes")))
    longest = paths.agg(F.max("n")).first()[0] or 0
    one = lambda c: F.array(F.col(c).cast("long"))
    none = F.array().cast("array<long>")
    labels = q.select("*", F.col("src").alias("v"), F.col("dep_min").alias("arr"), one("src").alias("vertices"), none.alias("edges"), one("dep_min").alias("arrs"), none.alias("leaves"))
    out = labels.where("src = dst").select("qid", "v", "arr", "vertices", "edges", "arrs", F.lit(True).alias("done"))
    for i in range(1, longest + 1):
        prefixes = paths.where(F.col("n") >= i).select("qid", F.slice("nodes", 1, i).alias("leaves")).distinct()
        step = labels.drop("leaves").join(labels.select("qid", "v", "arr", "vertices", "leaves"), ["qid", "v", "arr", "vertices"]).join(arcs, (F.col("v") == arcs["tail"]) & (F.col("wtype") == arcs["kind"]))
        t = F.col("arr") + F.col("w_min")
        step = step.where(t <= F.col("dep_min") + options.horizon_min).withColumn("leaves", F.concat("leaves", F.array("leaf")))
        if options.use_keyword:
            step = step.where(~keyword_blocked(F.col("kw"), F.col("s")))
        step = step.join(prefixes, ["qid", "leaves"], "left_semi")
        if options.use_weather:
            step = step.where(~trip_blocked(F.col("tail_w"), F.col("tail_p"), F.col("head_w"), F.col("head_p"), F.col("arr"), F.col("w_min"), F.col("eps"), F.col("alpha_pct"), options.unknown))
        if options.path_mode == "simple":
            step = step.where(~F.array_contains("vertices", F.col("head")))
        labels = stored(step.select(*[c for c in q.columns], F.col("head").alias("v"), t.alias("arr"), F.concat("vertices", F.array("head")).alias("vertices"), F.concat("edges", F.array("eid")).alias("edges"), F.concat("arrs", F.array(t)).alias("arrs"), "leaves"))
        keep = ["qid", "v", "arr", "vertices", "edges", "arrs"]
        out = out.unionByName(labels.where("v = dst").select(*keep, F.lit(True).alias("done")))
        labels = labels.where("v <> dst")
        ended = paths.where((F.col("n") == i) & ~F.col("stopped")).select("qid", F.col("nodes").alias("leaves")).distinct()
        out = out.unionByName(labels.join(ended, ["qid", "leaves"], "left_semi").select(*keep, F.lit(False).alias("done")))
    if options.path_mode == "walk":  # of labels at one vertex and minute any one stands for all
        best = F.min_by(F.struct("vertices", "edges", "arrs"), F.struct(F.size("edges"), F.col("vertices")))
        out = out.groupBy("qid", "v", "arr", "done").agg(best.alias("p")).select("qid", "v", "arr", "p.vertices", "p.edges", "p.arrs", "done")
    return stored(out)


def route_index(queries: DataFrame, net: Network, index: Index, forecasts: DataFrame, options: RouteOptions = RouteOptions(), best: DataFrame | None = None) -> DataFrame:
    """Answers and counters of the index-guided router: search.RESULT, node_reads, node_reads_distinct, max_queue.

    The descent leaves each query the leaf pages that a way within the horizon can touch; only their arcs are shipped.
    The search in the task takes labels by arrival plus the least minutes left over arcs that are not blocked throughout.
    node_reads counts inner nodes that are opened, node_reads_distinct the entries tested; ``best``: qid, lam of known answers."""
    ask = seen_from_pivots(queries, index)
    found = search.by_growing_horizons(ask, net, options, lambda q, o: _route_index(q, index, forecasts, o, best))
    return queries.select("qid").join(found, "qid", "left").withColumn("answered", F.coalesce("answered", F.lit(False)))


def _route_index(queries: DataFrame, index: Index, forecasts: DataFrame, options: RouteOptions, best: DataFrame | None) -> DataFrame:
    nodes, counters = reachable_nodes(queries, index, options, best)
    leaves = nodes.where("level = 1").select("qid", F.col("node").alias("leaf"))
    o = replace(options, reverse=options.use_time, extra=options.extra | {"thinned": options.use_weather and index.by_slot is not None})
    arcs = stored(page_bounds(queries, index, leaves, o, best))
    if o.extra.get("far") is not None:
        h = F.lit(0).cast("long")
        if index.pivots is not None:
            h = F.coalesce(lb_time(lb_dist(F.col("src_piv"), F.col("dst_piv")), F.lit(index.vmax)), h)
        queries = queries.withColumn("src_h", h)
    # by itself, as each stage of a plan has the driver note the whole plan's metrics again
    counters = stored(counters)
    found = search.search_in_tasks(queries, arcs, search.plain_seeds(queries), forecasts, o)
    return queries.select("qid").join(found, "qid", "left").join(counters, "qid", "left").withColumn("answered", F.coalesce("answered", F.lit(False)))


def route_index_paths(queries: DataFrame, net: Network, index: Index, forecasts: DataFrame, options: RouteOptions = RouteOptions(), piv: DataFrame | None = None) -> DataFrame:
    """The same answers by node paths: the search starts from the walks in the node paths that survive the descent."""
    descent = descend(queries, net, index, options)
    seeds = seed_labels(queries, net, index, forecasts, descent, options)
    arcs = search.bound_arcs(queries, net, options, piv, index.lookup)
    found = search.search_in_tasks(queries, arcs, seeds, forecasts, options)
    return queries.select("qid").join(found, "qid", "left").join(descent.metrics, "qid", "left").withColumn("answered", F.coalesce("answered", F.lit(False)))


def refine(answers: DataFrame, queries: DataFrame, net: Network, forecasts: DataFrame, unknown: float = 0.0) -> DataFrame:
    """qid, hops, bad_edges, bad_links, bad_times: every hop of every answer checked again from its definition."""
    hops = answers.where("answered").select("qid", F.posexplode("edges").alias("i", "eid"), "vertices", "arr").select(
        "qid", "i", "eid", F.get("vertices", F.col("i")).alias("tail"), F.get("vertices", F.col("i") + 1).alias("head"), F.get("arr", F.col("i")).alias("t0"), F.get("arr", F.col("i") + 1).alias("t1"))
    hops = hops.join(queries.select("qid", "wtype", "eps", "alpha_pct", "s"), "qid").join(net.arcs.withColumn("real", F.lit(True)), ["eid", "tail", "head"], "left")
    x = with_weather(hops, net.vertices, station_arrays(forecasts, None))
    bad = trip_blocked(F.col("tail_w"), F.col("tail_p"), F.col("head_w"), F.col("head_p"), F.col("t0"), F.col("w_min"), F.col("eps"), F.col("alpha_pct"), unknown)
    x = x.select("qid", F.coalesce(bad | keyword_blocked(F.col("kw"), F.col("s")), F.lit(False)).alias("bad"), F.col("w_min").isNull().alias("loose"), (F.col("t1") - F.col("t0") != F.col("w_min")).alias("late"))
    n = lambda c: F.sum(F.coalesce(c, F.lit(True)).cast("long"))
    return x.groupBy("qid").agg(F.count(F.lit(1)).alias("hops"), n(F.col("bad")).alias("bad_edges"), n(F.col("loose")).alias("bad_links"), n(F.col("late")).alias("bad_times"))


def greedy_route(queries: DataFrame, net: Network, forecasts: DataFrame, options: RouteOptions = RouteOptions(), piv: DataFrame | None = None, max_hops: int = 30, beam: int = 8) -> DataFrame:
    """qid and ub_min: minutes of one valid path, found by following the ``beam`` most promising labels."""
    arcs = with_weather(search.bound_arcs(queries, net, replace(options, use_time=True), piv), net.vertices, station_arrays(forecasts, None)).where("not kwb")
    arcs = stored(arcs.select("qid", "tail", "head", "w", "h", "tail_w", "tail_p", "head_w", "head_p"))
    q = queries.select("qid", "dst", "dep_min", "eps", "alpha_pct")
    front = queries.select("qid", F.col("src").alias("v"), F.col("dep_min").alias("arr"), F.array(F.col("src")).alias("seen"))
    # the conditions and columns of a hop, made once
    open_ = ~F.array_contains("seen", F.col("head")) & (F.col("arr") + F.col("w") <= F.col("dep_min") + options.horizon_min)
    safe = ~trip_blocked(F.col("tail_w"), F.col("tail_p"), F.col("head_w"), F.col("head_p"), F.col("arr"), F.col("w"), F.col("eps"), F.col("alpha_pct"), options.unknown)
    after = ["qid", F.col("head").alias("v"), (F.col("arr") + F.col("w")).alias("arr"), F.concat("seen", F.array("head")).alias("seen"), "h", "dst"]
    rank = F.row_number().over(Window.partitionBy("qid").orderBy(F.col("arr") + F.col("h"), "v", "arr"))
    arcs = arcs.withColumnRenamed("tail", "v")
    found = None
    for _ in range(max_hops):
        new = front.join(arcs, ["qid", "v"]).join(q, "qid").where(open_).where(safe).select(*after)
        new = stored(new.withColumn("k", rank).where(F.col("k") <= beam).drop("k"))
        done = new.where("v = dst").select("qid", "arr")
        found = done if found is None else found.unionAll(done)
        front = new.where("v <> dst").drop("h", "dst")
        if front.isEmpty():
            break
    best = found.groupBy("qid").agg(F.min("arr").alias("arr"))
    return q.join(best, "qid").select("qid", (F.col("arr") - F.col("dep_min")).alias("ub_min"))
