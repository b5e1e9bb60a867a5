"""Label search: within a task for one query, or in rounds of joins for a batch.

A label is (query, vertex, arrival minute). Weather varies with time, so a later arrival at a vertex may
succeed where an earlier one fails; labels are merged only at equal vertex and minute."""

from __future__ import annotations

import heapq
from collections.abc import Callable
from dataclasses import replace
from itertools import count
from threading import Lock

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bounds import euclid, lb_dist, lb_time
from ..functions.keywords import keyword_blocked
from ..functions.weather import py_trip_blocked, trip_blocked
from ..operators.storage import stored
from ..schema import RouteOptions
from ..sources.forecasts import station_arrays, with_weather
from ..sources.networks import Network, max_speed

ZONE = 50_000
RESULT = "qid int, answered boolean, total_min long, hops int, vertices array<long>, edges array<long>, arr array<long>, labels long, max_heap long, page_reads long, page_reads_distinct long, settled long, pruned_kw long, pruned_weather long, pruned_time long, no_way boolean"


def bounded_by(options: RouteOptions, pivots: bool, vmax: float) -> Callable[[str, str], F.Column]:
    """The options' bound on the minutes between two ends, of which there are columns _x, _y and _piv."""

    def bound(a: str, b: str) -> F.Column:
        if options.heuristic == "pivot" and pivots:
            return lb_time(lb_dist(F.col(f"{a}_piv"), F.col(f"{b}_piv")), F.lit(vmax))
        if options.heuristic == "euclid":  # lengths are rounded to a milli-mile an edge
            return lb_time(F.greatest(F.lit(0.0), euclid(F.col(f"{a}_x"), F.col(f"{a}_y"), F.col(f"{b}_x"), F.col(f"{b}_y")) - 200), F.lit(vmax))
        return F.lit(0).cast("long")

    return bound


def source_bounds(queries: DataFrame, net: Network, options: RouteOptions, piv: DataFrame | None = None) -> DataFrame:
    """Queries with src_h, the bound from source to destination by which ``bound_arcs`` drops arcs."""
    v = net.vertices.select("v", "x_mm", "y_mm")
    v = v.join(piv, "v") if piv is not None else v.withColumn("piv", F.array().cast("array<long>"))
    q = queries
    for p in ("src", "dst"):
        q = q.join(v.toDF(p, f"{p}_x", f"{p}_y", f"{p}_piv"), p, "left")
    return q.select(*queries.columns, bounded_by(options, piv is not None, max_speed(net.edges) or 1.0)("src", "dst").alias("src_h"))


def bound_arcs(queries: DataFrame, net: Network, options: RouteOptions, piv: DataFrame | None = None, pages: DataFrame | None = None) -> DataFrame:
    """Every arc that a query may use: qid, wtype, tail, head, eid, w, cells, h (time bound from head to dst), g (from src to tail), kwb, page.

    Arcs meet queries by zone of the plane, within what the horizon reaches from the source at top
    speed. With a heuristic, arcs are dropped that can't be on a way within the horizon."""
    v = net.vertices.select("v", "x_mm", "y_mm", "cell")
    vmax = max_speed(net.edges) or 1.0
    reach = int(options.horizon_min * vmax / 60) + 1
    kinds = v.join(piv, "v") if piv is not None else v.withColumn("piv", F.array().cast("array<long>"))
    ends = lambda p: kinds.select(F.col("v").alias(p), F.col("x_mm").alias(f"{p}_x"), F.col("y_mm").alias(f"{p}_y"), F.col("cell").alias(f"{p}_cell"), F.col("piv").alias(f"{p}_piv"))
    q = queries.join(ends("src"), "src").join(ends("dst"), "dst")
    zones = F.sequence(F.floor((F.col("src_x") - reach) / ZONE), F.floor((F.col("src_x") + reach) / ZONE))
    rows = F.sequence(F.floor((F.col("src_y") - reach) / ZONE), F.floor((F.col("src_y") + reach) / ZONE))
    q = q.withColumn("zx", F.explode(zones)).withColumn("zy", F.explode(rows))
    arcs = net.arcs.join(ends("tail"), "tail").join(ends("head"), "head")
    if pages is not None:
        arcs = arcs.join(pages.select("eid", F.col("leaf").alias("page")), "eid")
    else:
        arcs = arcs.withColumn("page", F.floor(F.col("eid") / 56))
    arcs = arcs.withColumns({"zx": F.floor(F.col("tail_x") / ZONE), "zy": F.floor(F.col("tail_y") / ZONE)})
    both = arcs.join(q, ["zx", "zy"])

    bound = bounded_by(options, piv is not None, vmax)
    both = both.withColumn("h", bound("head", "dst"))
    if options.use_time:
        both = both.where(bound("src", "tail") + F.col("w_min") + F.col("h") <= options.horizon_min)
    kwb = keyword_blocked(F.col("kw"), F.col("s")) if options.use_keyword else F.lit(False)
    g = F.lit(0.0)  # not rounded: along an arc it falls by no more than the arc's minutes
    if options.heuristic == "pivot" and piv is not None:
        g = 60 * lb_dist(F.col("src_piv"), F.col("tail_piv")) / F.lit(vmax)
    return both.select("qid", "wtype", "tail", "head", "eid", F.col("w_min").alias("w"), "tail_cell", "head_cell", "h", g.cast("double").alias("g"), kwb.alias("kwb"), "page")


def query_stations(queries: DataFrame, arcs: DataFrame, forecasts: DataFrame) -> DataFrame:
    """qid, cell, values, confs of the stations that a query's arcs lie at, of its own type."""
    cells = arcs.select("qid", "wtype", F.explode(F.array("tail_cell", "head_cell")).alias("cell")).distinct()
    return cells.join(all_stations(forecasts), ["cell", "wtype"]).select("qid", "cell", "values", "confs")


def all_stations(forecasts: DataFrame) -> DataFrame:
    """``station_arrays`` of all types, once for all batches on these forecasts."""
    known = forecasts.__dict__.setdefault("_stations", [])
    with _stations_lock:
        if not known:
            known.append(stored(station_arrays(forecasts, None)))
    return known[0]


class LimitReached(RuntimeError):
    """A limit set by the caller was met while labels were open: there is no answer to give."""


def within_limit(labels: int, options: RouteOptions) -> None:
    if options.label_limit and labels >= options.label_limit:
        raise LimitReached(f"{labels} labels, and more are open")


def best_simple(ways: dict, seeds: list, dst: int, dep: int, eps: float, alpha: int, weather: dict, options: RouteOptions, arrivals: list = ()) -> dict:
    """``best_first`` over paths that repeat no vertex, exact however many paths there are.

    First every (vertex, minute) that walks lead to is found, then backwards the earliest arrival at dst from
    each and the vertices on walks from it to dst. The arrival is the key; of labels at one vertex and minute
    one stands for all those that have visited what it has, as far as these vertices go."""
    limit = dep + options.horizon_min
    lam, best = min(((arr, (vs, es, ts)) for _, arr, vs, es, ts in arrivals), default=(float("inf"), None), key=lambda x: x[0])
    h_of = {x[0]: x[5] for out in ways.values() for x in out}
    open_, after = sorted({(arr, v) for v, arr, *_ in seeds}), {}
    labels = max_heap = reads = n_kw = n_weather = n_time = 0
    pages: set = set()
    queued = set(open_)
    while open_:
        max_heap = max(max_heap, len(open_))
        arr, v = heapq.heappop(open_)
        on = after[v, arr] = []
        if v == dst:
            continue
        own = {x[8] for x in ways.get(v, ())}
        reads += len(own)
        pages |= own
        for head, w, eid, c1, c2, h, _, kwb, _ in ways.get(v, ()):
            t = arr + w
            if kwb:
                n_kw += 1
            elif t > limit or (options.use_time and t + h > min(lam, limit)):
                n_time += 1
            elif options.use_weather and py_trip_blocked(weather[c1], weather[c2], arr, w, eps, alpha, options.unknown):
                n_weather += 1
            else:
                on.append((head, t, eid))
                if (t, head) not in queued:
                    queued.add((t, head))
                    heapq.heappush(open_, (t, head))
    bit = {v: 1 << i for i, v in enumerate(sorted({v for v, _ in after}))}
    goal, ahead = {}, {}
    for v, arr in sorted(after, key=lambda x: -x[1]):
        on = after[v, arr] = [x for x in after[v, arr] if (x[0], x[1]) in goal]
        if v == dst or on:
            goal[v, arr] = arr if v == dst else min(goal[x[0], x[1]] for x in on)
            reach = bit[v]
            for x in on:
                reach |= ahead[x[0], x[1]]
            ahead[v, arr] = reach
    heap, stand = [], {}

    def push(v: int, arr: int, hops: int, seen: int, path: tuple) -> None:
        seen &= ahead[v, arr]
        others = stand.setdefault((v, arr), [])
        if not any(o & ~seen == 0 for o in others):
            others.append(seen)
            heapq.heappush(heap, (goal[v, arr], arr, hops, v, seen, path))

    for v, arr, vs, es, ts in seeds:
        if (v, arr) in goal:
            push(v, arr, len(es), sum(bit.get(x, 0) for x in set(vs)), (vs, es, ts))
    while heap:
        max_heap = max(max_heap, len(heap))
        key, arr, hops, v, seen, path = heapq.heappop(heap)
        if key > lam:
            break
        within_limit(labels, options)
        labels += 1
        if v == dst:
            tail = []
            while len(path) == 4:
                tail.append(path[1:])
                path = path[0]
            vs, es, ts = path
            best = [*vs, *(x[0] for x in tail[::-1])], [*es, *(x[1] for x in tail[::-1])], [*ts, *(x[2] for x in tail[::-1])]
            break
        for head, t, eid in after[v, arr]:
            if not seen & bit[head]:
                push(head, t, hops + 1, seen | bit[head], (path, head, eid, t))
    counts = {"labels": labels, "max_heap": max_heap, "page_reads": reads, "page_reads_distinct": len(pages), "settled": 0, "pruned_kw": n_kw, "pruned_weather": n_weather, "pruned_time": n_time}
    return result(best, dep) | counts


class Back:
    """Least minutes to dst over the arcs that are not blocked throughout, found back from dst as far as asked.

    Vertices are settled in order of their distance plus the bound g from the source, which is consistent, so a settled
    distance is exact for these arcs and a lower bound for all walks."""

    def __init__(self, ways: dict, dst: int, cap: float, shut) -> None:  # noqa: ANN001
        self.into: dict[int, list] = {}
        for tail, out in ways.items():
            for head, w, _, c1, c2, _, g, kwb, page in out:
                if not kwb and not shut(c1, c2):
                    self.into.setdefault(head, []).append((tail, w, g, page))
        self.cap, self.done, self.heap, self.reads, self.pages = cap, {}, [(0.0, 0, dst)], 0, set()

    def to(self, v: int) -> float:
        done, heap = self.done, self.heap
        while v not in done and heap:
            key, d, u = heapq.heappop(heap)
            if key > self.cap:
                heap.clear()
            elif u not in done:
                done[u] = d
                own = self.into.get(u, ())
                read = {x[3] for x in own}
                self.reads += len(read)
                self.pages |= read
                for tail, w, g, _ in own:
                    if tail not in done:
                        heapq.heappush(heap, (d + w + g, d + w, tail))
        return done.get(v, float("inf"))


def shut_throughout(weather: dict, dep: int, options: RouteOptions, eps: float, alpha: int):  # noqa: ANN201
    """(tail cell, head cell) -> whether a trip is blocked at its start, or at its end, in every slot that it can fall in."""
    slots = range(dep // 60, (dep + options.horizon_min) // 60 + 1)
    known: dict = {}

    def shut(c1: int, c2: int) -> bool:
        if (c1, c2) not in known:
            start = end = True
            for s in slots:
                i = s % 24
                wj, pj, wk, pk = weather[c1][0][i], weather[c1][1][i], weather[c2][0][i], weather[c2][1][i]
                p = (pj * (100 - pk) if wj > eps else 0) + ((100 - pj) * pk if wk > eps else 0) + (100 - pj) * (100 - pk) * options.unknown
                start = start and p + (pj * pk if wj > eps else 0) >= 100 * alpha
                end = end and p + (pj * pk if wk > eps else 0) >= 100 * alpha
            known[c1, c2] = options.use_weather and (start or end)
        return known[c1, c2]

    return shut


def result(best: tuple | None, dep: int) -> dict:
    if best is None:
        return {"answered": False, "total_min": None, "hops": None, "vertices": None, "edges": None, "arr": None}
    return {"answered": True, "total_min": best[2][-1] - dep, "hops": len(best[1]), "vertices": best[0], "edges": best[1], "arr": best[2]}


def best_first(ways: dict, seeds: list, dst: int, dep: int, eps: float, alpha: int, weather: dict, options: RouteOptions, arrivals: list = ()) -> dict:
    """The earliest arrival at dst from labels (v, arr, vertices, edges, arrs), with counters.

    ``ways``: tail -> [(head, w, eid, tail cell, head cell, h, g, blocked by keyword, page)]; ``arrivals``: finished labels."""
    if options.path_mode == "simple":
        return best_simple(ways, seeds, dst, dep, eps, alpha, weather, options, arrivals)
    astar = options.key == "elapsed_plus_lb"
    lam, best = float("inf"), None
    limit = dep + options.horizon_min
    heap: list = []
    h_of = {x[0]: x[5] for out in ways.values() for x in out}
    parent: dict = {}
    labels = max_heap = reads = n_kw = n_weather = n_time = 0
    pages: set = set()
    back = Back(ways, dst, options.horizon_min, shut_throughout(weather, dep, options, eps, alpha)) if options.reverse and options.use_time else None
    for v, arr, vs, es, ts in arrivals:
        if arr < lam:
            lam, best = arr, (vs, es, ts)
    for v, arr, vs, es, ts in seeds:
        if (v, arr) not in parent:
            parent[v, arr] = (vs, es, ts)
            rest = back.to(v) if back else h_of.get(v, 0)
            if arr + rest <= limit:
                heapq.heappush(heap, (arr + (rest if astar else 0), arr, len(es), v))
    found = None
    while heap:
        max_heap = max(max_heap, len(heap))
        key, arr, hops, v = heapq.heappop(heap)
        if key > lam:
            break
        within_limit(labels, options)
        labels += 1
        if v == dst and arr <= lam:
            lam, found = arr, (v, arr)
            break
        out = ways.get(v, ())
        own = {x[8] for x in out}
        reads += len(own)
        pages |= own
        for head, w, eid, c1, c2, h, _, kwb, _ in out:
            if kwb:
                n_kw += 1
                continue
            t = arr + w
            if t > limit or (options.use_time and t + h > min(lam, limit)):
                n_time += 1
                continue
            if (head, t) in parent:
                continue
            if back and t + (h := back.to(head)) > min(lam, limit):
                n_time += 1
                continue
            if options.use_weather and py_trip_blocked(weather[c1], weather[c2], arr, w, eps, alpha, options.unknown):
                n_weather += 1
                continue
            parent[head, t] = (v, arr, eid)
            if head == dst:
                lam = min(lam, t)
            heapq.heappush(heap, (t + (h if astar else 0), t, hops + 1, head))
    if found:
        v, arr = found
        vs, es, ts = [], [], []
        while len(p := parent[v, arr]) and not isinstance(p[0], list):
            vs.append(v)
            es.append(p[2])
            ts.append(arr)
            v, arr = p[0], p[1]
        best = (p[0] + vs[::-1], p[1] + es[::-1], p[2] + ts[::-1])
    settled = 0
    if back:
        settled, reads, pages = len(back.done), reads + back.reads, pages | back.pages
    counts = {"labels": labels, "max_heap": max_heap, "page_reads": reads, "page_reads_distinct": len(pages), "settled": settled, "pruned_kw": n_kw, "pruned_weather": n_weather, "pruned_time": n_time}
    return result(best, dep) | counts


def no_way(ways: dict, seeds: list, dst: int, dep: int, eps: float, alpha: int, weather: dict, options: RouteOptions, far: dict, src_h: int) -> bool:
    """Whether there is no way within any horizon, shown by what was shipped for this one.

    Either all labels from the source come to an end, or roads free of keywords lead from the source, or back from dst, to few vertices only, before
    arcs can be missing. ``far``: the longest arc at a vertex; at e minutes from the source and h from dst, by their bounds, the arcs there are
    all shipped where e + 2 far + h (and a minute for each rounding) are within the horizon. Repeated vertices are allowed here, which
    only finds more ways. Where pages went out by weather (extra: thinned), roads aren't followed without their hours."""
    h_of = {x[0]: x[5] for out in ways.values() for x in out} | {v: src_h for v, *_ in seeds}
    if not seeds:
        return False
    room = options.horizon_min - 5
    heap, seen = [(arr, v) for v, arr, *_ in seeds], {(v, arr) for v, arr, *_ in seeds}
    while heap:
        arr, v = heapq.heappop(heap)
        if v == dst or arr - dep + 2 * far[v] + h_of[v] > room:
            break
        for head, w, _, c1, c2, _, _, kwb, _ in ways.get(v, ()):
            free = not kwb and not (options.use_weather and py_trip_blocked(weather[c1], weather[c2], arr, w, eps, alpha, options.unknown))
            if free and (head, arr + w) not in seen:
                seen.add((head, arr + w))
                heapq.heappush(heap, (arr + w, head))
    else:
        return True
    if options.extra.get("thinned"):
        return False
    sources, on, back = {v for v, *_ in seeds}, {}, {}
    for tail, out in ways.items():
        for head, w, _, _, _, _, _, kwb, _ in out:
            if not kwb:
                on.setdefault(tail, []).append((head, w))
                back.setdefault(head, []).append((tail, w))

    def closed(links: dict, ends: set, others: set, rest: Callable[[int, int], int]) -> bool:
        heap, known = [(0, v) for v in ends], set()
        while heap:
            d, v = heapq.heappop(heap)
            if v in others or v not in far or d + 2 * far[v] + rest(v, d) > room:
                return False
            if v not in known:
                known.add(v)
                for u, w in links.get(v, ()):
                    heapq.heappush(heap, (d + w, u))
        return True

    # back from dst, a vertex is at most so far from the source as dst is and the way between them
    return closed(on, sources, {dst}, lambda v, d: h_of[v]) or closed(back, {dst}, sources, lambda v, d: d + src_h)


def search_in_tasks(queries: DataFrame, arcs: DataFrame, seeds: DataFrame, forecasts: DataFrame, options: RouteOptions) -> DataFrame:
    """One task per query: its arcs meet its seeds (qid, v, arr, vertices, edges, arrs, done) and stations by cogroup.

    With ``far`` (v, far) in the options' extra and src_h in the queries, those without an answer are tested by ``no_way``."""
    ask = queries.select("qid", "src", "dst", "dep_min", "eps", "alpha_pct")
    far = options.extra.get("far")
    options = replace(options, extra={k: x for k, x in options.extra.items() if k != "far"})
    tested = far is not None and "src_h" in queries.columns
    if tested:
        longest = F.coalesce("far", F.lit(0)).alias("far")
        arcs = arcs.join(far.withColumnRenamed("v", "head"), "head", "left").select(*arcs.columns, longest)
        ask = queries.select(*ask.columns, "src_h", "src_far")
    at = query_stations(queries, arcs, forecasts)
    heads = ask.join(seeds.unionByName(at, allowMissingColumns=True), "qid", "left")

    def solve(key: tuple, a: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        if not len(q):
            return pd.DataFrame(columns=[x.split()[0] for x in RESULT.split(", ")])
        ways: dict = {}
        for t, *rest in zip(*(a[c].tolist() for c in ("tail", "head", "w", "eid", "tail_cell", "head_cell", "h", "g", "kwb", "page")), strict=True):
            ways.setdefault(t, []).append(tuple(rest))
        for t in ways:
            ways[t].sort()
        none = ([0.0] * 24, [0] * 24)
        weather = {c: none for out in ways.values() for x in out for c in x[3:5]}
        one = q.iloc[0]
        start, done = [], []
        for v, arr, vs, es, ts, end, cell, values, confs in zip(*(q[c] for c in ("v", "arr", "vertices", "edges", "arrs", "done", "cell", "values", "confs")), strict=True):
            if values is not None:
                weather[int(cell)] = list(map(float, values)), list(map(int, confs))
            elif vs is not None and len(vs):
                (done if end else start).append((int(v), int(arr), list(map(int, vs)), list(map(int, es)), list(map(int, ts))))
        start.sort()
        done.sort(key=lambda x: (x[1], len(x[3]), x[2]))
        out = best_first(ways, start, int(one["dst"]), int(one["dep_min"]), float(one["eps"]), int(one["alpha_pct"]), weather, options, done)
        out["no_way"] = False
        if tested and not out["answered"] and not done:
            ends = dict(zip(a["head"].tolist(), a["far"].tolist(), strict=True)) | {int(one["src"]): int(one["src_far"])}
            out["no_way"] = no_way(ways, start, int(one["dst"]), int(one["dep_min"]), float(one["eps"]), int(one["alpha_pct"]), weather, options, ends, int(one["src_h"]))
        return pd.DataFrame([{"qid": int(key[0])} | out])

    return arcs.groupBy("qid").cogroup(heads.withColumnRenamed("qid", "asked").groupBy("asked")).applyInPandas(solve, RESULT)


#: Most arcs that a query's whole horizon is searched over at once; larger networks are searched by growing horizons.
WHOLE_ARCS = 250_000
_far_lock, _stations_lock = Lock(), Lock()
COUNTERS = ("labels", "page_reads", "page_reads_distinct", "settled", "pruned_kw", "pruned_weather", "pruned_time", "node_reads", "node_reads_distinct")


def by_growing_horizons(queries: DataFrame, net: Network, options: RouteOptions, run: Callable[[DataFrame, RouteOptions], DataFrame], first: int = 24) -> DataFrame:
    """``run(queries, options)`` with a short horizon first, and one four times, then twice as long for the queries without an answer, up to the given one.

    The earliest arrival within a short horizon is the earliest of all, so an answer stands; a query without one is settled by
    ``no_way`` or by the whole horizon. Counters are summed over the horizons, maxima kept. Arcs shipped and labels opened grow with the horizon, not with the network."""
    horizon = first
    if horizon >= options.horizon_min or net.edges.count() * 2 <= WHOLE_ARCS:
        return run(queries, options)
    # arcs beyond the whole horizon are on no way
    known = net.__dict__.setdefault("_far", {})  # once for all batches on a network
    with _far_lock:
        if options.horizon_min not in known:
            known[options.horizon_min] = stored(net.arcs.where(F.col("w_min") <= options.horizon_min).groupBy(F.col("tail").alias("v")).agg(F.max("w_min").alias("far")))
    far = known[options.horizon_min]
    options = replace(options, extra=options.extra | {"far": far})
    # of the sources, which are few, once for all horizons
    own = far.join(F.broadcast(queries.select(F.col("src").alias("v")).distinct()), "v").toDF("src", "src_far")
    queries = stored(queries.join(own, "src", "left").withColumn("src_far", F.coalesce("src_far", F.lit(0).cast("long"))))
    open_, out = queries, None
    while True:
        last = horizon >= options.horizon_min
        got = stored(run(open_, replace(options, horizon_min=min(horizon, options.horizon_min))))
        out = got if out is None else out.unionByName(got)
        unsettled = got.where("not answered and not coalesce(no_way, false)").select("qid")
        if last or unsettled.isEmpty():
            break
        open_, horizon = stored(queries.join(unsettled, "qid", "left_semi")), horizon * (4 if horizon == first else 2)
    # a query's last row has its answer; there is one answered row at most
    aggs = []
    for c in out.columns:
        if c != "qid":
            f = F.sum if c in COUNTERS else F.max if c.startswith("max_") else F.bool_or if c in ("answered", "no_way") else None
            aggs.append((f(c) if f else F.max_by(c, F.col("answered").cast("int"))).alias(c))
    return stored(out.groupBy("qid").agg(*aggs).select(*out.columns))


def plain_seeds(queries: DataFrame) -> DataFrame:
    """The start of every query as its only label."""
    one = lambda c: F.array(F.col(c).cast("long"))
    return queries.select("qid", F.col("src").alias("v"), F.col("dep_min").alias("arr"), one("src").alias("vertices"), F.array().cast("array<long>").alias("edges"), one("dep_min").alias("arrs"), F.lit(False).alias("done"))


def search_in_rounds(queries: DataFrame, net: Network, forecasts: DataFrame, options: RouteOptions, piv: DataFrame | None = None, max_rounds: int | None = None) -> tuple[DataFrame, list[dict]]:
    """The same search for whole batches by joins: (qid, answered, total_min), and counts per round.

    Each round takes the ``batch_width`` labels of smallest key of every query (all, if None), joins the
    arcs by query and tail, tests keywords, trips and time, merges equal labels and lowers each query's best
    arrival, until no label is open; ``max_rounds`` raises where labels still are. The driver sees counts only;
    tables are cut every round."""
    arcs = with_weather(bound_arcs(queries, net, options, piv), net.vertices, station_arrays(forecasts, None)).where(~F.col("kwb"))
    arcs = stored(arcs.select("qid", "tail", "head", "eid", "w", "h", "tail_w", "tail_p", "head_w", "head_p"))
    q = queries.select("qid", "dst", "dep_min", "eps", "alpha_pct")
    seen = stored(queries.select("qid", F.col("src").alias("v"), F.col("dep_min").alias("arr"), F.lit(0).cast("long").alias("h")))
    open_, lam, history = seen, None, []
    for n in count():
        if max_rounds is not None and n >= max_rounds:
            raise LimitReached(f"{n} rounds, and {history[-1]['open'] if history else 'all'} labels are open")
        if options.batch_width:
            key = F.col("arr") + (F.col("h") if options.key == "elapsed_plus_lb" else 0)
            ranked = open_.withColumn("k", F.row_number().over(Window.partitionBy("qid").orderBy(key, "arr", "v")))
            front, wait = ranked.where(F.col("k") <= options.batch_width).drop("k"), ranked.where(F.col("k") > options.batch_width).drop("k")
        else:
            front, wait = open_, None
        step = front.drop("h").join(arcs.withColumnRenamed("tail", "v"), ["qid", "v"]).join(q, "qid")
        t = F.col("arr") + F.col("w")
        step = step.where((t <= F.col("dep_min") + options.horizon_min) & (F.col("v") != F.col("dst")))
        if options.use_weather:
            step = step.where(~trip_blocked(F.col("tail_w"), F.col("tail_p"), F.col("head_w"), F.col("head_p"), F.col("arr"), F.col("w"), F.col("eps"), F.col("alpha_pct"), options.unknown))
        new = step.select("qid", F.col("head").alias("v"), t.alias("arr"), "h").distinct().join(seen.select("qid", "v", "arr"), ["qid", "v", "arr"], "left_anti")
        new = stored(new)
        seen = stored(seen.unionByName(new)) if n % 8 == 7 else seen.unionByName(new)
        at_dst = new.join(q.select("qid", "dst"), "qid").where("v = dst").groupBy("qid").agg(F.min("arr").alias("lam"))
        lam = at_dst if lam is None else lam.unionAll(at_dst).groupBy("qid").agg(F.min("lam").alias("lam"))
        lam = stored(lam)
        open_ = new if wait is None else new.unionByName(wait)
        if options.use_time:
            open_ = open_.join(lam, "qid", "left").where(F.col("lam").isNull() | (F.col("arr") + F.col("h") < F.col("lam"))).drop("lam")
        open_ = stored(open_)
        left = open_.count()
        history.append({"round": n, "new": new.count(), "open": left})
        if not left:
            break
    out = q.join(lam, "qid", "left").select("qid", F.col("lam").isNotNull().alias("answered"), (F.col("lam") - F.col("dep_min")).alias("total_min"))
    return out, history
