"""Graph helpers over arcs: hops, components, shortest paths; rounds of joins and partial aggregates."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import stored


def degrees(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("a", "b")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("degree"))


def bfs_hops(arcs: DataFrame, sources: DataFrame, max_hops: int) -> DataFrame:
    """qid, v, hops for all vertices within max_hops of each source (columns qid, src)."""
    ways = stored(arcs.select("tail", "head").distinct())  # read anew in each hop, not found anew
    seen = sources.select("qid", F.col("src").alias("v"), F.lit(0).alias("hops"))
    front = seen
    for hop in range(1, max_hops + 1):
        step = front.join(ways, front["v"] == ways["tail"]).select("qid", F.col("head").alias("v")).distinct()
        front = stored(step.join(seen.select("qid", "v"), ["qid", "v"], "left_anti").withColumn("hops", F.lit(hop)))
        seen = seen.unionByName(front)
        if front.isEmpty():
            break
    return seen


def sssp(arcs: DataFrame, sources: DataFrame, weight: str = "len_mm", rounds_per_cut: int = 4) -> DataFrame:
    """src, v, dist from every source (column src); several sources relax together.

    Only vertices whose distance fell in the last round send messages. The tables are cut every round;
    the loop ends when nothing falls."""
    ways = stored(arcs.select("tail", "head", F.col(weight).alias("weight")))
    dist = stored(sources.select("src", F.col("src").alias("v"), F.lit(0).cast("long").alias("dist")))
    front = dist
    while True:
        sent = front.join(ways, front["v"] == ways["tail"]).groupBy("src", "head").agg(F.min(F.col("dist") + F.col("weight")).alias("new"))
        both = dist.withColumnRenamed("dist", "old").join(sent.withColumnRenamed("head", "v"), ["src", "v"], "full")
        both = stored(both.select("src", "v", F.least("old", "new").alias("dist"), (F.col("old").isNull() | (F.col("new") < F.col("old"))).alias("fell")))
        dist, front = both.select("src", "v", "dist"), both.where(F.coalesce("fell", F.lit(False))).select("src", "v", "dist")
        if front.isEmpty():
            return dist


def solve_lot(tail: np.ndarray, head: np.ndarray, weight: np.ndarray, sources: np.ndarray, only: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """src, v, dist from all sources at once; ``only``: the vertices whose distances are given, None for all.

    A state is a vertex of one source. States are taken by bands of their distance, the whole band at a time and again
    while distances in it fall, so a band ends with its distances final."""
    names = np.unique(np.concatenate([tail, head, sources]))
    n, k = len(names), len(sources)
    order = np.argsort(tail, kind="stable")
    to, cost = np.searchsorted(names, head[order]), weight[order]
    ptr = np.searchsorted(tail[order], np.append(names, names[-1] + 1))
    degree = np.diff(ptr)
    band = max(1, int(cost.mean())) if len(cost) else 1
    far = np.iinfo(np.int64).max
    dist, place, waits = np.full(k * n, far), np.zeros(k * n, np.int32), np.zeros(k * n, bool)
    later = np.arange(k) * n + np.searchsorted(names, sources)
    dist[later] = 0
    while len(later):
        d = dist[later]
        top = d.min() + band
        now, later = later[d < top], later[d >= top]
        waits[now] = False
        while len(now):
            v = now % n
            out = degree[v]
            at = np.repeat(ptr[v] - np.cumsum(out) + out, out) + np.arange(out.sum())
            state, new = np.repeat(now - v, out) + to[at], np.repeat(dist[now], out) + cost[at]
            less = new < dist[state]
            state, new = state[less], new[less]
            np.minimum.at(dist, state, new)
            place[state] = np.arange(len(state))
            state = state[place[state] == np.arange(len(state))]  # each once
            near = dist[state] < top
            now, wait = state[near], state[~near]
            wait = wait[~waits[wait]]
            waits[wait] = True
            later = np.concatenate([later, wait])
    dist = dist.reshape(k, n)
    if only is not None:
        kept = np.isin(names, only)
        names, dist = names[kept], dist[:, kept]
    i, j = np.nonzero(dist != far)
    return sources[i], names[j], dist[i, j]


def sssp_local(arcs: DataFrame, sources: DataFrame, weight: str = "len_mm", only: DataFrame | None = None) -> DataFrame:
    """As ``sssp`` where one network's arcs fit a task: sources are solved in lots, a task each. ``only``: the vertices (v) asked for."""
    import pandas as pd

    asked, whole = sources.select("src").distinct(), only is None
    k = asked.count()
    lots = max(1, min(-(-k // 3), max(8, -(-k // 16))))  # three sources take little longer than one
    each = F.explode(F.sequence(F.lit(0), F.lit(lots - 1)))
    # arcs go as few rows of arrays, so that no lot is sorted arc by arc
    ways = ("tail", "head", "weight")
    packs = arcs.select("tail", "head", F.col(weight).alias("weight")).groupBy(F.pmod(F.xxhash64("tail"), F.lit(64)).alias("pack")).agg(*[F.collect_list(c).alias(c) for c in ways])
    shipped = packs.drop("pack").withColumn("lot", each)
    # dealt by their order, as there are few of them
    dealt = asked.select(F.pmod(F.row_number().over(Window.orderBy("src")), F.lit(lots)).alias("deal"), "src", F.lit(None).cast("long").alias("v"))
    if only is not None:
        dealt = dealt.unionByName(only.select("v").distinct().select(each.alias("deal"), F.lit(None).cast("long").alias("src"), "v"))

    def solve(key: tuple, a: pd.DataFrame, s: pd.DataFrame) -> pd.DataFrame:
        column = lambda c: c.to_numpy(np.int64)
        wanted = None if whole else column(s["v"].dropna())
        out = solve_lot(*[np.concatenate([np.empty(0, np.int64), *a[c]]).astype(np.int64) for c in ways], column(s["src"].dropna()), wanted)
        return pd.DataFrame(dict(zip(("src", "v", "dist"), out, strict=True)))

    return shipped.groupBy("lot").cogroup(dealt.groupBy("deal")).applyInPandas(solve, "src long, v long, dist long")


def regions(vertices: DataFrame, n_arcs: int, arcs_per_region: int = 250_000) -> DataFrame:
    """v, region, and also: other regions that v is near to. A region has neighbouring strips of a network and about so many arcs;
    near it are a tenth as many strips on both sides. Where there are no strips, regions go by hash and nothing is near."""
    parts = max(1, -(-n_arcs // arcs_per_region))
    if "strip" not in vertices.columns:
        return vertices.select("v", F.pmod(F.xxhash64("v"), F.lit(parts)).cast("int").alias("region"), F.array().cast("array<int>").alias("also"))
    strips = 1 + (vertices.agg(F.max("strip")).first()[0] or 0)
    at = lambda s: F.floor(F.greatest(F.lit(0), F.least(F.lit(strips - 1), s)) * parts / strips).cast("int")
    near = strips // (10 * parts)
    own, below, above = at(F.col("strip")), at(F.col("strip") - near), at(F.col("strip") + near)
    return vertices.select("v", own.alias("region"), F.array_distinct(F.filter(F.array(below, above), lambda r: r != own)).alias("also"))


def sssp_regions(arcs: DataFrame, sources: DataFrame, place: DataFrame, weight: str = "len_mm") -> DataFrame:
    """As ``sssp`` by regions (``place``: v, region, also), so that rounds grow with the regions a way crosses, not with its arcs.

    What is known of a region from outside are its entries: the least distance at each vertex that an arc from another region,
    or a source, leads to. A round searches each region with a lower entry, for each such source, in one task from all its entries, and sends
    what leaves the region. The search goes on over the arcs near the region, so that a way that winds along a border needs no round
    for each crossing. When no entry falls, every region is searched once more for all its vertices."""
    import heapq

    import pandas as pd

    at = stored(place.select("v", "region"))
    ends = place.select("v", "region", "also")
    ways = arcs.select("tail", "head", F.col(weight).alias("weight")).join(ends.toDF("tail", "home", "also"), "tail").join(at.toDF("head", "there"), "head")
    ways = ways.groupBy("home", "also", "tail", "head", "there").agg(F.min("weight").alias("weight"))
    ways = stored(ways.select(F.explode(F.concat(F.array("home"), "also")).alias("region"), "home", "tail", "head", "there", "weight"))
    n_lots = max(8, -(-sources.count() // 8))
    entries = stored(sources.select("src").distinct().join(at, F.col("src") == F.col("v")).select("src", "region", "v", F.lit(0).cast("long").alias("dist"), F.lit(True).alias("fell")))

    def searched(known: DataFrame, leaving: bool) -> DataFrame:
        def solve(key: tuple, a: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
            ways: dict[int, list] = {}
            for t, h, w in zip(a["tail"].tolist(), a["head"].tolist(), a["weight"].tolist(), strict=True):
                ways.setdefault(t, []).append((h, w))
            gone = a[(a["home"] == key[0]) & (a["there"] != key[0])]
            out = list(zip(gone["tail"].tolist(), gone["head"].tolist(), gone["weight"].tolist(), strict=True))
            owned = set(a.loc[a["home"] == key[0], "tail"].tolist()) | set(e["v"].tolist())
            parts = []
            for src, own in e.groupby("src"):
                heap = list(zip(own["dist"].tolist(), own["v"].tolist(), strict=True))
                heapq.heapify(heap)
                best: dict[int, int] = {}
                while heap:
                    d, v = heapq.heappop(heap)
                    if v not in best:
                        best[v] = d
                        for h, w in ways.get(v, ()):
                            if h not in best:
                                heapq.heappush(heap, (d + w, h))
                if leaving:
                    far: dict[int, int] = {}
                    for t, h, w in out:
                        if t in best and best[t] + w < far.get(h, best[t] + w + 1):
                            far[h] = best[t] + w
                    best = far
                else:
                    best = {v: d for v, d in best.items() if v in owned}
                parts.append(pd.DataFrame({"src": src, "v": list(best), "dist": list(best.values())}, dtype="int64"))
            return pd.concat(parts) if parts else pd.DataFrame({"src": [], "v": [], "dist": []}, dtype="int64")

        # sources in groups, so that a task's result is bounded and all cores have work
        dealt = known.withColumn("lot", F.pmod(F.xxhash64("src"), F.lit(n_lots)))
        lots = dealt.select("region", "lot").distinct().toDF("region", "deal")
        return ways.join(F.broadcast(lots), "region").groupBy("region", "deal").cogroup(dealt.groupBy("region", "lot")).applyInPandas(solve, "src long, v long, dist long")

    while True:
        now = entries.where("fell").select("src", "region").distinct()
        sent = searched(entries.join(now, ["src", "region"], "left_semi"), True)
        both = entries.select("src", "region", "v", F.col("dist").alias("old"), F.lit(None).cast("long").alias("new"))
        both = both.unionByName(sent.join(at, "v").select("src", "region", "v", F.lit(None).cast("long").alias("old"), F.col("dist").alias("new")))
        both = both.groupBy("src", "region", "v").agg(F.min("old").alias("old"), F.min("new").alias("new"))
        entries = stored(both.select("src", "region", "v", F.least("old", "new").alias("dist"), (F.col("old").isNull() | (F.coalesce("new", "old") < F.col("old"))).alias("fell")))
        if entries.where("fell").isEmpty():
            return searched(entries, False)  # also of regions without an arc, whose entries are their own answers


#: Arcs of a region, and how many times as many ``distances`` ships whole to a task for a lot of sources (24 octets an arc).
LOCAL_ARCS = 250_000
WHOLE_TIMES = 12


def distances(arcs: DataFrame, sources: DataFrame, weight: str = "len_mm", vertices: DataFrame | None = None, only: DataFrame | None = None) -> DataFrame:
    """src, v, dist: in a task for each lot of sources up to WHOLE_TIMES * LOCAL_ARCS arcs, else by regions of ``vertices``, or in rounds without them.

    ``only``: the vertices (v) whose distances are given."""
    n = arcs.count()
    if n <= WHOLE_TIMES * LOCAL_ARCS:
        return sssp_local(arcs, sources, weight, only)
    dist = sssp(arcs, sources, weight) if vertices is None else sssp_regions(arcs, sources, regions(vertices, n, LOCAL_ARCS), weight)
    return dist if only is None else dist.join(only.select("v").distinct(), "v", "left_semi").select("src", "v", "dist")


def components(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """v and component (its smallest vertex): within regions first, in a task each, then over the regions' components in rounds.

    Only edges between regions, as pairs of the components at their ends, are left to the rounds."""
    n = edges.count()
    if n <= LOCAL_ARCS // 2:
        return component_rounds(vertices.select("v"), edges)
    import pandas as pd

    at = stored(regions(vertices, 2 * n, LOCAL_ARCS).select("v", "region"))
    ends = stored(edges.select("a", "b").join(at.toDF("a", "ra"), "a").join(at.toDF("b", "rb"), "b"))

    def joined(key: tuple, own: pd.DataFrame) -> pd.DataFrame:
        up: dict[int, int] = {}

        def top(v: int) -> int:
            while up.setdefault(v, v) != v:
                up[v] = v = up[up[v]]
            return v

        for a, b in zip(own["a"].tolist(), own["b"].tolist(), strict=True):
            x, y = top(a), top(b)
            up[max(x, y)] = min(x, y)
        return pd.DataFrame({"v": list(up), "l": [top(v) for v in up]}, dtype="int64")

    inner = ends.where("ra = rb").groupBy("ra").applyInPandas(joined, "v long, l long")
    labels = stored(vertices.select("v").join(inner, "v", "left").select("v", F.coalesce("l", "v").alias("l")))
    between = ends.where("ra <> rb").select("a", "b").join(labels.toDF("a", "la"), "a").join(labels.toDF("b", "lb"), "b").select(F.col("la").alias("a"), F.col("lb").alias("b")).where("a <> b").distinct()
    between = stored(between)
    tops = component_rounds(between.select(F.explode(F.array("a", "b")).alias("v")).distinct(), between)
    return labels.join(tops.toDF("l", "t"), "l", "left").select("v", F.coalesce("t", "l").alias("component"))


def component_rounds(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """v and component (its smallest vertex): labels fall along edges, then jump to their label's label."""
    both = stored(edges.select("a", "b").unionAll(edges.select("b", "a")).toDF("a", "b").distinct())
    labels = stored(vertices.select("v", F.col("v").alias("component")))
    while True:
        near = both.join(labels.toDF("b", "l"), "b").groupBy("a").agg(F.min("l").alias("l"))
        new = labels.join(near, labels["v"] == near["a"], "left").select("v", F.least("component", F.coalesce("l", "component")).alias("next"), F.col("component").alias("old"))
        far = new.select(F.col("v").alias("next"), F.col("next").alias("far"))
        new = stored(new.join(far, "next").select("v", F.least("next", "far").alias("component"), "old"))
        done = new.where("component <> old").isEmpty()
        labels = new.select("v", "component")
        if done:
            return labels


def k_hop(arcs: DataFrame, sources: DataFrame, k: int) -> DataFrame:
    """qid and the number of vertices within k hops."""
    return bfs_hops(arcs, sources, k).groupBy("qid").agg(F.count(F.lit(1)).alias("reached"))
