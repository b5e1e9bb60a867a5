"""Spatial index over edges: packed leaves, levels of summaries, connection graph and lookup.

Edges are ranked along a space-filling order (Z-order, or slices by x and then y); the node of an edge at
level l is its rank divided by fanout ** l, so parents, children and lookups are arithmetic."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, fields
from threading import RLock

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.keywords import bitmap
from ..operators.pruning import cell_slot_bounds
from ..operators.ranking import global_rank
from ..operators.storage import stored
from ..sources.networks import Network, max_speed, midpoints

PAGE_BYTES = 4096
#: Points of the grid on which nodes keep their bound; a query's limit is rounded up to the next.
EPS_GRID = (20, 30, 40, 50, 60, 70, 80, 90)


def default_fanout(pivots: int = 5, words: int = 1) -> int:
    """Entries of a 4 KB page: rectangle, two pivot vectors, keyword words, time range, child."""
    return PAGE_BYTES // (4 * 8 + 2 * 8 * pivots // 2 + 8 * words + 2 * 8 + 8)


class Late:
    """A part of an index that is made when it is first asked for."""

    def __init__(self, make: Callable) -> None:
        self.make, self.lock = make, RLock()


@dataclass(frozen=True)
class Index:
    """Parts given as ``Late`` are made once, where a query asks for them; ``complete`` makes all."""

    fanout: int
    height: int
    lookup: DataFrame  #: eid, pos, leaf
    nodes: DataFrame  #: level, node, parent, rectangle, lb_t, ub_t, kw_and, kw_or, n_edges
    weather: DataFrame | None  #: wtype, level, node, slot, lb_val, ub_val, ub_case3, ub_by_eps
    links: DataFrame  #: level, n1, n2
    pages: DataFrame | None = None  #: leaf, and its arcs with cells and pivot vectors of the ends
    ranges: DataFrame | None = None  #: level, node, piv_lo, piv_hi: least and largest distance to each pivot
    by_slot: DataFrame | None = None  #: wtype, level, node, slots: the weather of all slots in one row
    pivots: DataFrame | None = None  #: v, piv
    vmax: float = 1.0

    def __getattribute__(self, name: str):  # noqa: ANN204
        part = object.__getattribute__(self, name)
        if isinstance(part, Late):
            with part.lock:  # another thread may have made it meanwhile
                if object.__getattribute__(self, name) is part:
                    object.__setattr__(self, name, part.make(self))
            part = object.__getattribute__(self, name)
        return part

    def complete(self, but: tuple = ()) -> Index:
        for f in fields(self):
            if f.name not in but:
                getattr(self, f.name)
        return self

    def sharing(self, other: Index, names: tuple, **parts) -> Index:
        """This index with ``names`` of another, where they are made once, and with the parts given."""
        own = {f.name: object.__getattribute__(self, f.name) for f in fields(self)}
        return Index(**own | {n: Late(lambda i, n=n: getattr(other, n)) for n in names} | parts)

    def with_pivots(self, net: Network, piv: Callable) -> Index:
        """This index with the pivots that ``piv`` makes; what doesn't hang on pivots is shared."""
        parts = {"pages": Late(lambda i: stored(page_arcs(net, i.lookup, i.pivots))), "ranges": Late(lambda i: stored(pivot_ranges(net, i.lookup, i.pivots, i.fanout, i.height)))}
        return self.sharing(self, ("nodes", "weather", "links", "by_slot", "vmax"), **parts, pivots=Late(lambda i: piv()))

    def node_at(self, pos: Column, level: int) -> Column:
        return F.floor(pos / (self.fanout**level))


def packed(net: Network, packing: str = "zorder", fanout: int = 56) -> DataFrame:
    """Edges with their rectangle and ``pos``, the rank in the packing order."""
    m = stored(midpoints(net))
    if packing == "zorder":
        return stored(global_rank(m, ["z", "eid"], "pos"))
    n = m.count()
    leaves = -(-n // fanout)
    slices = max(1, int(leaves**0.5 + 0.999))
    by_x = global_rank(m.withColumn("mx", F.col("xmin") + F.col("xmax")), ["mx", "eid"], "px")
    sliced = by_x.withColumn("slice", F.floor(F.col("px") / (-(-n // slices)))).withColumn("my", F.col("ymin") + F.col("ymax"))
    return stored(global_rank(sliced, ["slice", "my", "eid"], "pos").drop("mx", "px", "slice", "my"))


def roll_up(leaves: DataFrame, fanout: int, height: int) -> DataFrame:
    """Summaries of all levels, each from the one below."""
    sums = (F.min("xmin"), F.min("ymin"), F.max("xmax"), F.max("ymax"), F.min("lb_t"), F.max("ub_t"), F.bit_and("kw_and"), F.bit_or("kw_or"), F.sum("n_edges"))
    names = ("xmin", "ymin", "xmax", "ymax", "lb_t", "ub_t", "kw_and", "kw_or", "n_edges")
    out, below = None, leaves
    for level in range(1, height + 1):
        below = below.groupBy(F.floor(F.col("key") / fanout).alias("key")).agg(*[s.alias(n) for s, n in zip(sums, names, strict=True)])
        below = stored(below)
        rows = below.select(F.lit(level).alias("level"), F.col("key").alias("node"), F.floor(F.col("key") / fanout).alias("parent"), *names)
        out = rows if out is None else out.unionAll(rows)
    return out


def connection_graph(ends: DataFrame, fanout: int, height: int) -> DataFrame:
    """level, n1, n2 of nodes that hold edges with a common end, themselves included."""
    out = None
    for level in range(1, height + 1):
        at = ends.select("v", F.floor(F.col("pos") / (fanout**level)).alias("n")).distinct()
        pairs = at.toDF("v", "n1").join(at.toDF("v", "n2"), "v").select(F.lit(level).alias("level"), "n1", "n2").distinct()
        out = pairs if out is None else out.unionAll(pairs)
    return out


def index_weather(net: Network, lookup: DataFrame, forecasts: DataFrame, fanout: int, height: int, wtypes: tuple = ("ANY",), grid: tuple = EPS_GRID) -> DataFrame:
    """Per type, level, node and slot: value range, the bound where both ends exceed, and the bound by limit.

    The bound grows with the limit, so the entry of the next grid point is safe."""
    from ..functions.weather import ub_prob_ok

    at = [ub_prob_ok(F.col("wj"), F.col("pj"), F.col("wk"), F.col("pk"), F.lit(float(e))).alias(f"u{e}") for e in grid]
    cells = net.vertices.select("v", "cell")
    ends = net.edges.select("eid", "a", "b").join(lookup.select("eid", "pos"), "eid").join(cells.toDF("a", "ca"), "a").join(cells.toDF("b", "cb"), "b")
    # edges of a leaf between the same cells have the same bounds: one stands for them, and its position for theirs
    alike = stored(ends.groupBy(F.floor(F.col("pos") / fanout).alias("leaf"), "ca", "cb").agg(F.min("pos").alias("pos")))
    rows = None
    for wtype in wtypes:
        base = cell_slot_bounds(alike, forecasts, float(grid[0]), wtype)
        part = base.select(F.lit(wtype).alias("wtype"), "slot", F.col("pos").alias("key"), "lb_val", "ub_val", ((100 - F.col("pj")) * (100 - F.col("pk"))).cast("long").alias("ub_case3"), *at)
        rows = part if rows is None else rows.unionAll(part)
    out, below = None, rows
    for level in range(1, height + 1):
        sums = [F.min("lb_val").alias("lb_val"), F.max("ub_val").alias("ub_val"), F.max("ub_case3").alias("ub_case3"), *[F.max(f"u{e}").alias(f"u{e}") for e in grid]]
        below = stored(below.groupBy("wtype", F.floor(F.col("key") / fanout).alias("key"), "slot").agg(*sums))
        table = F.create_map(*[x for e in grid for x in (F.lit(e), F.col(f"u{e}"))])
        part = below.select("wtype", F.lit(level).alias("level"), F.col("key").alias("node"), "slot", "lb_val", "ub_val", "ub_case3", table.alias("ub_by_eps"))
        out = part if out is None else out.unionAll(part)
    return out


def slots_of(weather: DataFrame) -> DataFrame:
    """wtype, level, node, slots: map from slot to (lb_val, ub_val, ub_case3, ub_by_eps)."""
    entry = F.struct("slot", F.struct("lb_val", "ub_val", "ub_case3", "ub_by_eps"))
    return weather.groupBy("wtype", "level", "node").agg(F.map_from_entries(F.collect_list(entry)).alias("slots"))


def pivot_ranges(net: Network, lookup: DataFrame, piv: DataFrame, fanout: int, height: int) -> DataFrame:
    """level, node, piv_lo, piv_hi over the ends of the node's edges."""
    d = len(piv.first()["piv"])
    ends = lookup.join(net.edges.select("eid", F.explode(F.array("a", "b")).alias("v")), "eid").join(piv, "v")
    out, below = None, ends.select(F.col("pos").alias("key"), F.col("piv").alias("lo"), F.col("piv").alias("hi"))
    for level in range(1, height + 1):
        lo, hi = (F.array(*[f(F.get(c, F.lit(i))) for i in range(d)]).alias(c) for f, c in ((F.min, "lo"), (F.max, "hi")))
        below = stored(below.groupBy(F.floor(F.col("key") / fanout).alias("key")).agg(lo, hi))
        part = below.select(F.lit(level).alias("level"), F.col("key").alias("node"), F.col("lo").alias("piv_lo"), F.col("hi").alias("piv_hi"))
        out = part if out is None else out.unionAll(part)
    return out


def page_arcs(net: Network, lookup: DataFrame, piv: DataFrame | None) -> DataFrame:
    """The arcs of every leaf page: leaf, tail, head, eid, w_min, kw, cells and pivot vectors of the ends."""
    v = net.vertices.select("v", "cell")
    v = v.join(piv, "v") if piv is not None else v.withColumn("piv", F.array().cast("array<long>"))
    ends = lambda p: v.toDF(p, f"{p}_cell", f"{p}_piv")
    return net.arcs.drop("len_mm").join(lookup.select("eid", "leaf"), "eid").join(ends("tail"), "tail").join(ends("head"), "head")


def bound_at(eps: Column, at: Column | None = None, grid: tuple = EPS_GRID) -> Column:
    """A node's bound at a limit: 1 above its values, the stored bound of both-exceed below, else by the grid.

    ``at``: the struct that has a slot's values, else columns of these names."""
    c = (lambda n: F.col(n)) if at is None else (lambda n: at[n])
    up = F.lit(10000).cast("long")
    for e in sorted(grid, reverse=True):
        up = F.when(eps <= e, F.element_at(c("ub_by_eps"), F.lit(e))).otherwise(up)
    return F.when(c("ub_val") <= eps, F.lit(10000).cast("long")).when(c("lb_val") > eps, c("ub_case3")).otherwise(up)


def build_index(net: Network, forecasts: DataFrame | None = None, fanout: int | None = None, packing: str = "zorder", piv: DataFrame | Callable | None = None, wtypes: tuple = ("ANY",)) -> Index:
    """``piv``: distances to pivots (or what makes them), which nodes keep as ranges; ``wtypes``: the types whose forecasts nodes keep.

    Queries of other types are answered too, without the prune of nodes by weather."""
    fanout = fanout or default_fanout()
    edges = packed(net, packing, fanout)
    n, height = edges.count(), 1
    while fanout**height < n:
        height += 1
    bits = F.get(bitmap(F.col("kw")), F.lit(0))
    leaves = edges.select(F.col("pos").alias("key"), "xmin", "ymin", "xmax", "ymax", F.col("w_min").alias("lb_t"), F.col("w_min").alias("ub_t"), bits.alias("kw_and"), bits.alias("kw_or"), F.lit(1).cast("long").alias("n_edges"))
    lookup = stored(edges.select("eid", "pos", F.floor(F.col("pos") / fanout).alias("leaf")))
    ends = edges.select(F.explode(F.array("a", "b")).alias("v"), "pos")
    return Index(
        fanout, height, lookup, Late(lambda i: stored(roll_up(leaves, fanout, height))),
        None if forecasts is None else Late(lambda i: stored(index_weather(net, lookup, forecasts, fanout, height, wtypes))),
        Late(lambda i: stored(connection_graph(ends, fanout, height))), Late(lambda i: stored(page_arcs(net, lookup, i.pivots))),
        None if piv is None else Late(lambda i: stored(pivot_ranges(net, lookup, i.pivots, fanout, height))),
        None if forecasts is None else Late(lambda i: stored(slots_of(i.weather))), Late(lambda i: piv()) if callable(piv) else piv, Late(lambda i: max_speed(net.edges) or 1.0))


def node_prune_keyword(nodes: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, level, node where every edge has one and the same keyword of the query."""
    q = queries.select("qid", F.get(bitmap(F.col("s")), F.lit(0)).alias("s_bits"))
    return nodes.join(F.broadcast(q)).where(F.col("kw_and").bitwiseAND(F.col("s_bits")) != 0).select("qid", "level", "node")


def node_prune_weather(weather: DataFrame, queries: DataFrame, horizon_min: int | None = None) -> DataFrame:
    """qid, level, node where in every slot the bound rules all edges in as obstacles.

    With a horizon only the slots count that a trip within it can touch, else all of the ring."""
    asked = ["wtype", "eps", "alpha_pct", *(["dep_min"] if horizon_min is not None else [])]
    kinds = queries.select(*asked).distinct()  # queries that ask alike share one test
    rows = weather.join(F.broadcast(kinds), "wtype")
    if horizon_min is not None:
        first = F.floor(F.col("dep_min") / 60)
        span = F.floor((F.col("dep_min") + horizon_min) / 60) - first
        rows = rows.where(F.pmod(F.col("slot") - first, F.lit(24)) <= span)
    top = rows.groupBy(*asked, "level", "node").agg(F.max(bound_at(F.col("eps"))).alias("ub"))
    return top.where(F.col("ub") < 100 * (100 - F.col("alpha_pct"))).join(queries.select("qid", *asked), asked).select("qid", "level", "node")


def cost_model(index: Index, sigma: int, degree: float) -> list[tuple[str, float]]:
    """Analytic costs of traversal and expansion from average degrees of the connection graphs.

    The traversal's closed form is printed for one term less than its sum has; both are given."""
    rows = index.links.where("n1 <> n2").groupBy("level").count().collect()
    per = {r["level"]: r["count"] for r in rows}
    count = {r["level"]: r["count"] for r in index.nodes.groupBy("level").count().collect()}
    deg = {k: per.get(k, 0) / count[k] for k in count}
    h = index.height
    exact = paper = 0.0
    for i in range(h + 1):
        d = deg.get(max(i, 1), 0.0)
        exact += sum((d + 1) ** j for j in range(h - i + 1)) * (d + 1)
        paper += sum((d + 1) ** j for j in range(h - i + 1))
    expand = (deg.get(1, 0.0) + 1) ** (h + 1) * degree ** max(0, sigma - h - 1)
    return [("traversal_exact_sum", exact), ("traversal_paper_form", paper), ("expansion", expand), ("total", exact + expand)]
