"""The public surface: networks, index, forecasts, routes, plans and metrics behind one object."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import pivots
from ..operators.storage import stored
from ..schema import RouteOptions
from ..sources import forecasts as fc
from ..sources import networks
from ..sources.queries import make_queries
from . import baselines, router, search
from .index import Index, build_index


class Engine:
    """Keeps what it has built for a network; nothing is built before it is asked for.

    ``strategy``: how pivots are chosen where a call doesn't say ('swap', 'greedy', 'farthest' or 'fixed')."""

    def __init__(self, spark: SparkSession, strategy: str = "swap") -> None:
        self.spark, self.strategy = spark, strategy
        self._kept: dict[tuple, tuple] = {}  # by all that an object is made of; the parts are held, so that no id is used again
        self._last: DataFrame | None = None

    def network(self, kind: str, sf_dir: str) -> networks.Network:
        return networks.build_network(self.spark, sf_dir, kind)

    def forecasts(self, events: DataFrame) -> DataFrame:
        """The ring of newest forecasts."""
        return stored(fc.ring(events))

    def queries(self, net: networks.Network, **options) -> DataFrame:
        return make_queries(net, **options)

    def _once(self, parts: tuple, rest: tuple, make):  # noqa: ANN001, ANN202
        key = (*map(id, parts), *rest)
        if key not in self._kept:
            self._kept[key] = parts, make()
        return self._kept[key][1]

    def pivots(self, net: networks.Network, d: int = 5, strategy: str | None = None) -> DataFrame:
        strategy = strategy or self.strategy

        def make() -> DataFrame:
            chosen = pivots.fixed_pivots(net, d) if strategy == "fixed" else pivots.choose_landmarks(net, d, strategy)
            return pivots.pivot_distances(net, chosen)

        return self._once((net,), ("pivots", d, strategy), make)

    def index(self, net: networks.Network, ring: DataFrame, fanout: int | None = None, packing: str = "zorder", d: int = 5, strategy: str | None = None, wtypes: tuple = ("ANY",)) -> Index:
        piv = self.pivots(net, d, strategy)
        return self._once((net, ring, piv), ("index", fanout, packing, wtypes), lambda: build_index(net, ring, fanout, packing, piv, wtypes))

    def route(self, queries: DataFrame, net: networks.Network, ring: DataFrame, method: str = "index", options: RouteOptions = RouteOptions()) -> DataFrame:
        """Answers of one method: 'index', 'index_paths', 'astar', 'filter_first', 'bfs', 'rounds', 'enumerate' or 'plain'."""
        if method == "index" and not options.use_index:
            method = "astar"
        if method == "index":
            out = router.route_index(queries, net, self.index(net, ring), ring, options)
        elif method == "index_paths":
            out = router.route_index_paths(queries, net, self.index(net, ring), ring, options, self.pivots(net))
        elif method == "astar":
            out = baselines.route_astar(queries, net, ring, options, options.heuristic, self.pivots(net) if options.heuristic == "pivot" else None)
        elif method == "filter_first":
            out = baselines.route_filter_first(queries, net, ring, options)
        elif method == "bfs":
            out = baselines.route_bfs(queries, net, ring, options)
        elif method == "rounds":
            out = search.search_in_rounds(queries, net, ring, options, self.pivots(net) if options.heuristic == "pivot" else None)[0]
        elif method == "enumerate":
            out = baselines.route_enumerate(queries, net, ring, **options.extra)
        elif method == "plain":
            out = baselines.route_plain(queries, net)
        else:
            raise ValueError(f"no method {method}")
        self._last = stored(out)
        return self._last

    def metrics(self) -> DataFrame:
        """Sums and maxima of the counters of the last answers."""
        if self._last is None:
            raise ValueError("no query has run")
        counters = [c for c in ("labels", "page_reads", "node_reads", "pruned_kw", "pruned_weather", "pruned_time") if c in self._last.columns]
        tops = [c for c in ("max_heap", "max_queue") if c in self._last.columns]
        return self._last.agg(F.count(F.lit(1)).alias("queries"), *[F.sum(c).alias(c) for c in counters], *[F.max(c).alias(c) for c in tops])

    def explain_route(self, queries: DataFrame, net: networks.Network, options: RouteOptions = RouteOptions()) -> str:
        """The plan that brings arcs to queries."""
        arcs = search.bound_arcs(queries, net, options, self.pivots(net))
        return arcs._jdf.queryExecution().explainString(arcs._sc._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))

    def register_sql(self, net: networks.Network, ring: DataFrame) -> None:
        """Views and SQL functions: vertices, edges, arcs, forecasts; idw(wj, wk, f)."""
        net.vertices.createOrReplaceTempView("vertices")
        net.edges.createOrReplaceTempView("edges")
        net.arcs.createOrReplaceTempView("arcs")
        ring.createOrReplaceTempView("forecasts")
        self.spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION idw(wj DOUBLE, wk DOUBLE, f DOUBLE) RETURNS DOUBLE RETURN (1 - f) * wj + f * wk")
