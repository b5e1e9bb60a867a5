"""What large networks need gives what small ones get."""

from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from saferoute.operators import graph, pivots, pruning
from saferoute.plans import baselines, index, router, search
from saferoute.schema import RouteOptions

from .fixtures import forecasts, network, queries
from .test_regions import odd  # noqa: F401

WAYS = "src", "v", "dist"


def rows(df, *columns):
    return sorted(map(tuple, df.select(*columns).collect()))


@pytest.mark.parametrize("only", [None, [(1,), (59,), (60,)]])
def test_distances_in_lots(spark, odd, monkeypatch, only):  # noqa: F811
    """Networks beyond one region are searched whole, several sources to a task."""
    net, v = odd
    sources = spark.createDataFrame([(i,) for i in (0, 7, 33, 60, *range(10, 30))], "src long")
    want = rows(graph.sssp(net.arcs, sources), *WAYS)
    monkeypatch.setattr(graph, "LOCAL_ARCS", 100)
    monkeypatch.setattr(graph, "sssp_regions", None)
    monkeypatch.setattr(graph, "sssp", None)
    asked = only and spark.createDataFrame(only, "v long")
    got = rows(graph.distances(net.arcs, sources, vertices=v, only=asked), *WAYS)
    assert got == [x for x in want if only is None or (x[1],) in only]


def test_distances_without_arcs(spark):
    none = spark.createDataFrame([], "tail long, head long, len_mm long")
    assert rows(graph.distances(none, spark.createDataFrame([(4,)], "src long")), *WAYS) == [(4, 4, 0)]


def test_scorer_asks_for_the_ends_of_its_pairs_only(spark, monkeypatch):
    net = network(spark, [(i, i + 1, 1, []) for i in range(300)])
    asked = []
    found = pivots.distances
    monkeypatch.setattr(pivots, "distances", lambda *a, only=None, **k: asked.append(only and only.count()) or found(*a, only=only, **k))
    score = pivots.Scorer(net, [0, 100, 300], 20, 1)
    assert 0 < asked[0] <= 80
    whole = pivots.pivot_distances(net, [0, 300])
    want = pivots.pivot_quality(whole, 20, 2).first()
    assert score.measure([0, 2])[0] == want["quality"] / want["n_pairs"] * 301 * 300


def horizons(monkeypatch):
    """(horizon, number of queries) of every search from now on, and networks of all sizes are searched by growing horizons."""
    asked, whole = [], search.search_in_tasks
    monkeypatch.setattr(search, "WHOLE_ARCS", 1)
    monkeypatch.setattr(search, "search_in_tasks", lambda q, *a: asked.append((a[-1].horizon_min, q.count())) or whole(q, *a))
    return asked


def test_a_long_road_far_away_keeps_no_query_open(spark, monkeypatch):
    """A source that all weather shuts in is settled by the first horizon, also where some road takes hours."""
    net = network(spark, [*((i, i + 1, 5, []) for i in range(30)), (30, 31, 300, [])])
    f = forecasts(spark, [(v, s, 90.0 if v in (2, 3, 4) else 10.0, 100) for v in range(32) for s in range(24)])
    ask = queries(spark, [(0, 3, 4, 480, 50.0, 50, [1]), (1, 10, 12, 480, 50.0, 50, [1])])
    piv = pivots.pivot_distances(net, [0, 31])
    for run in (lambda: baselines.route_astar(ask, net, f, RouteOptions(), "pivot", piv), lambda: router.route_index(ask, net, index.build_index(net, f, 2, piv=piv), f)):
        with monkeypatch.context() as m:
            asked = horizons(m)
            assert rows(run(), "qid", "answered", "total_min") == [(0, False, None), (1, True, 10)]
            assert asked == [(24, 2)]


@pytest.mark.parametrize("border", [6, 7])
def test_what_is_shut_now_may_open_later(spark, monkeypatch, border):
    """Pages that go out by the weather of a short horizon don't show that there is no way."""
    net = network(spark, [(i, i + 1, 5, []) for i in range(20)])
    f = forecasts(spark, [(v, s, 90.0 if v >= border and s == 8 else 10.0, 100) for v in range(21) for s in range(24)])
    ask = queries(spark, [(0, border - 1, border, 480, 50.0, 50, [1])])
    horizons(monkeypatch)
    idx = index.build_index(net, f, 2, piv=pivots.pivot_distances(net, [0, 20]))
    assert rows(router.route_index(ask, net, idx, f), "qid", "answered", "total_min") == [(0, True, 65)]


def test_nodes_weather_is_that_of_all_their_edges(spark, monkeypatch):
    """Found from a leaf's pairs of cells, not from each edge."""
    net = network(spark, [(i, i + 1, 5, []) for i in range(12)])
    net = replace(net, vertices=net.vertices.withColumn("cell", F.floor(F.col("v") / 4).cast("int")))
    f = forecasts(spark, [(c, s, 10.0 * c + s, 90 - c) for c in range(3) for s in range(0, 24, 2)])
    asked, bounds = [], pruning.cell_slot_bounds
    monkeypatch.setattr(index, "cell_slot_bounds", lambda ends, *a: asked.append(ends.count()) or bounds(ends, *a))
    idx = index.build_index(net, f, 12)
    edges = pruning.edge_slot_bounds(net.edges, net.vertices, f, 50.0).groupBy("slot").agg(F.min("lb_val").alias("lb_val"), F.max("ub_val").alias("ub_val"))
    assert rows(idx.weather.where("level = 1"), "slot", "lb_val", "ub_val") == rows(edges, "slot", "lb_val", "ub_val")
    assert asked == [6]
