"""Searches by regions give what whole searches give."""

import random

import pytest
from pyspark.sql import functions as F

from saferoute.operators import graph

from .fixtures import network


@pytest.fixture
def odd(spark):
    """A random network in three parts and a lone vertex, strips by number, so that ways go to and fro between regions."""
    rng = random.Random(3)
    edges = [(a, b, rng.randrange(1, 9), []) for part in range(3) for a, b in (rng.sample(range(20 * part, 20 * part + 20), 2) for _ in range(28))]
    net = network(spark, edges, 61)
    return net, net.vertices.withColumn("strip", F.floor(F.col("v") / 3))


@pytest.mark.parametrize("strips", [True, False])
def test_distances_by_regions(spark, odd, monkeypatch, strips):
    monkeypatch.setattr(graph, "LOCAL_ARCS", 12)
    monkeypatch.setattr(graph, "sssp", None)  # no rounds over single arcs
    net, v = odd
    sources = spark.createDataFrame([(0,), (7,), (33,), (60,)], "src long")
    rows = lambda d: sorted(map(tuple, d.select("src", "v", "dist").collect()))
    got = graph.distances(net.arcs, sources, vertices=v if strips else v.drop("strip"))
    assert rows(got) == rows(graph.sssp_local(net.arcs, sources))


def test_components_by_regions(odd, monkeypatch):
    net, v = odd
    want = sorted(map(tuple, graph.component_rounds(v.select("v"), net.edges).collect()))
    monkeypatch.setattr(graph, "LOCAL_ARCS", 12)
    left = []
    rounds = graph.component_rounds
    monkeypatch.setattr(graph, "component_rounds", lambda v, e: left.append(e.count()) or rounds(v, e))
    assert sorted(map(tuple, graph.components(v, net.edges).collect())) == want
    assert left[0] < net.edges.count()


def test_growing_horizons_answer_as_one(spark, monkeypatch):
    """Answers near and far, and none: by growing horizons as by the whole one, and closed ends are seen without it."""
    from saferoute.plans import baselines, search
    from saferoute.schema import RouteOptions

    from .fixtures import forecasts, queries

    chain = [(i, i + 1, 5, []) for i in range(30)] + [(30, 31, 5, [1]), (31, 32, 5, []), (32, 33, 5, [1]), (33, 34, 5, [])]
    net = network(spark, chain)
    ask = queries(spark, [(q, src, dst, 480, 50.0, 50, [1]) for q, (src, dst) in enumerate([(0, 2), (0, 29), (29, 31), (31, 0), (3, 3), (0, 34)])])
    f = forecasts(spark, [(v, s, 10.0, 100) for v in range(35) for s in range(24)])
    run = lambda: sorted(map(tuple, baselines.route_astar(ask, net, f, RouteOptions(), "euclid").select("qid", "answered", "total_min").collect()))
    want = run()
    assert [x[2] for x in want] == [10, 145, None, None, 0, None]
    asked = []
    whole = search.search_in_tasks
    monkeypatch.setattr(search, "WHOLE_ARCS", 1)
    monkeypatch.setattr(search, "search_in_tasks", lambda q, *a: asked.append((a[-1].horizon_min, sorted(r[0] for r in q.select("qid").collect()))) or whole(q, *a))
    assert run() == want
    assert asked[0] == (24, [0, 1, 2, 3, 4, 5]) and all(0 not in q for _, q in asked[1:])
    assert 2 not in asked[-1][1] and 3 not in asked[-1][1]


def test_index_parts_are_made_when_asked_for(spark, odd):
    from saferoute.plans.index import build_index

    def unwanted():
        raise AssertionError("nodes need no pivots")

    idx = build_index(odd[0], None, 4, piv=unwanted)
    assert idx.nodes.where("level = 1").agg(F.sum("n_edges")).first()[0] == odd[0].edges.count()
    with pytest.raises(AssertionError):
        idx.ranges  # noqa: B018


def test_quality_of_every_number_of_pivots(spark):
    from saferoute.operators.pivots import pivot_quality, pivot_quality_by_d

    piv = spark.createDataFrame([(v, [(7 * v) % 11, v * v % 13, -1 if v % 4 else v]) for v in range(20)], "v long, piv array<long>")
    got = {r["d"]: (r["quality"], r["n_pairs"]) for r in pivot_quality_by_d(piv).collect()}
    assert got == {d: tuple(pivot_quality(piv.select("v", F.slice("piv", 1, d).alias("piv"))).first()[:2]) for d in (1, 2, 3)}
