"""Queries that return their whole table, against brute force and against the slices that have SQL."""

import random

import pytest
from pyspark.sql import functions as F

from saferoute.plans import method_queries as M
from saferoute.plans import search
from saferoute.plans.world import world
from saferoute.schema import RouteOptions

from . import fixtures as fx

def test_index_queries_reach_the_root(spark, small):
    w = world(spark, small)
    i = w.index("uni", M._PAIRS)
    pruned = M.Q["nodes_kw_pruned"](spark, small)
    s = {r["qid"]: set(r["s"]) for r in w.queries().collect()}
    kw = {r["eid"]: set(r["kw"]) for r in w.net().edges.collect()}
    held = {}
    for r in i.lookup.collect():
        for level in range(1, i.height + 1):
            held.setdefault((level, r["pos"] // M._PAIRS**level), []).append(kw[r["eid"]])
    want = {(q, *node) for node, kws in held.items() for q in s if set.intersection(*kws) & s[q]}
    assert {tuple(r) for r in pruned.select("qid", "level", "node").collect()} == want
    for name in ("idx_nodes", "idx_time", "idx_kw", "idx_weather", "idx_links"):
        assert M.Q[name](spark, small).agg(F.max("level")).first()[0] == w.index().height


CALM = ([0.0] * 24, [0] * 24)


def two_way(edges):
    """edges: (a, b, minutes); the ways of ``best_first``, every vertex its own cell."""
    ways = {}
    for i, (a, b, w) in enumerate(edges):
        ways.setdefault(a, []).append((b, w, i, a, b, 0, 0.0, False, 0))
        ways.setdefault(b, []).append((a, w, i, b, a, 0, 0.0, False, 0))
    return ways


def test_simple_paths_by_the_million_are_answered():
    n = 30  # 2 ** 30 simple paths of equal length
    edges = [e for i in range(n) for e in ((3 * i, 3 * i + 1, 1), (3 * i, 3 * i + 2, 1), (3 * i + 1, 3 * i + 3, 1), (3 * i + 2, 3 * i + 3, 1))]
    weather = dict.fromkeys(range(3 * n + 1), CALM)
    got = search.best_first(two_way(edges), [(0, 480, [0], [], [480])], 3 * n, 480, 50.0, 50, weather, RouteOptions(path_mode="simple", horizon_min=70, label_limit=20_000))
    assert got["total_min"] == 2 * n and len(set(got["vertices"])) == got["hops"] + 1


def test_simple_paths_equal_brute_force_on_random_networks():
    rng = random.Random(5)
    found = other = 0
    for _ in range(150):
        n = 7
        edges = [(a, b, rng.randrange(5, 45)) for a in range(n) for b in range(a + 1, n) if rng.random() < 0.4]
        weather = {v: ([float(rng.choice((0, 0, 90))) for _ in range(24)], [100] * 24) for v in range(n)}
        ways, o = two_way(edges), RouteOptions(path_mode="simple", horizon_min=240)

        def best(v, t, seen):
            if v == n - 1:
                return t
            steps = [(x[0], t + x[1]) for x in ways.get(v, ()) if x[0] not in seen and t + x[1] <= 720 and not search.py_trip_blocked(weather[v], weather[x[0]], t, x[1], 50.0, 50, 0.0)]
            return min((best(h, u, seen | {h}) for h, u in steps), default=float("inf"))

        want = best(0, 480, {0})
        got = search.best_first(ways, [(0, 480, [0], [], [480])], n - 1, 480, 50.0, 50, weather, o)
        walk = search.best_first(ways, [(0, 480, [0], [], [480])], n - 1, 480, 50.0, 50, weather, RouteOptions(horizon_min=240))
        assert got["total_min"] == (None if want == float("inf") else want - 480)
        found += got["answered"]
        other += got["total_min"] != walk["total_min"]
    assert found > 20 and other > 0


@pytest.mark.parametrize("mode", ["walk", "simple"])
def test_a_label_limit_is_no_answer(mode):
    edges = [(i, i + 1, 5) for i in range(8)]
    with pytest.raises(search.LimitReached):
        search.best_first(two_way(edges), [(0, 480, [0], [], [480])], 8, 480, 50.0, 50, dict.fromkeys(range(9), CALM), RouteOptions(path_mode=mode, label_limit=3))


def test_rounds_do_not_end_with_open_labels(spark):
    net = fx.network(spark, [(i, i + 1, 5, []) for i in range(5)])
    f, q = fx.forecasts(spark, [(0, 8, 1.0, 1)]), fx.queries(spark, [(0, 0, 5, 480, 50.0, 50, [])])
    with pytest.raises(search.LimitReached):
        search.search_in_rounds(q, net, f, RouteOptions(batch_width=1), max_rounds=3)


def test_a_search_back_from_the_end_changes_no_answer():
    rng = random.Random(9)
    fewer = 0
    for _ in range(200):
        n = 9
        edges = [(a, b, rng.randrange(5, 45)) for a in range(n) for b in range(a + 1, n) if rng.random() < 0.3]
        weather = {v: ([float(rng.choice((0, 0, 90))) for _ in range(24)], [rng.choice((50, 100)) for _ in range(24)]) for v in range(n)}
        weather[3] = ([90.0] * 24, [100] * 24)  # never to be passed
        plain, back = (search.best_first(two_way(edges), [(0, 480, [0], [], [480])], n - 1, 480, 50.0, 50, weather, RouteOptions(horizon_min=240, reverse=r)) for r in (False, True))
        assert plain["total_min"] == back["total_min"] and back["labels"] <= plain["labels"]
        fewer += back["labels"] < plain["labels"]
    assert fewer > 20
