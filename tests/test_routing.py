"""All methods on hand-made networks and on the smallest tables: equal optima, valid paths, edge cases."""

import pytest
from pyspark.sql import functions as F

from saferoute.operators import pivots as P
from saferoute.plans import baselines as B
from saferoute.plans import index as I
from saferoute.plans import router as R
from saferoute.plans import search as Srch
from saferoute.plans.world import world
from saferoute.schema import RouteOptions

from . import fixtures as fx


def every_method(net, f, q, spark, options=RouteOptions(), fanout=3):
    piv = P.pivot_distances(net, [0, net.vertices.count() - 1])
    idx = I.build_index(net, f, fanout, piv=piv)
    out = {
        "zero": B.route_astar(q, net, f, options), "euclid": B.route_astar(q, net, f, options, "euclid"), "pivot": B.route_astar(q, net, f, options, "pivot", piv),
        "filter": B.route_filter_first(q, net, f, options), "index": R.route_index(q, net, idx, f, options), "paths": R.route_index_paths(q, net, idx, f, options, piv),
        "rounds": Srch.search_in_rounds(q, net, f, options)[0], "beam": Srch.search_in_rounds(q, net, f, RouteOptions(**{**options.__dict__, "batch_width": 1}))[0],
    }
    return {k: {r["qid"]: r["total_min"] for r in d.select("qid", "total_min").collect()} for k, d in out.items()}


def test_chemical_transport(spark):
    net, f = fx.chem(spark)
    q = fx.queries(spark, [(0, 8, 9, 480, 40.0, 50, [1])])
    answer = B.route_astar(q, net, f).first()
    assert answer["vertices"] == [8, 1, 3, 5, 6, 9] and answer["total_min"] == 50
    got = every_method(net, f, q, spark)
    assert all(m == {0: 50} for m in got.values()), got
    assert B.route_enumerate(q, net, f, 7).first()["total_min"] == 50


def test_windy_vertex_blocks_up_to_its_confidence(spark):
    net, f = fx.chem(spark)
    q = fx.queries(spark, [(a, 1, 2, 480, 40.0, a, []) for a in (50, 90, 91)])
    hour = RouteOptions(horizon_min=50)  # only in the first hour
    got = {r["qid"]: r["answered"] for r in B.route_astar(q, net, f, hour).collect()}
    assert got == {50: False, 90: False, 91: True}


def test_waiting_by_a_detour_beats_the_earliest_label(spark):
    # 0-1 early meets bad weather beyond 1 in slot 8; going 0-3-1 arrives in slot 9, when it is fine.
    net = fx.network(spark, [(0, 1, 10, []), (1, 2, 10, []), (0, 3, 30, []), (3, 1, 40, []), (2, 4, 5, [])])
    f = fx.forecasts(spark, [(2, 8, 90.0, 100)])
    q = fx.queries(spark, [(0, 0, 4, 480, 50.0, 50, [])])
    got = every_method(net, f, q, spark)
    assert len({tuple(m.items()) for m in got.values()}) == 1 and got["zero"][0] is not None, got
    assert got["zero"][0] > 25


def test_fork_is_no_walk_and_near_destination_is_not_overshot(spark):
    net = fx.network(spark, [(0, 1, 5, []), (1, 2, 5, []), (1, 3, 5, [7]), (3, 4, 5, [7])])
    f = fx.forecasts(spark, [(4, 8, 1.0, 1)])
    q = fx.queries(spark, [(0, 0, 1, 480, 50.0, 50, [7]), (1, 0, 2, 480, 50.0, 50, [7]), (2, 0, 4, 480, 50.0, 50, [7]), (3, 2, 2, 480, 50.0, 50, [])])
    got = every_method(net, f, q, spark, fanout=2)
    assert all(m == {0: 5, 1: 10, 2: None, 3: 0} for k, m in got.items() if k not in ("rounds", "beam")), got
    assert all({k: v for k, v in got[m].items() if k < 3} == {0: 5, 1: 10, 2: None} for m in ("rounds", "beam"))


def test_simple_paths_do_not_turn_back(spark):
    net = fx.network(spark, [(0, 1, 20, []), (1, 2, 10, [])])
    f = fx.forecasts(spark, [(2, 8, 90.0, 100)])
    q = fx.queries(spark, [(0, 0, 2, 480, 50.0, 50, [])])
    walk, simple = (B.route_astar(q, net, f, RouteOptions(path_mode=m)).first()["total_min"] for m in ("walk", "simple"))
    assert simple is None and walk is not None and walk > 60


def test_methods_agree_on_the_given_tables(spark, small):
    w = world(spark, small)
    q = w.queries("uni", sigma=4, n=10)
    got = {k: {r["qid"]: r["total_min"] for r in d.select("qid", "total_min").collect()} for k, d in {
        "zero": B.route_astar(q, w.net(), w.ring), "pivot": B.route_astar(q, w.net(), w.ring, RouteOptions(), "pivot", w.piv()),
        "filter": B.route_filter_first(q, w.net(), w.ring), "index": R.route_index(q, w.net(), w.index(), w.ring, RouteOptions()),
        "no_time": R.route_index(q, w.net(), w.index(), w.ring, RouteOptions(use_time=False)), "paths": R.route_index_paths(q, w.net(), w.index(), w.ring, RouteOptions(), w.piv())}.items()}
    assert len({tuple(sorted(m.items())) for m in got.values()}) == 1, got
    plain = {r["qid"]: r["total_min"] for r in B.route_plain(q, w.net()).collect()}
    assert all(t is None or t >= plain[k] for k, t in got["zero"].items())


def test_answers_hold_hop_by_hop(spark, small):
    w = world(spark, small)
    q = w.queries("uni", sigma=3)
    a = R.route_index(q, w.net(), w.index(), w.ring, RouteOptions())
    checked = R.refine(a, q, w.net(), w.ring).collect()
    assert all(r["bad_edges"] == r["bad_links"] == r["bad_times"] == 0 for r in checked)
    greedy = {r["qid"]: r["ub_min"] for r in R.greedy_route(q, w.net(), w.ring, RouteOptions(), w.piv()).collect()}
    best = {r["qid"]: r["total_min"] for r in a.collect()}
    assert all(best[k] is not None and best[k] <= ub for k, ub in greedy.items())


def test_any_slot_filter_never_finds_better(spark, small):
    w = world(spark, small)
    q = w.queries("uni", sigma=3)
    exact = {r["qid"]: r["total_min"] for r in B.route_filter_first(q, w.net(), w.ring).collect()}
    strict = {r["qid"]: r["total_min"] for r in B.route_filter_first(q, w.net(), w.ring, RouteOptions(prefilter="any_slot")).collect()}
    assert all(t is None or exact[k] is not None and exact[k] <= t for k, t in strict.items())


@pytest.mark.parametrize("packing", ["zorder", "str"])
def test_index_invariants(spark, small, packing):
    w = world(spark, small)
    i = I.build_index(w.net(), w.ring, 8, packing)
    rows = {(r["level"], r["node"]): r for r in i.nodes.collect()}
    assert len([1 for level, _ in rows if level == i.height]) == 1
    for (level, _), r in rows.items():
        if level < i.height:
            p = rows[level + 1, r["parent"]]
            assert p["xmin"] <= r["xmin"] and p["xmax"] >= r["xmax"] and p["ymin"] <= r["ymin"] and p["ymax"] >= r["ymax"]
            assert p["lb_t"] <= r["lb_t"] and p["ub_t"] >= r["ub_t"] and p["kw_and"] & ~r["kw_and"] == 0 and r["kw_or"] & ~p["kw_or"] == 0
    assert i.lookup.count() == i.lookup.select("eid").distinct().count() == w.net().edges.count()
    assert max(r["n_edges"] for (level, _), r in rows.items() if level == 1) <= 8


def test_pivot_choice_climbs_and_bounds_hold(spark, small):
    net = world(spark, small).net()
    n = net.vertices.count()
    exact = P.choose_pivots(net, 3, restarts=1, swaps=4, pairs=None)
    assert len(set(exact.pivots)) == 3 and exact.trace == sorted(exact.trace) and exact.error == 0
    piv = [r["piv"] for r in P.pivot_distances(net, exact.pivots).orderBy("v").collect()]
    brute = sum(max(abs(a - b) for a, b in zip(x, y, strict=True)) for x in piv for y in piv)
    assert exact.quality == exact.trace[-1] == brute
    drawn = P.Scorer(net, exact.pivots, 3_000, 7)
    quality, error = drawn.measure([0, 1, 2])
    assert 0 < error < brute / 10 and abs(quality - brute) < 5 * error
    chosen = P.choose_pivots(net, 3, restarts=2, swaps=60)
    assert chosen.trace == sorted(chosen.trace) and chosen.quality > 0 and max(chosen.pivots) < n
    best, by_count = P.choose_pivot_count(net, 4, 0.0, restarts=2, swaps=10)
    assert best <= len(by_count) <= 4


def test_swaps_reach_every_vertex(spark):
    """On a line either end is the best single pivot; with as many swaps as vertices one is found."""
    net = fx.network(spark, [(i, i + 1, 1, []) for i in range(7)])
    assert P.choose_pivots(net, 8, restarts=1, swaps=5, pairs=None).pivots == list(range(8))  # none is left to swap
    got = P.choose_pivots(net, 1, restarts=1, swaps=8, pairs=None)
    assert got.pivots[0] in (0, 7) and got.quality == sum(1000 * abs(i - j) for i in range(8) for j in range(8))


def test_landmarks_behind_the_destination(spark, small):
    w = world(spark, small)
    at = {r["v"]: (r["x_mm"], r["y_mm"]) for r in w.net().vertices.collect()}
    marks = P.fixed_pivots(w.net(), 6)
    got = {(r["qid"], r["landmark"]): r for r in P.landmarks_behind(w.queries(), w.net(), marks).collect()}
    for q in w.queries().collect():
        (sx, sy), (tx, ty) = at[q["src"]], at[q["dst"]]
        assert sorted(got[q["qid"], m]["place"] for m in marks) == list(range(1, len(marks) + 1))
        for m in marks:
            dot = (tx - sx) * (at[m][0] - tx) + (ty - sy) * (at[m][1] - ty)
            assert got[q["qid"], m]["behind"] == (dot > 0)


def test_pivot_detours_are_no_upper_bound_with_obstacles(spark):
    net, f = fx.chem(spark)
    q = fx.queries(spark, [(0, 1, 2, 480, 40.0, 50, [])])
    assert B.route_astar(q, net, f, RouteOptions(horizon_min=100)).first()["answered"] is False  # though a way over a pivot exists without obstacles
    assert B.route_plain(q, net).first()["total_min"] == 10


def test_a_batch_of_several_types_is_as_each_type_alone(spark, small):
    w = world(spark, small)
    kinds = F.array(*map(F.lit, ("ANY", "click", "view")))
    q = w.queries("uni", sigma=5).withColumn("wtype", F.get(kinds, F.col("qid") % 3))
    times = lambda d: {r["qid"]: r["total_min"] for r in d.select("qid", "total_min").collect()}
    idx = w.index("uni", wtypes=("ANY", "click"))
    want = {}
    for t in ("ANY", "click", "view"):
        alone = w.ring.where(F.col("wtype") == t).withColumn("wtype", F.lit("ANY"))
        want |= times(B.route_astar(q.where(F.col("wtype") == t).withColumn("wtype", F.lit("ANY")), w.net(), alone))
    got = {
        "astar": B.route_astar(q, w.net(), w.ring), "filter": B.route_filter_first(q, w.net(), w.ring), "index": R.route_index(q, w.net(), idx, w.ring),
        "paths": R.route_index_paths(q, w.net(), idx, w.ring, RouteOptions(), w.piv()),
    }
    assert all(times(d) == want for d in got.values()), {k: times(d) for k, d in got.items()}
    assert all(r["bad_edges"] == r["bad_links"] == r["bad_times"] == 0 for r in R.refine(got["index"], q, w.net(), w.ring).collect())


def test_the_index_reads_and_takes_less_than_pivots_alone(spark, small):
    from saferoute.plans.method_queries import metrics_of

    w = world(spark, small)
    by = {m[0]: m for m in metrics_of(w, methods=("index", "astar_pivot"))}
    assert by["index"][4] == by["astar_pivot"][4]
    labels, reads = 5, 7
    assert by["index"][labels] < by["astar_pivot"][labels] and by["index"][reads] < by["astar_pivot"][reads], by


def test_a_known_answer_narrows_the_descent(spark, small):
    w = world(spark, small)
    q = w.queries("uni", sigma=4)
    free = R.route_index(q, w.net(), w.index(), w.ring)
    best = free.where("answered").select("qid", F.col("total_min").alias("lam"))
    held = R.route_index(q, w.net(), w.index(), w.ring, RouteOptions(), best)
    times = lambda d: {r["qid"]: r["total_min"] for r in d.select("qid", "total_min").collect()}
    assert times(free) == times(held)


def test_two_level_example_cuts_the_paths_of_bad_nodes(spark):
    """Seven leaves in two levels: two of them carry the keyword on all their roads, so no path goes through them."""
    edges = [(i, i + 1, 10, [1] if i in (6, 7, 8, 9) else []) for i in range(14)] + [(6, 10, 60, [])]
    net, f = fx.network(spark, edges), fx.forecasts(spark, [(0, 8, 1.0, 1)])
    idx = I.build_index(net, f, 2, piv=P.pivot_distances(net, [0, 14]))
    q = fx.queries(spark, [(0, 0, 14, 480, 50.0, 50, [1])])
    bad = {(r["level"], r["node"]) for r in I.node_prune_keyword(idx.nodes, q).collect()}
    leaves = {r["eid"]: r["leaf"] for r in idx.lookup.collect()}
    assert bad and all({leaves[e] for e in leaves if leaves[e] == n} for level, n in bad if level == 1)
    paths = R.descend(q, net, idx, RouteOptions()).paths.collect()
    assert paths and not any((1, n) in bad for p in paths for n in p["nodes"])
    left = {(r["level"], r["node"]) for r in R.reachable_nodes(q, idx, RouteOptions())[0].collect()}
    assert left and not left & bad
    assert R.route_index(q, net, idx, f).first()["total_min"] == 6 * 10 + 60 + 4 * 10
