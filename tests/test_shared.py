"""What queries over several settings have in common is made once, and is what each would make for itself."""


import pytest
from pyspark.sql import functions as F

from saferoute.operators import pivots
from saferoute.plans import index, method_queries, router, search
from saferoute.plans.world import World
from saferoute.sources import forecasts as fc
from saferoute.sources import networks, queries

from .fixtures import forecasts, network
from .fixtures import queries as ask_for


@pytest.fixture(scope="module")
def w(spark, small):
    return World(spark, small)


def rows(df):
    return sorted(map(repr, df.select(*sorted(df.columns)).collect()))


def test_query_sets_share_their_ends(w, monkeypatch):
    found, calls = queries.bfs_hops, []
    monkeypatch.setattr(queries, "bfs_hops", lambda *a: calls.append(1) or found(*a))
    sets = [{"eps": 20.0}, {"eps": 90.0}, {"alpha_pct": 10}, {"s_size": 1}]
    got = [rows(w.queries(sigma=2, **o)) for o in sets]
    assert len(calls) == 1
    assert got == [rows(queries.make_queries(w.net(), sigma=2, **o)) for o in sets]


def test_indexes_of_several_numbers_of_pivots_share_the_rest(w, monkeypatch):
    found, calls = pivots.distances, []
    monkeypatch.setattr(pivots, "distances", lambda *a, **k: calls.append(1) or found(*a, **k))
    w.pivs("uni", (2, 3))
    a, b = w.index(d=2), w.index(d=3)
    assert a.nodes is b.nodes and a.by_slot is b.by_slot and a.lookup is b.lookup
    assert [len(x.pivots.first()["piv"]) for x in (a, b)] == [2, 3] and len(calls) == 1
    assert rows(b.pivots) == rows(pivots.pivot_distances(w.net(), pivots.fixed_pivots(w.net(), 3)))
    alone = index.build_index(w.net(), w.ring, a.fanout, piv=b.pivots)
    for part in ("ranges", "pages", "nodes", "weather"):
        assert rows(getattr(b, part)) == rows(getattr(alone, part))


def test_networks_of_several_periods_share_their_vertices(w, spark, small):
    a, b = w.net("uni+4"), w.net("uni+8")
    assert a.vertices is b.vertices
    assert rows(b.edges) == rows(networks.build_network(spark, small, "uni", period=8).edges)


def test_networks_of_several_keywords_share_all_but_keywords(w, spark, small):
    a, b = w.index("uni"), w.index("uni*")
    assert a.pivots is b.pivots and a.by_slot is b.by_slot and a.ranges is b.ranges
    net = networks.build_network(spark, small, "uni", skewed=True)
    assert rows(w.net("uni*").edges) == rows(net.edges)
    alone = index.build_index(net, w.ring, b.fanout, piv=a.pivots)
    for part in ("nodes", "pages", "weather", "ranges"):
        assert rows(getattr(b, part)) == rows(getattr(alone, part))


def test_costs_make_no_connection_graph(w, monkeypatch):
    monkeypatch.setattr(index, "connection_graph", None)
    assert method_queries.costs(w, [(1, "uni", {"sigma": 2})]).count() == 1


def test_ranks_in_several_tasks(spark):
    from saferoute.operators.ranking import global_rank

    got = global_rank(spark.range(1000).select((F.col("id") * 7 % 1000).alias("x")), ["x"], "p", 100)
    assert got.where("x <> p").isEmpty() and got.count() == 1000


def test_ring_reads_its_events_once(spark, small):
    events = spark.read.parquet(f"{small}/events.parquet")
    got = fc.ring(events)
    assert rows(got) == rows(fc.newest(fc.parsed(events, True).unionAll(fc.parsed(events, False))))
    assert got._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0].count("FileScan") == 1


def test_a_batch_is_placed_among_the_pivots_once(spark, monkeypatch):
    """And the second horizon is four times the first."""
    net = network(spark, [(i, i + 1, 5, []) for i in range(20)])
    f = forecasts(spark, [(v, s, 10.0, 100) for v in range(21) for s in range(24)])
    ask = ask_for(spark, [(0, 1, 15, 480, 50.0, 50, [1]), (1, 1, 3, 480, 50.0, 50, [1])])
    asked, whole = [], search.search_in_tasks
    monkeypatch.setattr(search, "WHOLE_ARCS", 1)
    monkeypatch.setattr(search, "search_in_tasks", lambda q, *a: asked.append((a[-1].horizon_min, q.count(), "src_piv" in q.columns)) or whole(q, *a))
    idx = index.build_index(net, f, 2, piv=pivots.pivot_distances(net, [0, 20]))
    got = router.route_index(ask, net, idx, f)
    assert sorted((r["qid"], r["total_min"]) for r in got.collect()) == [(0, 70), (1, 10)]
    assert asked == [(24, 2, True), (96, 1, True)]


def test_a_query_that_no_pivot_reaches_stays(spark):
    net = network(spark, [(0, 1, 5, []), (1, 2, 5, [])], 4)
    f = forecasts(spark, [(v, s, 10.0, 100) for v in range(4) for s in range(24)])
    idx = index.build_index(net, f, 2, piv=pivots.pivot_distances(net, [0]))
    got = router.route_index(ask_for(spark, [(0, 0, 2, 480, 50.0, 50, [1]), (1, 3, 3, 480, 50.0, 50, [1]), (2, 3, 0, 480, 50.0, 50, [1])]), net, idx, f)
    assert sorted((r["qid"], r["answered"], r["total_min"]) for r in got.collect()) == [(0, True, 10), (1, True, 0), (2, False, None)]


def test_parts_are_made_side_by_side(spark, small):
    from threading import Barrier

    from saferoute.plans import world

    met = Barrier(2, timeout=20)
    world.together(spark, met.wait, met.wait)
    with pytest.raises(ZeroDivisionError):
        world.together(spark, lambda: spark.range(3).count(), lambda: 1 // 0)
    own = World(spark, small)
    own.ready("uni*", sigma=2)
    made = {k[:2] for k in own._kept}
    assert {("net", "uni"), ("net", "uni*"), ("piv", "uni"), ("ends", "uni"), ("index", "uni*")} <= made


def test_threads_that_ask_for_the_same_wait_for_it(spark, small):
    import time

    from saferoute.plans.world import together

    w, calls = World(spark, small), []
    make = lambda: calls.append(1) or time.sleep(0.3) or len(calls)
    assert together(spark, *[lambda: w._once(("x",), make)] * 4) == [1] * 4
    part = index.Late(lambda i: make())
    i = index.Index(2, 1, None, part, None, None)
    assert together(spark, *[lambda: i.nodes] * 4) == [2] * 4


def test_batches_of_several_pivots_run_side_by_side(spark, small, monkeypatch):
    """All of them are under way at once, with the answers that each gives alone."""
    from threading import Barrier

    w, run, gate = World(spark, small), router.route_index, Barrier(len(method_queries.PIVOTS), timeout=120)
    monkeypatch.setattr(method_queries, "world", lambda *a: w)
    monkeypatch.setattr(router, "route_index", lambda *a: gate.wait() and None or run(*a))
    got = rows(method_queries.Q["sweep_d"](spark, small))
    want = [run(w.queries(), w.net(), w.index(d=d), w.ring).select(F.lit(d).alias("param"), "qid", "total_min") for d in method_queries.PIVOTS]
    assert got == sorted(x for d in want for x in rows(d))


def collections(spark):
    beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
    return sum(b.getCollectionCount() for b in beans if "Old" in b.getName() or "MarkSweep" in b.getName())


def test_the_driver_hands_back_heap_while_parts_are_made(spark, monkeypatch):
    """Also where the parts have parts of their own."""
    import time

    from saferoute.plans import world

    monkeypatch.setattr(world, "HAND_BACK_S", 0.2)
    before = collections(spark)
    world.together(spark, *[lambda: world.together(spark, lambda: time.sleep(0.5), lambda: time.sleep(1))] * 2)
    assert collections(spark) >= before + 2


def test_networks_of_one_size_are_made_few_at_once(spark, small, monkeypatch):
    import time
    from threading import Lock

    now, most, lock = [0], [0], Lock()

    def slow(*a, **k):
        with lock:
            now[0] += 1
            most[0] = max(most[0], now[0])
        time.sleep(0.3)
        with lock:
            now[0] -= 1

    w = World(spark, small)
    monkeypatch.setattr(w, "ready", slow)
    monkeypatch.setattr(method_queries, "metrics_of", lambda w, kind, **o: [(kind, *[None] * 17)])
    monkeypatch.setattr(method_queries, "world", lambda *a: w)
    got = method_queries.Q["sweep_edges_costs"](spark, small)
    assert got.count() == 5 and most[0] == method_queries.NETS_AT_ONCE < 5


def test_horizons_share_what_does_not_change(spark, monkeypatch):
    """Stations' arrays are found once, whatever the number of horizons."""
    net = network(spark, [(i, i + 1, 5, []) for i in range(20)])
    f = forecasts(spark, [(v, s, 10.0, 100) for v in range(21) for s in range(24)])
    ask = ask_for(spark, [(0, 1, 15, 480, 50.0, 50, [1])])
    made, arrays = [], search.station_arrays
    monkeypatch.setattr(search, "WHOLE_ARCS", 1)
    monkeypatch.setattr(search, "station_arrays", lambda *a: made.append(1) or arrays(*a))
    idx = index.build_index(net, f, 2, piv=pivots.pivot_distances(net, [0, 20]))
    assert router.route_index(ask, net, idx, f).first()["total_min"] == 70
    assert len(made) == 1
