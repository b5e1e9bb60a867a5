from saferoute.plans.engine import Engine
from saferoute.schema import RouteOptions


def test_engine_methods_agree(spark, small):
    e = Engine(spark)
    net, ring = e.network("gau", small), e.forecasts(spark.read.parquet(f"{small}/events.parquet"))
    q = e.queries(net, n=6, sigma=4)
    got = {m: {r["qid"]: r["total_min"] for r in e.route(q, net, ring, m).select("qid", "total_min").collect()} for m in ("index", "astar", "filter_first")}
    assert got["index"] == got["astar"] == got["filter_first"]
    short = RouteOptions(horizon_min=60)
    assert {r["qid"]: r["total_min"] for r in e.route(q, net, ring, "rounds", short).select("qid", "total_min").collect()} == {r["qid"]: r["total_min"] for r in e.route(q, net, ring, "bfs", short).select("qid", "total_min").collect()}
    assert e.metrics().count() == 1
    text = e.explain_route(q, net)
    assert "Join" in text and "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text
    e.register_sql(net, ring)
    assert spark.sql("SELECT idw(30D, 20D, 0.2D) AS x").first()["x"] == 28.0
