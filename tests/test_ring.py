"""The forecast ring: streams equal batches, late rows lose, the index follows."""

import pytest
from pyspark.sql import functions as F

from saferoute.plans.world import world
from saferoute.sources import forecasts as fc
from saferoute.streaming import ring as rg


def values(df):
    return sorted((r["cell"], r["slot"], r["value"], r["conf_pct"], r["event_id"]) for r in df.where("wtype = 'ANY'").collect())


def test_stream_of_days_equals_batch(spark, small):
    batch = fc.newest(fc.parsed(spark.read.parquet(f"{small}/events.parquet"), False))
    assert values(rg.streamed_ring(spark, small)) == values(batch)


def test_repeated_and_out_of_order_rows(spark, small):
    rows = fc.parsed(spark.read.parquet(f"{small}/events.parquet"), False)
    late, early = rows.where("dayofmonth(issued) > 15"), rows.where("dayofmonth(issued) <= 15")
    assert values(rg.merge(fc.newest(late), early.unionAll(early))) == values(fc.newest(rows))


@pytest.mark.parametrize("wide", [False, True])
def test_changed_nodes_are_those_of_a_full_rebuild(spark, small, wide):
    from saferoute.plans.index import build_index, index_weather
    from saferoute.plans.method_queries import next_hour

    w = world(spark, small)
    i = build_index(w.net(), w.ring, 8)
    two = w.ring.where("wtype = 'ANY' and slot = 8").orderBy("cell").limit(2).withColumns({"value": F.lit(999.0), "issued": F.expr("issued + interval 40 days"), "event_id": F.col("event_id") + 10**12})
    new = next_hour(w) if wide else two  # a whole hour, or two stations
    changed = rg.apply_forecasts(new, w.ring, w.net(), i)
    full = rg.flat(index_weather(w.net(), i.lookup, rg.merge(w.ring, new), i.fanout, i.height))
    before = rg.flat(i.weather)
    columns = full.columns
    expected = full.exceptAll(before)
    got = changed.select(*columns)
    assert expected.exceptAll(got).isEmpty() and got.exceptAll(expected).isEmpty() and not got.isEmpty()


def test_new_edge_attributes_change_the_nodes_of_a_full_rebuild(spark, small):
    from saferoute.plans.index import build_index

    w = world(spark, small)
    i = build_index(w.net(), None, 8)
    new = w.net().edges.orderBy("eid").limit(6).select("eid", (F.col("w_min") + 500).alias("w_min"), F.array(F.lit(63)).alias("kw"))
    columns = ["level", "node", "lb_t", "ub_t", "kw_and", "kw_or"]
    got = rg.apply_edge_attributes(new, w.net(), i).select(*columns)
    after = build_index(rg.apply_edge_updates(new, w.net()), None, 8).nodes.select(*columns)
    expected = after.exceptAll(i.nodes.select(*columns))
    assert expected.exceptAll(got).isEmpty() and got.exceptAll(expected).isEmpty() and not got.isEmpty()


def test_streams_end_whole_and_off_the_driver(spark, small):
    from pyspark.sql import functions as F

    from saferoute.streaming import windows as W

    def in_memory():
        return {r[0] for r in spark.sql("show tables").select("tableName").collect() if r[0].startswith("t") and len(r[0]) == 33}

    before, n = in_memory(), spark.read.parquet(f"{small}/events.parquet").count()
    assert W.session(spark, small).agg(F.sum("n")).first()[0] == n
    assert W.tumbling(spark, small).agg(F.sum("n")).first()[0] == n
    assert W.joined(spark, small).count() == n
    assert in_memory() == before
