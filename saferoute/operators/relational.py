"""The relational operators around the router, one registered query each with its SQL twin.

They are what a user needs to import networks, prepare forecasts and report on answers: scans, joins,
aggregates, windows, sets, functions, subqueries, graph and spatial helpers, user functions and sinks."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import oracle
from ..functions import spatial, weather
from ..plans.world import FANOUT, World, world
from ..sources.forecasts import parsed
from . import graph
from .storage import shared_dir

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
S: dict[str, str] = {}
NET = oracle.network("uni")
C, L = F.col, F.lit


def n_() -> F.Column:
    return F.count(F.lit(1)).alias("n")


def register(name: str, sql: str | None = None):  # noqa: ANN201
    def keep(f: Callable[[World], DataFrame]) -> Callable[[World], DataFrame]:
        Q[name] = lambda spark, sf_dir: f(world(spark, sf_dir))
        if sql:
            S[name] = sql
        return f

    return keep


def micros(c: str) -> F.Column:
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast({c} as timestamp_ntz))")


# --- scans and sinks --------------------------------------------------------------------------------------------


@register("op_scan_prune", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01'")
def _(w: World) -> DataFrame:
    return w.table("lineitem").where("l_shipdate >= '1995-01-01' and l_shipdate < '1996-01-01'").select("l_orderkey", "l_linenumber", "l_quantity")


@register("op_scan_formats")
def _(w: World) -> DataFrame:
    nation, folder = w.table("nation"), f"{shared_dir(w.spark)}/formats-{uuid.uuid4().hex}"
    out = None
    for kind in ("csv", "json", "orc"):
        nation.write.format(kind).save(f"{folder}/{kind}")
        part = w.spark.read.format(kind).schema(nation.schema).load(f"{folder}/{kind}").select(L(kind).alias("format"), "n_nationkey", "n_name", "n_regionkey")
        out = part if out is None else out.unionAll(part)
    nation.select(F.concat_ws("|", "n_nationkey", "n_name")).write.text(f"{folder}/text")
    text = w.spark.read.text(f"{folder}/text").select(F.split("value", r"\|").alias("x"))
    return out.unionAll(text.select(L("text"), F.get("x", L(0)).cast("int"), F.get("x", L(1)), L(None).cast("int")))


@register("op_partitioned_sink")
def _(w: World) -> DataFrame:
    path = f"{shared_dir(w.spark)}/cells-{uuid.uuid4().hex}"
    cells = w.net().vertices.select(C("v").alias("a"), "cell")
    w.net().edges.join(cells, "a").drop("kw").write.partitionBy("net", "cell").parquet(path)
    return w.spark.read.parquet(path).where("cell = 7").select("eid", "a", "b", "w_min")


@register("op_bucketed_lookup")
def _(w: World) -> DataFrame:
    name = "lookup_" + uuid.uuid4().hex
    path = f"{shared_dir(w.spark)}/{name}"
    w.index().lookup.write.bucketBy(8, "eid").sortBy("eid").option("path", path).saveAsTable(name)
    return w.spark.table(name).select("eid", "leaf")


@register("op_append_overwrite")
def _(w: World) -> DataFrame:
    path, region = f"{shared_dir(w.spark)}/modes-{uuid.uuid4().hex}", w.table("region")
    region.write.mode("overwrite").parquet(path)
    region.write.mode("append").parquet(path)
    return w.spark.read.parquet(path)


# --- projection and filters -------------------------------------------------------------------------------------


@register("op_project_struct", "SELECT o_orderkey, o_totalprice * 2 AS double_price, o_orderstatus FROM orders")
def _(w: World) -> DataFrame:
    s = w.table("orders").select(F.struct("o_orderkey", "o_totalprice", "o_orderstatus").alias("o"))
    s = s.withColumn("o", C("o").withField("double_price", C("o.o_totalprice") * 2).dropFields("o_totalprice"))
    return s.select("o.o_orderkey", "o.double_price", "o.o_orderstatus")


@register("op_filter_mix", "SELECT p_partkey FROM part WHERE p_size IN (1, 5, 9) OR p_retailprice BETWEEN 950 AND 960 OR p_name LIKE 'red%' OR regexp_matches(p_brand, '^Brand#1[0-9]$') OR p_type IS NULL OR p_size IS NOT DISTINCT FROM 7")
def _(w: World) -> DataFrame:
    c = C("p_size").isin(1, 5, 9) | C("p_retailprice").between(950, 960) | C("p_name").like("red%") | C("p_brand").rlike("^Brand#1[0-9]$") | C("p_type").isNull() | C("p_size").eqNullSafe(7)
    return w.table("part").where(c).select("p_partkey")


# --- joins ------------------------------------------------------------------------------------------------------


@register("op_join_inner_bhj", "SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def _(w: World) -> DataFrame:
    s, n, r = w.table("supplier"), w.table("nation"), w.table("region")
    return s.join(F.broadcast(n), C("s_nationkey") == C("n_nationkey")).join(F.broadcast(r), C("n_regionkey") == C("r_regionkey")).select("s_suppkey", "n_name", "r_name")


for _hint, _key in (("shuffle_hash", "op_join_shj"), ("merge", "op_join_smj")):

    @register(_key, "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
    def _(w: World, hint: str = _hint) -> DataFrame:
        j = w.table("orders").join(w.table("lineitem").hint(hint), C("o_orderkey") == C("l_orderkey"))
        return j.groupBy("o_orderpriority").agg(n_(), F.round(F.sum("l_quantity"), 2).alias("quantity"))


_F8 = "(SELECT * FROM ring WHERE wtype = 'click' AND slot = 8)"


@register("op_join_outer", f"WITH {NET}, {oracle.RING}, x AS (SELECT v, vtx.cell FROM vtx) SELECT 'left' AS kind, count(*) AS n, CAST(sum(coalesce(conf_pct, 0)) AS BIGINT) AS conf FROM x LEFT JOIN {_F8} f ON f.cell = x.cell UNION ALL SELECT 'right', count(*), CAST(sum(coalesce(conf_pct, 0)) AS BIGINT) FROM x RIGHT JOIN {_F8} f ON f.cell = x.cell UNION ALL SELECT 'full', count(*), CAST(sum(coalesce(conf_pct, 0)) AS BIGINT) FROM x FULL JOIN {_F8} f ON f.cell = x.cell")
def _(w: World) -> DataFrame:
    return _outer(w, w.net().vertices.select("v", "cell"))


def _outer(w: World, v: DataFrame) -> DataFrame:
    f, out = w.ring.where("wtype = 'click' and slot = 8").select("cell", "conf_pct"), None
    for how in ("left", "right", "full"):
        part = v.join(f, "cell", how).agg(n_(), F.sum(F.coalesce("conf_pct", L(0))).alias("conf")).select(L(how).alias("kind"), "n", "conf")
        out = part if out is None else out.unionAll(part)
    return out


@register("op_join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')")
def _(w: World) -> DataFrame:
    return w.table("customer").join(w.table("orders").where("o_orderstatus = 'F'"), C("c_custkey") == C("o_custkey"), "left_semi").select("c_custkey")


@register("op_join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def _(w: World) -> DataFrame:
    return w.table("customer").join(w.table("orders"), C("c_custkey") == C("o_custkey"), "left_anti").select("c_custkey")


@register("op_join_theta", "SELECT a.r_name AS first, b.r_name AS second FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")
def _(w: World) -> DataFrame:
    r = w.table("region")
    return r.alias("a").join(r.alias("b"), C("a.r_regionkey") < C("b.r_regionkey")).select(C("a.r_name").alias("first"), C("b.r_name").alias("second"))


@register("op_join_box_overlap", f"WITH {NET}, b AS (SELECT eid, least(p.x_mm, t.x_mm) AS x1, least(p.y_mm, t.y_mm) AS y1, greatest(p.x_mm, t.x_mm) AS x2, greatest(p.y_mm, t.y_mm) AS y2 FROM edg JOIN vtx p ON p.v = a JOIN vtx t ON t.v = b) SELECT eid FROM b WHERE x1 <= 180000 AND 120000 <= x2 AND y1 <= 180000 AND 120000 <= y2")
def _(w: World) -> DataFrame:
    from ..sources.networks import midpoints

    box = tuple(map(L, (120000, 120000, 180000, 180000)))
    return midpoints(w.net()).where(spatial.intersects((C("xmin"), C("ymin"), C("xmax"), C("ymax")), box)).select("eid")


@register("op_join_range_binned", f"WITH {NET}, b AS (SELECT i AS box, i * 70000 AS x1, i * 70000 + 90000 AS x2 FROM (SELECT unnest(range(5)) AS i)) SELECT box, count(*) AS n FROM b JOIN vtx ON x_mm BETWEEN x1 AND x2 AND y_mm BETWEEN x1 AND x2 GROUP BY box")
def _(w: World) -> DataFrame:
    side = 50_000
    boxes = w.spark.range(5).select(C("id").alias("box"), (C("id") * 70000).alias("x1"), (C("id") * 70000 + 90000).alias("x2"))
    bins = F.sequence(F.floor(C("x1") / side), F.floor(C("x2") / side))
    boxes = boxes.withColumn("bx", F.explode(bins)).withColumn("by", F.explode(bins))
    v = w.net().vertices.withColumns({"bx": F.floor(C("x_mm") / side), "by": F.floor(C("y_mm") / side)})
    return boxes.join(v, ["bx", "by"]).where(C("x_mm").between(C("x1"), C("x2")) & C("y_mm").between(C("x1"), C("x2"))).groupBy("box").agg(n_())


@register("op_join_asof", "WITH p AS (SELECT CAST(s AS INTEGER) AS cell, TIMESTAMP '2024-01-05 00:00:00' + INTERVAL 6 HOUR * i AS at FROM (SELECT unnest(range(25)) AS s), (SELECT unnest(range(20)) AS i)), e AS (SELECT CAST(user_id % 25 AS INTEGER) AS cell, max(event_id) AS event_id, ts FROM events GROUP BY 1, ts) SELECT p.cell, epoch_us(p.at) AS at_us, e.event_id FROM p ASOF LEFT JOIN e ON p.cell = e.cell AND p.at >= e.ts")
def _(w: World) -> DataFrame:
    e = w.table("events").groupBy((C("user_id") % 25).cast("int").alias("cell"), C("ts").cast("timestamp_ntz").alias("at")).agg(F.max("event_id").alias("event_id"))
    at = F.expr("timestamp_ntz'2024-01-05 00:00:00' + make_dt_interval(0, 6 * cast(i as int))")
    p = w.spark.range(25).select(C("id").cast("int").alias("cell")).join(w.spark.range(20).select(C("id").alias("i"))).select("cell", at.alias("at"), L(None).cast("long").alias("event_id"))
    both = e.withColumn("probe", L(False)).unionByName(p.withColumn("probe", L(True)))
    order = Window.partitionBy("cell").orderBy("at", "probe").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("event_id", F.last("event_id", ignorenulls=True).over(order)).where("probe").select("cell", micros("at").alias("at_us"), "event_id")


@register("op_join_interval", f"WITH {NET} SELECT tail, head, slot FROM arc, (SELECT unnest(range(24)) AS slot) WHERE 475 < (slot + 1) * 60 AND 475 + w_min >= slot * 60")
def _(w: World) -> DataFrame:
    slots = F.sequence(F.floor(L(475) / 60), F.floor((L(475) + C("w_min")) / 60))
    return w.net().arcs.select("tail", "head", F.explode(slots).alias("slot")).where("slot < 24")


@register("op_join_self_links", f"WITH {NET}, x AS (SELECT eid, a AS v FROM edg UNION ALL SELECT eid, b FROM edg) SELECT DISTINCT s.eid AS eid1, t.eid AS eid2 FROM x s JOIN x t ON s.v = t.v AND s.eid < t.eid")
def _(w: World) -> DataFrame:
    x = w.net().edges.select("eid", F.explode(F.array("a", "b")).alias("v"))
    return x.toDF("eid1", "v").join(x.toDF("eid2", "v"), "v").where("eid1 < eid2").select("eid1", "eid2").distinct()


@register("op_join_cross_sample", f"WITH {NET}, s AS (SELECT * FROM vtx WHERE v < 50) SELECT a.v AS u, b.v AS v, abs(a.x_mm - b.x_mm) + abs(a.y_mm - b.y_mm) AS manhattan FROM s a, s b")
def _(w: World) -> DataFrame:
    s = w.net().vertices.where("v < 50").select("v", "x_mm", "y_mm")
    return s.toDF("u", "x1", "y1").crossJoin(s).select("u", "v", (F.abs(C("x1") - C("x_mm")) + F.abs(C("y1") - C("y_mm"))).alias("manhattan"))


@register("op_join_lateral_knn", f"WITH RECURSIVE {NET}, {oracle.query_set()} SELECT q.v AS q, n.v AS v, n.d2 FROM (SELECT * FROM vtx WHERE v IN (SELECT src FROM q)) q, LATERAL (SELECT v, (x_mm - q.x_mm) * (x_mm - q.x_mm) + (y_mm - q.y_mm) * (y_mm - q.y_mm) AS d2 FROM vtx t WHERE t.v <> q.v ORDER BY d2, v LIMIT 3) n")
def _(w: World) -> DataFrame:
    """The three vertices nearest to each source of the query set, of all vertices."""
    return _nearest(w, w.queries().select(C("src").alias("v")).distinct())


def _nearest(w: World, asked: DataFrame) -> DataFrame:
    v = w.net().vertices.select("v", "x_mm", "y_mm")
    q = v.join(asked, "v", "left_semi").toDF("q", "qx", "qy")
    d2 = ((C("x_mm") - C("qx").outer()) * (C("x_mm") - C("qx").outer()) + (C("y_mm") - C("qy").outer()) * (C("y_mm") - C("qy").outer())).alias("d2")
    return q.lateralJoin(v.where(C("v") != C("q").outer()).select("v", d2).orderBy("d2", "v").limit(3)).select("q", "v", "d2")


# --- aggregates -------------------------------------------------------------------------------------------------


@register("op_agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS total, round(avg(l_discount), 6) AS mean, min(l_tax) AS low, max(l_tax) AS high, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS var FROM lineitem GROUP BY 1, 2")
def _(w: World) -> DataFrame:
    return w.table("lineitem").groupBy("l_returnflag", "l_linestatus").agg(n_(), F.round(F.sum("l_quantity"), 2).alias("total"), F.round(F.avg("l_discount"), 6).alias("mean"), F.min("l_tax").alias("low"), F.max("l_tax").alias("high"), F.round(F.stddev("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_quantity"), 6).alias("var"))


@register("op_agg_distinct", "SELECT p_type, count(DISTINCT l_suppkey) AS suppliers FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def _(w: World) -> DataFrame:
    return w.table("lineitem").join(w.table("part"), C("l_partkey") == C("p_partkey")).groupBy("p_type").agg(F.count_distinct("l_suppkey").alias("suppliers"))


@register("op_agg_approx")
def _(w: World) -> DataFrame:
    return w.table("lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median"))


_SEG = "SELECT c_mktsegment, o_orderpriority, CAST(grouping_id(c_mktsegment, o_orderpriority) AS BIGINT) AS level, count(*) AS n, round(sum(o_totalprice), 2) AS price FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY {} (c_mktsegment, o_orderpriority)"


for _how in ("rollup", "cube"):

    @register(f"op_agg_{_how}", _SEG.format(_how.upper()))
    def _(w: World, how: str = _how) -> DataFrame:
        j = w.table("orders").join(w.table("customer"), C("o_custkey") == C("c_custkey"))
        return getattr(j, how)("c_mktsegment", "o_orderpriority").agg(F.grouping_id().alias("level"), n_(), F.round(F.sum("o_totalprice"), 2).alias("price"))


@register("op_agg_gsets", "SELECT event_type, CAST(user_id % 25 AS INTEGER) AS cell, CAST(hour(ts) AS INTEGER) AS slot, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type, cell), (slot), ())")
def _(w: World) -> DataFrame:
    e = parsed(w.table("events")).select(C("wtype").alias("event_type"), "cell", "slot")
    return e.groupingSets([["event_type", "cell"], ["slot"], []], "event_type", "cell", "slot").agg(n_())


@register("op_agg_bits", f"WITH {NET}, x AS (SELECT cell, coalesce(list_aggregate(list_transform(kw, lambda k: CAST(1 AS BIGINT) << k), 'bit_or'), 0) AS word FROM edg JOIN vtx ON v = a) SELECT cell, bit_and(word) AS all_of, bit_or(word) AS any_of, bit_xor(word) AS odd FROM x GROUP BY cell")
def _(w: World) -> DataFrame:
    from ..functions.keywords import bitmap

    x = w.net().edges.join(w.net().vertices.select(C("v").alias("a"), "cell"), "a").select("cell", F.get(bitmap(C("kw")), L(0)).alias("word"))
    return x.groupBy("cell").agg(F.bit_and("word").alias("all_of"), F.bit_or("word").alias("any_of"), F.bit_xor("word").alias("odd"))


@register("op_agg_minby", f"WITH {NET} SELECT tail, min_by(eid, w_min * 1000000 + eid) AS cheapest, max_by(eid, w_min * 1000000 + eid) AS dearest FROM arc GROUP BY tail")
def _(w: World) -> DataFrame:
    key = F.struct("w_min", "eid")
    return w.net().arcs.groupBy("tail").agg(F.min_by("eid", key).alias("cheapest"), F.max_by("eid", key).alias("dearest"))


@register("op_agg_collect", f"WITH {NET} SELECT cell, array_to_string(list_sort(list_distinct(flatten(list(kw)))), ',') AS kws FROM edg JOIN vtx ON v = a GROUP BY cell")
def _(w: World) -> DataFrame:
    x = w.net().edges.join(w.net().vertices.select(C("v").alias("a"), "cell"), "a").select("cell", F.explode_outer("kw").alias("k"))
    return x.groupBy("cell").agg(F.array_join(F.array_sort(F.collect_set("k")), ",").alias("kws"))


@register("op_agg_filter", "SELECT CAST(user_id % 25 AS INTEGER) AS cell, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE value > 50) AS high, round(sum(value) FILTER (WHERE event_type = 'error'), 2) AS errors FROM events GROUP BY 1")
def _(w: World) -> DataFrame:
    e = w.table("events").withColumn("cell", (C("user_id") % 25).cast("int"))
    return e.groupBy("cell").agg(F.count_if(C("event_type") == "click").alias("clicks"), F.count_if(C("value") > 50).alias("high"), F.round(F.sum(F.when(C("event_type") == "error", C("value"))), 2).alias("errors"))


@register("op_agg_median", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")
def _(w: World) -> DataFrame:
    return w.table("events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.percentile("value", 0.9), 6).alias("p90"))


@register("op_pivot", "SELECT CAST(hour(ts) AS INTEGER) AS slot, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'error') AS error FROM events GROUP BY 1")
def _(w: World) -> DataFrame:
    return parsed(w.table("events")).groupBy("slot").pivot("wtype", ["click", "error"]).agg(F.count(L(1))).select("slot", F.coalesce("click", L(0)).alias("click"), F.coalesce("error", L(0)).alias("error"))


@register("op_unpivot", "SELECT s_suppkey, 'nation' AS name, CAST(s_nationkey AS DOUBLE) AS value FROM supplier UNION ALL SELECT s_suppkey, 'balance', s_acctbal FROM supplier")
def _(w: World) -> DataFrame:
    s = w.table("supplier").select("s_suppkey", C("s_nationkey").cast("double").alias("nation"), C("s_acctbal").alias("balance"))
    return s.unpivot("s_suppkey", ["nation", "balance"], "name", "value")


@register("op_having", "SELECT user_id, count(*) AS n FROM events GROUP BY 1 HAVING count(*) > (SELECT avg(c) FROM (SELECT count(*) AS c FROM events GROUP BY user_id))")
def _(w: World) -> DataFrame:
    per = w.table("events").groupBy("user_id").agg(n_())
    return per.join(F.broadcast(per.agg(F.avg("n").alias("mean")))).where("n > mean").select("user_id", "n")


@register("op_stats", f"WITH {NET} SELECT round(corr(len_mm, w_min), 6) AS r, round(covar_pop(len_mm, w_min), 3) AS cov, round(skewness(w_min), 4) > 0 AS skewed, count(*) AS n FROM edg")
def _(w: World) -> DataFrame:
    return w.net().edges.agg(F.round(F.corr("len_mm", "w_min"), 6).alias("r"), F.round(F.covar_pop("len_mm", "w_min"), 3).alias("cov"), (F.skewness("w_min") > 0).alias("skewed"), n_())


@register("op_histogram", f"WITH {NET} SELECT w_min // 10 AS bin, count(*) AS n FROM edg GROUP BY 1")
def _(w: World) -> DataFrame:
    return w.net().edges.groupBy(F.floor(C("w_min") / 10).alias("bin")).agg(n_())


# --- windows, order, sets ---------------------------------------------------------------------------------------



def _strip() -> Window:
    return Window.partitionBy("strip").orderBy("x_mm", "v")


@register("op_win_rank", f"WITH {NET} SELECT v, CAST(rank() OVER s AS INTEGER) AS rk, CAST(dense_rank() OVER s AS INTEGER) AS drk, CAST(ntile(4) OVER t AS INTEGER) AS nt, round(percent_rank() OVER s, 6) AS pr, round(cume_dist() OVER s, 6) AS cd FROM vtx WINDOW s AS (PARTITION BY strip ORDER BY cell), t AS (PARTITION BY strip ORDER BY x_mm, v)")
def _(w: World) -> DataFrame:
    s = Window.partitionBy("strip").orderBy("cell")
    return w.net().vertices.select("v", F.rank().over(s).alias("rk"), F.dense_rank().over(s).alias("drk"), F.ntile(4).over(_strip()).alias("nt"), F.round(F.percent_rank().over(s), 6).alias("pr"), F.round(F.cume_dist().over(s), 6).alias("cd"))


@register("op_win_offset", f"WITH {NET} SELECT v, lead(v) OVER t AS nxt, lag(x_mm, 1, 0) OVER t AS prv, first_value(v) OVER t AS fst, nth_value(v, 2) OVER (PARTITION BY strip ORDER BY x_mm, v ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS sec FROM vtx WINDOW t AS (PARTITION BY strip ORDER BY x_mm, v)")
def _(w: World) -> DataFrame:
    whole = _strip().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return w.net().vertices.select("v", F.lead("v").over(_strip()).alias("nxt"), F.lag("x_mm", 1, 0).over(_strip()).alias("prv"), F.first("v").over(_strip()).alias("fst"), F.nth_value("v", 2).over(whole).alias("sec"))


@register("op_win_rows", f"WITH {NET} SELECT v, CAST(sum(x_mm) OVER (PARTITION BY strip ORDER BY x_mm, v ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS near FROM vtx")
def _(w: World) -> DataFrame:
    return w.net().vertices.select("v", F.sum("x_mm").over(_strip().rowsBetween(-2, 0)).alias("near"))


@register("op_win_range", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id % 25 ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 6) AS mean FROM events")
def _(w: World) -> DataFrame:
    e = w.table("events").select("event_id", "value", (C("user_id") % 25).alias("cell"), F.floor(micros("ts") / 1000000).alias("s"))
    return e.select("event_id", F.round(F.avg("value").over(Window.partitionBy("cell").orderBy("s").rangeBetween(-3600, 0)), 6).alias("mean"))


@register("op_sort_multi", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100")
def _(w: World) -> DataFrame:
    return w.table("orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100).select("o_orderkey", "o_totalprice")


@register("op_limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 20 OFFSET 40")
def _(w: World) -> DataFrame:
    return w.table("orders").orderBy("o_orderkey").offset(40).limit(20).select("o_orderkey")


@register("op_topk_group", f"WITH {NET}, x AS (SELECT cell, eid, w_min, CAST(row_number() OVER (PARTITION BY cell ORDER BY w_min DESC, eid) AS INTEGER) AS k FROM edg JOIN vtx ON v = a) SELECT * FROM x WHERE k <= 3")
def _(w: World) -> DataFrame:
    x = w.net().edges.join(w.net().vertices.select(C("v").alias("a"), "cell"), "a")
    return x.select("cell", "eid", "w_min", F.row_number().over(Window.partitionBy("cell").orderBy(F.desc("w_min"), "eid")).alias("k")).where("k <= 3")


_SETS = {"union": ("unionAll", "union"), "intersect": ("intersectAll", "intersect"), "except": ("exceptAll", "subtract")}
def _both_kinds(a: DataFrame, b: DataFrame, every: str, once: str) -> DataFrame:
    one = getattr(a, once)(b)
    kinds = (("all", getattr(a, every)(b)), ("distinct", one.distinct() if once == "union" else one))
    x, y = (d.groupBy("k").agg(n_()).select(L(k).alias("kind"), "k", "n") for k, d in kinds)
    return x.unionAll(y)


for _op, (_all, _one) in _SETS.items():
    _a, _b = "SELECT o_custkey AS k FROM orders", "SELECT c_custkey AS k FROM customer"

    @register(f"op_set_{_op}", f"SELECT 'all' AS kind, k, count(*) AS n FROM ({_a} {_op.upper()} ALL {_b}) GROUP BY k UNION ALL SELECT 'distinct', k, count(*) FROM ({_a} {_op.upper()} {_b}) GROUP BY k")
    def _(w: World, every: str = _all, once: str = _one) -> DataFrame:
        return _both_kinds(w.table("orders").select(C("o_custkey").alias("k")), w.table("customer").select(C("c_custkey").alias("k")), every, once)


@register("op_union_by_name", "SELECT s_suppkey AS id, s_acctbal AS balance, CAST(NULL AS VARCHAR) AS segment FROM supplier UNION ALL SELECT c_custkey, c_acctbal, c_mktsegment FROM customer")
def _(w: World) -> DataFrame:
    s = w.table("supplier").select(C("s_suppkey").alias("id"), C("s_acctbal").alias("balance"))
    return s.unionByName(w.table("customer").select(C("c_custkey").alias("id"), C("c_acctbal").alias("balance"), C("c_mktsegment").alias("segment")), allowMissingColumns=True)


@register("op_dedupe", f"WITH {NET} SELECT DISTINCT tail, w_min FROM arc")
def _(w: World) -> DataFrame:
    return w.net().arcs.dropDuplicates(["tail", "w_min"]).select("tail", "w_min")


# --- functions --------------------------------------------------------------------------------------------------


@register("op_string", "SELECT p_partkey, upper(p_name) AS up, length(p_name) AS len, substring(p_name, 1, 3) AS head, reverse(p_brand) AS back, replace(p_brand, '#', '-') AS dash, lpad(p_type, 12, '*') AS pad, split_part(p_name, ' ', 2) AS second, regexp_replace(p_name, '[aeiou]', '', 'g') AS bare, concat_ws('/', p_brand, p_type) AS both, levenshtein(p_name, p_type) AS dist, translate(p_type, 'AEO', 'aeo') AS tr FROM part".replace("length(p_name)", "CAST(length(p_name) AS INTEGER)").replace("levenshtein(p_name, p_type)", "CAST(levenshtein(p_name, p_type) AS INTEGER)"))
def _(w: World) -> DataFrame:
    return w.table("part").select("p_partkey", F.upper("p_name").alias("up"), F.length("p_name").alias("len"), F.substring("p_name", 1, 3).alias("head"), F.reverse("p_brand").alias("back"), F.replace("p_brand", L("#"), L("-")).alias("dash"), F.lpad("p_type", 12, "*").alias("pad"), F.split_part("p_name", L(" "), L(2)).alias("second"), F.regexp_replace("p_name", "[aeiou]", "").alias("bare"), F.concat_ws("/", "p_brand", "p_type").alias("both"), F.levenshtein("p_name", "p_type").alias("dist"), F.translate("p_type", "AEO", "aeo").alias("tr"))


@register("op_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(day(o_orderdate) AS INTEGER) AS d, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS dow, epoch_us(date_trunc('month', o_orderdate)) AS month_us, CAST(date_diff('day', TIMESTAMP '1990-01-01', o_orderdate) AS INTEGER) AS days, epoch_us(o_orderdate + INTERVAL 3 DAY) AS later_us FROM orders")
def _(w: World) -> DataFrame:
    o = w.table("orders").withColumns({"month_": F.date_trunc("month", "o_orderdate"), "later_": F.expr("cast(o_orderdate as timestamp_ntz) + interval 3 days")})
    return o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofmonth("o_orderdate").alias("d"), F.dayofweek("o_orderdate").alias("dow"), micros("month_").alias("month_us"), F.datediff(C("o_orderdate"), L("1990-01-01")).alias("days"), micros("later_").alias("later_us"))


@register("op_interval", f"WITH {NET} SELECT tail, head, epoch_us(TIMESTAMP '2024-01-01 08:00:00' + INTERVAL 1 MINUTE * w_min) AS arrive_us, (480 + w_min) // 60 > 8 AS next_slot FROM arc")
def _(w: World) -> DataFrame:
    a = w.net().arcs.withColumn("at", F.expr("timestamp_ntz'2024-01-01 08:00:00' + make_dt_interval(0, 0, cast(w_min as int))"))
    return a.select("tail", "head", micros("at").alias("arrive_us"), (F.floor((480 + C("w_min")) / 60) > 8).alias("next_slot"))


@register("op_math", f"WITH {NET} SELECT v, round(sqrt(x_mm), 6) AS root, round(pow(cell, 2), 3) AS sq, round(ln(x_mm + 1), 6) AS lg, round(exp(cell / 10.0), 6) AS ex, abs(x_mm - y_mm) AS gap, CAST(sign(x_mm - y_mm) AS INTEGER) AS sgn, x_mm % 7 AS md, CAST(floor(x_mm / 1000.0) AS BIGINT) AS fl, CAST(ceil(x_mm / 1000.0) AS BIGINT) AS ce, round(radians(cell), 9) AS rad, round(degrees(atan2(y_mm, x_mm + 1)), 6) AS ang FROM vtx")
def _(w: World) -> DataFrame:
    x, y = C("x_mm"), C("y_mm")
    return w.net().vertices.select("v", F.round(F.sqrt(x), 6).alias("root"), F.round(F.pow("cell", L(2)), 3).alias("sq"), F.round(F.ln(x + 1), 6).alias("lg"), F.round(F.exp(C("cell") / 10.0), 6).alias("ex"), F.abs(x - y).alias("gap"), F.sign(x - y).cast("int").alias("sgn"), (x % 7).alias("md"), F.floor(x / 1000.0).alias("fl"), F.ceil(x / 1000.0).alias("ce"), F.round(F.radians("cell"), 9).alias("rad"), F.round(F.degrees(F.atan2(y, x + 1)), 6).alias("ang"))


_HAV = "2 * 3958.8 * asin(sqrt(pow(sin(radians((y_mm - 200000) / 10000.0) / 2), 2) + cos(radians(20.0)) * cos(radians(y_mm / 10000.0)) * pow(sin(radians((x_mm - 200000) / 10000.0) / 2), 2)))"


@register("op_haversine", f"WITH {NET} SELECT v, round({_HAV}, 6) AS miles FROM vtx")
def _(w: World) -> DataFrame:
    return w.net().vertices.select("v", F.round(spatial.haversine_miles(L(20.0), L(20.0), C("x_mm") / 10000.0, C("y_mm") / 10000.0), 6).alias("miles"))


@register("op_decimal", "SELECT l_orderkey, l_linenumber, CAST(CAST(CAST(l_extendedprice AS DECIMAL(12,2)) * (1 - CAST(l_discount AS DECIMAL(4,2))) AS DECIMAL(18,4)) AS VARCHAR) AS net FROM lineitem")
def _(w: World) -> DataFrame:
    net = C("l_extendedprice").cast("decimal(12,2)") * (1 - C("l_discount").cast("decimal(4,2)"))
    return w.table("lineitem").select("l_orderkey", "l_linenumber", net.cast("decimal(18,4)").cast("string").alias("net"))


@register("op_array", f"WITH {NET}, x AS (SELECT eid, list_distinct([eid % 5, eid % 3, 2, eid % 7]) AS p, [2, 4, eid % 5] AS q FROM edg) SELECT eid, CAST(len(p) AS INTEGER) AS n, list_contains(p, 4) AS has, array_to_string(list_sort(list_distinct(list_concat(p, q))), ',') AS uni, array_to_string(list_sort(list_distinct(list_intersect(p, q))), ',') AS inter, array_to_string(list_sort(list_filter(p, lambda z: NOT list_contains(q, z))), ',') AS exc, array_to_string(list_sort(p)[1:2], ',') AS two FROM x")
def _(w: World) -> DataFrame:
    e = C("eid")
    x = w.net().edges.select("eid", F.array_distinct(F.array(e % 5, e % 3, L(2).cast("long"), e % 7)).alias("p"), F.array(L(2).cast("long"), L(4).cast("long"), e % 5).alias("q"))
    j = lambda a: F.array_join(F.array_sort(a), ",")
    return x.select("eid", F.size("p").alias("n"), F.array_contains("p", 4).alias("has"), j(F.array_union("p", "q")).alias("uni"), j(F.array_intersect("p", "q")).alias("inter"), j(F.array_except("p", "q")).alias("exc"), F.array_join(F.slice(F.array_sort("p"), 1, 2), ",").alias("two"))


@register("op_higher_order", f"WITH RECURSIVE {NET}, {oracle.sssp(oracle.fixed_pivots())}, p AS (SELECT v, list(dist ORDER BY src) AS d FROM sp GROUP BY v) SELECT v, CAST(list_sum(list_transform(d, lambda x: x // 1000)) AS BIGINT) AS miles, CAST(len(list_filter(d, lambda x: x > 100000)) AS INTEGER) AS far, len(list_filter(d, lambda x: x = 0)) > 0 AS is_pivot, len(list_filter(d, lambda x: x < 300000)) = len(d) AS all_near FROM p")
def _(w: World) -> DataFrame:
    p = w.piv()
    return p.select("v", F.aggregate(F.transform("piv", lambda x: F.floor(x / 1000)), L(0).cast("long"), lambda a, x: a + x).alias("miles"), F.size(F.filter("piv", lambda x: x > 100000)).alias("far"), F.exists("piv", lambda x: x == 0).alias("is_pivot"), F.forall("piv", lambda x: x < 300000).alias("all_near"))


@register("op_explode", f"WITH {NET} SELECT eid, CAST(i - 1 AS INTEGER) AS pos, kw[i] AS k FROM (SELECT eid, kw, unnest(range(1, len(kw) + 1)) AS i FROM edg) UNION ALL SELECT eid, NULL, NULL FROM edg WHERE len(kw) = 0")
def _(w: World) -> DataFrame:
    return w.net().edges.select("eid", F.posexplode_outer("kw").alias("pos", "k"))


@register("op_map", f"WITH {NET} SELECT eid, CAST(len(list_filter([w_min, w_min * 2, w_min * 3], lambda x: x > 30)) AS INTEGER) AS over, w_min * 2 AS second FROM edg")
def _(w: World) -> DataFrame:
    m = F.map_from_arrays(F.array(L(20), L(50), L(90)), F.array(C("w_min"), C("w_min") * 2, C("w_min") * 3))
    x = w.net().edges.select("eid", m.alias("m"))
    return x.select("eid", F.size(F.map_keys(F.map_filter("m", lambda k, v: v > 30))).alias("over"), F.element_at(F.transform_values("m", lambda k, v: v), 50).alias("second"))


@register("op_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k, CAST(json_extract(props, '$.k') AS VARCHAR) AS text, '{\"cell\":' || (user_id % 25) || ',\"type\":\"' || event_type || '\"}' AS packed FROM events")
def _(w: World) -> DataFrame:
    return w.table("events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.get_json_object("props", "$.k").alias("text"), F.to_json(F.struct((C("user_id") % 25).alias("cell"), C("event_type").alias("type"))).alias("packed"))


@register("op_variant")
def _(w: World) -> DataFrame:
    return w.table("events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@register("op_conditional", "SELECT event_id, CASE WHEN value > 60 THEN 'high' WHEN value > 20 THEN 'mid' ELSE 'low' END AS band, coalesce(nullif(event_type, 'error'), 'none') AS kind, greatest(value, 10.0) AS floor_, least(value, 90.0) AS cap FROM events")
def _(w: World) -> DataFrame:
    band = F.when(C("value") > 60, "high").when(C("value") > 20, "mid").otherwise("low")
    return w.table("events").select("event_id", band.alias("band"), F.coalesce(F.nullif("event_type", L("error")), L("none")).alias("kind"), F.greatest("value", L(10.0)).alias("floor_"), F.least("value", L(90.0)).alias("cap"))


_SUB = """SELECT c_custkey, (SELECT max(o_totalprice) FROM orders WHERE o_custkey = c_custkey) AS top FROM customer
WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P') AND c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey < 3)"""


def with_views(w: World, *names: str) -> None:
    for n in names:
        w.table(n).createOrReplaceTempView(n)


@register("op_subquery", _SUB)
def _(w: World) -> DataFrame:
    with_views(w, "customer", "orders", "nation")
    return w.spark.sql(_SUB)


_CTE = "WITH per AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), big AS (SELECT * FROM per WHERE n > 10) SELECT c_mktsegment, count(*) AS customers, CAST(sum(n) AS BIGINT) AS orders_ FROM big JOIN customer ON c_custkey = o_custkey GROUP BY 1"


@register("op_cte", _CTE)
def _(w: World) -> DataFrame:
    with_views(w, "customer", "orders")
    return w.spark.sql(_CTE)


@register("op_cte_recursive", f"WITH RECURSIVE {NET}, r(v, hops) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT head, hops + 1 FROM r JOIN arc ON tail = v WHERE hops < 4) SELECT DISTINCT v FROM r")
def _(w: World) -> DataFrame:
    w.net().arcs.select("tail", "head").createOrReplaceTempView("arc")
    return w.spark.sql("WITH RECURSIVE r(v, hops) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT head, hops + 1 FROM r JOIN arc ON tail = v WHERE hops < 4) SELECT DISTINCT v FROM r")


@register("op_sample")
def _(w: World) -> DataFrame:
    return w.net().vertices.sample(0.1, 42).select("v").withColumn("kind", L("even")).unionAll(w.net().vertices.sampleBy("cell", {0: 0.5, 1: 0.5}, 42).select("v", L("by_cell")))


@register("op_vector", "WITH q AS (SELECT list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS q FROM embeddings WHERE vec_id = 0), x AS (SELECT vec_id, round(list_sum(list_transform(list_zip(embedding, q), lambda z: CAST(z[1] AS DOUBLE) * z[2])), 4) AS dot, round(sqrt(list_sum(list_transform(list_zip(embedding, q), lambda z: pow(CAST(z[1] AS DOUBLE) - z[2], 2)))), 4) AS l2 FROM embeddings, q) SELECT vec_id, dot, l2 FROM x ORDER BY dot DESC, vec_id LIMIT 5")
def _(w: World) -> DataFrame:
    v = w.table("embeddings").select("vec_id", C("embedding").cast("array<double>").alias("e"))
    q = v.where("vec_id = 0").select(C("e").alias("q"))
    add = lambda a, x: a + x
    dot = F.aggregate(F.zip_with("e", "q", lambda a, b: a * b), L(0.0), add)
    l2 = F.sqrt(F.aggregate(F.zip_with("e", "q", lambda a, b: (a - b) * (a - b)), L(0.0), add))
    return v.join(F.broadcast(q)).select("vec_id", F.round(dot, 4).alias("dot"), F.round(l2, 4).alias("l2")).orderBy(F.desc("dot"), "vec_id").limit(5)


# --- graph and space --------------------------------------------------------------------------------------------


@register("op_bfs_hops", f"WITH RECURSIVE {NET}, r(v, hops) AS (SELECT CAST(7 AS BIGINT), 0 UNION SELECT head, hops + 1 FROM r JOIN arc ON tail = v WHERE hops < 6) SELECT v, min(hops) AS hops FROM r GROUP BY v")
def _(w: World) -> DataFrame:
    src = w.spark.createDataFrame([(0, 7)], "qid int, src long")
    return graph.bfs_hops(w.net().arcs, src, 6).select("v", "hops")


@register("op_k_hop", f"WITH RECURSIVE {NET}, r(qid, v, hops) AS (SELECT v, v, 0 FROM vtx UNION SELECT qid, head, hops + 1 FROM r JOIN arc ON tail = v WHERE hops < 3) SELECT CAST(qid AS INTEGER) AS qid, count(DISTINCT v) AS reached FROM r GROUP BY qid")
def _(w: World) -> DataFrame:
    return graph.k_hop(w.net().arcs, w.net().vertices.select(C("v").cast("int").alias("qid"), C("v").alias("src")), 3)


@register("op_components", f"WITH RECURSIVE {NET}, reach(v) AS (SELECT CAST(0 AS BIGINT) UNION SELECT head FROM reach JOIN arc ON tail = v) SELECT v, CAST(0 AS BIGINT) AS component FROM reach")
def _(w: World) -> DataFrame:
    return graph.components(w.net().vertices, w.net().edges)


for _w, _n in (("len_mm", "op_sssp_len"), ("w_min", "op_sssp_time")):

    @register(_n, f"WITH RECURSIVE {NET}, {oracle.sssp('SELECT CAST(3 AS BIGINT) AS src', _w)} SELECT v, dist FROM sp")
    def _(w: World, weight: str = _w) -> DataFrame:
        return graph.distances(w.net().arcs, w.spark.createDataFrame([(3,)], "src long"), weight, w.net().vertices).select("v", "dist")


_IX = f"WITH {NET}, {oracle.index(FANOUT)}"


@register("op_zorder", f"{_IX} SELECT eid, z FROM pos")
def _(w: World) -> DataFrame:
    from ..sources.networks import midpoints

    return midpoints(w.net()).select("eid", "z")


@register("op_mbr", f"{_IX} SELECT pos // {FANOUT} AS leaf, min(xmin) AS xmin, min(ymin) AS ymin, max(xmax) AS xmax, max(ymax) AS ymax FROM pos GROUP BY 1")
def _(w: World) -> DataFrame:
    from ..sources.networks import midpoints

    m = midpoints(w.net()).join(w.index().lookup, "eid")
    return m.groupBy("leaf").agg(*[f(c).alias(c) for f, c in ((F.min, "xmin"), (F.min, "ymin"), (F.max, "xmax"), (F.max, "ymax"))])


@register("op_radius", f"WITH {NET} SELECT q.v AS q, count(*) AS n FROM vtx q JOIN vtx t ON (t.x_mm - q.x_mm) * (t.x_mm - q.x_mm) + (t.y_mm - q.y_mm) * (t.y_mm - q.y_mm) <= 900000000 GROUP BY 1")
def _(w: World) -> DataFrame:
    return _within(w)


def _within(w: World) -> DataFrame:
    side, r = 30_000, 30_000
    v = w.net().vertices.select("v", "x_mm", "y_mm", F.floor(C("x_mm") / side).alias("bx"), F.floor(C("y_mm") / side).alias("by"))
    near = lambda c: F.sequence(F.floor((C(c) - r) / side), F.floor((C(c) + r) / side))
    q = v.select(C("v").alias("q"), C("x_mm").alias("qx"), C("y_mm").alias("qy")).withColumn("bx", F.explode(near("qx"))).withColumn("by", F.explode(near("qy")))
    d2 = (C("x_mm") - C("qx")) * (C("x_mm") - C("qx")) + (C("y_mm") - C("qy")) * (C("y_mm") - C("qy"))
    return q.join(v, ["bx", "by"]).where(d2 <= r * r).groupBy("q").agg(n_())


# --- user functions ---------------------------------------------------------------------------------------------

_IDW = f"WITH {NET}, {oracle.RING}, {oracle.slot_bounds()} SELECT eid, round(0.75 * wj + 0.25 * wk, 6) AS value FROM sb WHERE slot = 8"


def _ends8(w: World) -> DataFrame:
    from .pruning import edge_slot_bounds

    return edge_slot_bounds(w.net().edges, w.net().vertices, w.ring, 50.0).where("slot = 8")


@register("op_sql_udf", _IDW)
def _(w: World) -> DataFrame:
    w.spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION idw(wj DOUBLE, wk DOUBLE, f DOUBLE) RETURNS DOUBLE RETURN (1 - f) * wj + f * wk")
    _ends8(w).createOrReplaceTempView("ends8")
    return w.spark.sql("SELECT eid, round(idw(wj, wk, 0.25D), 6) AS value FROM ends8")


@register("op_pandas_udf", _IDW)
def _(w: World) -> DataFrame:
    @F.pandas_udf("double")
    def mix(wj: pd.Series, wk: pd.Series) -> pd.Series:
        return 0.75 * wj + 0.25 * wk

    return _ends8(w).select("eid", F.round(mix("wj", "wk"), 6).alias("value"))


@register("op_pandas_agg", "SELECT event_type, round(sum(value * (CAST(json_extract(props, '$.k') AS INTEGER) + 1)) / sum(CAST(json_extract(props, '$.k') AS INTEGER) + 1), 4) AS mean FROM events GROUP BY 1")
def _(w: World) -> DataFrame:
    """Shows the surface of a grouped UDF; two sums give the same and are combined before the shuffle."""

    @F.pandas_udf("double")
    def weighted(x: pd.Series, c: pd.Series) -> float:
        return float((x * c).sum() / c.sum())

    return parsed(w.table("events")).groupBy(C("wtype").alias("event_type")).agg(F.round(weighted("value", "conf_pct"), 4).alias("mean"))


_LOCAL = oracle.sssp("SELECT cell, min(v) AS src FROM vtx GROUP BY cell").replace("JOIN arc ", "JOIN ca ").replace("arc.", "ca.")


@register("op_apply_grouped", f"WITH RECURSIVE {NET}, ca AS MATERIALIZED (SELECT arc.* FROM arc JOIN vtx x ON x.v = tail JOIN vtx y ON y.v = head WHERE x.cell = y.cell), {_LOCAL} SELECT x.cell, CAST(count(*) AS BIGINT) AS reached, CAST(max(dist) AS BIGINT) AS far FROM sp JOIN vtx x ON x.v = sp.src GROUP BY x.cell")
def _(w: World) -> DataFrame:
    """In every cell, a search from its first vertex over the roads within the cell."""
    import heapq

    at = w.net().vertices.select("v", "cell")
    arcs = w.net().arcs.join(at.toDF("tail", "cell"), "tail").join(at.toDF("head", "there"), "head").where("cell = there").select("cell", "tail", "head", "len_mm")
    rows = at.select("cell", C("v").alias("tail"), C("v").alias("head"), L(0).cast("long").alias("len_mm")).unionByName(arcs)

    def search(p: pd.DataFrame) -> pd.DataFrame:
        ways: dict = {}
        for t, h, x in zip(p["tail"].tolist(), p["head"].tolist(), p["len_mm"].tolist(), strict=True):
            ways.setdefault(t, []).append((h, x))
        heap, done = [(0, min(ways))], {}
        while heap:
            d, v = heapq.heappop(heap)
            if v not in done:
                done[v] = d
                for h, x in ways[v]:
                    heapq.heappush(heap, (d + x, h))
        return pd.DataFrame({"cell": [p["cell"].iloc[0]], "reached": [len(done)], "far": [max(done.values())]})

    return rows.groupBy("cell").applyInPandas(search, "cell int, reached long, far long")


@register("op_udtf")
def _(w: World) -> DataFrame:
    """The hops of every answered route, one row each."""
    from ..plans.method_queries import _index_answers

    @F.udtf(returnType="hop int, v long")
    class Hops:
        def eval(self, vertices: list) -> None:
            for i, v in enumerate(vertices or []):
                yield i, v

    w.spark.udtf.register("route_hops", Hops)
    _index_answers(w).where("answered").select("qid", "vertices").createOrReplaceTempView("answered_routes")
    return w.spark.sql("SELECT qid, hop, v FROM answered_routes, LATERAL route_hops(vertices)")


# --- streams ----------------------------------------------------------------------------------------------------

_WIN = "SELECT {k}epoch_us(s) AS start_us, epoch_us(s + INTERVAL {len}) AS end_us, count(*) AS n, round(sum(value), 2) AS total FROM {src} GROUP BY {k}s"


def _stream(name: str, sql: str | None = None) -> None:
    from ..streaming import windows

    Q[f"op_stream_{name}"] = lambda spark, sf_dir: getattr(windows, name)(spark, sf_dir)
    if sql:
        S[f"op_stream_{name}"] = sql


_stream("tumbling", _WIN.format(k="event_type, ", len="1 HOUR", src="(SELECT *, date_trunc('hour', ts) AS s FROM events)"))
_stream("sliding", _WIN.format(k="", len="2 HOUR", src="(SELECT *, time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE * i AS s FROM events, (SELECT unnest(range(4)) AS i))"))
_stream("session", "WITH x AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 10 MINUTE THEN 0 ELSE 1 END AS b FROM events), y AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM x) SELECT user_id, epoch_us(min(ts)) AS start_us, epoch_us(max(ts) + INTERVAL 10 MINUTE) AS end_us, count(*) AS n, round(sum(value), 2) AS total FROM y GROUP BY user_id, g")
_stream("deduplicated", "SELECT DISTINCT user_id, event_type FROM events")
_stream("joined", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
_stream("late")


@register("ring_stream_equals_batch", f"WITH {NET}, {oracle.RING} SELECT cell, wtype, slot, value, conf_pct, epoch_us(issued) AS issued_us FROM ring WHERE wtype = 'ANY'")
def _(w: World) -> DataFrame:
    from ..streaming.ring import streamed_ring

    return streamed_ring(w.spark, w.sf_dir).select("cell", "wtype", "slot", "value", "conf_pct", micros("issued").alias("issued_us"))


# --- other tables -----------------------------------------------------------------------------------------------


@register("op_documents_by_source", "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars, count(quality) AS labelled FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1, 2")
def _(w: World) -> DataFrame:
    j = w.table("documents").select("doc_id", "lang", "source", "n_chars").join(w.table("labels"), "doc_id", "left")
    return j.groupBy("lang", "source").agg(n_(), F.sum("n_chars").alias("chars"), F.count("quality").alias("labelled"))


@register("op_pages_by_host", "SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def _(w: World) -> DataFrame:
    return w.table("pages").groupBy(F.regexp_extract("url", "://([^/?#]*)", 1).alias("host")).agg(n_())


@register("op_conversation_turns", "SELECT conv_id, count(*) AS turns, count(*) FILTER (WHERE role = 'user') AS by_user, CAST(sum(length(text)) AS BIGINT) AS chars FROM conversations GROUP BY 1")
def _(w: World) -> DataFrame:
    return w.table("conversations").groupBy("conv_id").agg(F.count(L(1)).alias("turns"), F.count_if(C("role") == "user").alias("by_user"), F.sum(F.length("text")).alias("chars"))


@register("op_benchmark_length", "SELECT CAST(length(text) // 100 AS BIGINT) AS hundreds, count(*) AS n FROM benchmark GROUP BY 1")
def _(w: World) -> DataFrame:
    return w.table("benchmark").groupBy(F.floor(F.length("text") / 100).alias("hundreds")).agg(n_())


@register("op_text_vocabulary", "SELECT word, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]{4,}')) AS word FROM documents) GROUP BY 1 HAVING count(*) >= 50")
def _(w: World) -> DataFrame:
    words = w.table("documents").select(F.explode(F.regexp_extract_all(F.lower("text"), L("[a-z]{4,}"), 0)).alias("word"))
    return words.groupBy("word").agg(n_()).where("n >= 50")
