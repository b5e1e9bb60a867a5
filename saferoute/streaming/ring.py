"""The forecast ring as a stream: newest forecast per station, type and slot, and upkeep of the index.

State is one row per key. Expired forecasts need no deletion: a slot of the day is taken over by the next
day's forecast. A change goes up the index level by level; a parent is made anew from all its children (a
largest value can't be taken back from a difference) and the climb ends where a parent stays as it was."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.keywords import bitmap
from ..operators.pruning import edge_slot_bounds
from ..operators.storage import shared_dir, stored
from ..plans.index import EPS_GRID, Index
from ..sources.forecasts import newest, parsed
from ..sources.networks import Network


def merge(old: DataFrame, new: DataFrame) -> DataFrame:
    """The ring after new rows; a row older than the one of its key loses."""
    columns = ["cell", "wtype", "slot", "value", "conf_pct", "issued", "event_id"]
    return newest(old.select(*columns).unionByName(new.select(*columns)))


def _leaf_rows(net: Network, index: Index, ring: DataFrame, touched: DataFrame, wtype: str) -> DataFrame:
    from ..functions.weather import ub_prob_ok

    own = index.lookup.join(touched.select("leaf").distinct(), "leaf", "left_semi").select("eid", "leaf")
    edges = net.edges.join(own, "eid")
    base = edge_slot_bounds(edges.drop("leaf"), net.vertices, ring, 0.0, wtype).join(own, "eid").join(touched, ["leaf", "slot"], "left_semi")
    sums = [F.min("lb_val").alias("lb_val"), F.max("ub_val").alias("ub_val"), F.max((100 - F.col("pj")) * (100 - F.col("pk"))).cast("long").alias("ub_case3")]
    sums += [F.max(ub_prob_ok(F.col("wj"), F.col("pj"), F.col("wk"), F.col("pk"), F.lit(float(e)))).alias(f"u{e}") for e in EPS_GRID]
    return base.groupBy(F.col("leaf").alias("node"), "slot").agg(*sums)


def flat(weather: DataFrame) -> DataFrame:
    """Index weather with one column per grid point, which unlike maps can be compared."""
    return weather.select("level", "node", "slot", "lb_val", "ub_val", "ub_case3", *[F.element_at("ub_by_eps", F.lit(e)).alias(f"u{e}") for e in EPS_GRID])


def propagate(rows: DataFrame, level: int, before: DataFrame, fanout: int) -> tuple[DataFrame, DataFrame]:
    """(real changes of this level, summaries anew of their parents): parents from all children."""
    values = [c for c in rows.columns if c not in ("node", "slot")]
    old = before.where(F.col("level") == level).drop("level")
    same = F.lit(True)
    joined = rows.alias("n").join(old.alias("o"), ["node", "slot"], "left")
    for c in values:
        same = same & F.col(f"n.{c}").eqNullSafe(F.col(f"o.{c}"))
    changed = stored(joined.where(~same).select("node", "slot", *[F.col(f"n.{c}") for c in values]))
    parents = changed.select(F.floor(F.col("node") / fanout).alias("p"), "slot").distinct()
    children = old.join(changed.select("node", "slot"), ["node", "slot"], "left_anti").unionByName(changed)
    children = children.withColumn("p", F.floor(F.col("node") / fanout)).join(parents, ["p", "slot"], "left_semi")
    up = children.groupBy(F.col("p").alias("node"), "slot").agg(*[(F.min if c == "lb_val" else F.max)(c).alias(c) for c in values])
    return changed, up


def apply_forecasts(new: DataFrame, ring: DataFrame, net: Network, index: Index, wtype: str = "ANY") -> DataFrame:
    """level, node, slot and the new summaries of every index node that new forecasts change."""
    after = stored(merge(ring, new))
    moved = after.where(F.col("wtype") == wtype).join(ring.select("cell", "wtype", "slot", F.col("event_id").alias("old")), ["cell", "wtype", "slot"], "left").where("not event_id <=> old or value is not null").select("cell", "slot")
    moved = moved.join(new.where(F.col("wtype") == wtype).select("cell", "slot").distinct(), ["cell", "slot"], "left_semi")
    ends = net.edges.select("eid", F.explode(F.array("a", "b")).alias("v")).join(net.vertices.select("v", "cell"), "v")
    touched = stored(ends.join(moved, "cell").join(index.lookup.select("eid", "leaf"), "eid").select("leaf", "slot").distinct())
    before, out = flat(index.weather.where(F.col("wtype") == wtype)), None
    rows = _leaf_rows(net, index, after, touched, wtype)
    for level in range(1, index.height + 1):
        changed, rows = propagate(rows, level, before, index.fanout)
        part = changed.withColumn("level", F.lit(level))
        out = part if out is None else out.unionByName(part)
        if changed.isEmpty():
            break
    return out


def apply_edge_updates(updates: DataFrame, net: Network) -> Network:
    """A network with new minutes and keywords (columns eid, w_min, kw) for some edges."""
    new = updates.select("eid", F.col("w_min").alias("w_new"), F.col("kw").alias("kw_new"))
    edges = net.edges.join(new, "eid", "left").select("net", "eid", "a", "b", "len_mm", F.coalesce("w_new", "w_min").alias("w_min"), F.coalesce("kw_new", "kw").alias("kw"))
    return Network(net.kind, net.vertices, stored(edges))


def apply_edge_attributes(updates: DataFrame, net: Network, index: Index) -> DataFrame:
    """level, node, lb_t, ub_t, kw_and, kw_or of the index nodes that new minutes and keywords change.

    The touched leaves are made anew from their edges, parents from all their children, as for forecasts."""
    bits = F.get(bitmap(F.col("kw")), F.lit(0))
    values = {"lb_t": F.min, "ub_t": F.max, "kw_and": F.bit_and, "kw_or": F.bit_or}
    leaves = index.lookup.join(updates.select("eid"), "eid", "left_semi").select("leaf").distinct()
    edges = apply_edge_updates(updates, net).edges.join(index.lookup.join(leaves, "leaf", "left_semi").select("eid", "leaf"), "eid")
    edges = edges.select(F.col("leaf").alias("node"), F.col("w_min").alias("lb_t"), F.col("w_min").alias("ub_t"), bits.alias("kw_and"), bits.alias("kw_or"))
    rows, out = edges.groupBy("node").agg(*[f(c).alias(c) for c, f in values.items()]), None
    for level in range(1, index.height + 1):
        old = index.nodes.where(F.col("level") == level).select("node", *values)
        changed = stored(rows.exceptAll(old))
        part = changed.select(F.lit(level).alias("level"), "*")
        out = part if out is None else out.unionByName(part)
        if changed.isEmpty():
            break
        up = lambda df: df.withColumn("p", F.floor(F.col("node") / index.fanout))
        children = up(old.join(changed.select("node"), "node", "left_anti").unionByName(changed)).join(up(changed).select("p").distinct(), "p", "left_semi")
        rows = children.groupBy(F.col("p").alias("node")).agg(*[f(c).alias(c) for c, f in values.items()])
    return out


def events_stream(spark: SparkSession, sf_dir: str, folder: str | None = None, files: int = 1) -> DataFrame:
    """Events as a file stream: the given table, or a folder of part files."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    rows = reader.parquet(folder) if folder else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))  # event times need a time zone


def split_by_day(spark: SparkSession, sf_dir: str, parts: int = 6) -> str:
    """Events as ``parts`` files of some days each, for streams of several batches."""
    folder = f"{shared_dir(spark)}/days-{uuid.uuid4().hex}"
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    day = F.dayofmonth("ts") * parts / 32
    events.repartitionByRange(parts, F.floor(day)).write.parquet(folder)
    return folder


def start_forecast_stream(events: DataFrame, folder: str, typed: bool = False):  # noqa: ANN201
    """Keeps the ring in ``folder``/ring-<batch>: each batch writes the whole ring anew (one row per key).

    The newest row per key is a streaming aggregate, so its state is in the engine's store; late and
    repeated rows lose against the key's newest."""
    rows = parsed(events, typed)
    best = F.max_by(F.struct("value", "conf_pct", "issued", "event_id"), F.struct("issued", "event_id"))
    ring = rows.groupBy("cell", "wtype", "slot").agg(best.alias("x")).select("cell", "wtype", "slot", "x.*")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/ring-{number:06d}")

    return ring.writeStream.outputMode("complete").option("checkpointLocation", f"{folder}/state").foreachBatch(keep).trigger(availableNow=True).start()


def streamed_ring(spark: SparkSession, sf_dir: str, source: str | None = None) -> DataFrame:
    """The ring after a stream over all days, read from its last version."""
    folder = f"{shared_dir(spark)}/ring-{uuid.uuid4().hex}"
    query = start_forecast_stream(events_stream(spark, sf_dir, source or split_by_day(spark, sf_dir)), folder)
    query.awaitTermination()
    last = query.lastProgress["batchId"]
    return spark.read.parquet(f"{folder}/ring-{last:06d}")
