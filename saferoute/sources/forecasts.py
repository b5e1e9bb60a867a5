"""Forecasts of 25 stations from ``events``: the newest of each station, type and slot of the day."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import PROPS, SLOTS

STATIONS, ANY = 25, "ANY"


def parsed(events: DataFrame, typed: bool = True) -> DataFrame:
    """event_id, cell, wtype, slot, value, conf_pct, issued of every event; ``ANY`` in place of types if not typed."""
    k = F.from_json("props", PROPS)["k"]
    return events.select(
        "event_id", (F.col("user_id") % STATIONS).cast("int").alias("cell"), (F.col("event_type") if typed else F.lit(ANY)).alias("wtype"),
        F.hour("ts").alias("slot"), "value", F.least(F.lit(100), F.coalesce(k + 1, F.lit(0))).alias("conf_pct"), F.col("ts").alias("issued"))


def newest(rows: DataFrame) -> DataFrame:
    """One row per cell, wtype and slot; ties by event_id. Partial aggregation, whatever the rows per key."""
    best = F.max_by(F.struct("value", "conf_pct", "issued", "event_id"), F.struct("issued", "event_id"))
    return rows.groupBy("cell", "wtype", "slot").agg(best.alias("x")).select("cell", "wtype", "slot", "x.value", "x.conf_pct", "x.issued", "x.event_id")


def ring(events: DataFrame) -> DataFrame:
    """The ring of all types and of ANY."""
    typed = newest(parsed(events))  # the newest of all types is one of these
    return newest(typed.withColumn("wtype", F.explode(F.array("wtype", F.lit(ANY)))))


def station_arrays(forecasts: DataFrame, wtype: str | None = ANY) -> DataFrame:
    """cell, values and confs: arrays of 24 slots; a missing forecast is 0.0 with confidence 0.

    ``wtype`` None: of all types, with a column wtype."""
    keys = ["cell"] if wtype else ["cell", "wtype"]
    own = forecasts.where(F.col("wtype") == wtype) if wtype else forecasts
    rows = own.groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct("slot", F.struct("value", "conf_pct")))).alias("m"))
    slots = F.array(*[F.lit(i) for i in range(SLOTS)])
    return rows.select(
        *keys,
        F.transform(slots, lambda i: F.coalesce(F.element_at("m", i)["value"], F.lit(0.0))).alias("values"),
        F.transform(slots, lambda i: F.coalesce(F.element_at("m", i)["conf_pct"], F.lit(0))).alias("confs"))


def with_weather(arcs: DataFrame, vertices: DataFrame, stations: DataFrame) -> DataFrame:
    """Arcs with tail_w, tail_p, head_w, head_p; a cell without a station has confidence 0 throughout.

    Arcs with a column wtype meet the stations of that type."""
    keys = [c for c in ("cell", "wtype") if c in stations.columns]
    cells = vertices.select("v", "cell")
    zeros, nones = F.array_repeat(F.lit(0.0), SLOTS), F.array_repeat(F.lit(0), SLOTS)
    for end in ("tail", "head"):
        own = stations.select(*[F.col(k).alias(k if k == "wtype" else "c_") for k in keys], F.col("values").alias("w_"), F.col("confs").alias("p_"))
        arcs = arcs.join(cells.toDF(end, "c_"), end).join(own, ["c_", *keys[1:]], "left")
        arcs = arcs.withColumns({f"{end}_w": F.coalesce("w_", zeros), f"{end}_p": F.coalesce("p_", nones)}).drop("c_", "w_", "p_")
    return arcs
