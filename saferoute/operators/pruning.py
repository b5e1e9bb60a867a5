"""The three prunes of edges and partial paths."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.keywords import keyword_blocked
from ..functions.weather import discarded, ub_prob_ok


def prune_keyword(edges: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, eid of the edges that carry none of the query's keywords.

    Blocked pairs come from an equi-join on the keyword, so no query meets every edge twice."""
    return edges.select("eid").join(F.broadcast(queries.select("qid"))).join(keyword_pairs(edges, queries), ["qid", "eid"], "left_anti")


def keyword_pairs(edges: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, eid of the edges that carry a keyword of the query, each once."""
    return edges.select("eid", F.explode("kw").alias("k")).join(queries.select("qid", F.explode("s").alias("k")), "k").select("qid", "eid").distinct()


def edge_slot_bounds(edges: DataFrame, vertices: DataFrame, forecasts: DataFrame, eps: float, wtype: str = "ANY") -> DataFrame:
    """eid, slot, lb_val, ub_val, ub (ten-thousandths) and the case, for every slot of every edge."""
    cells = vertices.select("v", "cell")
    ends = edges.select("eid", "a", "b").join(cells.toDF("a", "ca"), "a").join(cells.toDF("b", "cb"), "b").select("eid", "ca", "cb")
    return cell_slot_bounds(ends, forecasts, eps, wtype).drop("ca", "cb")


def cell_slot_bounds(ends: DataFrame, forecasts: DataFrame, eps: float, wtype: str = "ANY") -> DataFrame:
    """As ``edge_slot_bounds`` for every slot of every row of ``ends`` (ca, cb: the cells of its ends; other columns stay)."""
    slots = ends.sparkSession.range(24).select(F.col("id").cast("int").alias("slot"))
    f = forecasts.where(F.col("wtype") == wtype).select("cell", "slot", "value", "conf_pct")
    rows = ends.join(F.broadcast(slots)).join(f.toDF("ca", "slot", "wj", "pj"), ["ca", "slot"], "left").join(f.toDF("cb", "slot", "wk", "pk"), ["cb", "slot"], "left")
    rows = rows.withColumns({"pj": F.coalesce("pj", F.lit(0)), "pk": F.coalesce("pk", F.lit(0)), "wj": F.coalesce("wj", F.lit(0.0)), "wk": F.coalesce("wk", F.lit(0.0))})
    e = F.lit(float(eps))
    return rows.select(
        *ends.columns, "slot", "wj", "pj", "wk", "pk", F.least("wj", "wk").alias("lb_val"), F.greatest("wj", "wk").alias("ub_val"),
        ub_prob_ok(F.col("wj"), F.col("pj"), F.col("wk"), F.col("pk"), e).alias("ub"))


def prune_weather(bounds: DataFrame, alpha_pct: int) -> DataFrame:
    """eid, slot of the edge slots that the bound can't rule out."""
    return bounds.where(~discarded(F.col("ub"), F.lit(alpha_pct))).select("eid", "slot")


def prune_time(frontier: DataFrame, best: DataFrame) -> DataFrame:
    """Partial paths (qid, lb) whose lower bound is not above the best arrival (qid, lam) known."""
    return frontier.join(best, "qid", "left").where(F.col("lam").isNull() | (F.col("lb") <= F.col("lam"))).drop("lam")


def keyword_prune_naive(edges: DataFrame, queries: DataFrame) -> DataFrame:
    """``prune_keyword`` by testing every pair; for comparison on small inputs."""
    q = queries.select("qid", "s")
    return edges.join(F.broadcast(q)).where(~keyword_blocked(F.col("kw"), F.col("s"))).select("qid", "eid")
