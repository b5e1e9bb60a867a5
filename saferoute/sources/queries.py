"""Query sets: sources spread over the vertices, destinations at an exact hop distance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.graph import bfs_hops
from ..operators.storage import stored
from .forecasts import ANY
from .networks import Network


def query_ends(net: Network, n: int = 20, sigma: int = 10) -> DataFrame:
    """qid, src, dst. A source without a vertex at sigma hops has no row."""
    spark, size = net.vertices.sparkSession, net.vertices.count()
    rows = spark.range(n).select(F.col("id").cast("int").alias("qid"), (F.col("id") * 7919 % max(1, size)).alias("src"))
    hops = bfs_hops(net.arcs, rows, sigma).where(F.col("hops") == sigma)
    return stored(rows.join(hops.groupBy("qid").agg(F.min("v").alias("dst")), "qid"))


def make_queries(net: Network, n: int = 20, sigma: int = 10, s_size: int = 5, eps: float = 50.0, alpha_pct: int = 50, wtype: str = ANY, ends: DataFrame | None = None) -> DataFrame:
    """qid, src, dst, dep_min, wtype, eps, alpha_pct, s; ``ends``: those of ``query_ends``, which hang on n and sigma alone."""
    ends = query_ends(net, n, sigma) if ends is None else ends
    s = F.array(*[((7 * F.col("qid") + 11 * j) % 50 + 1).cast("int") for j in range(s_size)])
    return ends.select(
        "qid", "src", "dst", (480 + 37 * F.col("qid") % 720).cast("long").alias("dep_min"), F.lit(wtype).alias("wtype"),
        F.lit(float(eps)).alias("eps"), F.lit(int(alpha_pct)).alias("alpha_pct"), s.alias("s"))


def delivery_queries(net: Network, orders: DataFrame, n: int = 20, sigma: int = 6, eps: float = 50.0, alpha_pct: int = 50, keywords: tuple = (3, 17, 29)) -> DataFrame:
    """Deliveries: sources are the customers of the first n orders, all avoid the same city-road keywords."""
    first = orders.orderBy("o_orderkey").limit(n).select(F.col("o_orderkey").cast("int").alias("qid"), F.col("o_custkey").cast("long").alias("src"))
    hops = bfs_hops(net.arcs, first, sigma).where(F.col("hops") == sigma)
    dst = hops.groupBy("qid").agg(F.min("v").alias("dst"))
    return stored(first.join(dst, "qid").select(
        "qid", "src", "dst", F.lit(480).cast("long").alias("dep_min"), F.lit(ANY).alias("wtype"), F.lit(float(eps)).alias("eps"),
        F.lit(int(alpha_pct)).alias("alpha_pct"), F.array(*[F.lit(k) for k in keywords]).alias("s")))
