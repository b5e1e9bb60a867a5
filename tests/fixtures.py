"""Small networks made by hand."""

from pyspark.sql import functions as F

from saferoute.sources.networks import Network


def network(spark, edges, n=None):
    """edges: (a, b, minutes, keywords); every vertex is its own weather cell, on a line."""
    n = n or 1 + max(max(a, b) for a, b, *_ in edges)
    v = spark.createDataFrame([("t", i, i * 1000, 0, i, 0, i) for i in range(n)], "net string, v long, x_mm long, y_mm long, cell int, strip long, r long")
    rows = [("t", i, min(a, b), max(a, b), 1000 * abs(a - b), w, sorted(kw)) for i, (a, b, w, kw) in enumerate(edges)]
    return Network("t", v, spark.createDataFrame(rows, "net string, eid long, a long, b long, len_mm long, w_min long, kw array<int>"))


def forecasts(spark, rows):
    """rows: (vertex, slot, value, confidence); type ANY."""
    df = spark.createDataFrame([(*r, i) for i, r in enumerate(rows)], "cell int, slot int, value double, conf_pct int, event_id long")
    return df.select("cell", F.lit("ANY").alias("wtype"), "slot", "value", "conf_pct", F.lit("2024-01-01").cast("timestamp").alias("issued"), "event_id")


def queries(spark, rows):
    """rows: (qid, src, dst, departure, eps, alpha, keywords)."""
    df = spark.createDataFrame(rows, "qid int, src long, dst long, dep_min long, eps double, alpha_pct int, s array<int>")
    return df.withColumn("wtype", F.lit("ANY"))


#: Vertices 0-7 as in the transport example, 8 = src, 9 = dst; keyword 1 = metropolitan.
CHEM_EDGES = [(8, 1, 10, []), (1, 3, 10, []), (3, 5, 10, []), (5, 6, 10, []), (6, 9, 10, []), (4, 6, 12, [1]), (2, 4, 25, []), (2, 5, 10, []), (5, 4, 10, []), (1, 2, 10, [])]
CHEM_8 = [(0, 10, 90), (1, 15, 80), (2, 50, 90), (3, 20, 90), (4, 35, 90), (5, 20, 100), (6, 10, 80), (7, 10, 90), (8, 10, 90), (9, 10, 90)]
CHEM_9 = [(0, 15, 100), (1, 20, 90), (2, 65, 80), (3, 25, 80), (4, 40, 90), (5, 25, 90), (6, 15, 100), (7, 10, 100), (8, 10, 90), (9, 10, 90)]


def chem(spark):
    rows = [(v, 8, float(x), c) for v, x, c in CHEM_8] + [(v, 9, float(x), c) for v, x, c in CHEM_9]
    return network(spark, CHEM_EDGES), forecasts(spark, rows)
