"""Road networks derived from the given tables, and their validation.

Three stand-ins: ``uni`` (customer; uniform), ``gau`` (embeddings; clustered), ``sparse`` (part; hardly more
edges than vertices). Vertices are cut into strips by y and chained by x within a strip; every k-th rank
is linked to the next strip. All numbers are integers, so other engines derive the same network."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.spatial import z_code
from ..operators.ranking import global_rank
from ..operators.storage import stored

#: Table and key of the vertices, period of the cross links, constant speed or None.
KINDS = {"uni": ("customer", "c_custkey", 3, None), "gau": ("embeddings", "vec_id", 3, None), "sparse": ("part", "p_partkey", 32, 50)}
Y_STEP, X_STEP, BOX, CELL = 247213, 7919, 400_000, 80_000


@dataclass(frozen=True)
class Network:
    """vertices: net, v, x_mm, y_mm, cell, strip, r; edges: net, eid, a, b, len_mm, w_min, kw."""

    kind: str
    vertices: DataFrame
    edges: DataFrame

    @property
    def arcs(self) -> DataFrame:
        """Both directions of every edge: tail, head, eid, len_mm, w_min, kw."""
        e = self.edges
        one = e.select(F.col("a").alias("tail"), F.col("b").alias("head"), "eid", "len_mm", "w_min", "kw")
        return one.unionByName(e.select(F.col("b").alias("tail"), F.col("a").alias("head"), "eid", "len_mm", "w_min", "kw"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def positions(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """v, x_mm, y_mm."""
    name, key, *_ = KINDS[kind]
    t, v = table(spark, sf_dir, name), F.col(key).cast("long")
    if kind == "uni":
        x, y = F.floor((F.col("c_acctbal") + 1000.0) * 400.0 / 11.0), v * Y_STEP % BOX
    elif kind == "gau":
        at = lambda i: F.round((F.get("embedding", F.lit(i)).cast("double") + 1.0) * 200000.0)
        x, y = at(0), at(1)
    else:
        x, y = v * Y_STEP % BOX, (F.col("p_size").cast("long") - 1) * 8000 + v * X_STEP % 8000
    return t.select(v.alias("v"), x.cast("long").alias("x_mm"), y.cast("long").alias("y_mm"))


def cell_of(x: F.Column, y: F.Column) -> F.Column:
    side = BOX // CELL - 1
    return (F.least(F.lit(side), F.floor(x / CELL)) + 5 * F.least(F.lit(side), F.floor(y / CELL))).cast("int")


def build_vertices(spark: SparkSession, sf_dir: str, kind: str, quarters: int = 4) -> DataFrame:
    """Vertices of one network; ``quarters``: of the table's vertices."""
    base = positions(spark, sf_dir, kind)
    if quarters < 4:
        base = base.where(F.col("v") < base.count() * quarters // 4)
    base = stored(base)
    n = base.count()
    size = max(2, n // max(1, int(n**0.5)))
    strips = global_rank(base, ["y_mm", "v"], "p").withColumn("strip", F.floor(F.col("p") / size))
    r = F.row_number().over(Window.partitionBy("strip").orderBy("x_mm", "v")).cast("long") - 1
    return stored(strips.select(F.lit(kind).alias("net"), "v", "x_mm", "y_mm", cell_of(F.col("x_mm"), F.col("y_mm")).alias("cell"), "strip", r.alias("r")))


def build_roads(vertices: DataFrame, kind: str, period: int | None = None) -> DataFrame:
    """eid, a, b, len_mm: edges numbered by their ends; ``period``: of cross links, the fewer the larger it is."""
    period = period or KINDS[kind][2]
    here = vertices.select("v", "x_mm", "y_mm", "strip", "r")
    ends = ["v", "x_mm", "y_mm", "v2", "x2", "y2"]
    along = Window.partitionBy("strip").orderBy("r")
    chain = here.withColumns({b: F.lead(a).over(along) for a, b in (("v", "v2"), ("x_mm", "x2"), ("y_mm", "y2"))}).where("v2 IS NOT NULL").select(*ends)
    linked = here.where(F.col("r") % period == 0)
    there = linked.select(F.col("v").alias("v2"), F.col("x_mm").alias("x2"), F.col("y_mm").alias("y2"), (F.col("strip") - 1).alias("strip"), "r")
    pairs = chain.unionByName(linked.join(there, ["strip", "r"]).select(*ends)).select(
        F.least("v", "v2").alias("a"), F.greatest("v", "v2").alias("b"),
        F.round(F.sqrt(((F.col("x_mm") - F.col("x2")) * (F.col("x_mm") - F.col("x2")) + (F.col("y_mm") - F.col("y2")) * (F.col("y_mm") - F.col("y2"))).cast("double"))).cast("long").alias("len_mm"))
    return global_rank(stored(pairs), ["a", "b"], "eid")


def build_network(spark: SparkSession, sf_dir: str, kind: str, quarters: int = 4, period: int | None = None, skewed: bool = False, vertices: DataFrame | None = None, roads: DataFrame | None = None) -> Network:
    """Vertices and edges of one network; edges are numbered by their ends.

    ``quarters``: of the table's vertices; ``period``: of cross links, the fewer the larger it is; ``skewed``: keywords
    are squares, so that few of them are on most roads; ``vertices``, ``roads``: where they are built already."""
    speed = KINDS[kind][3]
    vertices = build_vertices(spark, sf_dir, kind, quarters) if vertices is None else vertices
    edges = build_roads(vertices, kind, period) if roads is None else roads
    mph = F.lit(speed).cast("long") if speed else 30 + 10 * (F.col("eid") % 5)
    minutes = F.greatest(F.lit(1).cast("long"), F.floor((F.col("len_mm") * 60 + 1000 * mph - 1) / (1000 * mph)))
    sizes = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("k"), F.col("p_size").cast("int").alias("kw1"))
    if skewed:
        sizes = sizes.withColumn("kw1", (F.col("kw1") * F.col("kw1") % 50).cast("int"))
    parts = sizes.count()
    edges = edges.withColumns({"w_min": minutes.cast("long"), "k1": 31 * F.col("eid") % parts, "k2": (17 * F.col("eid") + 7) % parts})
    edges = edges.join(sizes.withColumnRenamed("k", "k1"), "k1", "left").join(sizes.select(F.col("k").alias("k2"), F.col("kw1").alias("kw2")), "k2", "left")
    kw = F.when(F.col("eid") % 6 == 0, F.array("kw1", "kw2")).when(F.col("eid") % 2 == 0, F.array("kw1")).otherwise(F.array().cast("array<int>"))
    edges = edges.select(F.lit(kind).alias("net"), "eid", "a", "b", "len_mm", "w_min", F.array_sort(F.array_distinct(kw)).alias("kw"))
    return Network(kind, vertices, stored(edges))


def max_speed(edges: DataFrame) -> float:
    """Highest speed in milli-miles an hour; 0 for no edges."""
    return float(edges.agg(F.max(60.0 * F.col("len_mm") / F.col("w_min"))).first()[0] or 0.0)


def edge_speed(edges: DataFrame) -> DataFrame:
    return edges.select("net", "eid", (60.0 * F.col("len_mm") / F.col("w_min")).alias("mm_per_hour"))


def midpoints(net: Network) -> DataFrame:
    """eid, the edge's rectangle, and the Z-code of its middle."""
    v = net.vertices.select("v", "x_mm", "y_mm")
    a, b = v.toDF("a", "ax", "ay"), v.toDF("b", "bx", "by")
    e = net.edges.join(a, "a").join(b, "b")
    return e.select(
        "eid", "a", "b", "len_mm", "w_min", "kw",
        F.least("ax", "bx").alias("xmin"), F.least("ay", "by").alias("ymin"), F.greatest("ax", "bx").alias("xmax"), F.greatest("ay", "by").alias("ymax"),
        z_code(F.floor((F.col("ax") + F.col("bx")) / 2), F.floor((F.col("ay") + F.col("by")) / 2)).alias("z"))
