"""Mixing sources to target weights by Pareto order sampling.

Each source gets a target of words: ``budget`` times all words, shared by weight, no source above
``most`` times its own words, the excess reshared by weight (a water level). A document's expected
copies are its source's target / words; their whole part is certain. The rest is drawn with inclusion
probabilities that grow with the root of a document's size, so that a long document is drawn more surely
than a short one; their scale makes the expected words the remaining ones. Documents whose probability comes to one
or more are certain units: they are taken once more, and the scale is found anew for the others, ``UNITS`` times.
With a uniform U from a hash of the row and a probability p, the other documents are ranked by the ratio of
odds (U / (1 - U)) / (p / (1 - p)), and the smallest are taken until the source's remaining words are
met: the sample's size is fixed in words, as targets are, not in documents.

The cut is found from sums over narrow rank bins, refined twice within the bin where the sum crosses the
remainder: no sort of a source, whatever its share of the rows. At each cut the nearer side is taken.

Null texts have size 0; a null source is a source of its own, last in order; sources without words
have target 0. Equal rows have equal ranks and are taken together. Columns other than doc_id, text and
source are carried by ``draw`` unchanged. Reruns agree, whatever the partitions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

#: Relative weights of the sources in order, repeated; share of all words; most words of a source.
WEIGHTS, BUDGET, MOST = (3, 1, 2), 1.5, 2
SEED = "mix-1"
BINS, LEVELS = 1024, 3
#: Rounds in which certain units are moved out of the draw.
UNITS = 4


def sizes(docs: DataFrame, seed: str = SEED, keep: bool = False) -> DataFrame:
    """doc_id, source, size and the uniform ``u`` (of 52 bits, never 0 or 1) of every row; ``keep``: and the row."""
    text = F.coalesce("text", F.lit(""))
    salt = F.concat_ws("|", F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.sha2(text, 256))
    bits = F.conv(F.substring(F.sha2(salt, 256), 1, 13), 16, 10).cast("double")
    row = [F.struct(*docs.columns).alias("row")] if keep else []
    return docs.select("doc_id", "source", *row, F.regexp_count(text, F.lit(common.WORD)).cast("long").alias("size"), ((bits + 0.5) / F.lit(2.0**52)).alias("u"))


def targets(sized: DataFrame, weights: tuple = WEIGHTS, budget: float = BUDGET, most: float = MOST) -> DataFrame:
    """source, source_size, powers (sum of size to the 1.5, floored) and target: one row per source.

    With sources ordered by ``most`` * size / weight, those below the water level are filled; the level
    is what is left for the others over their weights. Runs on one row per source."""
    table = F.array(*[F.lit(float(w)) for w in weights])
    order = Window.orderBy(F.col("source").asc_nulls_last())
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.sum(F.floor(F.col("size") * F.sqrt("size"))).alias("powers"))
    per = per.withColumn("weight", F.get(table, ((F.row_number().over(order) - 1) % len(weights)).cast("int")))
    per = per.withColumn("cap", most * F.col("source_size")).withColumn("fill", F.col("cap") / F.col("weight"))
    by_fill = Window.orderBy("fill", F.col("source").asc_nulls_last())
    everything = Window.partitionBy(F.lit(1))
    left = F.sum("source_size").over(everything) * F.lit(float(budget)) - F.coalesce(F.sum("cap").over(by_fill.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    level = left / F.sum("weight").over(by_fill.rowsBetween(0, Window.unboundedFollowing))
    per = per.withColumn("level", level)
    water = F.max(F.when(F.col("level") <= F.col("fill"), F.col("level"))).over(everything)
    return per.select("source", "source_size", "powers", F.least(F.col("cap"), F.col("weight") * F.coalesce(water, F.col("fill"))).alias("target"))


def _same(a: Column, b: Column) -> Column:
    return a.eqNullSafe(b)


def units(sized: DataFrame, per_source: DataFrame) -> DataFrame:
    """per_source with whole, rest (words to draw beside certain units), bar and scale.

    A document is a certain unit where bar * sqrt(size) is 1 or more; of the others scale * sqrt(size) is the probability."""
    copies = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    s = per_source.withColumn("whole", F.floor(copies)).withColumn("all_rest", F.col("target") - F.col("whole") * F.col("source_size"))
    s = s.withColumns({"scale": F.col("all_rest") / F.greatest(F.col("powers"), F.lit(1)), "bar": F.lit(0.0), "rest": F.col("all_rest")})
    for _ in range(UNITS):
        s = common.materialise(s)
        now = s.select(F.col("source").alias("s_"), F.col("scale").alias("scale_"))
        sure = sized.join(now, _same(sized["source"], now["s_"])).where(F.sqrt("size") * F.col("scale_") >= 1)
        sums = sure.groupBy("s_").agg(F.sum("size").alias("big"), F.sum(F.floor(F.col("size") * F.sqrt("size"))).alias("gone"), F.lit(True).alias("any_"))
        s = s.withColumnRenamed("scale", "old").join(sums, _same(F.col("source"), F.col("s_")), "left")
        rest = F.col("all_rest") - F.coalesce("big", F.lit(0))
        s = s.select("source", "source_size", "powers", "target", "whole", "all_rest", (rest / F.greatest(F.col("powers") - F.coalesce("gone", F.lit(0)), F.lit(1))).alias("scale"), F.col("old").alias("bar"), rest.alias("rest"))
    return s


def ranked(sized: DataFrame, per_source: DataFrame) -> DataFrame:
    """Adds whole (certain copies), sure (a certain unit), rest (words still to draw in the source) and rank in (0, 1).

    The rank is x / (1 + x) for the ratio of odds x, which keeps the order and is bounded."""
    s = per_source.withColumnRenamed("source", "s_")
    out = sized.join(s, _same(sized["source"], s["s_"])).drop("s_", "all_rest").withColumn("sure", F.sqrt("size") * F.col("bar") >= 1)
    p = F.least(F.lit(1 - 1e-6), F.greatest(F.lit(1e-6), F.col("scale") * F.sqrt("size")))
    odds = (F.col("u") / (1 - F.col("u"))) / (p / (1 - p))
    return out.withColumn("rank", odds / (1 + odds)).drop("powers", "bar", "scale")


def cuts(ranks: DataFrame) -> DataFrame:
    """source and cut: rows of a rank up to the cut are drawn.

    Level by level the bin of ranks is found in which the running sum of sizes passes ``rest``; the
    sums are combined before the shuffle and have at most BINS rows per source and level."""
    rows = ranks.where("size > 0 and rest > 0 and not sure").select("source", "rank", "size", "rest")
    state = None
    for level in range(1, LEVELS + 1):
        width = float(BINS) ** level
        bins = rows.withColumn("bin", F.floor(F.col("rank") * F.lit(width)))
        if state is not None:
            s = state.select(F.col("source").alias("s_"), F.col("bin").alias("upper"), "before")
            bins = bins.join(s, _same(bins["source"], s["s_"]) & (F.floor(bins["bin"] / BINS) == s["upper"])).drop("s_", "upper")
        else:
            bins = bins.withColumn("before", F.lit(0).cast("long"))
        sums = bins.groupBy("source", "bin").agg(F.sum("size").alias("words"), F.first("rest").alias("rest"), F.first("before").alias("base"), F.max("rank").alias("top"))
        w = Window.partitionBy("source").orderBy("bin")
        sums = sums.withColumn("before", F.col("base") + F.coalesce(F.sum("words").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        sums = sums.withColumn("after", F.col("before") + F.col("words"))
        crossing = sums.where("before < rest and after >= rest")
        state = crossing if level == LEVELS else common.materialise(crossing)
    nearer = F.when(F.col("rest") - F.col("before") < F.col("after") - F.col("rest"), F.col("bin") / F.lit(float(BINS) ** LEVELS)).otherwise(F.col("top"))
    below = F.col("rest") - F.col("before") < F.col("after") - F.col("rest")
    return state.select("source", nearer.alias("cut"), below.alias("open"))


def draw(docs: DataFrame, carry: bool = False, **options) -> DataFrame:
    """doc_id, source, size, source_size, target, copies and taken of every row.

    ``carry``: row (all columns of ``docs``) and copies instead. Sizes and ranks are then worked out again where
    the texts are read, and only the tables of one row per source are joined to them."""
    sized = common.materialise(sizes(docs))
    per_source = common.written(units(sized, common.written(targets(sized, **options), "mix-targets")), "mix-units")
    c = common.written(cuts(ranked(sized, per_source)), "mix-cuts").withColumnRenamed("source", "s_")
    ranks = ranked(sizes(docs, keep=True) if carry else sized, per_source)
    drawn = ranks.join(c, _same(ranks["source"], c["s_"]), "left")
    hit = F.col("sure") | (F.col("rest") > 0) & F.coalesce(F.when(F.col("open"), F.col("rank") < F.col("cut")).otherwise(F.col("rank") <= F.col("cut")), F.lit(False))
    drawn = drawn.withColumn("copies", F.col("whole") + F.when(hit, 1).otherwise(0))
    if carry:
        return drawn.select("row", "copies")
    return drawn.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mixed(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: every row of ``docs`` as often as it is drawn."""
    drawn = draw(docs, carry=True, **options)
    return drawn.select("row", F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int")))).select("row.*")


def op8_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return draw(common.table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")
