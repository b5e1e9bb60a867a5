"""Fixture rows that every operator must stand: nulls, empty and long texts, ties, repeats, extra columns."""

from pyspark.sql import functions as F

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs(spark, texts, sources=None):
    rows = [(i, t, "en", (sources[i] if sources else "a"), None if t is None else len(t)) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


def awkward(spark):
    """Null text, id, source; empty and blank texts; a long one; repeated rows; extra columns with clashing names."""
    rows = [
        (0, None, None, None, None), (None, "no id here, mail a@b.co or +1 (234) 555-6789 now", "en", "b", 10), (2, "", "en", "a", 0), (3, " \n\t ", "en", "a", 4),
        (4, "word " * 20_000, "en", "a", 100_000), (5, "one two three four five six seven eight nine ten eleven", "de", "b", 55),
        (5, "one two three four five six seven eight nine ten eleven", "de", "b", 55), (6, "one two three four five six seven eight nine ten eleven", "de", None, 55), (7, "kurz", "de", "b", 4),
    ]
    names = ["cls", "label", "key", "n", "size", "rank", "u", "row", "k1", "base", "spans", "words", "copies", "kind", "score", "block", "x", "y"]
    return spark.createDataFrame(rows, DOCS).withColumns({n: F.lit("extra") for n in names})


def empty(spark):
    return spark.createDataFrame([], DOCS)


def table(df):
    return [r.asDict() for r in df.collect()]
