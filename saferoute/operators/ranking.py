"""A global row number without a single task: range partitions, ranks within, offsets of partitions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def global_rank(df: DataFrame, order: list[Column | str], name: str, rows_per_task: int = 200_000) -> DataFrame:
    """``df`` with the rank from 0 in ``order`` (which must not leave ties) as ``name``.

    The driver sees one number per partition. The ranged rows are written to the checkpoint folder, so
    that a recomputation can't move a border between counting and numbering."""
    from .storage import stored

    tasks = max(1, -(-df.count() // rows_per_task))
    ranged = stored(df.repartitionByRange(tasks, *order).withColumn("_part", F.spark_partition_id()) if tasks > 1 else df.withColumn("_part", F.lit(0)))
    counts = {r["_part"]: r["count"] for r in ranged.groupBy("_part").count().collect()}
    offset, table = 0, []
    for part in sorted(counts):
        table += [F.lit(part), F.lit(offset).cast("long")]
        offset += counts[part]
    base = F.element_at(F.create_map(*table), F.col("_part")) if table else F.lit(0).cast("long")
    return ranged.withColumn(name, F.row_number().over(Window.partitionBy("_part").orderBy(*order)) - 1 + base).drop("_part")
