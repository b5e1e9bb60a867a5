"""Windowed, deduplicated and joined event streams, run to their end on what is there."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.storage import shared_dir
from .ring import events_stream


#: Later than every event; see ``ended``.
END = "9999-12-31 00:00:00"
#: All files are one batch, so that no event is late.
WHOLE = 1_000_000


def run_to_end(stream: DataFrame) -> DataFrame:
    """All rows that the stream appends, through files in the shared folder; no row passes through the driver."""
    spark, path = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    query = stream.writeStream.format("parquet").outputMode("append").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start(f"{path}/rows")
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def ended(events: DataFrame) -> DataFrame:
    """The events and one more row of time END, from a stream of its own, in the same batch.

    It moves the watermark past all windows of the events, which are then appended whole; its own window never closes."""
    spark, path = events.sparkSession, f"{shared_dir(events.sparkSession)}/end-{uuid.uuid4().hex}"
    row = [F.lit(END if f.name == "ts" else None).cast(f.dataType).alias(f.name) for f in events.schema]
    spark.range(1).select(*row).coalesce(1).write.parquet(path)
    return events.unionByName(spark.readStream.schema(events.schema).parquet(path))


def micros(c: str) -> F.Column:
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast({c} as timestamp_ntz))")


def _windowed(events: DataFrame, window: F.Column, *keys: str) -> DataFrame:
    agg = events.withWatermark("ts", "1 hour").groupBy(window.alias("w"), *keys).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 2).alias("total"))
    return agg.select("w.start", "w.end", *keys, "n", "total")


def _out(df: DataFrame) -> DataFrame:
    return df.withColumns({"start_us": micros("start"), "end_us": micros("end")}).drop("start", "end")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _out(run_to_end(_windowed(ended(events_stream(spark, sf_dir, files=WHOLE)), F.window("ts", "1 hour"), "event_type")))


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _out(run_to_end(_windowed(ended(events_stream(spark, sf_dir, files=WHOLE)), F.window("ts", "2 hours", "30 minutes"))))


def session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _out(run_to_end(_windowed(ended(events_stream(spark, sf_dir, files=WHOLE)), F.session_window("ts", "10 minutes"), "user_id")))


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = events_stream(spark, sf_dir, files=WHOLE).withWatermark("ts", "1 hour").dropDuplicates(["user_id", "event_type"])
    return run_to_end(rows.select("user_id", "event_type"))


def joined(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream-static join: events with their user's market segment."""
    users = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return run_to_end(events_stream(spark, sf_dir, files=WHOLE).join(users, "user_id").select("event_id", "c_mktsegment"))


def late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly counts when the last days come first: rows older than the watermark are dropped and counted."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    folder = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    for part, condition in enumerate(("dayofmonth(ts) > 15", "dayofmonth(ts) <= 15")):
        events.where(condition).coalesce(1).write.mode("append").parquet(folder + f"/{part}")
    schema = events.schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))
    name = "t" + uuid.uuid4().hex
    agg = _windowed(stream, F.window("ts", "1 hour"))
    query = agg.writeStream.format("memory").queryName(name).outputMode("update").option("checkpointLocation", f"{shared_dir(spark)}/{name}").trigger(availableNow=True).start()
    query.awaitTermination()
    dropped = sum(int(o.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for o in p["stateOperators"])
    return spark.table(name).agg(F.count(F.lit(1)).alias("windows"), F.sum("n").alias("rows_kept")).withColumn("groups_dropped", F.lit(dropped).cast("long"))
