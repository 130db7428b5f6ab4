"""Structured Streaming twins: progress windows, duplicates, joins and stateful sighting of files in arriving chunks."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import shared_dir


def file_stream(spark: SparkSession, folder: str, pattern: str | None = None) -> DataFrame:
    """A file stream with the schema of what lies in the folder now."""
    schema = spark.read.parquet(f"{folder}/{pattern}" if pattern else folder).schema
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", 4)
    if pattern:
        reader = reader.option("pathGlobFilter", pattern)
    return reader.parquet(folder)


def drain(stream: DataFrame, *, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is available and returns what it wrote to a table in the shared folder."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
    else:

        def keep(batch, number):  # complete results: the last batch holds all
            batch.write.mode("overwrite").parquet(f"{base}/out")

        query = stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{base}/state").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


def tumbling(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", "2 hours").groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str) -> DataFrame:
    return events.withWatermark("ts", "2 hours").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def distinct_events(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "2 hours").dropDuplicatesWithinWatermark(["event_id"])


def sightings(chunks: DataFrame) -> DataFrame:
    """Headers and footers in arriving blocks (pos, payload): counts per kind, complete after every batch."""
    kind = F.when(F.col("payload").startswith("~H1:"), "header").when(F.col("payload").contains("~E1:"), "footer")
    return chunks.select(kind.alias("kind")).where("kind is not null").groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


def followed(first: DataFrame, second: DataFrame, within: str) -> DataFrame:
    """first_id, second_id: rows of the second stream (event_id, user_id, ts) at most ``within`` after one of the first with
    the same user. State is kept for the interval and the watermark only; rows later than that find nothing."""
    a = first.withWatermark("ts", "2 hours").select(F.col("event_id").alias("first_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"))
    b = second.withWatermark("ts", "2 hours").select(F.col("event_id").alias("second_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"))
    near = (F.col("a_user") == F.col("b_user")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"interval {within}"))
    return a.join(b, near).select("first_id", "second_id")
