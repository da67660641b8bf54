"""Windowed aggregates and deduplication over an event stream, replayed to the end of what there is."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.files import scratch
from ..sources.tables import table


def events(spark: SparkSession, sf_dir: str, files_per_batch: int = 4) -> DataFrame:
    """The events table as a stream of files; ts as an instant in UTC."""
    schema = table(spark, sf_dir, "events").schema
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(f"{sf_dir}/event[s].parquet")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def replay(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Run a stream to its end and give its result.

    Aggregates (mode complete, small) go to memory; rows (append) to files.
    """
    spark, name = stream.sparkSession, f"replay_{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", scratch(spark, "stream")).trigger(availableNow=True)
    if mode == "complete":
        writer.format("memory").queryName(name).start().awaitTermination()
        return spark.table(name)
    path = scratch(spark, name)
    writer.format("parquet").start(path).awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def tumbling(stream: DataFrame, every: str = "1 hour", late: str = "2 hours") -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", every).alias("w"), "event_type")
    return w.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


def sliding(stream: DataFrame, size: str = "1 hour", every: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", size, every).alias("w"))
    return w.agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "6 hours", late: str = "12 hours") -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w"))
    return w.agg(F.count("*").alias("n")).select("user_id", "n")


def first_seen(stream: DataFrame) -> DataFrame:
    """Each (user, type) once; the state grows with distinct pairs, so bound it by a watermark where those do not end."""
    return stream.select("user_id", "event_type").dropDuplicates(["user_id", "event_type"])
