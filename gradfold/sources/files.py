"""Round trips through file formats, and a partitioned, bucketed sink."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh path in the shared folder that the session names; a session on one machine may name none and gets a local one."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = tempfile.mkdtemp(prefix="gradfold-")
    return f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, form: str, **options) -> DataFrame:
    """Written and read again with the same schema, without inference."""
    path = scratch(df.sparkSession, form)
    df.write.format(form).options(**options).save(path)
    return df.sparkSession.read.format(form).schema(df.schema).options(**options).load(path)


def partitioned(df: DataFrame, column: str) -> DataFrame:
    path = scratch(df.sparkSession, "partitioned")
    df.write.partitionBy(column).parquet(path)
    return df.sparkSession.read.parquet(path)


def bucketed(df: DataFrame, column: str, buckets: int, name: str) -> DataFrame:
    """A bucketed and sorted table: joins on the column need no exchange of it."""
    df.write.mode("overwrite").bucketBy(buckets, column).sortBy(column).option("path", scratch(df.sparkSession, name)).saveAsTable(name)
    return df.sparkSession.table(name)
