"""Model tables: saved by run and epoch, loaded as a warm start, applied to rows."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import vectors as V
from .tasks import LINEAR, LinearTask

#: Coordinates up to this number are one array and travel as one row; beyond, a model is a table by feature.
DENSE = 4_000_000


def save(spark: SparkSession, path: str, run: str, epoch: int, task: str, w, steps: int = 0) -> None:
    row = [(run, epoch, task, [float(v) for v in w], steps)]
    spark.createDataFrame(row, "run string, epoch int, task string, w array<double>, steps long").write.mode("append").partitionBy("run").parquet(path)


def load(spark: SparkSession, path: str, run: str, epoch: int | None = None) -> tuple[np.ndarray, str]:
    """The weights and task of a run's latest epoch, or of one epoch."""
    found = spark.read.parquet(path).where(F.col("run") == run)
    found = found.where(F.col("epoch") == epoch) if epoch is not None else found
    row = found.orderBy(F.desc("epoch")).limit(1).collect()[0]
    return np.array(row.w), row.task


def predict(df: DataFrame, model: DataFrame, task: LinearTask | str) -> DataFrame:
    """Adds score and prediction; `model` is one row with w, broadcast to the rows (its length is that of x)."""
    task = LINEAR[task] if isinstance(task, str) else task
    u = V.dot(F.col("w"), F.col("x"))
    scored = df.crossJoin(F.broadcast(model.select("w").limit(1))).withColumn("u", u)
    sign = F.when(F.col("u") < 0, -1.0).otherwise(1.0)
    return scored.withColumn("score", task.score(F.col("u"))).withColumn("prediction", sign if task.name in ("lr", "svm") else F.col("score")).drop("w", "u")


def predict_sparse(rows: DataFrame, model: DataFrame) -> DataFrame:
    """(id, margin) of rows (id, feature, value) under a model table (feature, w) of any size: a join and a sum."""
    return rows.join(model, "feature").groupBy("id").agg(F.sum(F.col("value") * F.col("w")).alias("margin"))
