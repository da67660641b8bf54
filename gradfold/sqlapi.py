"""The front end: training and prediction by names, in Python and as SQL table functions.

`train` runs the engine on a table of any size.  The SQL functions run inside one
worker and keep one partition's rows: they are for small tables, or for one model
for each partition of a table.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from .operators import loop, models
from .operators.tasks import LINEAR


def train(spark: SparkSession, model: str, source: str | DataFrame, vector: str, label: str, task: str = "svm", path: str | None = None, **options) -> loop.FitResult:
    """Train a model on columns of a table and, with a path, save it under its name."""
    df = spark.table(source) if isinstance(source, str) else source
    ident = options.pop("ident", None)
    key = F.col(ident) if ident else F.xxhash64(vector, label)
    rows = df.select(key.alias("id"), F.col(vector).cast("array<double>").alias("x"), F.col(label).cast("double").alias("y"))
    d = rows.select(F.max(F.size("x"))).first()[0]
    fit = loop.fit(rows, LINEAR[task], d, **options)
    if path:
        models.save(spark, path, model, len(fit.history), task, fit.w, fit.history[-1]["steps"])
    return fit


def svm_train(spark, model, source, vector, label, **options):
    return train(spark, model, source, vector, label, "svm", **options)


def lr_train(spark, model, source, vector, label, **options):
    return train(spark, model, source, vector, label, "lr", **options)


def apply(spark: SparkSession, model: str, path: str, source: str | DataFrame, vector: str) -> DataFrame:
    """The rows of a table with score and prediction of a saved model."""
    w, task = models.load(spark, path, model)
    df = spark.table(source) if isinstance(source, str) else source
    frame = spark.createDataFrame([(w.tolist(),)], "w array<double>")
    return models.predict(df.withColumn("x", F.col(vector).cast("array<double>")), frame, task)


class _Train:
    """train(TABLE(k, x, y) ..., task, alpha, epochs): rows arrive in the order that the call states."""

    def __init__(self):
        self.x, self.y, self.args = [], [], ("lr", 0.1, 1)

    def eval(self, row, task: str, alpha: float, epochs: int):
        self.x.append(row["x"])
        self.y.append(row["y"])
        self.args = (task, float(alpha), int(epochs))

    def terminate(self):
        task, alpha, epochs = self.args
        if not self.y:
            return
        x, w = np.array(self.x, float), np.zeros(len(self.x[0]))
        for _ in range(epochs):
            for i, y in enumerate(self.y):
                w += alpha * float(LINEAR[task].move_np(x[i] @ w, y)) * x[i]
        for j, v in enumerate(w.tolist()):
            yield j, v


class _Predict:
    """predict(TABLE(id, x), weights): a margin for each row."""

    def eval(self, row, weights: list):
        yield row["id"], float(np.dot(np.array(row["x"], float), np.array(weights, float)))


def register(spark: SparkSession) -> None:
    """Make gf_train and gf_predict known to SQL."""
    spark.udtf.register("gf_train", udtf(_Train, returnType="j int, w double"))
    spark.udtf.register("gf_predict", udtf(_Predict, returnType="id bigint, margin double"))
