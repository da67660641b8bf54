"""Multinomial logistic regression: a model row for each class, over rows (x, c) with classes 0 to C - 1."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V
from .folds import dense

STATE = "seg long, n long, w array<double>"


def chances(w: np.ndarray, x: np.ndarray) -> np.ndarray:
    """(rows, classes) probabilities."""
    u = x @ w.T
    u = np.exp(u - u.max(axis=1, keepdims=True))
    return u / u.sum(axis=1, keepdims=True)


def fold(df: DataFrame, classes: int, d: int, alpha: float, start: np.ndarray | None = None) -> DataFrame:
    """(seg, n, w): a pass over each segment of (seg, k, x, c) in the order of k, one partition a segment; w is the model row by row."""
    begin = np.zeros((classes, d)) if start is None else np.array(start, float).reshape(classes, d)

    def run(batches):
        seg, n, w = None, 0, begin.copy()

        def out():
            return pa.RecordBatch.from_arrays([pa.array([seg], pa.int64()), pa.array([n], pa.int64()), pa.array([w.ravel().tolist()], pa.list_(pa.float64()))], names=["seg", "n", "w"])

        for b in batches:
            for s, x, c in zip(b.column(0).to_pylist(), dense(b.column(1)), b.column(2).to_pylist(), strict=True):
                if s != seg:
                    if seg is not None:
                        yield out()
                    seg, n, w = s, 0, begin.copy()
                p = chances(w, x[None, :])[0]
                p[c] -= 1
                w -= alpha * p[:, None] * x
                n += 1
        if seg is not None:
            yield out()

    rows = df.select("seg", "k", "x", "c").sortWithinPartitions("seg", "k").select("seg", "x", "c")
    return rows.mapInArrow(run, STATE)


def loss(df: DataFrame, w: np.ndarray) -> DataFrame:
    """(n, loss) over rows (x, c), inside the JVM."""
    margins = F.array(*(V.dot(V.literal(row.tolist()), F.col("x")) for row in np.asarray(w, float)))
    top = F.array_max("u")
    total = F.log(V.total(F.transform("u", lambda v: F.exp(v - top)))) + top - F.element_at("u", F.col("c").cast("int") + 1)
    return df.select(margins.alias("u"), "c").agg(F.count("*").alias("n"), F.sum(total).alias("loss"))


def predict(df: DataFrame, w: np.ndarray) -> DataFrame:
    """Adds `prediction`, the likeliest class, of ties the lowest."""
    margins = F.array(*(F.struct(V.dot(V.literal(row.tolist()), F.col("x")).alias("u"), F.lit(-i).alias("c")) for i, row in enumerate(np.asarray(w, float))))
    return df.withColumn("prediction", -F.array_max(margins)["c"])
