"""What the fold is compared with: batch and second-order methods, MLlib, exact solvers, single-process loops."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V
from .loop import gradient
from .tasks import LR, LinearTask


def batch_descent(df: DataFrame, task: LinearTask, d: int, alpha: float, iters: int, start=None) -> tuple[np.ndarray, list[float]]:
    """One step along the mean gradient for each pass."""
    w = np.zeros(d) if start is None else np.array(start, float)
    n, norms = df.count(), []
    for _ in range(iters):
        g = np.zeros(d)
        for r in gradient(df, task, w).collect():
            g[r.j] = r.g
        w = w - alpha * g / n
        norms.append(float(np.linalg.norm(g)))
    return w, norms


def hessian(df: DataFrame, w) -> DataFrame:
    """(a, b, h) for a <= b: the second derivatives of the logistic loss, as one aggregate per pair of coordinates."""
    p = 1.0 / (1.0 + F.exp(-V.dot(V.literal(list(w)), F.col("x"))))
    each = df.select(V.let(p, lambda q: q * (1.0 - q)).alias("s"), "x")
    pairs = each.select("s", "x", F.posexplode("x").alias("a", "va")).select("s", "a", "va", F.posexplode("x").alias("b", "vb")).where("a <= b")
    return pairs.groupBy("a", "b").agg(F.sum(F.col("s") * F.col("va") * F.col("vb")).alias("h"))


def newton_lr(df: DataFrame, d: int, iters: int = 8, ridge: float = 1e-9, start=None) -> np.ndarray:
    """Iteratively reweighted least squares; d*d sums for each pass and a solve by the driver."""
    w = np.zeros(d) if start is None else np.array(start, float)
    for _ in range(iters):
        h, g = np.eye(d) * ridge, ridge * w
        for r in hessian(df, w).collect():
            h[r.a, r.b] += r.h
            if r.a != r.b:
                h[r.b, r.a] += r.h
        for r in gradient(df, LR, w).collect():
            g[r.j] += r.g
        w = w - np.linalg.solve(h, g)
    return w


def normal_sums(df: DataFrame) -> DataFrame:
    """(a, b, h): sums of x_a * x_b, with b = -1 for x_a * y."""
    full = df.select(F.array_append("x", F.col("y")).alias("z"))
    pairs = full.select("z", F.posexplode("z").alias("a", "va")).select("a", "va", F.posexplode("z").alias("b", "vb")).where("a <= b")
    return pairs.groupBy("a", "b").agg(F.sum(F.col("va") * F.col("vb")).alias("h"))


def exact_lsq(df: DataFrame, d: int) -> np.ndarray:
    a = np.zeros((d + 1, d + 1))
    for r in normal_sums(df).collect():
        a[r.a, r.b] = a[r.b, r.a] = r.h
    return np.linalg.lstsq(a[:d, :d], a[:d, d], rcond=None)[0]


def _assembled(df: DataFrame):
    from pyspark.ml.functions import array_to_vector

    return df.select(array_to_vector("x").alias("features"), (F.col("y") > 0).cast("double").alias("label"))


def mllib_lr(df: DataFrame, iters: int = 100, reg: float = 0.0, l1_share: float = 0.0):
    from pyspark.ml.classification import LogisticRegression

    m = LogisticRegression(maxIter=iters, regParam=reg, elasticNetParam=l1_share, fitIntercept=False, standardization=False, tol=1e-9).fit(_assembled(df))
    return np.array(m.coefficients)


def mllib_svc(df: DataFrame, iters: int = 100, reg: float = 0.0):
    from pyspark.ml.classification import LinearSVC

    m = LinearSVC(maxIter=iters, regParam=reg, fitIntercept=False, standardization=False).fit(_assembled(df))
    return np.array(m.coefficients)


def mllib_als(cells: DataFrame, rank: int = 4, iters: int = 10, reg: float = 1e-3, seed: int = 42) -> tuple[DataFrame, float]:
    """Predictions on the cells (i, j, m), and their squared error."""
    from pyspark.ml.recommendation import ALS

    model = ALS(rank=rank, maxIter=iters, regParam=reg, userCol="i", itemCol="j", ratingCol="m", seed=seed).fit(cells)
    out = model.transform(cells)
    return out, float(out.agg(F.sum((F.col("m") - F.col("prediction")) ** 2)).first()[0])


def numpy_igd(x: np.ndarray, y: np.ndarray, task: LinearTask, alpha: float, epochs: int = 1, start=None) -> np.ndarray:
    """The serial method in one process, for comparison and tests."""
    w = np.zeros(x.shape[1]) if start is None else np.array(start, float)
    for _ in range(epochs):
        for i in range(len(y)):
            w += alpha * float(task.move_np(x[i] @ w, y[i])) * x[i]
    return w
