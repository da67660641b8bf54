"""Learning tasks over rows (x, y).

A linear task is two formulas of the margin u = w.x and the target y: the
coefficient c with which a step adds alpha * c * x to the model, and the loss.
Both are written once for Catalyst columns and once for numpy; everything else -
folds, orders, parallel schemes, measures - is shared by all tasks.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions import vectors as V


@dataclass(frozen=True)
class LinearTask:
    name: str
    #: coefficient of x in a descent step, and loss, of (margin, target)
    move: Callable[[Column, Column], Column]
    loss: Callable[[Column, Column], Column]
    move_np: Callable
    loss_np: Callable
    #: prediction of (margin)
    score: Callable[[Column], Column]
    sql_move: str = ""
    sql_loss: str = ""
    #: `move` of two Python floats; what a serial walk calls for each row
    move_one: Callable[[float, float], float] | None = None

    def one(self) -> Callable[[float, float], float]:
        return self.move_one or (lambda u, y: float(self.move_np(u, y)))

    def loss_of(self, w: Column, x: Column, y: Column) -> Column:
        return V.let(V.dot(w, x), lambda u: self.loss(u, y))


def _log1pexp(v: Column) -> Column:
    """log(1 + exp(v)) without overflow."""
    return F.log(1.0 + F.exp(-F.abs(v))) + F.greatest(v, F.lit(0.0))


def _sigmoid(v):
    return np.where(v >= 0, 1 / (1 + np.exp(-np.abs(v))), np.exp(-np.abs(v)) / (1 + np.exp(-np.abs(v))))


LR = LinearTask(
    "lr",
    lambda u, y: y / (1.0 + F.exp(y * u)),
    lambda u, y: _log1pexp(-y * u),
    lambda u, y: y * _sigmoid(-y * u),
    lambda u, y: np.logaddexp(0, -y * u),
    lambda u: 1.0 / (1.0 + F.exp(-u)),
    "({y} / (1.0::DOUBLE + exp({y} * ({u}))))",
    "(ln(1.0::DOUBLE + exp(-abs({u}))) + greatest(-({y}) * ({u}), 0.0::DOUBLE))",
    lambda u, y: y / (1.0 + math.exp(min(y * u, 700.0))),
)
SVM = LinearTask(
    "svm",
    lambda u, y: F.when(y * u < 1.0, y).otherwise(0.0),
    lambda u, y: F.greatest(F.lit(0.0), 1.0 - y * u),
    lambda u, y: np.where(y * u < 1.0, y, 0.0),
    lambda u, y: np.maximum(0.0, 1.0 - y * u),
    lambda u: F.when(u < 0, -1.0).otherwise(1.0),
    "(CASE WHEN {y} * ({u}) < 1.0 THEN {y} ELSE 0.0::DOUBLE END)",
    "greatest(0.0::DOUBLE, 1.0::DOUBLE - {y} * ({u}))",
    lambda u, y: y if y * u < 1.0 else 0.0,
)
LSQ = LinearTask(
    "lsq",
    lambda u, y: y - u,
    lambda u, y: 0.5 * (u - y) * (u - y),
    lambda u, y: y - u,
    lambda u, y: 0.5 * (u - y) ** 2,
    lambda u: u,
    "({y} - ({u}))",
    "(0.5::DOUBLE * (({u}) - {y}) * (({u}) - {y}))",
    lambda u, y: y - u,
)
HUBER = LinearTask(
    "huber",
    lambda u, y: F.greatest(F.lit(-1.0), F.least(F.lit(1.0), y - u)),
    lambda u, y: F.when(F.abs(u - y) <= 1.0, 0.5 * (u - y) * (u - y)).otherwise(F.abs(u - y) - 0.5),
    lambda u, y: np.clip(y - u, -1, 1),
    lambda u, y: np.where(np.abs(u - y) <= 1, 0.5 * (u - y) ** 2, np.abs(u - y) - 0.5),
    lambda u: u,
    "greatest(-1.0::DOUBLE, least(1.0::DOUBLE, {y} - ({u})))",
    "(CASE WHEN abs(({u}) - {y}) <= 1.0 THEN 0.5::DOUBLE * (({u}) - {y}) * (({u}) - {y}) ELSE abs(({u}) - {y}) - 0.5::DOUBLE END)",
)
ABSOLUTE = LinearTask(
    "absolute",
    lambda u, y: F.signum(y - u),
    lambda u, y: F.abs(u - y),
    lambda u, y: np.sign(y - u),
    lambda u, y: np.abs(u - y),
    lambda u: u,
    "sign({y} - ({u}))",
    "abs(({u}) - {y})",
)
POISSON = LinearTask(
    "poisson",
    lambda u, y: y - F.exp(u),
    lambda u, y: F.exp(u) - y * u,
    lambda u, y: y - np.exp(u),
    lambda u, y: np.exp(u) - y * u,
    lambda u: F.exp(u),
    "({y} - exp({u}))",
    "(exp({u}) - {y} * ({u}))",
)
NULL = LinearTask("null", lambda u, y: F.lit(0.0), lambda u, y: F.lit(0.0), lambda u, y: 0.0 * u, lambda u, y: 0.0 * u, lambda u: u, "0.0::DOUBLE", "0.0::DOUBLE", lambda u, y: 0.0)

LINEAR = {t.name: t for t in (LR, SVM, LSQ, HUBER, ABSOLUTE, POISSON, NULL)}
