"""Stop rules: Boolean tests after an epoch, on the history so far (rows of dicts with epoch, loss, seconds, w)."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np


class Rule:
    #: does the rule read `grad_norm`, the full gradient's norm?
    wants_gradient = False

    def __or__(self, other: Rule) -> Rule:
        return Either(self, other)

    def __call__(self, history: list[dict]) -> bool:
        raise NotImplementedError


@dataclass
class Either(Rule):
    a: Rule
    b: Rule

    @property
    def wants_gradient(self):
        return self.a.wants_gradient or self.b.wants_gradient

    def __call__(self, history):
        return self.a(history) or self.b(history)


@dataclass
class MaxEpochs(Rule):
    n: int

    def __call__(self, history):
        return len(history) >= self.n


@dataclass
class GradNorm(Rule):
    """Needs the full gradient's norm, which `loop.fit` adds when this rule is used."""

    eps: float
    wants_gradient = True

    def __call__(self, history):
        return history[-1]["grad_norm"] <= self.eps


@dataclass
class RelDrop(Rule):
    """The loss changed by at most `tol` of its last value, or by at most `floor`: a loss that falls towards zero may drop by half for ever."""

    tol: float
    floor: float = 1e-12

    def __call__(self, history):
        if len(history) < 2:
            return False
        before, now = history[-2]["loss"], history[-1]["loss"]
        return abs(before - now) <= max(self.tol * abs(before), self.floor)


@dataclass
class OptGap(Rule):
    best: float
    tol: float = 1e-3

    def __call__(self, history):
        return history[-1]["loss"] - self.best <= self.tol * abs(self.best)


@dataclass
class Multiple(Rule):
    best: float
    factor: float = 2.0

    def __call__(self, history):
        return history[-1]["loss"] <= self.factor * self.best


@dataclass
class TargetLoss(Rule):
    value: float

    def __call__(self, history):
        return history[-1]["loss"] <= self.value


@dataclass
class ModelPredicate(Rule):
    test: Callable[[np.ndarray], bool]

    def __call__(self, history):
        return bool(self.test(history[-1]["w"]))


@dataclass
class SqlPredicate(Rule):
    """A query with one Boolean result over the views `model` (j, w) and `history`."""

    spark: object
    query: str

    def __call__(self, history):
        w = history[-1]["w"]
        self.spark.createDataFrame([(j, float(v)) for j, v in enumerate(w)], "j int, w double").createOrReplaceTempView("model")
        self.spark.createDataFrame([(h["epoch"], float(h["loss"])) for h in history], "epoch int, loss double").createOrReplaceTempView("history")
        return bool(self.spark.sql(self.query).first()[0])


@dataclass
class MaxSeconds(Rule):
    s: float

    def __call__(self, history):
        return sum(h["seconds"] for h in history) >= self.s
