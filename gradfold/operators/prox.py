"""Proximal maps of regularisers and constraints.

A map takes the model after a step, the step size and the share of the penalty
that one step stands for (1/N, so that an epoch applies the penalty once).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions import vectors as V


@dataclass(frozen=True)
class Prox:
    name: str
    column: Callable[[Column, float], Column]
    array: Callable[[np.ndarray, float], np.ndarray]
    penalty: Callable[[np.ndarray], float]
    #: DuckDB text with {v} for one coordinate and {t} for the threshold, where it acts on each alone
    sql: str = "{v}"


def none() -> Prox:
    return Prox("none", lambda w, t: w, lambda w, t: w, lambda w: 0.0)


def soft(w: np.ndarray, t: float) -> np.ndarray:
    return np.sign(w) * np.maximum(np.abs(w) - t, 0.0)


def l1(mu: float) -> Prox:
    return Prox("l1", lambda w, t: F.transform(w, lambda v: F.signum(v) * F.greatest(F.abs(v) - t * mu, F.lit(0.0))), lambda w, t: soft(w, t * mu), lambda w: mu * float(np.abs(w).sum()), f"(sign({{v}}) * greatest(abs({{v}}) - {{t}} * {mu}::DOUBLE, 0.0::DOUBLE))")


def l2(mu: float) -> Prox:
    return Prox("l2", lambda w, t: F.transform(w, lambda v: v / (1.0 + 2.0 * t * mu)), lambda w, t: w / (1 + 2 * t * mu), lambda w: mu * float(w @ w), f"({{v}} / (1.0::DOUBLE + 2.0::DOUBLE * {{t}} * {mu}::DOUBLE))")


def box(low: float, high: float) -> Prox:
    return Prox("box", lambda w, t: F.transform(w, lambda v: F.greatest(F.lit(low), F.least(F.lit(high), v))), lambda w, t: np.clip(w, low, high), lambda w: 0.0, f"greatest({low}::DOUBLE, least({high}::DOUBLE, {{v}}))")


def ball(radius: float) -> Prox:
    def column(w, t):
        return V.let(V.norm2(w), lambda n: V.scale(w, F.when(n > radius, radius / n).otherwise(1.0)))

    return Prox("ball", column, lambda w, t: w * min(1.0, radius / max(float(np.linalg.norm(w)), 1e-300)), lambda w: 0.0)


def onto_simplex(w: np.ndarray) -> np.ndarray:
    """The nearest point with non-negative coordinates that sum to one."""
    u = np.sort(w)[::-1]
    excess = (np.cumsum(u) - 1) / np.arange(1, len(u) + 1)
    return np.maximum(w - excess[np.flatnonzero(u > excess)[-1]], 0.0)


def simplex_column(w: Column) -> Column:
    u = F.reverse(F.array_sort(w))
    # the threshold is the largest of the mean excesses of the k largest coordinates
    excess = F.transform(u, lambda v, i: (V.total(F.slice(u, F.lit(1), i + 1)) - 1.0) / (i + 1))
    return V.let(F.array_max(excess), lambda theta: F.transform(w, lambda v: F.greatest(v - theta, F.lit(0.0))))


def simplex() -> Prox:
    return Prox("simplex", lambda w, t: simplex_column(w), lambda w, t: onto_simplex(w), lambda w: 0.0)


class LazyL1:
    """Soft thresholding put off until a coordinate is next touched: for sparse rows.

    Thresholding twice with no step between equals thresholding once by the sum.
    """

    def __init__(self, d: int, mu: float):
        self.mu, self.sum, self.seen = mu, 0.0, np.zeros(d)

    def touch(self, w: np.ndarray, idx: np.ndarray) -> None:
        w[idx] = soft(w[idx], self.sum - self.seen[idx])
        self.seen[idx] = self.sum

    def spend(self, t: float) -> None:
        self.sum += t * self.mu

    def settle(self, w: np.ndarray) -> np.ndarray:
        w[:] = soft(w, self.sum - self.seen)
        self.seen[:] = self.sum
        return w


class ScaledL2:
    """w = s * v: shrinking all coordinates changes one number."""

    def __init__(self, mu: float):
        self.mu, self.s = mu, 1.0

    def shrink(self, v: np.ndarray, t: float) -> None:
        self.s /= 1 + 2 * t * self.mu
        if self.s < 1e-6:
            v *= self.s
            self.s = 1.0
