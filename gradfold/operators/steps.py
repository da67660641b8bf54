"""Step rules: the size of step k (from 1) in epoch e (from 1)."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Constant:
    a: float

    def __call__(self, e: int, k: int = 1) -> float:
        return self.a


@dataclass(frozen=True)
class PerEpoch:
    a: float
    p: float = 0.5

    def __call__(self, e: int, k: int = 1) -> float:
        return self.a / e**self.p


@dataclass(frozen=True)
class PerStep:
    """Changes with every step; `per_step` tells folds to count them."""

    a: float
    p: float = 1.0
    k0: float = 0.0
    per_step = True

    def __call__(self, e: int, k: int = 1) -> float:
        return self.a / (self.k0 + k) ** self.p


@dataclass(frozen=True)
class Geometric:
    a: float
    rho: float

    def __call__(self, e: int, k: int = 1) -> float:
        return self.a * self.rho ** (e - 1)
