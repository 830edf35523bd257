"""Convex losses: value and slope in the prediction, as columns and as numpy; Lipschitz constants and dual bounds."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Loss:
    """``value(y, f)`` and ``slope(y, f)``, a subgradient in f. ``lipschitz`` may depend on C and kappa (square loss)."""

    name: str
    value: Callable
    slope: Callable
    value_np: Callable
    slope_np: Callable
    constant: float | None

    def lipschitz(self, C: float = 1.0, kappa: float = 1.0) -> float:
        if self.constant is not None:
            return self.constant
        return 2 * (1 + kappa * math.sqrt(2 * C))

    def dual_bound(self, C: float, kappa: float = 1.0) -> float:
        """Bound on the L1 norm of the dual variables."""
        return C * self.lipschitz(C, kappa)


def custom(name: str, value_np: Callable, slope_np: Callable, lipschitz: float, value: Callable, slope: Callable) -> Loss:
    """Any convex Lipschitz loss, differentiable or not."""
    return Loss(name, value, slope, value_np, slope_np, lipschitz)


Hinge = Loss(
    "hinge",
    lambda y, f: F.greatest(F.lit(0.0), 1 - y * f),
    lambda y, f: F.when(y * f < 1, -y).otherwise(F.lit(0.0)),
    lambda y, f: np.maximum(0.0, 1 - y * f),
    lambda y, f: np.where(y * f < 1, -y, 0.0),
    1.0,
)
Square = Loss("square", lambda y, f: (y - f) * (y - f), lambda y, f: 2 * (f - y), lambda y, f: (y - f) ** 2, lambda y, f: 2 * (f - y), None)
Logistic = Loss(
    "logistic",
    lambda y, f: F.log1p(F.exp(-F.abs(f))) + F.greatest(F.lit(0.0), -y * f),
    lambda y, f: -y / (1 + F.exp(y * f)),
    lambda y, f: np.log1p(np.exp(-np.abs(f))) + np.maximum(0.0, -y * f),
    lambda y, f: -y / (1 + np.exp(y * f)),
    1.0,
)
LOSSES: dict[str, Loss] = {x.name: x for x in (Hinge, Square, Logistic)}


def margin(y: Column, f: Column) -> Column:
    return y * f


def side(f: Column) -> Column:
    """The class, sign(f) with ties to +1."""
    return F.when(f >= 0, 1.0).otherwise(-1.0)
