"""How a release is planned before any row is read: the solver, the noise and the cost of a pass, from public facts alone."""

from __future__ import annotations

from dataclasses import dataclass

from ..functions import calibrate as cal
from ..functions.losses import LOSSES
from ..operators import solvers


@dataclass(frozen=True)
class Plan:
    solver: str
    lam: float | None
    rows_needed: int
    feasible: bool
    flops_a_pass: float


def plan(n: int, features: int, kappa: float, phi: float, C: float, beta: float, eps: float, delta: float, loss: str = "hinge") -> Plan:
    """Chooses the solver and the least noise, and says how many rows the wanted privacy and accuracy need."""
    L = LOSSES[loss].lipschitz(C, kappa)
    p = cal.plan_release(beta, eps, delta, C, n, features, kappa, phi, L)
    how = solvers.choose(LOSSES[loss], C, kappa, features)
    per_row = features * (features + 2) if how in ("ridge", "newton") else 2 * features
    return Plan(how, p["lam"], p["rows_needed"], p["feasible"], float(n) * per_row)
