"""Closed forms that link privacy, noise, accuracy and sizes. All take numbers; ``columns`` of the same name take columns.

Names: n rows, F features, m frequencies (F = 2m), C loss weight, L Lipschitz constant of the loss, kappa bound of the map's norm,
Phi bound of a feature, lam Laplace scale, beta privacy level, eps and delta accuracy and failure probability, big_l bound on the duals' L1 norm.
"""

from __future__ import annotations

import math
from types import SimpleNamespace

from pyspark.sql import Column
from pyspark.sql import functions as F

from .kernels import UnboundedSpectrum

_num = SimpleNamespace(sqrt=math.sqrt, log=math.log, least=min, greatest=max, exp=math.exp, power=pow, ceil=math.ceil)
_col = SimpleNamespace(sqrt=lambda x: F.sqrt(_lit(x)), log=lambda x: F.log(_lit(x)), least=lambda *a: F.least(*map(_lit, a)), greatest=lambda *a: F.greatest(*map(_lit, a)), exp=lambda x: F.exp(_lit(x)), power=lambda x, p: F.pow(_lit(x), _lit(p)), ceil=lambda x: F.when(_lit(x) < 2.0**53, F.ceil(_lit(x)).cast("double")).otherwise(_lit(x)))


def _lit(x):
    return x if isinstance(x, Column) else F.lit(float(x))


def _of(*args):
    return _col if any(isinstance(a, Column) for a in args) else _num


def weight_sensitivity(C, n, kappa=1.0, L=1.0, norm=2, features=1, gap=0.0, tight=False):
    """Largest change of the weights when one row is replaced. ``gap``: objective gap of the solver; ``tight``: half the constant."""
    o = _of(C, n, kappa, L, features, gap)
    base = (2 if tight else 4) * L * C * kappa / n + 2 * o.sqrt(2 * gap)
    return base * o.sqrt(features) if norm == 1 else base


def min_noise_finite(beta, n, C, kappa=1.0, features=1, L=1.0, gap=0.0):
    """Least Laplace scale for beta-privacy of a finite map."""
    return weight_sensitivity(C, n, kappa, L, 1, features, gap) / beta


def min_noise_random(beta, n, C, m, L=1.0):
    """The same for m random frequencies (unit norm, 2m features)."""
    o = _of(beta, n, C, m, L)
    return 2**2.5 * L * C * o.sqrt(m) / (beta * n)


def privacy_of(lam, n, C, kappa=1.0, features=1, L=1.0):
    """Privacy level of a scale: the inverse of ``min_noise_finite``."""
    return min_noise_finite(lam, n, C, kappa, features, L)


def max_noise_finite(eps, delta, features, phi=1.0, exact_tail=False):
    """Largest scale for which all predictions stay within eps with probability 1 - delta."""
    if exact_tail:
        return eps / (phi * erlang_quantile(int(features), 1 - delta))
    o = _of(eps, delta, features, phi)
    return eps / (2 * phi * (features * math.log(2) + o.log(1 / delta)))


def failure_probability(lam, eps, features, phi=1.0):
    o = _of(lam, eps, features, phi)
    return o.least(1.0, o.exp(features * math.log(2) - eps / (2 * lam * phi)))


def max_noise_random(eps, delta, m):
    """Largest scale that leaves half of eps (and of delta) to the kernel's approximation."""
    o = _of(eps, delta, m)
    return o.least(eps / (16 * math.log(2) * o.sqrt(m)), eps * o.sqrt(m) / (8 * o.log(2 / delta)))


def erlang_cdf(k: int, x: float) -> float:
    """P(sum of k unit exponentials <= x)."""
    if x <= 0:
        return 0.0
    return 1 - sum(math.exp(i * math.log(x) - x - math.lgamma(i + 1)) for i in range(k))


def erlang_quantile(k: int, p: float) -> float:
    lo, hi = 0.0, 10.0 * k + 50
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if erlang_cdf(k, mid) < p else (lo, mid)
    return hi


def _m(o, d, error2, delta_term, sigma_p2, diam):
    """The common form 4 (d + 2) / error2 * ln(...), rounded up, 1 at least."""
    return o.greatest(1, o.ceil(4 * (d + 2) / error2 * delta_term))


def frequencies_for_kernel_error(error, d, delta, sigma_p2, diam):
    """Frequencies that bring the kernel within error everywhere on the domain with probability 1 - delta."""
    o = _of(error, d, delta, sigma_p2, diam)
    if o is _num and math.isinf(sigma_p2):
        raise UnboundedSpectrum("the spectral law has no second moment")
    return _m(o, d, error * error, o.log(256 * sigma_p2 * diam * diam / (delta * error * error)), sigma_p2, diam)


def kernel_error_for_frequencies(m, d, delta, sigma_p2, diam) -> float:
    lo, hi = 1e-9, 1e6
    for _ in range(200):
        mid = math.sqrt(lo * hi)
        lo, hi = (mid, hi) if 4 * (d + 2) / mid**2 * math.log(256 * sigma_p2 * diam**2 / (delta * mid**2)) > m else (lo, mid)
    return hi


def _reach(o, C, L, big_l):
    return big_l + 2 * o.sqrt((C * L + big_l / 2) * big_l)


def kernel_error_budget(eps, C, big_l, L=1.0):
    """Kernel error that keeps the classifiers within eps / 2."""
    o = _of(eps, C, big_l, L)
    return o.least(1.0, eps * eps / (4 * o.power(_reach(o, C, L, big_l), 2)))


def theta(eps, C, big_l, L=1.0):
    o = _of(eps, C, big_l, L)
    return o.least(1.0, o.power(eps, 4) / (16 * o.power(_reach(o, C, L, big_l), 4)))


def theta_hinge(eps, C, constant="stated"):
    """For the hinge loss: the stated power of two, or the exact constant behind it."""
    o = _of(eps, C)
    k = 2.0**12 if constant == "stated" else 16 * (1 + math.sqrt(6)) ** 4
    return o.least(1.0, o.power(eps, 4) / (k * o.power(C, 4)))


def frequencies_needed(th, d, delta, sigma_p2, diam):
    """Frequencies for (eps, delta)-usefulness, th from ``theta`` or ``theta_hinge``."""
    o = _of(th, d, delta, sigma_p2, diam)
    if o is _num and math.isinf(sigma_p2):
        raise UnboundedSpectrum("the spectral law has no second moment")
    return _m(o, d, th, o.log(512 * sigma_p2 * diam * diam / (delta * th)), sigma_p2, diam)


def plan_release(beta, eps, delta, C, n, features, kappa=1.0, phi=1.0, L=1.0) -> dict:
    """Noise for a finite map, or the fewest rows for which privacy and accuracy meet."""
    lo, hi = min_noise_finite(beta, n, C, kappa, features, L), max_noise_finite(eps, delta, features, phi)
    need = math.ceil(weight_sensitivity(C, 1, kappa, L, 1, features) / (beta * hi))
    return {"feasible": lo <= hi, "lam": lo if lo <= hi else None, "lam_min": lo, "lam_max": hi, "rows_needed": need}


def plan_release_random(beta, eps, delta, C, n, d, sigma_p2, diam, constant="stated") -> dict:
    """Hinge, random map: the frequencies that usefulness asks for, then the noise that privacy and accuracy leave, or the fewest rows for which they meet.

    Takes numbers or columns and gives the same kind.
    """
    o = _of(beta, eps, delta, C, n, d, sigma_p2, diam)
    m = frequencies_needed(theta_hinge(eps, C, constant), d, delta, sigma_p2, diam)
    lo, hi = min_noise_random(beta, n, C, m), max_noise_random(eps, delta, m)
    return {"m": m, "lam_min": lo, "lam_max": hi, "feasible": lo <= hi, "rows_needed": o.ceil(min_noise_random(beta, 1, C, m) / hi)}
