"""Bounds on the best privacy that any accurate mechanism can have."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import calibrate as cal


def upper_random(eps, delta, C, n, m, L=1.0):
    """What the random-feature mechanism reaches at the largest admissible noise; a bound only if m frequencies make it useful (``upper_rbf``)."""
    return cal.min_noise_random(cal.max_noise_random(eps, delta, m), n, C, m, L)


def upper_finite(eps, delta, C, n, features, kappa=1.0, phi=1.0, L=1.0):
    return cal.privacy_of(cal.max_noise_finite(eps, delta, features, phi), n, C, kappa, features, L)


def published_rate(eps: Column, delta: Column, n: Column) -> Column:
    """The stated asymptotic rate without its constant; its power of eps doesn't follow from the steps, ``upper_random`` is exact."""
    x = F.log(1 / (delta * eps))
    return F.sqrt(x) * (F.log(1 / eps) + x * x) / (F.pow(eps, 3) * n)


def lower_linear(eps, delta, C, n):
    """ln((1 - delta) / delta) while eps < sqrt(C) / (2n), else null."""
    return F.when((eps > 0) & (eps < F.sqrt(C) / (2 * n)), F.log((1 - delta) / delta))


def packing_size(sigma):
    """Points on the circle whose databases stay apart under this width."""
    if isinstance(sigma, Column):
        return F.floor(2 / sigma * math.sqrt(2 / math.log(2)))
    return math.floor(2 / sigma * math.sqrt(2 / math.log(2)))


def lower_rbf(eps, delta, C, n, sigma):
    ok = (n > C) & (eps > 0) & (eps < C / (4 * n)) & (sigma < math.sqrt(1 / (2 * math.log(2))))
    return F.when(ok, F.log((1 - delta) * (packing_size(sigma) - 1) / delta))


def is_impossible(eps, delta, beta, C, n, corrected: bool = True):
    """Whether no mechanism has this accuracy and privacy at once: delta below 1 / (1 + e^beta), or the weaker printed e^-beta."""
    limit = 1 / (1 + F.exp(beta)) if corrected else F.exp(-beta)
    return (eps < F.sqrt(C) / (2 * n)) & (delta < limit)


def is_impossible_rbf(eps, delta, beta, C, n, sigma):
    """The same for the RBF kernel, by its packing of databases."""
    return F.coalesce(lower_rbf(eps, delta, C, n, sigma) > beta, F.lit(False))


def upper_rbf(eps, delta, C, n, sigma, d, diam=2.0, constant="stated"):
    """(m, beta): the frequencies that make the random-feature mechanism useful for this width, and the privacy it then reaches."""
    m = cal.frequencies_needed(cal.theta_hinge(eps, C, constant), d, delta, d / (sigma * sigma), diam)
    return m, upper_random(eps, delta, C, n, m)


def bracket_linear(sweep: DataFrame) -> DataFrame:
    """sweep (eps, delta, C, n, d) with ``lower`` (null where its conditions fail) and ``upper``, both for the linear kernel on the unit ball."""
    a = [F.col(k) for k in ("eps", "delta", "C", "n")]
    return sweep.withColumn("lower", lower_linear(*a)).withColumn("upper", upper_finite(*a, F.col("d")))


def bracket_rbf(sweep: DataFrame, diam: float = 2.0) -> DataFrame:
    """sweep (eps, delta, C, n, sigma, d) with ``lower`` (null where its conditions fail), ``m`` and ``upper``, all for the RBF kernel of that width."""
    a = [F.col(k) for k in ("eps", "delta", "C", "n", "sigma")]
    m, upper = upper_rbf(*a, F.col("d"), diam)
    return sweep.withColumn("lower", lower_rbf(*a)).withColumn("m", m).withColumn("upper", upper)
