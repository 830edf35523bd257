"""Translation-invariant kernels, their spectral laws, and the random trigonometric map."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import rng, vectors


class UnboundedSpectrum(ValueError):
    """The spectral law has no second moment: no number of frequencies is certified."""


@dataclass(frozen=True)
class Kernel:
    """``column(x, z)`` and ``numpy(delta)`` give the value; ``draw(u)`` turns uniforms into frequencies of the normalised law."""

    name: str
    column: Callable[[Column, Column], Column]
    numpy: Callable[[np.ndarray], np.ndarray]
    draw: Callable[[int, Column], Column]
    second_moment: Callable[[int], float]
    #: What the map is multiplied with to get the printed instead of the normalised kernel, for d dimensions.
    scale: Callable[[int], float] = lambda d: 1.0


def _each(x: Column, z: Column, f) -> Column:
    return F.zip_with(x, z, lambda a, b: f(a.cast("double") - b.cast("double")))


def rbf(sigma: float = 1.0) -> Kernel:
    """exp(-|x - z|^2 / (2 sigma^2)); frequencies are normal with variance 1 / sigma^2."""
    return Kernel(
        f"rbf({sigma:g})",
        lambda x, z: F.exp(-vectors.total(_each(x, z, lambda t: t * t)) / (2 * sigma * sigma)),
        lambda t: np.exp(-(t * t).sum(-1) / (2 * sigma * sigma)),
        lambda seed, i: rng.normal(rng.uniform(seed, "fa", i), rng.uniform(seed, "fb", i)) / sigma,
        lambda d: d / sigma**2,
    )


def laplacian() -> Kernel:
    """exp(-|x - z|_1); frequencies are standard Cauchy, whose second moment is infinite."""
    return Kernel(
        "laplacian",
        lambda x, z: F.exp(-vectors.total(_each(x, z, F.abs))),
        lambda t: np.exp(-np.abs(t).sum(-1)),
        lambda seed, i: rng.cauchy(rng.uniform(seed, "fa", i)),
        lambda d: math.inf,
    )


def cauchy_kernel(paper_scale: bool = False) -> Kernel:
    """Product of 1 / (1 + t^2), normalised to 1 at zero; ``paper_scale`` keeps the printed factor 2^d. Frequencies are Laplace(0, 1)."""
    factor = (lambda d: 2.0 ** (d / 2)) if paper_scale else (lambda d: 1.0)
    top = (lambda x: F.pow(F.lit(2.0), F.size(x))) if paper_scale else (lambda x: F.lit(1.0))
    return Kernel(
        "cauchy",
        lambda x, z: top(x) * F.aggregate(_each(x, z, lambda t: 1 / (1 + t * t)), F.lit(1.0), lambda a, v: a * v),
        lambda t: (2.0 ** t.shape[-1] if paper_scale else 1.0) * np.prod(1 / (1 + t * t), axis=-1),
        lambda seed, i: rng.laplace(rng.uniform(seed, "fa", i), 1.0),
        lambda d: 2.0 * d,
        factor,
    )


def translation_invariant(name: str, column, numpy, draw, second_moment: float) -> Kernel:
    """A user's kernel: its value, a sampler of its spectral law, and that law's second moment for one dimension."""
    return Kernel(name, column, numpy, draw, lambda d: second_moment * d)


def sample_frequencies(spark: SparkSession, kernel: Kernel, d: int, m: int, seed: int) -> DataFrame:
    """(j, coord, rho), independent of all data; regenerated anywhere from the public seed."""
    return spark.range(m * d).select(F.floor(F.col("id") / d).cast("long").alias("j"), (F.col("id") % d).alias("coord"), kernel.draw(seed, F.col("id")).alias("rho"))


def frequency_matrix(spark: SparkSession, kernel: Kernel, d: int, m: int, seed: int) -> np.ndarray:
    """(m, d) on the driver: small, and public."""
    rows = sample_frequencies(spark, kernel, d, m, seed).collect()
    out = np.zeros((m, d))
    for r in rows:
        out[r.j, r.coord] = r.rho
    return out


def trig_map(x: Column, rho: np.ndarray, scale: float = 1.0) -> Column:
    """Unit-norm features (cos, sin) of every frequency, for few and short frequencies; ``trig_batch`` for many."""
    m = len(rho)
    parts = [vectors.dot_literal(x, r) for r in rho]
    return F.array(*[f(p) * (scale / math.sqrt(m)) for p in parts for f in (F.cos, F.sin)])


def trig_batch(x: np.ndarray, rho: np.ndarray, scale: float = 1.0) -> np.ndarray:
    """(rows, 2m): one matrix product a batch; cos and sin of a frequency are neighbours."""
    p = x @ rho.T
    out = np.empty((len(x), 2 * len(rho)))
    out[:, 0::2], out[:, 1::2] = np.cos(p), np.sin(p)
    return out * (scale / math.sqrt(len(rho)))


def approx_kernel(pairs: DataFrame, frequencies: DataFrame, x: str = "x", z: str = "z", keys: tuple[str, ...] = ("i", "j")) -> DataFrame:
    """Inner product of random features of pairs: the mean of cos(rho . (x - z)) over frequencies (coordinates gathered first)."""
    f = frequencies.groupBy("j").agg(F.array_sort(F.collect_list(F.struct("coord", "rho"))).alias("f")).select(F.col("j").alias("freq"), F.transform("f", lambda s: s["rho"]).alias("f"))
    diff = F.zip_with(x, z, lambda a, b: a.cast("double") - b.cast("double"))
    return pairs.crossJoin(F.broadcast(f)).groupBy(*keys).agg(F.avg(F.cos(vectors.dot(F.col("f"), diff))).alias("khat"))
