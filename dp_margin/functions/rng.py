"""Counter-based randomness: the same draw on every engine, partition and retry, for tests and for public frequencies; and secure noise."""

from __future__ import annotations

import hashlib
import math
import secrets as os_secrets

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TWO52 = 4503599627370496


def uniform(seed: int, stream: str, i: Column) -> Column:
    """Uniform in (0, 1) from 52 bits of md5("seed:stream:i")."""
    text = F.concat(F.lit(f"{seed}:{stream}:"), i.cast("string"))
    return (F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("long").cast("double") + 0.5) / F.lit(float(TWO52))


def uniform_py(seed: int, stream: str, i: int) -> float:
    return (int(hashlib.md5(f"{seed}:{stream}:{i}".encode()).hexdigest()[:13], 16) + 0.5) / TWO52


def laplace(u: Column, lam: float | Column) -> Column:
    c = u - 0.5
    return -(lam if isinstance(lam, Column) else F.lit(float(lam))) * F.signum(c) * F.log(1 - 2 * F.abs(c))


def normal(a: Column, b: Column) -> Column:
    return F.sqrt(-2 * F.log(a)) * F.cos(2 * math.pi * b)


def cauchy(u: Column) -> Column:
    return F.tan(math.pi * (u - 0.5))


def laplace_vector(spark: SparkSession, size: int, lam: float, seed: int, stream: str = "lap") -> DataFrame:
    """(pos, mu): independent Laplace draws of scale lam."""
    return spark.range(size).select(F.col("id").alias("pos"), laplace(uniform(seed, stream, F.col("id")), lam).alias("mu"))


class SeededRng:
    """Test mode: the draws of ``laplace_vector`` on the driver."""

    def __init__(self, seed: int):
        self.seed = seed

    def laplace(self, size: int, lam: float) -> np.ndarray:
        u = np.array([uniform_py(self.seed, "lap", i) for i in range(size)]) - 0.5
        return -lam * np.sign(u) * np.log(1 - 2 * np.abs(u))


class SecureRng:
    """Production: bits of the operating system; ``grid`` rounds noise to multiples, against attacks on the low bits of doubles."""

    def __init__(self, grid: float | None = None):
        self.grid = grid

    def laplace(self, size: int, lam: float) -> np.ndarray:
        u = np.array([(os_secrets.randbits(52) + 0.5) / TWO52 for _ in range(size)]) - 0.5
        x = -lam * np.sign(u) * np.log(1 - 2 * np.abs(u))
        return x if self.grid is None else np.round(x / self.grid) * self.grid
