"""The SQL surface: functions and table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="pos: bigint, mu: double")
class Noise:
    """Laplace draws of the counter generator."""

    def eval(self, size: int, lam: float, seed: int):
        import math

        from dp_margin.functions.rng import uniform_py

        for i in range(size):
            c = uniform_py(seed, "lap", i) - 0.5
            yield i, -lam * math.copysign(1.0, c) * math.log(1 - 2 * abs(c))


@udtf(returnType="j: bigint, coord: bigint, rho: double")
class Frequencies:
    """Frequencies of the Gaussian kernel from a public seed."""

    def eval(self, m: int, d: int, sigma: float, seed: int):
        import math

        from dp_margin.functions.rng import uniform_py

        for i in range(m * d):
            u = math.sqrt(-2 * math.log(uniform_py(seed, "fa", i))) * math.cos(2 * math.pi * uniform_py(seed, "fb", i))
            yield i // d, i % d, u / sigma


@udtf(returnType="db: bigint, x1: double, x2: double")
class Packing:
    """Last rows of the packing's databases."""

    def eval(self, sigma: float):
        import math

        size = math.floor(2 / sigma * math.sqrt(2 / math.log(2)))
        for k in range(size):
            yield k, math.cos(2 * math.pi * k / size), math.sin(2 * math.pi * k / size)


def register_all(spark: SparkSession) -> None:
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dpm_dot(x ARRAY<DOUBLE>, w ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(x, w, (a, b) -> a * b), 0D, (a, b) -> a + b)")
    for name, f in (("dpm_noise", Noise), ("dpm_frequencies", Frequencies), ("dpm_packing", Packing)):
        spark.udtf.register(name, f)
