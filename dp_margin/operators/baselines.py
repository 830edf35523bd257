"""What the mechanisms are compared with."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import rng
from ..functions.kernels import Kernel, frequency_matrix
from ..functions.losses import Hinge, Loss
from . import passes, solvers


def random_features_nonprivate(df: DataFrame, kernel: Kernel, d: int, m: int, C: float, seed: int, loss: Loss = Hinge) -> tuple[solvers.Fit, np.ndarray]:
    """Large-scale learning in the random space, without noise."""
    rho = frequency_matrix(df.sparkSession, kernel, d, m, seed)
    return solvers.fit(df, C, 2 * m, 1.0, loss, rho=rho), rho


def naive_disclosure(alpha: DataFrame, tol: float = 1e-12) -> DataFrame:
    """(exposed, share): rows that releasing the duals with their support vectors would lay open. Measured, never offered."""
    hit = F.when(F.col("alpha") > tol, 1).otherwise(0)
    return alpha.agg(F.sum(hit).alias("exposed"), F.avg(hit.cast("double")).alias("share"))


def private_histogram(df: DataFrame, key: str, domain: list, beta: float, seed: int) -> DataFrame:
    """(key, noisy): Laplace counts over a public domain; a replaced row moves two counts by one, so the scale is 2 / beta."""
    spark: SparkSession = df.sparkSession
    cells = spark.createDataFrame([(i, k) for i, k in enumerate(domain)], ["cell", key])
    counts = df.groupBy(key).agg(F.count("*").alias("n"))
    noise = rng.laplace(rng.uniform(seed, "hist", F.col("cell")), 2 / beta)
    return F.broadcast(cells).join(counts, key, "left").select("cell", key, (F.coalesce("n", F.lit(0)) + noise).alias("noisy"))


def private_class_means(df: DataFrame, features: int, beta: float, seed: int, phi: float = 1.0) -> DataFrame:
    """(pos, w): difference of the classes' noisy feature sums over n, a learner made of subset sums."""
    n = solvers.rows_and_weight(df)
    s = passes.sql_sums(df, {str(i): F.col("y") * F.get("x", F.lit(i)) for i in range(features)})
    rows = df.sparkSession.createDataFrame([(i, s[str(i)]) for i in range(features)], "pos long, s double")
    noise = rng.laplace(rng.uniform(seed, "means", F.col("pos")), 2 * phi * features / beta)
    return rows.select("pos", ((F.col("s") + noise) / n).alias("w"))


def majority(df: DataFrame) -> DataFrame:
    """(y, n): the most frequent class."""
    return df.groupBy("y").agg(F.count("*").alias("n")).agg(F.max_by("y", "n").alias("y"), F.max("n").alias("n"))


def cost_model(n: Column, d: Column, m: Column) -> tuple[Column, Column]:
    """Operations of the kernel matrix: with the original kernel, and with m random features."""
    return d * n * n, m * n * n


def ml_crosscheck(df: DataFrame, C: float, loss: str = "hinge") -> list[float]:
    """Weights of Spark's own linear models for the same objective: no intercept, no standardisation."""
    from pyspark.ml.classification import LinearSVC, LogisticRegression
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.regression import LinearRegression

    t = df.select(array_to_vector("x").alias("features"), (((F.col("y") + 1) / 2) if loss != "square" else F.col("y")).alias("label"))
    if loss == "hinge":
        m = LinearSVC(regParam=1 / C, fitIntercept=False, standardization=False, maxIter=500, tol=1e-12).fit(t)
    elif loss == "logistic":
        m = LogisticRegression(regParam=1 / C, fitIntercept=False, standardization=False, maxIter=500, tol=1e-12).fit(t)
    else:
        m = LinearRegression(regParam=1 / (2 * C), fitIntercept=False, standardization=False, maxIter=500, tol=1e-12, solver="l-bfgs").fit(t)
    return m.coefficients.toArray().tolist()
