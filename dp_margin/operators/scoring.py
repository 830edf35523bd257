"""Scores of released and reference models."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as v
from ..functions.kernels import trig_batch
from . import blocks
from .mechanisms import Release
from .passes import matrix
from .solvers import DUAL_ROWS

LITERAL_FEATURES = 128


def score(df: DataFrame, release: Release) -> DataFrame:
    """df (row_id, x, ...) with ``score``: a flat sum for short weights, Arrow batches for random features and long ones."""
    if release.rho is None and len(release.w) <= LITERAL_FEATURES:
        return df.withColumn("score", v.dot_literal(F.col("x"), release.w))
    w, rho, at, scale = release.w, release.rho, df.columns.index("x"), release.kappa
    schema = df.withColumn("score", F.lit(0.0)).schema
    schema["score"].nullable = True

    def run(batches):
        for b in batches:
            x = matrix(b.column(at))
            f = (trig_batch(x, rho, scale) if rho is not None else x) @ w if b.num_rows else np.zeros(0)
            yield pa.record_batch([*b.columns, pa.array(f)], schema.names)

    return df.mapInArrow(run, schema)


def classify(df: DataFrame, release: Release) -> DataFrame:
    return score(df, release).withColumn("side", F.when(F.col("score") >= 0, 1.0).otherwise(-1.0))


def score_dual(test: DataFrame, train: DataFrame, alpha: DataFrame, kernel=None) -> DataFrame:
    """(test_id, score): the signed kernel expansion over rows with alpha > 0; their number is counted, and more than the dual solves for are refused."""
    held = alpha.where("alpha > 0").count()
    if held > DUAL_ROWS:
        raise ValueError(f"{held} support vectors; at most {DUAL_ROWS} are broadcast")
    sv = train.join(alpha.where("alpha > 0"), "row_id").select(F.col("x").alias("sx"), (F.col("alpha") * F.col("y")).alias("ay"))
    k = (lambda a, b: v.dot(a, b)) if kernel is None else kernel.column
    pairs = test.select(F.col("row_id").alias("test_id"), "x").crossJoin(F.broadcast(sv))
    return pairs.groupBy("test_id").agg(F.sum(F.col("ay") * k(F.col("x"), F.col("sx"))).alias("score"))


def score_dual_blocks(test: DataFrame, train: DataFrame, alpha: DataFrame, kernel=None) -> DataFrame:
    """(test_id, score): the same for any number of rows with alpha > 0, by blocks of test rows that meet blocks of support vectors."""
    sv = train.join(alpha.where("alpha > 0"), "row_id").select("row_id", "x", (F.col("alpha") * F.col("y")).alias("c"))
    return blocks.crossed(test, sv, lambda x, z: blocks.gram(x, z, kernel)).select(F.col("row_id").alias("test_id"), F.col("value").alias("score"))
