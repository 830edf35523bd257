"""Databases built to show what no accurate mechanism can hide, and the closed forms of their minimisers."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.optimal import packing_size
from . import solvers


def hard_pair_linear(spark: SparkSession, n: int, C: float, eps: float) -> DataFrame:
    """(db, row_id, x, y): two neighbours on the line whose classifiers differ by 2 eps at 1; the last row's label tells them apart."""
    big, mid = 2 * n * eps / C, n * eps / C
    half = n // 2
    rows = spark.range(n).crossJoin(spark.createDataFrame([(1,), (2,)], "db int"))
    last = F.col("id") == n - 1
    x = F.when(last, mid).when(F.col("id") < half, -big).otherwise(big)
    y = F.when(last, F.when(F.col("db") == 1, -1.0).otherwise(1.0)).when(F.col("id") < half, -1.0).otherwise(1.0)
    return rows.select("db", F.col("id").alias("row_id"), x.alias("x"), y.alias("y"))


def hard_pair_of(df: DataFrame, C: float, share: float = 0.4) -> DataFrame:
    """The same neighbours over a table's own rows (row_id, y): all keep their labels but the row of the largest id, which tells the two apart; eps is a share of sqrt(C) / 2n."""
    mid = share / (2 * math.sqrt(C))  # n eps / C
    last = F.col("row_id") == F.col("last")
    rows = df.crossJoin(F.broadcast(df.agg(F.max("row_id").alias("last")))).crossJoin(F.broadcast(df.sparkSession.createDataFrame([(1,), (2,)], "db int")))
    y = F.when(last, F.when(F.col("db") == 1, -1.0).otherwise(1.0)).otherwise(F.col("y"))
    return rows.select("db", "row_id", F.when(last, mid).otherwise(2 * mid * F.col("y")).alias("x"), y.alias("y"))


def hard_pair_weights(n, C, eps):
    """Minimisers of both databases, on numbers or columns."""
    big, mid = 2 * n * eps / C, n * eps / C
    return C * (big * (n - 1) - mid) / n, C * (big * (n - 1) + mid) / n


def hard_packing_rbf(spark: SparkSession, n: int, sigma: float) -> DataFrame:
    """(db, row_id, x, y): N databases that differ in their last row, a point on the circle; all the others lie at one place."""
    return _packed(spark.range(n).select(F.col("id").alias("row_id"), F.lit(n - 1).alias("last")), sigma)


def hard_packing_of(df: DataFrame, sigma: float) -> DataFrame:
    """The same over a table's own rows (row_id); the last row is that of the largest id."""
    rows = df.select("row_id")
    return _packed(rows.crossJoin(F.broadcast(rows.agg(F.max("row_id").alias("last")))), sigma)


def _packed(rows: DataFrame, sigma: float) -> DataFrame:
    size = packing_size(sigma)
    rows = rows.crossJoin(F.broadcast(rows.sparkSession.range(size).withColumnRenamed("id", "db")))
    turn = 2 * math.pi * F.col("db") / size
    last = F.col("row_id") == F.col("last")
    x = F.when(last, F.array(F.cos(turn), F.sin(turn))).otherwise(F.array(F.lit(0.0), F.lit(0.0)))
    return rows.select(F.col("db").cast("int").alias("db"), "row_id", x.alias("x"), F.when(last, 1.0).otherwise(-1.0).alias("y"))


def packing_dual(C, n, gamma):
    """(alpha_1, alpha_n, case) of the two-variable dual: n - 1 equal rows share alpha_1, the last row has alpha_n; columns in, columns out.

    Each of the four ways to bind the box gives a candidate; the objective picks the feasible one.
    """
    top = C / n
    m = n - 1

    def clipped(v):
        return F.greatest(F.lit(0.0), F.least(top, v))

    inner1 = (1 + gamma) / (m * (1 - gamma * gamma))
    inner_n = (1 + gamma) / (1 - gamma * gamma)
    case1 = (inner1 <= top) & (inner_n <= top)
    at_n = (1 + gamma * top) / m  # last row bound
    at_1 = 1 + gamma * m * top  # the others bound
    case4 = (at_n <= top) & ~case1
    case2 = (at_1 <= top) & ~case1 & ~case4
    a1 = F.when(case1, inner1).when(case4, at_n).otherwise(top)
    an = F.when(case1, inner_n).when(case4, top).when(case2, at_1).otherwise(top)
    return clipped(a1), clipped(an), F.when(case1, "interior").when(case4, "last bound").when(case2, "first bound").otherwise("both bound")


def packing_separation(C: float, n: int, sigma: float) -> float:
    """Least distance of two of the packing's classifiers."""
    return C / n * (1 - math.exp(-2 / sigma**2 * math.sin(math.pi / packing_size(sigma)) ** 2))


def fixed_point_curve(pair: DataFrame, C: float, n: int) -> DataFrame:
    """(db, w, level): the step function against w at its breakpoints, for both databases."""
    out = None
    for db in (1, 2):
        own = pair.where(F.col("db") == db).select("row_id", F.array("x").alias("x"), "y")
        st = solvers.hinge_1d_steps(own).select(F.lit(db).alias("db"), F.col("b").alias("w"), (F.lit(C / n) * F.col("below")).alias("below"), (F.lit(C / n) * F.col("above")).alias("above"))
        out = st if out is None else out.union(st)
    return out
