"""Measures on private data. Nothing here enters a release; frames that come from private rows carry ``non_private = true``."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import rng
from ..functions import vectors as v
from ..functions.losses import Hinge, Loss
from . import blocks, solvers
from .passes import matrix


def tagged(df: DataFrame) -> DataFrame:
    return df.withColumn("non_private", F.lit(True))


def risk(df: DataFrame, w, C: float, loss: Loss = Hinge) -> DataFrame:
    """(empirical, regularised) in one aggregation."""
    f = v.dot_literal(F.col("x"), w)
    norm = 0.5 * sum(float(a) ** 2 for a in w)
    e = F.avg(loss.value(F.col("y"), f))
    return tagged(df.agg(e.alias("empirical"), (F.lit(norm) + C * e).alias("regularised")))


def gradient_long(df: DataFrame, w, loss: Loss = Hinge) -> DataFrame:
    """(pos, g): mean slope times feature."""
    f = v.dot_literal(F.col("x"), w)
    rows = df.select(loss.slope(F.col("y"), f).alias("s"), F.posexplode("x").alias("pos", "v"))
    return rows.groupBy("pos").agg(F.avg(F.col("s") * F.col("v")).alias("g"))


def pair_privacy_loss(w1: np.ndarray, w2: np.ndarray, lam: float) -> float:
    """Largest log density ratio between the responses on two databases under Laplace noise."""
    return float(np.abs(w1 - w2).sum() / lam)


def audit_privacy(spark: SparkSession, w1: float, w2: float, lam: float, trials: int, bins: int, seed: int) -> DataFrame:
    """(worst): largest log ratio of two response histograms, bins of fewer than 50 hits left out; one coordinate."""
    low, high = min(w1, w2) - 4 * lam, max(w1, w2) + 4 * lam

    def hist(w: float, stream: str, name: str) -> DataFrame:
        t = spark.range(trials).select((F.lit(w) + rng.laplace(rng.uniform(seed, stream, F.col("id")), lam)).alias("t"))
        return t.groupBy(F.width_bucket("t", F.lit(low), F.lit(high), F.lit(bins)).alias("bin")).agg(F.count("*").alias(name))

    both = hist(w1, "a", "p").join(hist(w2, "b", "q"), "bin", "full").fillna(0)
    return both.where("p >= 50 AND q >= 50").agg(F.max(F.abs(F.log(F.col("p") / F.col("q")))).alias("worst"))


def usefulness(spark: SparkSession, probes: DataFrame, features: int, lam: float, eps: float, trials: int, seed: int) -> DataFrame:
    """(useful): share of noise draws whose classifier stays within eps on all probes (x)."""
    noise = spark.range(trials * features).select(F.floor(F.col("id") / features).alias("trial"), (F.col("id") % features).alias("pos"), rng.laplace(rng.uniform(seed, "use", F.col("id")), lam).alias("mu"))
    held = np.zeros((trials, features))
    for r in noise.collect():  # trials x features numbers
        held[r.trial, r.pos] = r.mu

    def run(batches):
        far = np.zeros(trials)
        for b in batches:
            if b.num_rows:
                far = np.maximum(far, np.abs(matrix(b.column(0)) @ held.T).max(axis=0))
        yield pa.record_batch([pa.array(np.arange(trials)), pa.array(far)], ["trial", "far"])

    far = probes.select("x").mapInArrow(run, "trial long, far double").groupBy("trial").agg(F.max("far").alias("far"))
    return far.agg(F.avg(F.when(F.col("far") <= eps, 1.0).otherwise(0.0)).alias("useful"))


def sup_distance(df: DataFrame, w1, w2, phi: float = 1.0) -> DataFrame:
    """(data_max, l1_bound, box_max): largest score gap on the data, its bound by features, its exact value on the box [0, phi]^F."""
    gap = np.asarray(w1, float) - np.asarray(w2, float)
    box = max(gap[gap > 0].sum(), -gap[gap < 0].sum()) * phi
    return tagged(df.agg(F.max(F.abs(v.dot_literal(F.col("x"), gap))).alias("data_max")).withColumn("l1_bound", F.lit(float(np.abs(gap).sum() * phi))).withColumn("box_max", F.lit(float(box))))


def trig_sup_bound(gap: np.ndarray) -> float:
    """Bound of a score gap over all points for random trigonometric features."""
    m = len(gap) // 2
    return float(np.sqrt(gap[0::2] ** 2 + gap[1::2] ** 2).sum() / math.sqrt(m))


def risk_gap(df: DataFrame, w1, w2, loss: Loss = Hinge) -> DataFrame:
    """(gap, bound): difference of empirical risks, and Lipschitz constant times sup distance on the data."""
    f1, f2 = v.dot_literal(F.col("x"), w1), v.dot_literal(F.col("x"), w2)
    return tagged(df.agg(F.abs(F.avg(loss.value(F.col("y"), f1)) - F.avg(loss.value(F.col("y"), f2))).alias("gap"), (F.max(F.abs(f1 - f2)) * loss.lipschitz()).alias("bound")))


def replace_row(df: DataFrame, row_id: int, x: list[float], y: float) -> DataFrame:
    """The neighbour that differs in one row: a projection, n stays."""
    here = F.col("row_id") == row_id
    return df.withColumn("x", F.when(here, F.array(*map(F.lit, map(float, x)))).otherwise(F.col("x"))).withColumn("y", F.when(here, F.lit(float(y))).otherwise(F.col("y")))


def measured_sensitivity_saturated(df: DataFrame, replaced: DataFrame, C: float) -> DataFrame:
    """(l1, l2): largest weight change over neighbours in the saturated regime, where the minimiser is a plain sum.

    replaced: (row_id, x2, y2); each row of it is one neighbour, so the change is (C/n)(y2 x2 − y x).
    """
    n = solvers.rows_and_weight(df)
    both = df.join(replaced, "row_id")
    change = F.zip_with("x2", "x", lambda a, b: F.lit(C / n) * (F.col("y2") * a - F.col("y") * b))
    both = both.select(change.alias("change"))
    return tagged(both.agg(F.max(v.norm1(F.col("change"))).alias("l1"), F.max(v.norm2(F.col("change"))).alias("l2")))


def uniform_stability(df: DataFrame, w1, w2, loss: Loss = Hinge) -> DataFrame:
    f1, f2 = v.dot_literal(F.col("x"), w1), v.dot_literal(F.col("x"), w2)
    return tagged(df.agg(F.max(F.abs(loss.value(F.col("y"), f1) - loss.value(F.col("y"), f2))).alias("change")))


def dual_l1(alpha: DataFrame) -> DataFrame:
    return tagged(alpha.agg(F.sum(F.abs("alpha")).alias("l1")))


def kernel_error(pairs: DataFrame) -> DataFrame:
    """(max_error, mean_error) of pairs with columns k and khat."""
    e = F.abs(F.col("k") - F.col("khat"))
    return pairs.agg(F.max(e).alias("max_error"), F.avg(e).alias("mean_error"))


def kernel_error_blocks(df: DataFrame, kernel, rhos: list[np.ndarray], rows: int = 512) -> DataFrame:
    """(m, pairs, max_error, mean_error) over all pairs i < j of df (row_id, x): blocks of rows meet, and every meeting gives one row of aggregates."""
    blocks = max(1, -(-df.count() // rows))
    b = df.select(F.pmod(F.xxhash64("row_id"), F.lit(blocks)).alias("block"), "row_id", "x").groupBy("block").agg(F.collect_list("row_id").alias("ids"), F.collect_list("x").alias("xs"))
    met = b.toDF("p", "i", "x").join(b.toDF("q", "j", "z"), F.col("p") <= F.col("q"))

    def run(batches):
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                x, z, i, j = np.array(r["x"]), np.array(r["z"]), np.array(r["i"]), np.array(r["j"])
                # equal ids lie in one block
                use = i[:, None] < j[None, :] if r["p"] == r["q"] else np.ones((len(i), len(j)), bool)
                k = solvers.gram(x, z, kernel)
                for rho in rhos:
                    e = np.abs(k - solvers.gram(x, z, None, rho))[use]
                    if len(e):
                        out.append((len(rho), len(e), float(e.max()), float(e.sum())))
            cols = list(zip(*out, strict=True)) if out else [[]] * 4
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.float64(), pa.float64()), strict=True)], ["m", "n", "most", "total"])

    parts = met.repartition(max(1, min(2000, blocks * (blocks + 1) // 2)), "p", "q").mapInArrow(run, "m long, n long, most double, total double")
    return parts.groupBy("m").agg(F.sum("n").alias("pairs"), F.max("most").alias("max_error"), (F.sum("total") / F.sum("n")).alias("mean_error"))


def noise_norm_stats(spark: SparkSession, features: int, lam: float, trials: int, seed: int) -> DataFrame:
    """(mean, var): of the L1 norm of noise vectors; the law has mean F·lam and variance F·lam²."""
    t = spark.range(trials * features).select(F.floor(F.col("id") / features).alias("trial"), F.abs(rng.laplace(rng.uniform(seed, "norm", F.col("id")), lam)).alias("a"))
    return t.groupBy("trial").agg(F.sum("a").alias("s")).agg(F.avg("s").alias("mean"), F.var_pop("s").alias("var"))


def confusion(df: DataFrame, score: Column) -> DataFrame:
    """(n, tp, fp, tn, fn, accuracy) of classes sign(score)."""
    pos = score >= 0
    one = lambda c: F.sum(F.when(c, 1).otherwise(0))
    y = F.col("y") > 0
    return df.agg(F.count("*").alias("n"), one(pos & y).alias("tp"), one(pos & ~y).alias("fp"), one(~pos & ~y).alias("tn"), one(~pos & y).alias("fn"), F.avg(F.when(pos == y, 1.0).otherwise(0.0)).alias("accuracy"))


def auc(df: DataFrame, score: Column, ranges: int = 64) -> DataFrame:
    """(auc): by counts under each distinct score, ties half; prefix sums in ranges, no single-task sort."""
    from ..functions.prefix import prefix_sums

    c = df.select(score.alias("s"), (F.col("y") > 0).cast("double").alias("p")).groupBy("s").agg(F.sum("p").alias("pos"), F.sum(1 - F.col("p")).alias("neg"))
    t = prefix_sums(c, "s", ["neg"], ranges)
    return t.agg((F.sum(F.col("pos") * (F.col("neg_to") - F.col("neg") / 2)) / (F.sum("pos") * F.sum("neg"))).alias("auc"))


def perturbation_chain(x: np.ndarray, y: np.ndarray, exact: solvers.DualModel, approx: solvers.DualModel, C: float, L: float = 1.0) -> dict:
    """The steps from kernel error to classifier distance on a sample: measured values and their bounds."""
    k, kh = exact.gram(x), approx.gram(x)
    err, big = float(np.abs(k - kh).max()), C * L
    f, fh = k @ (exact.alpha * y), kh @ (approx.alpha * y)
    moved = kh @ (exact.alpha * y)  # the exact machine's coefficients in the random space
    back = k @ (approx.alpha * y)
    # both functions have the same random space: their distance there
    diff = (exact.alpha - approx.alpha) * y
    hilbert = math.sqrt(max(0.0, diff @ kh @ diff))

    def reg(g, a, gram):
        return 0.5 * (a * y) @ gram @ (a * y) + C * float(np.mean(np.maximum(0, 1 - y * g)))

    return {
        "kernel_error": err,
        "shift": float(np.abs(moved - f).max()), "shift_bound": err * big,
        "transfer": reg(moved, exact.alpha, kh) - reg(fh, approx.alpha, kh), "transfer_bound": 2 * (C * L + big / 2) * big * err,
        "back": reg(back, approx.alpha, k) - reg(f, exact.alpha, k),
        "hilbert": hilbert, "hilbert_bound": 2 * math.sqrt((C * L + big / 2) * big * err),
        "total": float(np.abs(f - fh).max()), "total_bound": err * big + 2 * math.sqrt((C * L + big / 2) * big * err),
    }


def perturbation_chain_table(df: DataFrame, exact: DataFrame, approx: DataFrame, kernel, rho: np.ndarray, C: float, L: float = 1.0) -> dict:
    """``perturbation_chain`` for any number of rows: df (row_id, x, y) and both machines' (row_id, alpha); all pairs meet in blocks and the driver gets one row."""
    rows = df.join(exact.toDF("row_id", "a"), "row_id").join(approx.toDF("row_id", "b"), "row_id").withColumns({"a": F.col("a") * F.col("y"), "b": F.col("b") * F.col("y")})
    terms = {"f": (0, "a"), "moved": (1, "a"), "fh": (1, "b"), "back": (0, "b")}
    made = blocks.expansions(rows, [lambda x, z: solvers.gram(x, z, kernel), lambda x, z: solvers.gram(x, z, None, rho)], terms, "err")
    t, c = rows.select("row_id", "y", "a", "b").join(made, "row_id"), F.col

    def reg(g, coefficient):
        return 0.5 * F.sum(c(coefficient) * c(g)) + C * F.avg(F.greatest(F.lit(0.0), 1 - c("y") * c(g)))

    far = {"shift": F.max(F.abs(c("moved") - c("f"))), "total": F.max(F.abs(c("f") - c("fh"))), "kernel_error": F.max("err"), "diff": F.sum((c("a") - c("b")) * (c("moved") - c("fh")))}
    s = t.agg(*[v.alias(k) for k, v in far.items()], (reg("moved", "a") - reg("fh", "b")).alias("transfer"), (reg("back", "b") - reg("f", "a")).alias("back")).first()
    err, big = s.kernel_error, C * L
    hilbert = 2 * math.sqrt((C * L + big / 2) * big * err)
    return {
        "kernel_error": err, "shift": s.shift, "shift_bound": err * big, "transfer": s.transfer, "transfer_bound": 2 * (C * L + big / 2) * big * err, "back": s.back,
        "hilbert": math.sqrt(max(0.0, s["diff"])), "hilbert_bound": hilbert, "total": s.total, "total_bound": err * big + hilbert,
    }
