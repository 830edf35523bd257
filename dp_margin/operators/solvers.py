"""Minimisers of ½|w|² + (C/n) Σ loss: exact where there is a closed form, else iterative with a certificate.

No solver returns without a certified gap: noise is calibrated for the true minimiser, and a gap that is left enters the sensitivity.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as v
from ..functions.kernels import Kernel, trig_batch
from ..functions.losses import Hinge, Loss, Square
from ..functions.prefix import RANGES, prefix_sums
from ..sources.scratch import saved
from . import passes
from .blocks import expansions, gram

#: Rows up to which the dual with its full kernel matrix is solved on the driver; with more it stays a table.
DUAL_ROWS = 5000
#: Rows of which a round over that table changes the duals, on the driver.
WORKING = 2000


class NotConverged(RuntimeError):
    """Raised instead of returning weights without a certificate."""


@dataclass(frozen=True)
class Fit:
    w: np.ndarray
    gap: float
    passes: int
    objective: float


def rows_and_weight(df: DataFrame) -> float:
    return float((df.agg(F.sum("weight")) if "weight" in df.columns else df.agg(F.count("*"))).first()[0] or 0)


def _map(rho, scale):
    return (lambda x: x) if rho is None else (lambda x: trig_batch(x, rho, scale))


def saturated(df: DataFrame, C: float, features: int, rho: np.ndarray | None = None, scale: float = 1.0) -> Fit:
    """Hinge with C kappa² <= 1: no margin passes 1, so w = (C/n) Σ y x, one pass of plain sums."""
    n = rows_and_weight(df)
    if rho is None and features <= passes.SQL_FEATURES:
        weight = F.col("weight") if "weight" in df.columns else F.lit(1.0)
        s = passes.sql_sums(df, {str(i): weight * F.col("y") * F.get("x", F.lit(i)) for i in range(features)})
        w = np.array([s[str(i)] for i in range(features)])
    else:
        phi = _map(rho, scale)
        w = passes.sum_pass(df, features, lambda x, y, k: (k * y) @ phi(x))
    w = w * (C / n)
    return Fit(w, 0.0, 1, 0.5 * w @ w + C - w @ w)


def saturated_classes(df: DataFrame, classes: list, C: float, features: int) -> tuple[np.ndarray, int]:
    """(w, n): the saturated minimisers of every class against the rest, a row a class, and the number of rows, in one pass over df (x, label)."""
    at = F.coalesce(F.array_position(F.array(*map(F.lit, classes)), F.col("label")), F.lit(0)) - 1

    def batch(x, y, k):
        side = np.where(y[:, None] == np.arange(len(classes)), k[:, None], -k[:, None])
        return np.append((side.T @ x).ravel(), k.sum())

    s = passes.sum_pass(df.withColumn("y", at.cast("double")), len(classes) * features + 1, batch)
    return s[:-1].reshape(len(classes), features) * (C / s[-1]) if s[-1] else s[:-1].reshape(len(classes), features), int(s[-1])


def ridge(df: DataFrame, C: float, features: int, rho=None, scale: float = 1.0) -> Fit:
    """Square loss by the normal equations: one pass for the Gram matrix of features."""
    n, phi = rows_and_weight(df), _map(rho, scale)

    def batch(x, y, k):
        p = phi(x)
        return np.concatenate(((p.T * k) @ p, ((k * y) @ p)[None], np.full((1, features), k @ (y * y)) / features)).ravel()

    s = passes.sum_pass(df, features * (features + 2), batch).reshape(features + 2, features)
    g, b = s[:features], s[features]
    w = np.linalg.solve(np.eye(features) + (2 * C / n) * g, (2 * C / n) * b)
    return Fit(w, 0.0, 1, 0.5 * w @ w + C / n * (w @ g @ w - 2 * w @ b + s[-1].sum()))


def _risk_and_slope(df: DataFrame, w: np.ndarray, loss: Loss, features: int, rho, scale) -> tuple[float, np.ndarray]:
    phi = _map(rho, scale)

    def batch(x, y, k):
        p = phi(x)
        f = p @ w
        return np.concatenate(([k @ loss.value_np(y, f)], (k * loss.slope_np(y, f)) @ p))

    s = passes.sum_pass(df, features + 1, batch)
    return s[0], s[1:]


def _simplex_dual(a: np.ndarray, b: np.ndarray, C: float) -> np.ndarray:
    """max of b·t − ½|aᵀt|² over t >= 0, Σt = C: pairwise steps until the best pair gains nothing."""
    g = a @ a.T
    t = np.zeros(len(b))
    t[-1] = C
    for _ in range(200_000):
        d = b - g @ t
        up = int(np.argmax(d))
        down = int(np.argmin(np.where(t > 0, d, np.inf)))
        if d[up] - d[down] <= 1e-15 * max(1.0, abs(d[up])):
            break
        curve = g[up, up] + g[down, down] - 2 * g[up, down]
        step = min(t[down], (d[up] - d[down]) / curve if curve > 0 else np.inf)
        t[up] += step
        t[down] -= step
        if step == 0:
            break
    return t


def cutting_plane(df: DataFrame, C: float, features: int, loss: Loss = Hinge, tol: float = 1e-9, most: int = 300, rho=None, scale: float = 1.0) -> Fit:
    """Any convex loss: each pass adds one plane under the risk; the small dual on the driver gives a lower bound, and so the gap."""
    n = rows_and_weight(df)
    w, planes, offsets = np.zeros(features), [], []
    best, best_w = math.inf, w
    for step in range(1, most + 1):
        risk, slope = _risk_and_slope(df, w, loss, features, rho, scale)
        risk, slope = risk / n, slope / n
        value = 0.5 * w @ w + C * risk
        if value < best:
            best, best_w = value, w
        planes.append(slope)
        offsets.append(risk - slope @ w)
        a, b = np.array(planes), np.array(offsets)
        t = _simplex_dual(a, b, C)
        w = -(a.T @ t)
        lower = b @ t - 0.5 * w @ w
        if best - lower <= tol:
            return Fit(best_w, max(0.0, best - lower), step, best)
    raise NotConverged(f"gap {best - lower:.3g} after {most} passes")


def newton(df: DataFrame, C: float, features: int, loss: Loss, curvature, tol: float = 1e-18, most: int = 60, rho=None, scale: float = 1.0) -> Fit:
    """Smooth losses: value, gradient and curvature in one pass; half the squared gradient bounds the gap (1-strong convexity)."""
    n, phi, w = rows_and_weight(df), _map(rho, scale), np.zeros(features)

    def batch_at(w):
        def batch(x, y, k):
            p = phi(x)
            f = p @ w
            h = k * curvature(y, f)
            return np.concatenate(([k @ loss.value_np(y, f)], (k * loss.slope_np(y, f)) @ p, ((p.T * h) @ p).ravel()))

        return batch

    for step in range(1, most + 1):
        s = passes.sum_pass(df, 1 + features + features**2, batch_at(w))
        grad = w + C / n * s[1 : 1 + features]
        if 0.5 * grad @ grad <= tol:
            return Fit(w, float(0.5 * grad @ grad), step, 0.5 * w @ w + C / n * s[0])
        w = w - np.linalg.solve(np.eye(features) + C / n * s[1 + features :].reshape(features, features), grad)
    raise NotConverged(f"half squared gradient {0.5 * grad @ grad:.3g} after {most} passes")


def logistic_curvature(y, f):
    p = 1 / (1 + np.exp(-f))
    return p * (1 - p)


def subgradient_steps(df: DataFrame, C: float, features: int, loss: Loss, steps: int) -> list[float]:
    """Test mode: full-batch steps of size 1 / (t + 1) from zero in plain SQL aggregates."""
    n, w = rows_and_weight(df), [0.0] * features
    for t in range(steps):
        f = v.dot_literal(F.col("x"), w)
        s = passes.sql_sums(df, {str(i): loss.slope(F.col("y"), f) * F.get("x", F.lit(i)) for i in range(features)})
        eta = 1.0 / (t + 1)
        w = [a - eta * (a + C / n * s[str(i)]) for i, a in enumerate(w)]
    return w


def choose(loss: Loss, C: float, kappa: float, features: int) -> str:
    """Which solver a fit takes; decided by public facts alone."""
    if loss.name == "hinge" and C * kappa * kappa <= 1:
        return "saturated"
    if loss.name == "square" and features <= 4096:
        return "ridge"
    if loss.name == "logistic" and features <= 512:
        return "newton"
    return "cutting_plane"


def fit(df: DataFrame, C: float, features: int, kappa: float, loss: Loss = Hinge, tol: float = 1e-9, rho=None, scale: float = 1.0) -> Fit:
    how = choose(loss, C, kappa, features)
    if how == "saturated":
        return saturated(df, C, features, rho, scale)
    if how == "ridge":
        return ridge(df, C, features, rho, scale)
    if how == "newton":
        return newton(df, C, features, loss, logistic_curvature, rho=rho, scale=scale)
    return cutting_plane(df, C, features, loss, tol, rho=rho, scale=scale)


def certificate(df: DataFrame, w: np.ndarray, C: float, loss: Loss = Hinge, rho=None, scale: float = 1.0) -> float:
    """Half the squared subgradient norm: bounds the gap of any weights."""
    n = rows_and_weight(df)
    _, slope = _risk_and_slope(df, w, loss, len(w), rho, scale)
    g = w + C / n * slope
    return float(0.5 * g @ g)


# --- the dual: up to DUAL_ROWS rows on the driver, beyond them in a table ---------------------------------------------------------------------


@dataclass(frozen=True)
class DualModel:
    ids: np.ndarray
    x: np.ndarray
    y: np.ndarray
    alpha: np.ndarray
    gap: float
    objective: float
    kernel: Kernel | None
    rho: np.ndarray | None = None

    def gram(self, z: np.ndarray) -> np.ndarray:
        return gram(z, self.x, self.kernel, self.rho)

    def frame(self, spark) -> DataFrame:
        return spark.createDataFrame([(int(i), float(a)) for i, a in zip(self.ids, self.alpha, strict=True)], "row_id long, alpha double")


@dataclass(frozen=True)
class DualTable:
    """A dual of any number of rows: rows (row_id, x, y, top, alpha) stay in a table, top being the largest dual a row may have."""

    rows: DataFrame
    gap: float
    objective: float
    kernel: Kernel | None
    rho: np.ndarray | None = None

    def frame(self, spark) -> DataFrame:
        return self.rows.select("row_id", "alpha")


def reference(df: DataFrame, C: float, kernel: Kernel | None = None, rho=None, tol: float = 1e-9, sweeps: int = 20_000) -> DualModel | DualTable:
    """The non-private kernel machine with hinge loss: box-constrained dual by coordinate ascent, with its whole kernel matrix for up to DUAL_ROWS rows."""
    if df.limit(DUAL_ROWS + 1).count() > DUAL_ROWS:
        return reference_table(df, C, kernel, rho, tol)
    rows = df.collect()
    rows.sort(key=lambda r: r.row_id)
    x, y = np.array([r.x for r in rows]), np.array([r.y for r in rows])
    weight = np.array([getattr(r, "weight", 1.0) for r in rows]) if "weight" in df.columns else np.ones(len(rows))
    n = weight.sum()
    k = gram(x, x, kernel, rho)
    q = k * np.outer(y, y)
    top, alpha, f = C / n * weight, np.zeros(len(y)), np.zeros(len(y))
    diag = np.maximum(np.diag(q), 1e-12)
    for sweep in range(sweeps):
        _sweep(q, diag, top, alpha, f)
        quad = alpha @ f
        primal, dual = 0.5 * quad + top @ np.maximum(0, 1 - f), alpha.sum() - 0.5 * quad
        if primal - dual <= tol:
            return DualModel(np.array([r.row_id for r in rows]), x, y, alpha, float(max(0.0, primal - dual)), float(primal), kernel, rho)
        if sweep % 50 == 49:
            f = q @ alpha
    raise NotConverged(f"gap {primal - dual:.3g} after {sweeps} sweeps")


def _sweep(q: np.ndarray, diag: np.ndarray, top: np.ndarray, alpha: np.ndarray, f: np.ndarray) -> None:
    """Every dual once to its best value in the box; f follows."""
    for i in range(len(alpha)):
        new = min(top[i], max(0.0, alpha[i] + (1 - f[i]) / diag[i]))
        if new != alpha[i]:
            f += q[:, i] * (new - alpha[i])
            alpha[i] = new


def _margins(rows: DataFrame, kernel: Kernel | None, rho) -> DataFrame:
    """(row_id, f): y times the expansion, for rows with duals; one pass over sums for an explicit map, all pairs in blocks for a kernel."""
    signed = rows.withColumn("c", F.col("alpha") * F.col("y"))
    if kernel is not None and rho is None:
        made = expansions(signed, [lambda x, z: gram(x, z, kernel)], {"f": (0, "c")})
        return rows.select("row_id", "y").join(made, "row_id").select("row_id", (F.col("y") * F.col("f")).alias("f"))
    phi = _map(rho, 1.0)
    size = 2 * len(rho) if rho is not None else len((rows.select("x").first() or [[]])[0])
    w = passes.sum_pass(signed.select("x", F.col("c").alias("y")), size, lambda x, y, k: y @ phi(x))
    return _with_product(rows, lambda x: phi(x) @ w)


def _with_product(rows: DataFrame, product) -> DataFrame:
    """(row_id, f): y times product(x), an array of a number a row."""

    def run(batches):
        for b in batches:
            f = b.column(2).to_numpy(zero_copy_only=False) * product(passes.matrix(b.column(1))) if b.num_rows else np.zeros(0)
            yield pa.record_batch([b.column(0), pa.array(f, pa.float64())], ["row_id", "f"])

    return rows.select("row_id", "x", "y").mapInArrow(run, "row_id long, f double")


def reference_table(df: DataFrame, C: float, kernel: Kernel | None = None, rho=None, tol: float = 1e-9, working: int | None = None, most: int = 1000) -> DualTable:
    """The same dual for any number of rows: all duals start at their bound, where they stay while no margin passes 1.

    Else rounds follow. A round takes the rows that add most to the gap and those between their bounds to the driver, ascends over them
    while all others are held, and one pass brings their changes to all margins. The gap is a sum over all rows, each of whose terms is zero at the optimum;
    margins that were only carried on are computed anew before a gap is believed.
    """
    working = working or WORKING
    weight = F.col("weight") if "weight" in df.columns else F.lit(1.0)
    base = saved(df.select("row_id", "x", "y", (F.lit(C / rows_and_weight(df)) * weight).alias("top")))
    state = saved(base.withColumn("alpha", F.col("top")).transform(lambda t: t.select("row_id", "alpha").join(_margins(t, kernel, rho), "row_id")))
    term = F.col("alpha") * (F.col("f") - 1) + F.col("top") * F.greatest(F.lit(0.0), 1 - F.col("f"))
    fresh = True
    for _ in range(most):
        rows = base.join(state, "row_id").withColumn("term", term)
        s = rows.agg(F.sum("term").alias("gap"), F.sum(0.5 * F.col("alpha") * F.col("f") + F.col("top") * F.greatest(F.lit(0.0), 1 - F.col("f"))).alias("primal")).first()
        if s.gap <= tol and fresh:
            return DualTable(rows.select("row_id", "x", "y", "top", "alpha"), max(0.0, float(s.gap)), float(s.primal), kernel, rho)
        if s.gap <= tol:
            state, fresh = saved(state.select("row_id", "alpha").join(_margins(rows, kernel, rho), "row_id")), True
            continue
        free = rows.where((F.col("alpha") > 0) & (F.col("alpha") < F.col("top"))).orderBy(F.abs(F.col("f") - 1)).limit(working // 2)
        own = {r.row_id: r for r in [*rows.where("term > 0").orderBy(F.desc("term")).limit(working - working // 2).collect(), *free.collect()]}
        ids = np.array(sorted(own))
        x, y, top, alpha, f = (np.array([own[i][c] for i in ids]) for c in ("x", "y", "top", "alpha", "f"))
        q = gram(x, x, kernel, rho) * np.outer(y, y)
        before, diag = alpha.copy(), np.maximum(np.diag(q), 1e-12)
        left = first = sum(own[i].term for i in ids)
        for _ in range(1000):
            _sweep(q, diag, top, alpha, f)
            left = (alpha * (f - 1) + top * np.maximum(0, 1 - f)).sum()
            if left <= max(0.1 * tol, 1e-3 * first):
                break
        state, fresh = saved(_moved(base, state, ids, x, alpha, (alpha - before) * y, kernel, rho)), False
    raise NotConverged(f"gap {s.gap:.3g} after {most} rounds")


def _moved(base: DataFrame, state: DataFrame, ids, x, alpha, change, kernel, rho) -> DataFrame:
    """state (row_id, alpha, f) after the rows ids took the duals alpha and their signed changes reached every margin."""
    if kernel is None or rho is not None:
        phi = _map(rho, 1.0)
        w = change @ phi(x)
        more = _with_product(base, lambda z: phi(z) @ w)
    else:
        use = change != 0
        more = _with_product(base, lambda z: np.concatenate([gram(z[lo : lo + 1024], x[use], kernel) @ change[use] for lo in range(0, len(z), 1024)]))
    new = base.sparkSession.createDataFrame([(int(i), float(a)) for i, a in zip(ids, alpha, strict=True)], "row_id long, new double")
    return state.join(more.withColumnRenamed("f", "more"), "row_id").join(F.broadcast(new), "row_id", "left").select("row_id", F.coalesce("new", "alpha").alias("alpha"), (F.col("f") + F.col("more")).alias("f"))


def primal_from_dual(alpha: DataFrame, df: DataFrame) -> DataFrame:
    """(pos, w) of Σ alpha y x."""
    return df.join(alpha, "row_id").select(F.col("alpha"), F.col("y"), F.posexplode("x").alias("pos", "v")).groupBy("pos").agg(F.sum(F.col("alpha") * F.col("y") * F.col("v")).alias("w"))


# --- one feature: exact -----------------------------------------------------------------------------------------------


def hinge_1d_steps(df: DataFrame, ranges: int = RANGES) -> DataFrame:
    """(b, below, above): the limits of the step function T(w) = Σ of y x over rows with y x w < 1, at each of its breakpoints b = 1 / (y x).

    Rows with y x > 0 count left of their breakpoint, rows with y x < 0 right of theirs.
    """
    s = df.select((F.col("y") * F.get("x", F.lit(0))).alias("s")).where("s <> 0").groupBy("s").agg(F.sum("s").alias("t"))
    b = s.select((1 / F.col("s")).alias("b"), F.when(F.col("s") > 0, F.col("t")).otherwise(0.0).alias("pos"), F.when(F.col("s") < 0, F.col("t")).otherwise(0.0).alias("neg"))
    sums = prefix_sums(b, "b", ["pos", "neg"], ranges)
    return sums.select("b", (F.col("pos_from") + F.col("neg_to") - F.col("neg")).alias("below"), (F.col("pos_from") - F.col("pos") + F.col("neg_to")).alias("above"))


def hinge_1d_path(df: DataFrame, Cs: list[float], ranges: int = RANGES) -> DataFrame:
    """(C, w) for every C: where the falling step function (C/n) T meets the diagonal, at a breakpoint or on the level between two; the steps are made once."""
    n = rows_and_weight(df)
    st, made = hinge_1d_steps(df, ranges), []
    for C in Cs:
        c = F.lit(C / n if n else 0.0)
        # the last breakpoint that lies under the function; behind it the level must fall to the diagonal before the next one
        last, first = F.max_by(F.struct("b", "above"), F.when(c * F.col("below") >= F.col("b"), F.col("b"))), F.min_by("below", "b")
        w = F.when(last.isNull(), c * first).otherwise(F.greatest(last["b"], c * last["above"]))
        made.append(F.struct(F.lit(float(C)).alias("C"), w.alias("w")))
    return st.agg(F.array(*made).alias("path")).select(F.inline("path")).where("w IS NOT NULL")


def fit_hinge_1d(df: DataFrame, C: float, ranges: int = RANGES) -> DataFrame:
    """(w): the minimiser for one C."""
    return hinge_1d_path(df, [C], ranges).select("w")


__all__ = ["DualModel", "DualTable", "Fit", "Hinge", "NotConverged", "Square", "certificate", "choose", "cutting_plane", "fit", "fit_hinge_1d", "hinge_1d_path", "hinge_1d_steps", "newton", "primal_from_dual", "reference", "reference_table", "ridge", "saturated", "saturated_classes", "subgradient_steps"]
