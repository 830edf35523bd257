"""The two release mechanisms: fit with a certificate, noise on the weights, one released record.

A record holds the noisy weights and public facts only: no noise-free weights, duals, support vectors, noise seeds or training measures.
"""

from __future__ import annotations

import math
import uuid
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import calibrate as cal
from ..functions.kernels import Kernel, frequency_matrix
from ..functions.losses import Hinge, Loss
from ..functions.rng import SecureRng
from . import solvers

RELEASE = T.StructType([
    T.StructField("release_id", T.StringType()), T.StructField("mechanism", T.StringType()), T.StructField("kernel", T.StringType()), T.StructField("freq_seed", T.LongType()),
    T.StructField("freq", T.ArrayType(T.ArrayType(T.DoubleType()))), T.StructField("w", T.ArrayType(T.DoubleType())), T.StructField("loss", T.StringType()), T.StructField("C", T.DoubleType()),
    T.StructField("L", T.DoubleType()), T.StructField("kappa", T.DoubleType()), T.StructField("n", T.LongType()), T.StructField("beta", T.DoubleType()), T.StructField("lam", T.DoubleType()), T.StructField("gap_tolerance", T.DoubleType()),
])


@dataclass(frozen=True)
class Release:
    """A mechanism's response."""

    w: np.ndarray
    lam: float
    beta: float
    n: int
    C: float
    L: float
    kappa: float
    loss: str
    mechanism: str
    kernel: str | None = None
    rho: np.ndarray | None = None
    freq_seed: int | None = None
    d: int | None = None
    gap_tolerance: float = 0.0
    release_id: str = field(default_factory=lambda: uuid.uuid4().hex)

    def row(self, encode: str = "freq") -> tuple:
        """``encode``: the frequencies themselves, or only their public seed, from which anyone can draw them again."""
        freq = self.rho.tolist() if self.rho is not None and encode == "freq" else None
        return (self.release_id, self.mechanism, self.kernel, self.freq_seed, freq, self.w.tolist(), self.loss, float(self.C), float(self.L), float(self.kappa), int(self.n), float(self.beta), float(self.lam), float(self.gap_tolerance))

    def frame(self, spark: SparkSession, encode: str = "freq") -> DataFrame:
        return spark.createDataFrame([self.row(encode)], RELEASE)


def _noise_scale(beta, lam, least, of_lam):
    if (beta is None) == (lam is None):
        raise ValueError("give either beta or lam")
    return (least(beta), beta) if lam is None else (lam, of_lam(lam))


def release_finite(df: DataFrame, features: int, kappa: float, C: float, loss: Loss = Hinge, beta: float | None = None, lam: float | None = None, rng=None, tol: float = 1e-9, fit: solvers.Fit | None = None) -> Release:
    """Explicit feature maps: the exact minimiser and Laplace noise of the least scale for beta (or of scale lam); ``fit`` is one that ``solvers.fit`` made of the same arguments."""
    n, L = int(solvers.rows_and_weight(df)), loss.lipschitz(C, kappa)
    if n < 2:
        raise ValueError("a database has at least two rows")
    how = solvers.choose(loss, C, kappa, features)
    slack = {"cutting_plane": tol, "newton": 1e-18}.get(how, 0.0)  # public, whatever gap the data gave
    lam_, beta_ = _noise_scale(beta, lam, lambda b: cal.min_noise_finite(b, n, C, kappa, features, L, slack), lambda x: cal.privacy_of(x, n, C, kappa, features, L) + 2 * math.sqrt(2 * slack) * math.sqrt(features) / x)
    w = (fit or solvers.fit(df, C, features, kappa, loss, tol)).w
    noise = (rng or SecureRng()).laplace(features, lam_)
    return Release(w + noise, lam_, beta_, n, C, L, kappa, loss.name, "finite", gap_tolerance=slack)


def release_random_features(df: DataFrame, kernel: Kernel, d: int, m: int, C: float, loss: Loss = Hinge, beta: float | None = None, lam: float | None = None, freq_seed: int = 0, rng=None, tol: float = 1e-9) -> Release:
    """Translation-invariant kernels: data-independent frequencies, a fit in the random space, noise on its 2m weights, both released."""
    n, L, scale = int(solvers.rows_and_weight(df)), loss.lipschitz(C, kernel.scale(d)), kernel.scale(d)
    if n < 2:
        raise ValueError("a database has at least two rows")
    rho = frequency_matrix(df.sparkSession, kernel, d, m, freq_seed)
    how = solvers.choose(loss, C, scale, 2 * m)
    slack = {"cutting_plane": tol, "newton": 1e-18}.get(how, 0.0)
    extra = 2 * math.sqrt(2 * slack) * math.sqrt(2 * m)
    lam_, beta_ = _noise_scale(beta, lam, lambda b: scale * cal.min_noise_random(b, n, C, m, L) + extra / b, lambda x: scale * cal.min_noise_random(x, n, C, m, L) + extra / x)
    w = solvers.fit(df, C, 2 * m, scale, loss, tol, rho, scale).w
    noise = (rng or SecureRng()).laplace(2 * m, lam_)
    return Release(w + noise, lam_, beta_, n, C, L, scale, loss.name, "random_features", kernel.name, rho, freq_seed, d, slack)


def release_one_vs_rest(df: DataFrame, classes: list, features: int, kappa: float, C: float, beta: float, loss: Loss = Hinge, rng=None, tol: float = 1e-9) -> dict[object, Release]:
    """One release a class of df (x, label) against the rest; the classes share beta, as each release sees all rows.

    Where the minimiser is a plain sum, all classes and the number of rows come from one pass; elsewhere each class has its own fit.
    """
    rng, share, L = rng or SecureRng(), beta / len(classes), loss.lipschitz(C, kappa)
    if solvers.choose(loss, C, kappa, features) != "saturated":
        sides = {k: df.withColumn("y", F.when(F.col("label") == F.lit(k), 1.0).otherwise(-1.0)) for k in classes}
        return {k: release_finite(f, features, kappa, C, loss, beta=share, rng=rng, tol=tol) for k, f in sides.items()}
    w, n = solvers.saturated_classes(df, classes, C, features)
    if n < 2:
        raise ValueError("a database has at least two rows")
    lam = cal.min_noise_finite(share, n, C, kappa, features, L)
    noise = rng.laplace(w.size, lam).reshape(w.shape)
    return {k: Release(w[i] + noise[i], lam, share, n, C, L, kappa, loss.name, "finite") for i, k in enumerate(classes)}
