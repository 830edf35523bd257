"""Fits and releases on the workloads."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions import vectors as v
from ..functions.losses import Hinge, Logistic, Square
from ..functions.rng import SeededRng
from ..operators import baselines, mechanisms, scoring, solvers
from ..sources import examples
from ..sources.scratch import saved
from .base import SQL_EMBEDDINGS, SQL_LINEITEM, query, sql_laplace, sql_u
from .kernels import _F64, SEED


def frame(spark, values, digits=9):
    return spark.createDataFrame([(i, float(round(float(x), digits)) + 0.0) for i, x in enumerate(values)], "pos long, w double")


def _sums(table, C, features, digits=9, noise=""):
    """SQL of (C/n) Σ y x, one row a feature."""
    return f"SELECT (p - 1)::BIGINT AS pos, round({C} * sum(y * x[p]) / count(*){noise}, {digits}) + 0.0 AS w FROM {table}, range(1, {features + 1}) AS t(p) GROUP BY p"


_LI_NOISE = " + any_value(" + sql_laplace(sql_u(7, "lap", "(p - 1)"), "2 * {}::DOUBLE / (SELECT count(*) FROM lineitem)") + ")"


@query("finite_release_lineitem", _sums(SQL_LINEITEM, 0.25, 4, 9, _LI_NOISE.format("2")))
def finite_release_lineitem(spark, sf_dir):
    """Hinge, C = 1/4: saturated, so exact in one pass; scale 4 C kappa sqrt(F) / n at beta = 1."""
    r = mechanisms.release_finite(examples.lineitem(spark, sf_dir), 4, 2.0, 0.25, beta=1.0, rng=SeededRng(7))
    return frame(spark, r.w)


@query("finite_release_embeddings", _sums(SQL_EMBEDDINGS, 1.0, 64, 9, " + any_value(" + sql_laplace(sql_u(7, "lap", "(p - 1)"), "32::DOUBLE / (SELECT count(*) FROM embeddings)") + ")"))
def finite_release_embeddings(spark, sf_dir):
    return frame(spark, mechanisms.release_finite(examples.embeddings(spark, sf_dir), 64, 1.0, 1.0, beta=1.0, rng=SeededRng(7)).w)


@query("saturated_weights_embeddings", _sums(SQL_EMBEDDINGS, 1.0, 64))
def saturated_weights_embeddings(spark, sf_dir):
    return frame(spark, solvers.saturated(examples.embeddings(spark, sf_dir), 1.0, 64).w)


_RFF = f"(SELECT row_id, y, flatten(list([cos(p) / sqrt(8), sin(p) / sqrt(8)] ORDER BY f)) AS x FROM (SELECT row_id, y, f, list_dot_product(x, rho) AS p FROM {SQL_EMBEDDINGS}, {_F64.format(m=8)}) GROUP BY row_id, y)"


@query("saturated_weights_rff", _sums(_RFF, 1.0, 16))
def saturated_weights_rff(spark, sf_dir):
    rho = K.frequency_matrix(spark, K.rbf(), 64, 8, SEED)
    return frame(spark, solvers.saturated(examples.embeddings(spark, sf_dir), 1.0, 16, rho).w)


@query("rff_release_embeddings", _sums(_RFF, 1.0, 16, 9, " + any_value(" + sql_laplace(sql_u(7, "lap", "(p - 1)"), "16::DOUBLE / (SELECT count(*) FROM embeddings)") + ")"))
def rff_release_embeddings(spark, sf_dir):
    """Eight frequencies, C = 1: saturated on unit-norm features; scale 2^2.5 sqrt(8) / n at beta = 1."""
    return frame(spark, mechanisms.release_random_features(examples.embeddings(spark, sf_dir), K.rbf(), 64, 8, 1.0, beta=1.0, freq_seed=SEED, rng=SeededRng(7)).w)


def _steps(table, C, features, steps, slope):
    """SQL of unrolled subgradient steps."""
    zero = ", ".join(["0.0::DOUBLE"] * features)
    ctes, last = [f"s0 AS (SELECT [{zero}] AS w)"], "s0"
    for t in range(steps):
        eta = 1.0 / (t + 1)
        parts = ", ".join(f"any_value(w[{i}]) - {eta!r}::DOUBLE * (any_value(w[{i}]) + {C}::DOUBLE * sum({slope} * x[{i}]) / count(*))" for i in range(1, features + 1))
        ctes.append(f"s{t + 1} AS (SELECT [{parts}] AS w FROM (SELECT x, y, w, list_dot_product(x, w) AS f FROM {table} AS q, {last}))")
        last = f"s{t + 1}"
    return f"WITH {', '.join(ctes)} SELECT (p - 1)::BIGINT AS pos, round(w[p], 9) + 0.0 AS w FROM {last}, range(1, {features + 1}) AS t(p)"


_HINGE, _LOGI = "CASE WHEN y * f < 1 THEN -y ELSE 0 END", "(-y / (1 + exp(y * f)))"


@query("hinge_steps_lineitem", _steps(SQL_LINEITEM, 10, 4, 3, _HINGE))
def hinge_steps_lineitem(spark, sf_dir):
    return frame(spark, solvers.subgradient_steps(examples.lineitem(spark, sf_dir), 10.0, 4, Hinge, 3))


@query("hinge_steps_embeddings", _steps(SQL_EMBEDDINGS, 10, 64, 2, _HINGE))
def hinge_steps_embeddings(spark, sf_dir):
    return frame(spark, solvers.subgradient_steps(examples.embeddings(spark, sf_dir), 10.0, 64, Hinge, 2))


@query("logistic_steps_lineitem", _steps(SQL_LINEITEM, 10, 4, 3, _LOGI))
def logistic_steps_lineitem(spark, sf_dir):
    return frame(spark, solvers.subgradient_steps(examples.lineitem(spark, sf_dir), 10.0, 4, Logistic, 3))


@query("rff_nonprivate_steps", _steps(_RFF, 10, 16, 2, _HINGE))
def rff_nonprivate_steps(spark, sf_dir):
    """Non-private learning in the random space, in test mode."""
    rho = K.frequency_matrix(spark, K.rbf(), 64, 8, SEED)
    e = examples.embeddings(spark, sf_dir)
    return frame(spark, solvers.subgradient_steps(e.select("row_id", K.trig_map(F.col("x"), rho).alias("x"), "y"), 10.0, 16, Hinge, 2))


_RIDGE = f"""WITH s AS (SELECT 1 + 2 * 10.0::DOUBLE / count(*) * sum(x[1] * x[1]) AS a, 2 * 10.0::DOUBLE / count(*) * sum(x[1] * x[2]) AS b, 1 + 2 * 10.0::DOUBLE / count(*) * sum(x[2] * x[2]) AS d,
2 * 10.0::DOUBLE / count(*) * sum(y * x[1]) AS u, 2 * 10.0::DOUBLE / count(*) * sum(y * x[2]) AS v FROM {SQL_LINEITEM})
SELECT 0::BIGINT AS pos, round((d * u - b * v) / (a * d - b * b), 9) AS w FROM s UNION ALL SELECT 1::BIGINT, round((a * v - b * u) / (a * d - b * b), 9) FROM s"""


@query("ridge_weights_lineitem", _RIDGE)
def ridge_weights_lineitem(spark, sf_dir):
    two = examples.lineitem(spark, sf_dir).select("row_id", F.slice("x", 1, 2).alias("x"), "y")
    return frame(spark, solvers.ridge(two, 10.0, 2).w)


@query("hinge_certified_lineitem", "SELECT 10.0::DOUBLE AS C, true AS certified, true AS few_passes, true AS accurate")
def hinge_certified_lineitem(spark, sf_dir):
    """The cutting-plane minimiser with an intercept: gap within 1e-6, few passes, and the workload's accuracy."""
    df = examples.lineitem(spark, sf_dir, intercept=True)
    fit = solvers.cutting_plane(df, 10.0, 5, tol=1e-6)
    acc = scoring.score(df, mechanisms.Release(fit.w, 0, 0, 1, 10, 1, math.sqrt(5), "hinge", "none")).agg(F.avg(F.when((F.col("score") >= 0) == (F.col("y") > 0), 1.0).otherwise(0.0))).first()[0]
    return spark.createDataFrame([(10.0, bool(fit.gap <= 1e-6), fit.passes < 60, bool(acc > 0.9))], "C double, certified boolean, few_passes boolean, accurate boolean")


@query("rff_release_certified", "SELECT m, true AS certified, true AS scale_ok, true AS encoded FROM (VALUES (8::BIGINT), (32::BIGINT)) AS t(m)")
def rff_release_certified(spark, sf_dir):
    """C = 10: beyond saturation; the gap enters the noise scale, and the seed alone gives the frequencies back."""
    e, out = examples.embeddings(spark, sf_dir), []
    n = e.count()
    for m in (8, 32):
        r = mechanisms.release_random_features(e, K.rbf(), 64, m, 10.0, beta=1.0, freq_seed=SEED, rng=SeededRng(7), tol=1e-6)
        floor = 2**2.5 * 10 * math.sqrt(m) / n
        out.append((m, r.gap_tolerance == 1e-6, r.lam > floor, bool(np.allclose(r.rho, K.frequency_matrix(spark, K.rbf(), 64, m, SEED)))))
    return spark.createDataFrame(out, "m long, certified boolean, scale_ok boolean, encoded boolean")


@query("encode_roundtrip", "SELECT true AS same_scores, true AS seed_is_shorter")
def encode_roundtrip(spark, sf_dir):
    e = examples.embeddings(spark, sf_dir)
    r = mechanisms.release_random_features(e, K.rbf(), 64, 8, 1.0, beta=1.0, freq_seed=SEED, rng=SeededRng(7))
    row = r.frame(spark, "seed").first()
    again = mechanisms.Release(np.array(row.w), row.lam, row.beta, row.n, row.C, row.L, row.kappa, row.loss, row.mechanism, row.kernel, K.frequency_matrix(spark, K.rbf(), 64, len(row.w) // 2, row.freq_seed))
    both = scoring.score(e, r).select("row_id", F.col("score").alias("a")).join(scoring.score(e, again).select("row_id", F.col("score").alias("b")), "row_id")
    return both.agg((F.max(F.abs(F.col("a") - F.col("b"))) < 1e-12).alias("same_scores")).withColumn("seed_is_shorter", F.lit(row.freq is None))


def _logistic_sql(steps: int = 9) -> str:
    """SQL of the logistic minimiser over two features at C = 10: unrolled Newton steps with the 2 x 2 system solved in place."""
    ctes = ["s0 AS (SELECT 0.0::DOUBLE AS a, 0.0::DOUBLE AS b)"]
    for t in range(steps):
        ctes.append(f"""s{t + 1} AS (SELECT a - (h22 * ga - h12 * gb) / (h11 * h22 - h12 * h12) AS a, b - (h11 * gb - h12 * ga) / (h11 * h22 - h12 * h12) AS b FROM (SELECT any_value(a) AS a, any_value(b) AS b,
any_value(a) - 10.0::DOUBLE / count(*) * sum(y * x1 / (1 + exp(y * f))) AS ga, any_value(b) - 10.0::DOUBLE / count(*) * sum(y * x2 / (1 + exp(y * f))) AS gb,
1 + 10.0::DOUBLE / count(*) * sum(h * x1 * x1) AS h11, 10.0::DOUBLE / count(*) * sum(h * x1 * x2) AS h12, 1 + 10.0::DOUBLE / count(*) * sum(h * x2 * x2) AS h22
FROM (SELECT *, 1 / (1 + exp(-f)) * (1 - 1 / (1 + exp(-f))) AS h FROM (SELECT y, x[1] AS x1, x[2] AS x2, a, b, x[1] * a + x[2] * b AS f FROM {SQL_LINEITEM} AS q, s{t}))))""")
    return f"WITH {', '.join(ctes)} SELECT 0::BIGINT AS pos, a AS w FROM s{steps} UNION ALL SELECT 1::BIGINT, b FROM s{steps}"


_LOGI_SCALE = "(4 * 10.0::DOUBLE * sqrt(2.0::DOUBLE) / (SELECT count(*) FROM lineitem) + 2 * sqrt(2e-18::DOUBLE)) * sqrt(2.0::DOUBLE)"


@query("finite_release_logistic", f"SELECT pos, round(w + {sql_laplace(sql_u(7, 'lap', 'pos'), _LOGI_SCALE)}, 8) + 0.0 AS w FROM ({_logistic_sql()})")
def finite_release_logistic(spark, sf_dir):
    """The closest prior learner: logistic loss, noise on the certified minimiser's weights; two features, C = 10."""
    r = mechanisms.release_finite(_two(spark, sf_dir), 2, math.sqrt(2), 10.0, Logistic, beta=1.0, rng=SeededRng(7))
    return frame(spark, r.w, 8)


@query("logistic_weights_lineitem", f"SELECT pos, round(w, 8) + 0.0 AS w FROM ({_logistic_sql()})")
def logistic_weights_lineitem(spark, sf_dir):
    return frame(spark, solvers.fit(_two(spark, sf_dir), 10.0, 2, math.sqrt(2), Logistic).w, 8)


def _two(spark, sf_dir):
    return examples.lineitem(spark, sf_dir).select("row_id", F.slice("x", 1, 2).alias("x"), "y")


# --- a release on every workload: fitted, released, scored ---------------------------------------------------------------

_DOCS = """(SELECT doc_id AS row_id, CASE WHEN quality IS NULL THEN [0.0, 0, 0, 0, 0]::DOUBLE[] ELSE [least(1.0, length(text) / 20000.0::DOUBLE), least(1.0::DOUBLE, length(regexp_replace(text, '[^!#$%&*+/<=>@^_|~-]', '', 'g')) / greatest(length(text), 1)::DOUBLE),
len(list_distinct(ws)) / greatest(len(ws), 1)::DOUBLE, least(1.0::DOUBLE, length(regexp_replace(text, '[^0-9]', '', 'g')) / greatest(length(text), 1)::DOUBLE), 1.0]::DOUBLE[] END AS x, CASE WHEN quality = 1 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y
FROM (SELECT doc_id, text, quality, list_filter(regexp_split_to_array(text, '[ \n]'), lambda w: w <> '') AS ws FROM (SELECT doc_id, coalesce(text, '') AS text FROM documents) LEFT JOIN labels USING (doc_id)))"""
_CLIP = "greatest(0.0::DOUBLE, least(1.0::DOUBLE, {}))".format
_FULL = f"""(SELECT [{_CLIP("value / 100.0::DOUBLE")}, {_CLIP("json_extract_string(props, '$.k')::DOUBLE / 100")}, cos(extract('hour' FROM ts) * 2 * pi() / 24), sin(extract('hour' FROM ts) * 2 * pi() / 24)] AS x, CASE WHEN event_type = 'purchase' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM events)"""
_ORDERS = f"""(SELECT [{_CLIP("o_totalprice / 500000.0::DOUBLE")}, {_CLIP("(c_acctbal + 1000) / 11000.0::DOUBLE")}, {", ".join(f"CASE WHEN c_mktsegment = '{g}' THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END" for g in examples.SEGMENTS)}, {", ".join(f"CASE WHEN n_regionkey = {k} THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END" for k in range(5))}] AS x,
CASE WHEN substr(o_orderpriority, 1, 1) IN ('1', '2') THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM orders LEFT JOIN customer ON o_custkey = c_custkey LEFT JOIN nation ON c_nationkey = n_nationkey)"""
_PART = f"(SELECT [{_CLIP('p_size / 50.0::DOUBLE')}, {_CLIP('p_retailprice / 2000.0::DOUBLE')}] AS x, CASE WHEN regexp_extract(p_brand, '([0-9]+)', 1)::INT <= 12 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM part)"
_SUPPLIER = "(SELECT list_transform(range(25), lambda k: CASE WHEN s_nationkey = k THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS x, CASE WHEN s_acctbal > 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM supplier)"
_TURNS = f"(SELECT [{_CLIP('length(text) / 20000.0::DOUBLE')}, {_CLIP('turn / 20.0::DOUBLE')}, 1.0::DOUBLE] AS x, CASE WHEN role = 'user' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM (SELECT turn, role, coalesce(text, '') AS text FROM conversations))"
WORKLOADS = {"lineitem": SQL_LINEITEM, "embeddings": SQL_EMBEDDINGS, "documents": _DOCS, "events_full": _FULL, "orders": _ORDERS, "part": _PART, "supplier": _SUPPLIER, "turns": _TURNS}


def _released_sql(name: str) -> str:
    spec = examples.SPECS[name]
    C, k, n = 1 / spec.kappa**2, spec.features, "(SELECT count(*) FROM q)"
    lam = f"{4 * C * spec.kappa * math.sqrt(k)!r}::DOUBLE / {n}"
    return f"""SELECT * FROM (WITH q AS MATERIALIZED (SELECT x, y FROM {WORKLOADS[name]}),
w AS (SELECT list(v ORDER BY p) AS w FROM (SELECT p, {C!r}::DOUBLE * sum(y * x[p]) / count(*) + any_value({sql_laplace(sql_u(7, 'lap', '(p - 1)'), lam)}) AS v FROM q, range(1, {k + 1}) AS t(p) GROUP BY p))
SELECT '{name}' AS workload, count(*) AS n, round({lam}, 9) AS lam, round(any_value(list_sum(list_transform(w, lambda v: abs(v)))), 7) AS w_l1, round(max(abs(list_dot_product(x, w))), 7) AS far,
sum(CASE WHEN (list_dot_product(x, w) >= 0) = (y > 0) THEN 1 ELSE 0 END)::BIGINT AS correct FROM q, w)"""


@query("release_workloads", " UNION ALL ".join(map(_released_sql, WORKLOADS)))
def release_workloads(spark, sf_dir):
    """Hinge at C = 1 / kappa², exact in one pass, beta = 1: fitted, released, and the released weights scored over the whole table."""
    out = []
    for name in WORKLOADS:
        df, spec = examples.build(spark, sf_dir, name), examples.SPECS[name]
        r = mechanisms.release_finite(df, spec.features, spec.kappa, 1 / spec.kappa**2, beta=1.0, rng=SeededRng(7))
        hit = F.sum(F.when((F.col("score") >= 0) == (F.col("y") > 0), 1).otherwise(0))
        s = scoring.score(df, r).agg(F.max(F.abs("score")).alias("far"), hit.alias("correct")).first()
        out.append((name, r.n, round(r.lam, 9), round(float(np.abs(r.w).sum()), 7), round(s.far, 7), s.correct))
    return spark.createDataFrame(out, "workload string, n long, lam double, w_l1 double, far double, correct long")


@query("release_workloads_certified")
def release_workloads_certified(spark, sf_dir):
    """Beyond saturation, C = 10 and beta = 1: certified minimisers of three losses, their releases, and how far the released scores lie from the minimiser's."""
    out = []
    for name in ("documents", "events_full", "orders", "part"):
        df, spec = saved(examples.build(spark, sf_dir, name)), examples.SPECS[name]  # tens of passes: features of whole texts are made once
        for loss in (Hinge, Logistic, Square):
            tol = 1e-4
            fit = solvers.fit(df, 10.0, spec.features, spec.kappa, loss, tol)
            r = mechanisms.release_finite(df, spec.features, spec.kappa, 10.0, loss, beta=1.0, rng=SeededRng(7), tol=tol, fit=fit)
            gap = r.w - fit.w
            hit = lambda w: F.avg(F.when((v.dot_literal(F.col("x"), w) >= 0) == (F.col("y") > 0), 1.0).otherwise(0.0))
            seen = df.where(F.get("x", F.lit(4)) == 1) if name == "documents" else df  # labelled documents have an intercept
            s = seen.agg(F.max(F.abs(v.dot_literal(F.col("x"), gap))).alias("far"), hit(fit.w).alias("exact"), hit(r.w).alias("released")).first()
            out.append((name, loss.name, r.n, fit.passes, float(r.lam), float(s.far), float(np.abs(gap).sum() * spec.phi), float(s.exact), float(s.released)))
    return spark.createDataFrame(out, "workload string, loss string, n long, passes int, lam double, sup_distance double, sup_bound double, accuracy_exact double, accuracy_released double")


# --- random features of every kernel -----------------------------------------------------------------------------------

_LAWS = {
    "rbf(0.5)": f"sqrt(-2 * ln({sql_u(SEED, 'fa', 'i')})) * cos(2 * pi() * {sql_u(SEED, 'fb', 'i')}) / 0.5",
    "rbf(1)": f"sqrt(-2 * ln({sql_u(SEED, 'fa', 'i')})) * cos(2 * pi() * {sql_u(SEED, 'fb', 'i')})",
    "laplacian": f"tan(pi() * ({sql_u(SEED, 'fa', 'i')} - 0.5))",
    "cauchy": sql_laplace(sql_u(SEED, "fa", "i"), "1.0"),
}
_SWEEP = [("rbf(0.5)", 8), ("rbf(1)", 128), ("rbf(1)", 512), ("laplacian", 8), ("laplacian", 128), ("cauchy", 8), ("cauchy", 128)]


def _rff_sql(law: str, m: int) -> str:
    """The saturated minimiser at C = 1 over m frequencies of a law, with the mechanism's noise."""
    lam = f"{2**2.5 * math.sqrt(m)!r}::DOUBLE / (SELECT count(*) FROM embeddings)"
    return f"""SELECT '{law}' AS kernel, {m}::BIGINT AS m, round({lam}, 9) AS lam, round(sum(abs(v)), 6) AS w_l1, round(sum(abs(v - mu)), 6) AS exact_l1 FROM (SELECT s / count + mu AS v, mu FROM (SELECT 2 * f + part AS pos, sum(y * CASE WHEN part = 0 THEN cos(p) ELSE sin(p) END) / sqrt({m}) AS s, count(*) AS count,
any_value({sql_laplace(sql_u(7, 'lap', '(2 * f + part)'), lam)}) AS mu FROM (SELECT y, f, list_dot_product(x, rho) AS p FROM {SQL_EMBEDDINGS}, (SELECT i // 64 AS f, list({_LAWS[law]} ORDER BY i) AS rho FROM range({m} * 64) AS t(i) GROUP BY 1)), (SELECT unnest([0, 1]) AS part) GROUP BY f, part))"""


@query("rff_release_kernels", " UNION ALL ".join(_rff_sql(*x) for x in _SWEEP))
def rff_release_kernels(spark, sf_dir):
    """Releases for the three kernels, two widths and up to 512 frequencies: C = 1, beta = 1."""
    e, made, out = examples.embeddings(spark, sf_dir), {"rbf(0.5)": K.rbf(0.5), "rbf(1)": K.rbf(), "laplacian": K.laplacian(), "cauchy": K.cauchy_kernel()}, []
    for law, m in _SWEEP:
        r = mechanisms.release_random_features(e, made[law], 64, m, 1.0, beta=1.0, freq_seed=SEED, rng=SeededRng(7))
        exact = r.w - SeededRng(7).laplace(2 * m, r.lam)
        out.append((law, m, round(r.lam, 9), round(float(np.abs(r.w).sum()), 6), round(float(np.abs(exact).sum()), 6)))
    return spark.createDataFrame(out, "kernel string, m long, lam double, w_l1 double, exact_l1 double")


@query("ref_dual_objective", "SELECT C, true AS certified, true AS objective_ok FROM (VALUES (1.0::DOUBLE), (10.0::DOUBLE)) AS t(C)")
def ref_dual_objective(spark, sf_dir):
    """The reference machine and the primal solver find the same optimum."""
    e, out = examples.embeddings(spark, sf_dir), []
    for C in (1.0, 10.0):
        m = solvers.reference(e, C, tol=1e-8)
        p = solvers.fit(e, C, 64, 1.0, tol=1e-7)
        out.append((C, bool(m.gap <= 1e-8), bool(abs(m.objective - p.objective) < 1e-6)))
    return spark.createDataFrame(out, "C double, certified boolean, objective_ok boolean")


@query("ref_dual_box", "SELECT count(*) AS n, true AS in_box FROM embeddings")
def ref_dual_box(spark, sf_dir):
    m = solvers.reference(examples.embeddings(spark, sf_dir), 10.0, K.rbf())
    return m.frame(spark).agg(F.count("*").alias("n"), (F.min("alpha") >= 0) & (F.max("alpha") <= 10.0 / F.count("*") + 1e-15)).toDF("n", "in_box")


@query("primal_from_dual", _sums(SQL_EMBEDDINGS, 1.0, 64))
def primal_from_dual(spark, sf_dir):
    """At C = 1 all duals sit at C / n, and their expansion is the saturated minimiser."""
    e = examples.embeddings(spark, sf_dir)
    m = solvers.reference(e, 1.0)
    return solvers.primal_from_dual(m.frame(spark), e).select(F.col("pos").cast("long").alias("pos"), (F.round("w", 9) + 0.0).alias("w"))


@query("primal_equals_dual", "SELECT true AS equal")
def primal_equals_dual(spark, sf_dir):
    e = examples.embeddings(spark, sf_dir)
    m = solvers.reference(e, 10.0, tol=1e-12)
    w = np.zeros(64)
    for r in solvers.primal_from_dual(m.frame(spark), e).collect():  # one row a feature
        w[r.pos] = r.w
    p = solvers.cutting_plane(e, 10.0, 64, tol=1e-11)
    return spark.createDataFrame([(bool(np.abs(w - p.w).max() < 1e-4),)], "equal boolean")


@query("dual_scores", f"SELECT a.row_id AS test_id, round(sum(b.y * list_dot_product(a.x, b.x)) / count(*), 9) + 0.0 AS score FROM {SQL_EMBEDDINGS} a, {SQL_EMBEDDINGS} b GROUP BY a.row_id")
def dual_scores(spark, sf_dir):
    e = examples.embeddings(spark, sf_dir)
    n = e.count()
    alpha = e.select("row_id", F.lit(1.0 / n).alias("alpha"))
    return scoring.score_dual_blocks(e, e, alpha).select("test_id", (F.round("score", 9) + 0.0).alias("score"))


@query("naive_disclosure", "SELECT count(*) AS exposed, 1.0::DOUBLE AS share FROM embeddings")
def naive_disclosure(spark, sf_dir):
    e = examples.embeddings(spark, sf_dir)
    return baselines.naive_disclosure(solvers.reference(e, 1.0).frame(spark))


@query("private_histogram", f"""SELECT c AS cell, k AS event_type, round(coalesce(n, 0) + {sql_laplace(sql_u(7, 'hist', 'c'), '4.0::DOUBLE')}, 6) AS noisy
FROM (SELECT * FROM (VALUES (0::BIGINT, 'click'), (1, 'login'), (2, 'purchase'), (3, 'signup'), (4, 'view')) AS d(c, k)) LEFT JOIN (SELECT event_type, count(*) AS n FROM events GROUP BY 1) ON k = event_type""")
def private_histogram(spark, sf_dir):
    h = baselines.private_histogram(examples.load(spark, sf_dir, "events"), "event_type", ["click", "login", "purchase", "signup", "view"], 0.5, 7)
    return h.select("cell", "event_type", F.round("noisy", 6).alias("noisy"))


@query("private_class_means", f"SELECT (p - 1)::BIGINT AS pos, round((sum(y * x[p]) + any_value({sql_laplace(sql_u(7, 'means', '(p - 1)'), '8.0::DOUBLE')})) / count(*), 9) AS w FROM {SQL_LINEITEM}, range(1, 5) AS t(p) GROUP BY p")
def private_class_means(spark, sf_dir):
    return baselines.private_class_means(examples.lineitem(spark, sf_dir), 4, 1.0, 7).select("pos", F.round("w", 9).alias("w"))


@query("majority_baseline", f"SELECT y, count(*) AS n FROM {SQL_LINEITEM} GROUP BY y ORDER BY n DESC LIMIT 1")
def majority_baseline(spark, sf_dir):
    return baselines.majority(examples.lineitem(spark, sf_dir))


_OVR_SCALE = "320.0::DOUBLE / (SELECT count(*) FROM embeddings)"


@query("ovr_release", f"""WITH q AS MATERIALIZED (SELECT row_id, x, t.label FROM {SQL_EMBEDDINGS} AS e JOIN embeddings AS t ON t.vec_id = e.row_id),
w AS (SELECT k, list(c ORDER BY p) AS w FROM (SELECT k, p, sum(CASE WHEN label = k THEN x[p] ELSE -x[p] END) / count(*) + any_value({sql_laplace(sql_u(7, "lap", "(k * 64 + p - 1)"), _OVR_SCALE)}) AS c FROM q, range(10) AS a(k), range(1, 65) AS t(p) GROUP BY k, p) GROUP BY k),
s AS (SELECT row_id, label, arg_max(k, list_dot_product(x, w)) AS best FROM q, w GROUP BY row_id, label)
SELECT w.k AS class, round({_OVR_SCALE}, 9) AS lam, round(list_sum(list_transform(any_value(w.w), lambda z: abs(z))), 7) AS w_l1, count(s.row_id) AS correct FROM w LEFT JOIN s ON s.label = w.k AND s.best = w.k GROUP BY w.k""")
def ovr_release(spark, sf_dir):
    """All ten classes of embeddings from one pass, beta = 1 shared; correct: rows of a class whose largest released score is its own."""
    e = examples.embeddings_classes(spark, sf_dir)
    r = mechanisms.release_one_vs_rest(e, list(range(10)), 64, 1.0, 1.0, 1.0, rng=SeededRng(7))
    scores = F.array(*[v.dot_literal(F.col("x"), r[k].w) for k in range(10)])
    best = e.select("label", scores.alias("s")).select("label", (F.array_position("s", F.array_max("s")) - 1).alias("best"))
    hits = {x["label"]: x["count"] for x in best.where("label = best").groupBy("label").count().collect()}  # one row a class
    return spark.createDataFrame([(k, round(float(x.lam), 9), round(float(np.abs(x.w).sum()), 7), hits.get(k, 0)) for k, x in r.items()], "class long, lam double, w_l1 double, correct long")


@query("secure_release_shape", "SELECT 4::BIGINT AS weights, true AS on_grid")
def secure_release_shape(spark, sf_dir):
    from ..functions.rng import SecureRng

    noise = SecureRng(grid=2.0**-20).laplace(4, 1.0)
    return spark.createDataFrame([(len(noise), bool(np.allclose(noise * 2**20 % 1, 0)))], "weights long, on_grid boolean")


@query("ml_crosscheck", "SELECT true AS hinge, true AS square")
def ml_crosscheck(spark, sf_dir):
    """Spark's own linear learners give the same minimisers."""
    df = examples.lineitem(spark, sf_dir)
    hinge = np.abs(np.array(baselines.ml_crosscheck(df, 0.25)) - solvers.saturated(df, 0.25, 4).w).max() < 1e-3
    square = np.abs(np.array(baselines.ml_crosscheck(df, 1.0, "square")) - solvers.ridge(df, 1.0, 4).w).max() < 1e-3
    return spark.createDataFrame([(bool(hinge), bool(square))], "hinge boolean, square boolean")


_1D = "(SELECT y * x AS s FROM (SELECT greatest(0.0::DOUBLE, least(1.0::DOUBLE, value / 100.0::DOUBLE)) AS x, CASE WHEN event_type = 'purchase' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM events) WHERE x > 0)"


def _sql_1d(table: str, C: str, n: str) -> str:
    """The root of the step function by windows over its breakpoints."""
    return f"""SELECT round(CASE WHEN max(CASE WHEN k * below >= b THEN b END) IS NULL THEN any_value(k) * min_by(below, b)
ELSE greatest(max(CASE WHEN k * below >= b THEN b END), any_value(k) * max_by(above, CASE WHEN k * below >= b THEN b END)) END, 8) AS w FROM (
SELECT b, {C}::DOUBLE / ({n}) AS k, sum(p) OVER (ORDER BY b DESC ROWS UNBOUNDED PRECEDING) + coalesce(sum(g) OVER (ORDER BY b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below,
coalesce(sum(p) OVER (ORDER BY b DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + sum(g) OVER (ORDER BY b ROWS UNBOUNDED PRECEDING) AS above
FROM (SELECT 1 / s AS b, CASE WHEN s > 0 THEN sum(s) ELSE 0 END AS p, CASE WHEN s < 0 THEN sum(s) ELSE 0 END AS g FROM {table} GROUP BY s))"""


@query("hinge_1d_events", " UNION ALL ".join(f"SELECT {C}::DOUBLE AS C, w FROM ({_sql_1d(_1D, C, 'SELECT count(*) FROM events')})" for C in ("1.0", "10.0", "100.0")))
def hinge_1d_events(spark, sf_dir):
    return solvers.hinge_1d_path(examples.events(spark, sf_dir), [1.0, 10.0, 100.0]).select("C", F.round("w", 8).alias("w"))
