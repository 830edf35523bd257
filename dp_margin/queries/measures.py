"""Accuracy, privacy and stability measures."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F

from ..functions import calibrate as cal
from ..functions import kernels as K
from ..functions import vectors as v
from ..functions.rng import SeededRng
from ..operators import blocks, measure, solvers
from ..sources import examples
from ..sources.tables import load
from .base import SQL_EMBEDDINGS, SQL_LINEITEM, query, sql_laplace, sql_u
from .kernels import _F64, SEED

W = (-0.002, 0.018, 0.005, 0.015)
_F = "(" + " + ".join(f"x[{i + 1}] * {w}::DOUBLE" for i, w in enumerate(W)) + ")"


@query("risk_lineitem", f"SELECT round(avg(greatest(0.0::DOUBLE, 1 - y * {_F})), 9) AS empirical, round({0.5 * sum(a * a for a in W)!r}::DOUBLE + 10 * avg(greatest(0.0::DOUBLE, 1 - y * {_F})), 9) AS regularised FROM {SQL_LINEITEM}")
def risk_lineitem(spark, sf_dir):
    r = measure.risk(examples.lineitem(spark, sf_dir), W, 10.0)
    return r.select(F.round("empirical", 9).alias("empirical"), F.round("regularised", 9).alias("regularised"))


@query("gradient_long", f"SELECT (p - 1)::INTEGER AS pos, round(avg(CASE WHEN y * {_F} < 1 THEN -y ELSE 0 END * x[p]), 9) + 0.0 AS g FROM {SQL_LINEITEM}, range(1, 5) AS t(p) GROUP BY p")
def gradient_long(spark, sf_dir):
    return measure.gradient_long(examples.lineitem(spark, sf_dir), W).select("pos", (F.round("g", 9) + 0.0).alias("g"))


_NEAR = f"(SELECT x, y, [0.125::DOUBLE FOR i IN range(64)] AS x2, -1.0::DOUBLE AS y2 FROM {SQL_EMBEDDINGS} WHERE row_id = 0)"


@query("pair_privacy_loss", f"SELECT round(sum(abs(y2 * x2[p] - y * x[p])) / 32, 9) AS loss, sum(abs(y2 * x2[p] - y * x[p])) / 32 <= 1 AS within FROM {_NEAR}, range(1, 65) AS t(p)")
def pair_privacy_loss(spark, sf_dir):
    """Neighbours of embeddings: the exact loss of the pair at the noise for beta = 1; the number of rows cancels out."""
    e = examples.embeddings(spark, sf_dir)
    n = e.count()
    w1 = solvers.saturated(e, 1.0, 64).w
    w2 = solvers.saturated(measure.replace_row(e, 0, [0.125] * 64, -1.0), 1.0, 64).w
    loss = measure.pair_privacy_loss(w1, w2, cal.min_noise_finite(1.0, n, 1.0, 1.0, 64))
    return spark.createDataFrame([(round(loss, 9), loss <= 1.0)], "loss double, within boolean")


@query("privacy_audit", "SELECT true AS within, true AS informative")
def privacy_audit(spark, sf_dir):
    """Histograms of responses on the hard pair: the largest log ratio is near the pair's exact loss, and below beta with a margin for chance."""
    n, C, eps = 100, 1.0, 0.002
    lam = cal.min_noise_finite(2.0, n, C, 0.4)
    w1, w2 = 0.5, 0.5 + 2 * eps
    a = measure.audit_privacy(spark, w1, w2, lam, 200_000, 20, 11).first()
    exact = 2 * eps / lam
    return spark.createDataFrame([(bool(a.worst <= 2.0), bool(abs(a.worst - exact) < 0.3))], "within boolean, informative boolean")


LAM, TRIALS = cal.max_noise_finite(0.5, 0.05, 4), 200
_USE = f"""SELECT round(avg(CASE WHEN far <= 0.5 THEN 1.0 ELSE 0.0 END), 9) AS useful FROM (SELECT trial, max(abs({' + '.join(f'x[{i + 1}] * mu[{i + 1}]' for i in range(4))})) AS far FROM
(SELECT i // 4 AS trial, list({sql_laplace(sql_u(5, 'use', 'i'), repr(LAM) + '::DOUBLE')} ORDER BY i) AS mu FROM range({TRIALS * 4}) AS t(i) GROUP BY 1), (SELECT x FROM {SQL_LINEITEM}) GROUP BY trial)"""


@query("usefulness_finite", _USE)
def usefulness_finite(spark, sf_dir):
    """At the largest admissible noise, at least 95 % of draws stay within eps on every row of the table."""
    probes = examples.lineitem(spark, sf_dir).select("x")
    return measure.usefulness(spark, probes, 4, LAM, 0.5, TRIALS, 5).select(F.round("useful", 9).alias("useful"))


def _use_rff(m: int) -> str:
    """Share of draws within a quarter on every embedding, in the space of m frequencies."""
    x = f"(SELECT row_id, flatten(list([cos(p) / sqrt({m}), sin(p) / sqrt({m})] ORDER BY f)) AS x FROM (SELECT row_id, f, list_dot_product(x, rho) AS p FROM {SQL_EMBEDDINGS}, {_F64.format(m=m)}) GROUP BY row_id)"
    mu = f"(SELECT i // {2 * m} AS trial, list({sql_laplace(sql_u(5, 'use', 'i'), repr(cal.max_noise_random(0.5, 0.05, m)) + '::DOUBLE')} ORDER BY i) AS mu FROM range({TRIALS * 2 * m}) AS t(i) GROUP BY 1)"
    useful = "avg(CASE WHEN far <= 0.25 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END)"
    return f"SELECT {m}::BIGINT AS m, round({useful}, 9) AS useful, {useful} >= 0.95 AS enough FROM (SELECT trial, max(abs(list_dot_product(x, mu))) AS far FROM {mu}, {x} GROUP BY trial)"


@query("usefulness_rff", " UNION ALL ".join(map(_use_rff, (8, 32))))
def usefulness_rff(spark, sf_dir):
    e, out = examples.embeddings(spark, sf_dir), []
    for m in (8, 32):
        rho = K.frequency_matrix(spark, K.rbf(), 64, m, SEED)
        probes = e.select(K.trig_map(F.col("x"), rho).alias("x"))
        u = measure.usefulness(spark, probes, 2 * m, cal.max_noise_random(0.5, 0.05, m), 0.25, TRIALS, 5).first()[0]
        out.append((m, round(u, 9), bool(u >= 0.95)))
    return spark.createDataFrame(out, "m long, useful double, enough boolean")


@query("sup_distance", f"SELECT round(max(abs({_F})), 9) AS data_max, {sum(map(abs, W))!r}::DOUBLE AS l1_bound, {round(W[1] + W[2] + W[3], 9)!r}::DOUBLE AS box_max FROM {SQL_LINEITEM}")
def sup_distance(spark, sf_dir):
    s = measure.sup_distance(examples.lineitem(spark, sf_dir), W, (0, 0, 0, 0))
    return s.select(F.round("data_max", 9).alias("data_max"), F.round("l1_bound", 9).alias("l1_bound"), F.round("box_max", 9).alias("box_max"))


_W2 = (0.5, 1.0, -1.0, 0.2)
_F2 = "(" + " + ".join(f"x[{i + 1}] * {w}::DOUBLE" for i, w in enumerate(_W2)) + ")"


@query("risk_gap", f"SELECT round(abs(avg(greatest(0.0::DOUBLE, 1 - y * {_F})) - avg(greatest(0.0::DOUBLE, 1 - y * {_F2}))), 9) AS gap, round(max(abs({_F} - {_F2})), 9) AS bound, abs(avg(greatest(0.0::DOUBLE, 1 - y * {_F})) - avg(greatest(0.0::DOUBLE, 1 - y * {_F2}))) <= max(abs({_F} - {_F2})) AS within FROM {SQL_LINEITEM}")
def risk_gap(spark, sf_dir):
    g = measure.risk_gap(examples.lineitem(spark, sf_dir), W, _W2)
    return g.select(F.round("gap", 9).alias("gap"), F.round("bound", 9).alias("bound"), (F.col("gap") <= F.col("bound")).alias("within"))


def _sql_sensitivity(table: str, C: float, kappa: float, features: int) -> str:
    """Every neighbour that turns one row round changes the weights by 2 C x / n."""
    l2, l1 = f"max(sqrt(list_sum(list_transform(x, lambda v: v * v)))) * {2 * C!r}::DOUBLE", f"max(list_sum(list_transform(x, lambda v: abs(v)))) * {2 * C!r}::DOUBLE"
    return f"round({l2}, 9) AS l2_n, round({l1}, 9) AS l1_n, {l2} <= {4 * C * kappa!r}::DOUBLE AS l2_within, {l1} <= {4 * C * kappa * math.sqrt(features)!r}::DOUBLE AS l1_within, {l2} <= {2 * C * kappa!r}::DOUBLE + 1e-9 AS tight_within FROM {table}"


@query("measured_sensitivity", f"SELECT 'embeddings' AS workload, {_sql_sensitivity(SQL_EMBEDDINGS, 1.0, 1.0, 64)} UNION ALL SELECT 'lineitem', {_sql_sensitivity(SQL_LINEITEM, 0.25, 2.0, 4)}")
def measured_sensitivity(spark, sf_dir):
    """All neighbours that turn one row round: the largest weight change times n, against the bounds."""
    out = []
    for name, C in (("embeddings", 1.0), ("lineitem", 0.25)):
        df, spec = examples.build(spark, sf_dir, name), examples.SPECS[name]
        n = df.count()
        other = df.select("row_id", F.transform("x", lambda a: -a).alias("x2"), F.col("y").alias("y2"))
        r = measure.measured_sensitivity_saturated(df, other, C).first()
        bound = [cal.weight_sensitivity(C, n, spec.kappa, norm=k, features=spec.features, tight=t) for k, t in ((2, False), (1, False), (2, True))]
        out.append((name, round(r.l2 * n, 9), round(r.l1 * n, 9), r.l2 <= bound[0], r.l1 <= bound[1], r.l2 <= bound[2] + 1e-9 / n))
    return spark.createDataFrame(out, "workload string, l2_n double, l1_n double, l2_within boolean, l1_within boolean, tight_within boolean")


@query("refit_sensitivity")
def refit_sensitivity(spark, sf_dir):
    """lineitem with an intercept at C = 10, beyond the saturated regime: refits after one row is replaced, each with its certificate, against the bound."""
    df, out = examples.lineitem(spark, sf_dir, intercept=True), []
    n, tol = df.count(), 1e-6
    w = solvers.cutting_plane(df, 10.0, 5, tol=tol).w
    first, last = df.agg(F.min("row_id"), F.max("row_id")).first()
    for row, x, y in ((first, [1.0, 1.0, 1.0, 1.0, 1.0], -1.0), (last, [0.0, 0.0, 0.0, 0.0, 1.0], 1.0)):
        again = solvers.cutting_plane(measure.replace_row(df, row, x, y), 10.0, 5, tol=tol).w
        bound = cal.weight_sensitivity(10.0, n, math.sqrt(5), gap=tol)
        out.append((int(row), float(np.linalg.norm(again - w)), bound, bool(np.linalg.norm(again - w) <= bound)))
    return spark.createDataFrame(out, "row_id long, l2 double, bound double, within boolean")


_WS = f"SELECT list(sum ORDER BY p) AS w1, list(sum - (y * x[p] + 0.125) / n ORDER BY p) AS w2 FROM (SELECT p, sum(y * x[p]) / count(*) AS sum, count(*) AS n FROM {SQL_EMBEDDINGS}, range(1, 65) AS t(p) GROUP BY p), (SELECT x, y FROM {SQL_EMBEDDINGS} WHERE row_id = 0)"


@query("uniform_stability", f"SELECT round(max(abs(greatest(0.0::DOUBLE, 1 - y * list_dot_product(x, w1)) - greatest(0.0::DOUBLE, 1 - y * list_dot_product(x, w2)))) * count(*), 6) AS change_n, max(abs(greatest(0.0::DOUBLE, 1 - y * list_dot_product(x, w1)) - greatest(0.0::DOUBLE, 1 - y * list_dot_product(x, w2)))) * count(*) <= 4 AS within FROM {SQL_EMBEDDINGS}, ({_WS})")
def uniform_stability(spark, sf_dir):
    e = examples.embeddings(spark, sf_dir)
    n = e.count()
    w1, w2 = solvers.saturated(e, 1.0, 64).w, solvers.saturated(measure.replace_row(e, 0, [0.125] * 64, -1.0), 1.0, 64).w
    return measure.uniform_stability(e, w1, w2).select(F.round(F.col("change") * n, 6).alias("change_n"), (F.col("change") <= 4.0 / n).alias("within"))


@query("dual_l1", "SELECT true AS within")
def dual_l1(spark, sf_dir):
    m = solvers.reference(examples.embeddings(spark, sf_dir), 10.0)
    return measure.dual_l1(m.frame(spark)).select((F.col("l1") <= 10.0 + 1e-9).alias("within"))


@query("perturbation_chain", "SELECT step, true AS within FROM (VALUES ('back'), ('hilbert'), ('shift'), ('total'), ('transfer')) AS t(step)")
def perturbation_chain(spark, sf_dir):
    """Each step from kernel error to classifier distance, measured against its bound on all rows."""
    e = examples.embeddings(spark, sf_dir)
    rho = K.frequency_matrix(spark, K.rbf(), 64, 64, SEED)
    a, b = solvers.reference(e, 1.0, K.rbf()), solvers.reference(e, 1.0, rho=rho)
    c = measure.perturbation_chain_table(e, a.frame(spark), b.frame(spark), K.rbf(), rho, 1.0)
    c["back_bound"] = 2 * 1.5 * c["kernel_error"]
    return spark.createDataFrame([(k, bool(c[k] <= c[f"{k}_bound"] + 1e-9)) for k in ("shift", "transfer", "back", "hilbert", "total")], "step string, within boolean")


@query("swap_space_scores", "SELECT true AS within")
def swap_space_scores(spark, sf_dir):
    """A minimiser moved to the other space with its coefficients: scores change by at most kernel error times C, over all rows."""
    e = examples.embeddings(spark, sf_dir)
    rho = K.frequency_matrix(spark, K.rbf(), 64, 64, SEED)
    m = solvers.reference(e, 1.0, K.rbf()).frame(spark)
    signed = e.join(m, "row_id").withColumn("c", F.col("alpha") * F.col("y"))
    t = blocks.expansions(signed, [lambda x, z: solvers.gram(x, z, K.rbf()), lambda x, z: solvers.gram(x, z, None, rho)], {"f": (0, "c"), "moved": (1, "c")}, "err")
    return t.agg((F.max(F.abs(F.col("f") - F.col("moved"))) <= F.max("err") * 1.0 + 1e-12).alias("within"))


_CERT = f"""SELECT scale, round(0.5 * sum(g * g), 9) + 0.0 AS bound FROM (SELECT scale, p, scale * any_value(w[p]) + avg(CASE WHEN y * scale * list_dot_product(x, w) < 1 THEN -y * x[p] ELSE 0.0::DOUBLE END) AS g
FROM {SQL_EMBEDDINGS}, (SELECT list(a ORDER BY p) AS w FROM (SELECT p, avg(y * x[p]) AS a FROM {SQL_EMBEDDINGS}, range(1, 65) AS t(p) GROUP BY p)), (SELECT unnest([1.0, 2.0, 8.0]::DOUBLE[]) AS scale), range(1, 65) AS t(p) GROUP BY scale, p) GROUP BY scale"""


@query("certificate", _CERT)
def certificate(spark, sf_dir):
    """Embeddings at C = 1: the bound on the gap is zero at the minimiser and grows away from it."""
    e = examples.embeddings(spark, sf_dir)
    w = solvers.saturated(e, 1.0, 64).w
    return spark.createDataFrame([(k, round(solvers.certificate(e, k * w, 1.0), 9) + 0.0) for k in (1.0, 2.0, 8.0)], "scale double, bound double")


_NORM = f"SELECT round(avg(s), 6) AS mean, round(var_pop(s), 6) AS var FROM (SELECT i // 64 AS trial, sum(abs({sql_laplace(sql_u(3, 'norm', 'i'), '0.5')})) AS s FROM range({64 * 500}) AS t(i) GROUP BY 1)"


@query("noise_norm_stats", _NORM)
def noise_norm_stats(spark, sf_dir):
    return measure.noise_norm_stats(spark, 64, 0.5, 500, 3).select(F.round("mean", 6).alias("mean"), F.round("var", 6).alias("var"))


_TEXT = """SELECT d.doc_id AS row_id, least(1.0, length(text) / 20000.0::DOUBLE) AS f0, least(1.0::DOUBLE, length(regexp_replace(text, '[^!#$%&*+/<=>@^_|~-]', '', 'g')) / greatest(length(text), 1)::DOUBLE) AS f1,
len(list_distinct(ws)) / greatest(len(ws), 1)::DOUBLE AS f2, length(regexp_replace(text, '[^0-9]', '', 'g')) / greatest(length(text), 1)::DOUBLE AS f3, quality, toxic
FROM (SELECT *, list_filter(regexp_split_to_array(text, '[ \n]'), lambda w: w <> '') AS ws FROM documents) d LEFT JOIN labels USING (doc_id)"""


@query("text_features", f"SELECT row_id, round(f0, 9) AS f0, round(f1, 9) AS f1, round(f2, 9) AS f2, round(f3, 9) AS f3 FROM ({_TEXT})")
def text_features(spark, sf_dir):
    f = examples.text_features(F.col("text"))
    return load(spark, sf_dir, "documents").select(F.col("doc_id").alias("row_id"), *[F.round(c, 9).alias(f"f{i}") for i, c in enumerate(f)])


@query("text_features_conv", "SELECT conv_id, turn, least(1.0, length(text) / 20000.0::DOUBLE) AS len, role = 'user' AS is_user FROM conversations")
def text_features_conv(spark, sf_dir):
    t = load(spark, sf_dir, "conversations")
    return t.select("conv_id", "turn", v.clip(F.length("text") / 20000.0).alias("len"), (F.col("role") == "user").alias("is_user"))


@query("page_features", r"""SELECT page_id, regexp_extract(html, '<html lang="([a-z]+)"', 1) AS lang, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS chars, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages""")
def page_features(spark, sf_dir):
    p = load(spark, sf_dir, "pages")
    return p.select("page_id", F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("lang"), F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("chars"), F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host"))


_RUNS = "SELECT DISTINCT {0}, array_to_string(w[p:p + 7], ' ') AS run FROM (SELECT {0}, w, unnest(range(1, len(w) - 6)) AS p FROM (SELECT {0}, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[ \n\t]'), lambda x: x <> '') AS w FROM {1}))".format


@query("passage_overlap", f"SELECT d.doc_id, count(r.run) AS shared FROM documents d LEFT JOIN (SELECT * FROM ({_RUNS('doc_id', 'documents')}) WHERE run IN (SELECT run FROM ({_RUNS('item_id', 'benchmark')}))) r ON d.doc_id = r.doc_id GROUP BY 1")
def passage_overlap(spark, sf_dir):
    """Runs of eight words that documents share with benchmark passages: a feature of theirs."""
    return examples.passage_overlap(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))


_LINEAR = "(-0.2 - 8 * f1 + f2)"


@query("accuracy_documents", f"""SELECT count(*) AS n, sum(CASE WHEN {_LINEAR} >= 0 AND quality = 1 THEN 1 ELSE 0 END)::BIGINT AS tp, sum(CASE WHEN {_LINEAR} >= 0 AND quality = 0 THEN 1 ELSE 0 END)::BIGINT AS fp,
sum(CASE WHEN {_LINEAR} < 0 AND quality = 0 THEN 1 ELSE 0 END)::BIGINT AS tn, sum(CASE WHEN {_LINEAR} < 0 AND quality = 1 THEN 1 ELSE 0 END)::BIGINT AS fn, round(avg(CASE WHEN ({_LINEAR} >= 0) = (quality = 1) THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END), 9) AS accuracy FROM ({_TEXT}) WHERE quality IS NOT NULL""")
def accuracy_documents(spark, sf_dir):
    """Confusion of a fixed linear rule on labelled documents."""
    d = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id")
    f = examples.text_features(F.col("text"))
    d = d.select((-0.2 - 8 * f[1] + f[2]).alias("s"), examples.pm(F.col("quality") == 1).alias("y"))
    return measure.confusion(d, F.col("s")).withColumn("accuracy", F.round("accuracy", 9))


@query("accuracy_vs_beta", "SELECT beta, true AS sensible FROM (VALUES (0.01::DOUBLE), (1.0::DOUBLE), (100.0::DOUBLE)) AS t(beta)")
def accuracy_vs_beta(spark, sf_dir):
    """lineitem, hinge, C = 10 with an intercept: accuracy of releases rises with beta towards the non-private one."""
    df = examples.lineitem(spark, sf_dir, intercept=True)
    fit = solvers.cutting_plane(df, 10.0, 5, tol=1e-6)
    n, out = solvers.rows_and_weight(df), []
    accs = {}
    for beta in (0.01, 1.0, 100.0):
        w = fit.w + SeededRng(7).laplace(5, cal.min_noise_finite(beta, n, 10.0, math.sqrt(5), 5, gap=1e-6))
        accs[beta] = df.agg(F.avg(F.when((v.dot_literal(F.col("x"), w) >= 0) == (F.col("y") > 0), 1.0).otherwise(0.0))).first()[0]
    for beta in accs:
        out.append((beta, bool(accs[100.0] >= accs[beta] - 0.02 and accs[100.0] > 0.8)))
    return spark.createDataFrame(out, "beta double, sensible boolean")


@query("win_rank_auc", "SELECT round((sum(CASE WHEN quality = 1 THEN r ELSE 0 END) - p * (p + 1) / 2) / (p * q), 9) AS auc FROM (SELECT quality, rank() OVER (ORDER BY s) + (count(*) OVER (PARTITION BY s) - 1) / 2.0 AS r, sum(quality) OVER ()::DOUBLE AS p, sum(1 - quality) OVER ()::DOUBLE AS q FROM (SELECT quality, round(f2, 6) AS s FROM (" + _TEXT + ") WHERE quality IS NOT NULL)) GROUP BY p, q")
def win_rank_auc(spark, sf_dir):
    d = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id")
    d = d.select(F.round(examples.text_features(F.col("text"))[2], 6).alias("s"), examples.pm(F.col("quality") == 1).alias("y"))
    return measure.auc(d, F.col("s")).select(F.round("auc", 9).alias("auc"))


