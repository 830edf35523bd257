"""Calibration and bounds: closed forms over sweeps of public parameters and the tables' row counts."""

from __future__ import annotations


from pyspark.sql import functions as F

from ..functions import calibrate as cal
from ..functions import losses, optimal
from ..sources.examples import lineitem_x
from ..sources.tables import load
from .base import grid, query, sql_grid

B, D, E, C = [0.01, 0.1, 0.5, 1, 2, 10], [0.01, 0.05, 0.1], [0.05, 0.1, 0.5, 1], [0.1, 1, 10]
c = F.col
_r = lambda e: F.round(e, 9) + 0.0


def _frame(df, keep, **cols):
    return df.select(*keep, *[_r(v).alias(k) for k, v in cols.items()])


_SENS = sql_grid(True, C=C, kappa=[1, 2], F=[4, 64])


@query("sensitivity_sweep", f"SELECT tbl, C, kappa, F, round(4 * C * kappa / n, 9) AS l2, round(4 * C * kappa * sqrt(F) / n, 9) AS l1, round(2 * C * kappa / n, 9) AS l2_tight, round(4 * C * kappa / n + 2 * sqrt(2e-9::DOUBLE), 9) AS l2_gap FROM {_SENS}")
def sensitivity_sweep(spark, sf_dir):
    g = grid(spark, sf_dir, True, C=C, kappa=[1, 2], F=[4, 64])
    a = (c("C"), c("n"), c("kappa"))
    return _frame(g, ["tbl", "C", "kappa", "F"], l2=cal.weight_sensitivity(*a), l1=cal.weight_sensitivity(*a, norm=1, features=c("F")), l2_tight=cal.weight_sensitivity(*a, tight=True), l2_gap=cal.weight_sensitivity(*a, gap=F.lit(1e-9)))


_FLOOR = sql_grid(True, beta=B, C=C, F=[4, 64, 512])


@query("noise_floor_sweep", f"SELECT tbl, beta, C, F, round(4 * C * sqrt(F) / (beta * n), 9) AS finite, round(power(2.0::DOUBLE, 2.5) * C * sqrt(F / 2) / (beta * n), 9) AS random FROM {_FLOOR}")
def noise_floor_sweep(spark, sf_dir):
    g = grid(spark, sf_dir, True, beta=B, C=C, F=[4, 64, 512])
    return _frame(g, ["tbl", "beta", "C", "F"], finite=cal.min_noise_finite(c("beta"), c("n"), c("C"), features=c("F")), random=cal.min_noise_random(c("beta"), c("n"), c("C"), c("F") / 2))


@query("privacy_sweep", f"SELECT tbl, lam, C, F, round(4 * C * sqrt(F) / (lam * n), 9) AS beta FROM {sql_grid(True, lam=[0.001, 0.01, 0.1], C=C, F=[4, 64])}")
def privacy_sweep(spark, sf_dir):
    g = grid(spark, sf_dir, True, lam=[0.001, 0.01, 0.1], C=C, F=[4, 64])
    return _frame(g, ["tbl", "lam", "C", "F"], beta=cal.privacy_of(c("lam"), c("n"), c("C"), features=c("F")))


_CEIL = sql_grid(eps=E, delta=D, F=[4, 64, 512], phi=[0.5, 1])


@query("noise_ceiling_finite", f"SELECT eps, delta, F, phi, round(eps / (2 * phi * (F * ln(2::DOUBLE) + ln(1 / delta))), 9) AS lam FROM {_CEIL}")
def noise_ceiling_finite(spark, sf_dir):
    return _frame(grid(spark, eps=E, delta=D, F=[4, 64, 512], phi=[0.5, 1]), ["eps", "delta", "F", "phi"], lam=cal.max_noise_finite(c("eps"), c("delta"), c("F"), c("phi")))


@query("noise_ceiling_exact", "SELECT F::BIGINT AS F, 0.95::DOUBLE AS cdf_at_quantile, true AS above_chernoff FROM (VALUES (1), (4), (64), (512)) AS t(F)")
def noise_ceiling_exact(spark, sf_dir):
    rows = [(k, round(cal.erlang_cdf(k, cal.erlang_quantile(k, 0.95)), 9), cal.max_noise_finite(0.5, 0.05, k, exact_tail=True) >= cal.max_noise_finite(0.5, 0.05, k)) for k in (1, 4, 64, 512)]
    return spark.createDataFrame(rows, "F long, cdf_at_quantile double, above_chernoff boolean")


_DAYS = f"(SELECT * FROM (SELECT ts::DATE AS day, count(*)::DOUBLE AS n FROM events GROUP BY 1), {sql_grid(eps=E, F=[4, 64])})"


@query("failure_probability_sweep", f"SELECT day, eps, F, round(lam, 9) AS lam, round(least(1.0::DOUBLE, exp(F * ln(2::DOUBLE) - eps / (2 * lam))), 9) AS delta FROM (SELECT *, 4 * sqrt(F) / n AS lam FROM {_DAYS})")
def failure_probability_sweep(spark, sf_dir):
    """A release of each day's events at C = 1 and beta = 1: the noise that privacy asks for, and how often it passes eps."""
    days = load(spark, sf_dir, "events").groupBy(F.to_date("ts").alias("day")).agg(F.count("*").cast("double").alias("n"))
    g = days.crossJoin(F.broadcast(grid(spark, eps=E, F=[4, 64]))).withColumn("lam", cal.min_noise_finite(F.lit(1.0), c("n"), F.lit(1.0), features=c("F")))
    return _frame(g, ["day", "eps", "F"], lam=c("lam"), delta=cal.failure_probability(c("lam"), c("eps"), c("F")))


@query("noise_ceiling_random", f"SELECT eps, delta, m, round(least(eps / (16 * ln(2::DOUBLE) * sqrt(m)), eps * sqrt(m) / (8 * ln(2 / delta))), 9) AS lam FROM {sql_grid(eps=E, delta=D, m=[1, 4, 16, 64, 256, 1024])}")
def noise_ceiling_random(spark, sf_dir):
    return _frame(grid(spark, eps=E, delta=D, m=[1, 4, 16, 64, 256, 1024]), ["eps", "delta", "m"], lam=cal.max_noise_random(c("eps"), c("delta"), c("m")))


#: Diameter of the box around the features of each return flag's lines.
_BOX = f"""(SELECT flag, sqrt({" + ".join(f"(max(x[{k}]) - min(x[{k}])) * (max(x[{k}]) - min(x[{k}]))" for k in range(1, 5))}) AS diam
FROM (SELECT l_returnflag AS flag, [{", ".join(f"greatest(0.0::DOUBLE, least(1.0::DOUBLE, coalesce({v}, 0)))" for v in ("l_quantity / 50.0::DOUBLE", "l_extendedprice / 105000.0::DOUBLE", "l_discount / 0.1::DOUBLE", "l_tax / 0.08::DOUBLE"))}] AS x FROM lineitem) GROUP BY 1)"""


def _box(spark, sf_dir):
    x = lambda k: F.get("x", F.lit(k))
    width = [F.max(x(k)) - F.min(x(k)) for k in range(4)]
    return load(spark, sf_dir, "lineitem").select(c("l_returnflag").alias("flag"), lineitem_x().alias("x")).groupBy("flag").agg(F.sqrt(sum((w * w for w in width[1:]), width[0] * width[0])).alias("diam"))


@query("freq_count_kernel", f"SELECT flag, error, delta, greatest(1, ceil(4 * (4 + 2) / (error * error) * ln(256 * 4 * diam * diam / (delta * error * error))))::BIGINT AS m FROM {_BOX}, {sql_grid(error=[0.1, 0.5, 1], delta=D)}")
def freq_count_kernel(spark, sf_dir):
    """Frequencies for the kernel over the lines of each return flag: four features, and the diameter of their box."""
    g = _box(spark, sf_dir).crossJoin(F.broadcast(grid(spark, error=[0.1, 0.5, 1], delta=D)))
    return g.select("flag", "error", "delta", cal.frequencies_for_kernel_error(c("error"), F.lit(4.0), c("delta"), F.lit(4.0), c("diam")).cast("long").alias("m"))


_BUDGET = "least(1.0::DOUBLE, eps * eps / (4 * power(C + 2 * sqrt((C + C / 2) * C), 2)))"


@query("kernel_error_budget", f"SELECT eps, C, round({_BUDGET}, 9) AS error FROM {sql_grid(eps=E, C=C)}")
def kernel_error_budget(spark, sf_dir):
    return _frame(grid(spark, eps=E, C=C), ["eps", "C"], error=cal.kernel_error_budget(c("eps"), c("C"), c("C")))


_TH = "least(1.0::DOUBLE, power(eps, 4) / (16 * power(C + 2 * sqrt((C + C / 2) * C), 4)))"


@query("freq_count_utility", f"SELECT flag, eps, C, delta, greatest(1, ceil(4 * (4 + 2) / {_TH} * ln(512 * 4 * diam * diam / (delta * {_TH}))))::BIGINT AS m FROM {_BOX}, {sql_grid(eps=E, C=[0.1, 1], delta=D)}")
def freq_count_utility(spark, sf_dir):
    """Frequencies for usefulness over the lines of each return flag."""
    g = _box(spark, sf_dir).crossJoin(F.broadcast(grid(spark, eps=E, C=[0.1, 1], delta=D)))
    return g.select("flag", "eps", "C", "delta", cal.frequencies_needed(cal.theta(c("eps"), c("C"), c("C")), F.lit(4.0), c("delta"), F.lit(4.0), c("diam")).cast("long").alias("m"))


@query("theta_hinge_sweep", f"SELECT eps, C, round(least(1.0::DOUBLE, power(eps, 4) / (4096 * power(C, 4))), 9) AS stated, round(least(1.0::DOUBLE, power(eps, 4) / (16 * power(1 + sqrt(6::DOUBLE), 4) * power(C, 4))), 9) AS exact FROM {sql_grid(eps=E, C=C)}")
def theta_hinge_sweep(spark, sf_dir):
    return _frame(grid(spark, eps=E, C=C), ["eps", "C"], stated=cal.theta_hinge(c("eps"), c("C")), exact=cal.theta_hinge(c("eps"), c("C"), "exact"))


_PLAN = sql_grid(True, beta=[0.1, 1, 10], eps=[0.1, 0.5, 1], C=[0.1, 1], F=[4, 64])


@query("release_plan_tables", f"""SELECT tbl, beta, eps, C, F, round(lo, 9) AS lam_min, round(hi, 9) AS lam_max, lo <= hi AS feasible, ceil(4 * C * sqrt(F) / (beta * hi))::BIGINT AS rows_needed
FROM (SELECT *, 4 * C * sqrt(F) / (beta * n) AS lo, eps / (2 * (F * ln(2::DOUBLE) + ln(20::DOUBLE))) AS hi FROM {_PLAN})""")
def release_plan_tables(spark, sf_dir):
    g = grid(spark, sf_dir, True, beta=[0.1, 1, 10], eps=[0.1, 0.5, 1], C=[0.1, 1], F=[4, 64])
    lo = cal.min_noise_finite(c("beta"), c("n"), c("C"), features=c("F"))
    hi = cal.max_noise_finite(c("eps"), F.lit(0.05), c("F"))
    need = F.ceil(cal.weight_sensitivity(c("C"), F.lit(1.0), norm=1, features=c("F")) / (c("beta") * hi))
    return g.select("tbl", "beta", "eps", "C", "F", _r(lo).alias("lam_min"), _r(hi).alias("lam_max"), (lo <= hi).alias("feasible"), need.cast("long").alias("rows_needed"))


def _sql_m(eps: str, delta: str, C: str, d: str, moment: str) -> str:
    """SQL of the frequencies that usefulness for the hinge loss asks for, on a domain of diameter 2."""
    th = f"least(1.0::DOUBLE, power({eps}, 4) / (4096 * power({C}, 4)))"
    return f"greatest(1.0::DOUBLE, ceil(4 * ({d} + 2) / {th} * ln(512 * {moment} * 4 / ({delta} * {th}))))"


_SQL_CEILING = "least(eps / (16 * ln(2::DOUBLE) * sqrt(m)), eps * sqrt(m) / (8 * ln(2 / delta)))"
_RP = dict(beta=[0.1, 1, 10], eps=[0.5, 1], C=[0.1, 1], d=[4, 64])


@query("release_plan_random", f"""SELECT tbl, beta, eps, C, d, round(log10(m), 9) AS log_m, round(lo, 9) AS lam_min, round(hi * 1e6, 9) AS lam_max_e6, lo <= hi AS feasible, round(log10(ceil(power(2.0::DOUBLE, 2.5) * C * sqrt(m) / (beta * hi))), 9) AS log_rows_needed
FROM (SELECT *, power(2.0::DOUBLE, 2.5) * C * sqrt(m) / (beta * n) AS lo, {_SQL_CEILING} AS hi FROM (SELECT *, 0.05::DOUBLE AS delta, {_sql_m("eps", "0.05::DOUBLE", "C", "d", "d")} AS m FROM {sql_grid(True, **_RP)}))""")
def release_plan_random(spark, sf_dir):
    """RBF of width 1 on a domain of diameter 2: the frequencies are picked, not given."""
    g = grid(spark, sf_dir, True, **_RP)
    p = cal.plan_release_random(c("beta"), c("eps"), F.lit(0.05), c("C"), c("n"), c("d"), c("d"), F.lit(2.0))
    return g.select("tbl", "beta", "eps", "C", "d", _r(F.log10(p["m"])).alias("log_m"), _r(p["lam_min"]).alias("lam_min"), _r(p["lam_max"] * 1e6).alias("lam_max_e6"), p["feasible"].alias("feasible"), _r(F.log10(p["rows_needed"])).alias("log_rows_needed"))


_UP = dict(eps=E, delta=D, C=C, sigma=[0.5, 1])


@query("upper_bound_sweep", f"""SELECT tbl, eps, delta, C, sigma, round(log10(m), 7) AS log_m, round(log10(power(2.0::DOUBLE, 2.5) * C * sqrt(m) / ({_SQL_CEILING} * n)), 7) AS log_exact,
round(sqrt(ln(1 / (delta * eps))) * (ln(1 / eps) + power(ln(1 / (delta * eps)), 2)) / (power(eps, 3) * n), 7) AS published FROM (SELECT *, {_sql_m("eps", "delta", "C", "4", "(4 / (sigma * sigma))")} AS m FROM {sql_grid(True, **_UP)})""")
def upper_bound_sweep(spark, sf_dir):
    """RBF in four dimensions, diameter 2: what the mechanism reaches with the frequencies that make it useful, beside the stated rate."""
    g = grid(spark, sf_dir, True, **_UP)
    m, exact = optimal.upper_rbf(c("eps"), c("delta"), c("C"), c("n"), c("sigma"), F.lit(4.0))
    return g.select("tbl", "eps", "delta", "C", "sigma", F.round(F.log10(m), 7).alias("log_m"), F.round(F.log10(exact), 7).alias("log_exact"), F.round(optimal.published_rate(c("eps"), c("delta"), c("n")), 7).alias("published"))


@query("upper_bound_finite", f"SELECT tbl, eps, delta, C, F, round(8 * C * sqrt(F) * (F * ln(2::DOUBLE) + ln(1 / delta)) / (eps * n), 7) AS beta FROM {sql_grid(True, eps=E, delta=D, C=C, F=[4, 64])}")
def upper_bound_finite(spark, sf_dir):
    g = grid(spark, sf_dir, True, eps=E, delta=D, C=C, F=[4, 64])
    return g.select("tbl", "eps", "delta", "C", "F", F.round(optimal.upper_finite(c("eps"), c("delta"), c("C"), c("n"), c("F")), 7).alias("beta"))


_LOW = sql_grid(True, eps=[1e-7, 1e-5, 1e-3, 0.1], delta=D, C=C)


@query("lower_bound_linear", f"SELECT tbl, eps, delta, C, round(CASE WHEN eps < sqrt(C) / (2 * n) THEN ln((1 - delta) / delta) END, 9) AS beta FROM {_LOW}")
def lower_bound_linear(spark, sf_dir):
    return _frame(grid(spark, sf_dir, True, eps=[1e-7, 1e-5, 1e-3, 0.1], delta=D, C=C), ["tbl", "eps", "delta", "C"], beta=optimal.lower_linear(c("eps"), c("delta"), c("C"), c("n")))


_RBF = sql_grid(True, eps=[1e-7, 1e-5, 1e-3], delta=D, C=C, sigma=[0.1, 0.25, 0.5, 0.8, 1])
_N = "floor(2 / sigma * sqrt(2 / ln(2::DOUBLE)))"


@query("lower_bound_rbf", f"SELECT tbl, eps, delta, C, sigma, round(CASE WHEN n > C AND eps < C / (4 * n) AND sigma < sqrt(1 / (2 * ln(2::DOUBLE))) THEN ln((1 - delta) * ({_N} - 1) / delta) END, 9) AS beta FROM {_RBF}")
def lower_bound_rbf(spark, sf_dir):
    g = grid(spark, sf_dir, True, eps=[1e-7, 1e-5, 1e-3], delta=D, C=C, sigma=[0.1, 0.25, 0.5, 0.8, 1])
    return _frame(g, ["tbl", "eps", "delta", "C", "sigma"], beta=optimal.lower_rbf(c("eps"), c("delta"), c("C"), c("n"), c("sigma")))


_IMP = sql_grid(True, eps=[1e-7, 1e-5, 0.1], delta=[0.001, 0.01, 0.1], beta=[0.5, 2, 5, 10], C=[1])


@query("impossibility_grid", f"SELECT tbl, eps, delta, beta, C, eps < sqrt(C) / (2 * n) AND delta < 1 / (1 + exp(beta)) AS impossible, eps < sqrt(C) / (2 * n) AND delta < exp(-beta) AS printed FROM {_IMP}")
def impossibility_grid(spark, sf_dir):
    g = grid(spark, sf_dir, True, eps=[1e-7, 1e-5, 0.1], delta=[0.001, 0.01, 0.1], beta=[0.5, 2, 5, 10], C=[1])
    a = (c("eps"), c("delta"), c("beta"), c("C"), c("n"))
    return g.select("tbl", "eps", "delta", "beta", "C", optimal.is_impossible(*a).alias("impossible"), optimal.is_impossible(*a, corrected=False).alias("printed"))


_IMPR = dict(eps=[1e-7, 1e-5, 0.1], delta=[0.001, 0.01, 0.1], beta=[0.5, 2, 5, 10], sigma=[0.25, 0.5, 1])


@query("impossibility_rbf", f"SELECT tbl, eps, delta, beta, sigma, n > 1 AND eps < 1 / (4 * n) AND sigma < sqrt(1 / (2 * ln(2::DOUBLE))) AND ln((1 - delta) * ({_N} - 1) / delta) > beta AS impossible FROM {sql_grid(True, **_IMPR)}")
def impossibility_rbf(spark, sf_dir):
    g = grid(spark, sf_dir, True, **_IMPR)
    return g.select("tbl", "eps", "delta", "beta", "sigma", optimal.is_impossible_rbf(c("eps"), c("delta"), c("beta"), F.lit(1.0), c("n"), c("sigma")).alias("impossible"))


_BL, _BR = dict(eps=[1e-7, 1e-5, 1e-3, 0.5], delta=D, C=[0.1, 1], d=[4, 64]), dict(eps=[1e-5, 1e-3, 0.5], delta=D, C=[0.1, 1], sigma=[0.25, 0.5, 1], d=[4])


@query("privacy_bracket", f"""SELECT 'linear' AS kernel, tbl, eps, delta, C, d, NULL::DOUBLE AS sigma, NULL::DOUBLE AS log_m, round(lower, 6) AS lower, round(log10(upper), 6) AS log_upper, coalesce(lower <= upper, true) AS holds FROM
(SELECT *, CASE WHEN eps < sqrt(C) / (2 * n) THEN ln((1 - delta) / delta) END AS lower, 8 * C * sqrt(d) * (d * ln(2::DOUBLE) + ln(1 / delta)) / (eps * n) AS upper FROM {sql_grid(True, **_BL)})
UNION ALL SELECT 'rbf', tbl, eps, delta, C, d, sigma, round(log10(m), 6), round(lower, 6), round(log10(upper), 6), coalesce(lower <= upper, true) FROM
(SELECT *, CASE WHEN n > C AND eps < C / (4 * n) AND sigma < sqrt(1 / (2 * ln(2::DOUBLE))) THEN ln((1 - delta) * ({_N} - 1) / delta) END AS lower, power(2.0::DOUBLE, 2.5) * C * sqrt(m) / ({_SQL_CEILING} * n) AS upper
FROM (SELECT *, {_sql_m("eps", "delta", "C", "d", "(d / (sigma * sigma))")} AS m FROM {sql_grid(True, **_BR)}))""")
def privacy_bracket(spark, sf_dir):
    """Lower and upper bound of the best privacy, for one kernel at a time."""
    a = optimal.bracket_linear(grid(spark, sf_dir, True, **_BL)).withColumns({"kernel": F.lit("linear"), "sigma": F.lit(None).cast("double"), "m": F.lit(None).cast("double")})
    b = optimal.bracket_rbf(grid(spark, sf_dir, True, **_BR)).withColumn("kernel", F.lit("rbf"))
    said = ["kernel", "tbl", "eps", "delta", "C", "d", "sigma", F.round(F.log10("m"), 6).alias("log_m"), F.round("lower", 6).alias("lower"), F.round(F.log10("upper"), 6).alias("log_upper"), F.coalesce(F.col("lower") <= F.col("upper"), F.lit(True)).alias("holds")]
    return a.select(*said).union(b.select(*said))


@query("kernel_cost", f"SELECT tbl, d, m, d * n * n AS direct, m * n * n AS random FROM {sql_grid(True, d=[4, 64], m=[16, 256])}")
def kernel_cost(spark, sf_dir):
    from ..operators.baselines import cost_model

    a, b = cost_model(c("n"), c("d"), c("m"))
    return grid(spark, sf_dir, True, d=[4, 64], m=[16, 256]).select("tbl", "d", "m", a.alias("direct"), b.alias("random"))


_Z = [x / 4 for x in range(-12, 13)]


@query("loss_table", f"""SELECT y, f, round(greatest(0.0, 1 - y * f), 9) AS hinge, round((y - f) * (y - f), 9) AS square, round(ln(1 + exp(-y * f)), 9) AS logistic,
round(CASE WHEN y * f < 1 THEN -y ELSE 0 END, 9) + 0.0 AS hinge_slope, round(2 * (f - y), 9) + 0.0 AS square_slope, round(-y / (1 + exp(y * f)), 9) AS logistic_slope FROM {sql_grid(y=[-1, 1], f=_Z)}""")
def loss_table(spark, sf_dir):
    y, f = c("y"), c("f")
    cols = {k: x.value(y, f) for k, x in losses.LOSSES.items()} | {f"{k}_slope": x.slope(y, f) for k, x in losses.LOSSES.items()}
    return _frame(grid(spark, y=[-1, 1], f=_Z), ["y", "f"], **cols)


@query("loss_constants", f"SELECT C, kappa, 1.0::DOUBLE AS hinge, 1.0::DOUBLE AS logistic, round(2 * (1 + kappa * sqrt(2 * C)), 9) AS square, C AS hinge_dual, round(C * 2 * (1 + kappa * sqrt(2 * C)), 9) AS square_dual FROM {sql_grid(C=C, kappa=[1, 2])}")
def loss_constants(spark, sf_dir):
    rows = [(a, k, losses.Hinge.lipschitz(a, k), losses.Logistic.lipschitz(a, k), round(losses.Square.lipschitz(a, k), 9), losses.Hinge.dual_bound(a, k), round(losses.Square.dual_bound(a, k), 9)) for a in map(float, C) for k in (1.0, 2.0)]
    return spark.createDataFrame(rows, "C double, kappa double, hinge double, logistic double, square double, hinge_dual double, square_dual double")


@query("group_privacy", f"SELECT beta, k, users, beta * k AS level FROM (SELECT k, count(*) AS users FROM (SELECT user_id, count(*)::DOUBLE AS k FROM events GROUP BY 1) GROUP BY 1), {sql_grid(beta=B)}")
def group_privacy(spark, sf_dir):
    """What a level for one event means for users of k events, and how many there are."""
    from ..operators.ledger import group_privacy as level

    users = load(spark, sf_dir, "events").groupBy("user_id").agg(F.count("*").cast("double").alias("k")).groupBy("k").agg(F.count("*").alias("users"))
    return users.crossJoin(F.broadcast(grid(spark, beta=B))).select("beta", "k", "users", level(c("beta"), c("k")).alias("level"))
