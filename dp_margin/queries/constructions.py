"""The adversarial databases and what follows from them."""

from __future__ import annotations


from pyspark.sql import functions as F

from ..functions.optimal import packing_size
from ..operators import adversarial as adv
from ..operators import solvers
from ..sources.examples import collapse_duplicates as collapse
from ..sources.examples import events, pm
from ..sources.tables import load
from .base import grid, query, sql_grid
from .fits import _sql_1d

N, C, EPS = 100, 1.0, 0.002
_PAIR = f"""(SELECT db, i AS row_id, CASE WHEN i = {N} - 1 THEN {N} * {EPS}::DOUBLE WHEN i < {N} // 2 THEN -2 * {N} * {EPS}::DOUBLE ELSE 2 * {N} * {EPS}::DOUBLE END AS x,
CASE WHEN i = {N} - 1 THEN CASE WHEN db = 1 THEN -1.0::DOUBLE ELSE 1.0::DOUBLE END WHEN i < {N} // 2 THEN -1.0::DOUBLE ELSE 1.0::DOUBLE END AS y FROM range({N}) AS t(i), (SELECT unnest([1, 2]) AS db))"""


#: The same pair over customers: the sign of their account is the label, and n eps / C is 0.2.
_CUSTOMERS = """(SELECT db, c_custkey AS row_id, CASE WHEN c_custkey = last THEN 0.2::DOUBLE ELSE 0.4::DOUBLE * side END AS x, CASE WHEN c_custkey = last THEN CASE WHEN db = 1 THEN -1.0::DOUBLE ELSE 1.0::DOUBLE END ELSE side END AS y
FROM (SELECT c_custkey, CASE WHEN c_acctbal > 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS side FROM customer), (SELECT max(c_custkey) AS last FROM customer), (SELECT unnest([1, 2]) AS db))"""


def _customers(spark, sf_dir):
    return load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("row_id"), pm(F.col("c_acctbal") > 0).alias("y"))


@query("hard_pair_linear_rows", f"SELECT db, row_id, round(x, 12) AS x, y FROM {_CUSTOMERS}")
def hard_pair_linear_rows(spark, sf_dir):
    """The hard pair over all customers."""
    return adv.hard_pair_of(_customers(spark, sf_dir), C).select("db", "row_id", F.round("x", 12).alias("x"), "y")


_W = "SELECT C, n, round(C * (2 * n * e / C * (n - 2) + n * e / C) / n, 9) AS w1, round(C * (2 * n * e / C * n - n * e / C) / n, 9) AS w2, round(2 * e, 9) AS difference FROM (SELECT C, n, 0.4 * sqrt(C) / (2 * n) AS e FROM {g})"


@query("hard_pair_linear_weights", _W.format(g="(SELECT C, n FROM (SELECT unnest([0.5, 1, 4]::DOUBLE[]) AS C), (SELECT unnest([10, 100]::DOUBLE[]) AS n UNION ALL SELECT count(*)::DOUBLE FROM customer UNION ALL SELECT count(*)::DOUBLE FROM orders))"))
def hard_pair_linear_weights(spark, sf_dir):
    n = grid(spark, n=[10, 100])
    for t in ("customer", "orders"):
        n = n.union(load(spark, sf_dir, t).agg(F.count("*").cast("double").alias("n")))
    g = grid(spark, C=[0.5, 1, 4]).crossJoin(F.broadcast(n)).withColumn("e", 0.4 * F.sqrt("C") / (2 * F.col("n")))
    w1, w2 = adv.hard_pair_weights(F.col("n"), F.col("C"), F.col("e"))
    return g.select("C", "n", F.round(w1, 9).alias("w1"), F.round(w2, 9).alias("w2"), F.round(w2 - w1, 9).alias("difference"))


@query("hinge_1d_hard_pair", " UNION ALL ".join(f"SELECT {db} AS db, w FROM ({_sql_1d(f'(SELECT x * y AS s FROM {_PAIR} WHERE db = {db})', '1.0', f'SELECT {N}')})" for db in (1, 2)))
def hinge_1d_hard_pair(spark, sf_dir):
    """The exact solver on both databases: their minimisers differ by 2 eps."""
    p, out = adv.hard_pair_linear(spark, N, C, EPS), None
    for db in (1, 2):
        own = p.where(F.col("db") == db).select("row_id", F.array("x").alias("x"), "y")
        row = solvers.fit_hinge_1d(own, C).select(F.lit(db).alias("db"), F.round("w", 8).alias("w"))
        out = row if out is None else out.union(row)
    return out


@query("fig61_curve", f"""SELECT db, round(b, 9) AS w, round(k * below, 9) + 0.0 AS below, round(k * above, 9) + 0.0 AS above FROM (SELECT db, b, {C} / (SELECT count(*) FROM customer) AS k,
sum(p) OVER (PARTITION BY db ORDER BY b DESC ROWS UNBOUNDED PRECEDING) + coalesce(sum(g) OVER (PARTITION BY db ORDER BY b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below,
coalesce(sum(p) OVER (PARTITION BY db ORDER BY b DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + sum(g) OVER (PARTITION BY db ORDER BY b ROWS UNBOUNDED PRECEDING) AS above
FROM (SELECT db, 1 / s AS b, CASE WHEN s > 0 THEN sum(s) ELSE 0 END AS p, CASE WHEN s < 0 THEN sum(s) ELSE 0 END AS g FROM (SELECT db, x * y AS s FROM {_CUSTOMERS}) GROUP BY db, s))""")
def fig61_curve(spark, sf_dir):
    """The step functions of the hard pair over all customers."""
    own = _customers(spark, sf_dir)
    t = adv.fixed_point_curve(adv.hard_pair_of(own, C), C, own.count())
    return t.select("db", F.round("w", 9).alias("w"), (F.round("below", 9) + 0.0).alias("below"), (F.round("above", 9) + 0.0).alias("above"))


PS, PC = 0.5, 2.0
_SIZE = packing_size(PS)


@query("hard_packing_rows", f"""SELECT db::INTEGER AS db, c_custkey AS row_id, CASE WHEN c_custkey = last THEN round(cos(2 * pi() * db / {_SIZE}), 9) + 0.0 ELSE 0.0::DOUBLE END AS x1,
CASE WHEN c_custkey = last THEN round(sin(2 * pi() * db / {_SIZE}), 9) + 0.0 ELSE 0.0::DOUBLE END AS x2, CASE WHEN c_custkey = last THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM range({_SIZE}) AS s(db), customer, (SELECT max(c_custkey) AS last FROM customer)""")
def hard_packing_rows(spark, sf_dir):
    """The packing over all customers."""
    x = lambda k: (F.round(F.get("x", F.lit(k)), 9) + 0.0).alias(f"x{k + 1}")
    return adv.hard_packing_of(_customers(spark, sf_dir), PS).select("db", "row_id", x(0), x(1), "y")


_SIGMAS = (0.1, 0.25, 0.5, 0.8)


@query("hard_packing_gaps", f"""SELECT segment, n, sigma, size, round({PC} / n * (1 - exp(-2 / (sigma * sigma) * power(sin(pi() / size), 2))), 9) AS separation,
{PC} / n * (1 - exp(-2 / (sigma * sigma) * power(sin(pi() / size), 2))) >= {PC} / (2 * n) AS apart
FROM (SELECT segment, n, sigma, floor(2 / sigma * sqrt(2 / ln(2::DOUBLE)))::BIGINT AS size FROM (SELECT c_mktsegment AS segment, count(*)::DOUBLE AS n FROM customer GROUP BY 1), {sql_grid(sigma=_SIGMAS)})""")
def hard_packing_gaps(spark, sf_dir):
    """Least pairwise distance, over the customers of each segment, at the points where the packing's classifiers differ most: at one database's own last row."""
    own = load(spark, sf_dir, "customer").select(F.col("c_mktsegment").alias("segment"), F.col("c_custkey").alias("row_id"))
    n = own.groupBy("segment").agg(F.count("*").cast("double").alias("n"))
    last, out = own.agg(F.max("row_id").alias("row_id")), None
    for sigma in _SIGMAS:
        k = packing_size(sigma)
        p = adv.hard_packing_of(last, sigma).select("db", "x")
        q = p.select(F.col("db").alias("other"), F.col("x").alias("z"))
        far = F.aggregate(F.zip_with("x", "z", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda a, b: a + b)
        least = p.join(F.broadcast(q), F.col("db") < F.col("other")).agg(F.min(1 - F.exp(-far / (2 * sigma * sigma))).alias("g"))
        gap = F.lit(PC) / F.col("n") * F.col("g")
        row = n.crossJoin(F.broadcast(least)).select("segment", "n", F.lit(sigma).alias("sigma"), F.lit(k).cast("long").alias("size"), F.round(gap, 9).alias("separation"), (gap >= PC / (2 * F.col("n"))).alias("apart"))
        out = row if out is None else out.union(row)
    return out


@query("packing_dual_cases", f"""SELECT C, n, gamma, round(CASE WHEN (1 + gamma) / (1 - gamma * gamma) <= C / n THEN (1 + gamma) / ((n - 1) * (1 - gamma * gamma)) WHEN (1 + gamma * C / n) / (n - 1) <= C / n THEN (1 + gamma * C / n) / (n - 1) ELSE C / n END, 9) AS alpha1,
round(CASE WHEN (1 + gamma) / (1 - gamma * gamma) <= C / n THEN (1 + gamma) / (1 - gamma * gamma) ELSE C / n END, 9) AS alphan FROM {sql_grid(C=[1, 2, 19], n=[20, 200], gamma=[0.000335463, 0.1, 0.135335283, 0.457833362])}""")
def packing_dual_cases(spark, sf_dir):
    g = grid(spark, C=[1, 2, 19], n=[20, 200], gamma=[0.000335463, 0.1, 0.135335283, 0.457833362])
    a, b, _ = adv.packing_dual(F.col("C"), F.col("n"), F.col("gamma"))
    return g.select("C", "n", "gamma", F.round(a, 9).alias("alpha1"), F.round(b, 9).alias("alphan"))


@query("neighbour_diff", "SELECT 1 AS db, 99 AS row_id UNION ALL SELECT 2, 99")
def neighbour_diff(spark, sf_dir):
    """The rows that only one of two neighbours has: exactly one each."""
    p = adv.hard_pair_linear(spark, N, C, EPS)
    a, b = (p.where(F.col("db") == d).drop("db") for d in (1, 2))
    one = a.exceptAll(b).select(F.lit(1).alias("db"), F.col("row_id").cast("int").alias("row_id"))
    return one.unionByName(b.exceptAll(a).select(F.lit(2).alias("db"), F.col("row_id").cast("int").alias("row_id")))


@query("collapse_duplicates", """SELECT min(event_id) AS row_id, round(x, 9) AS x, y, count(*)::DOUBLE AS weight FROM (SELECT event_id, greatest(0.0::DOUBLE, least(1.0::DOUBLE, coalesce(value, 0) / 100.0::DOUBLE)) AS x,
CASE WHEN event_type = 'purchase' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM events) GROUP BY x, y""")
def collapse_duplicates(spark, sf_dir):
    """Events of equal value and label as one weighted row."""
    return collapse(events(spark, sf_dir)).select("row_id", F.round(F.get("x", F.lit(0)), 9).alias("x"), "y", "weight")
