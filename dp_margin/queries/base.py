"""Registration of queries and the SQL snippets that their oracles share."""

from __future__ import annotations

QUERIES: dict = {}
ORACLES: dict = {}
#: Tables whose row counts enter the sweeps.
COUNTED = ("lineitem", "embeddings", "documents", "events", "orders")


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def grid(spark, sf_dir=None, counts: bool = False, **lists):
    """Cross product of small public lists, and of the tables' row counts."""
    from functools import reduce

    from pyspark.sql import functions as F

    from ..sources.tables import load

    frames = [spark.createDataFrame([(float(x),) for x in values], f"{k} double") for k, values in lists.items()]
    if counts:
        frames.append(reduce(lambda a, b: a.union(b), [load(spark, sf_dir, t).agg(F.count("*").cast("double").alias("n")).select(F.lit(t).alias("tbl"), "n") for t in COUNTED]))
    return reduce(lambda a, b: a.crossJoin(F.broadcast(b)), frames)


def sql_grid(counts: bool = False, **lists) -> str:
    parts = [f"(SELECT unnest([{', '.join(repr(float(x)) for x in v)}]::DOUBLE[]) AS {k})" for k, v in lists.items()]
    if counts:
        parts.append("(" + " UNION ALL ".join(f"SELECT '{t}' AS tbl, count(*)::DOUBLE AS n FROM {t}" for t in COUNTED) + ")")
    return "(SELECT * FROM " + ", ".join(f"{p} AS g{i}" for i, p in enumerate(parts)) + ")"


def sql_u(seed: int, stream: str, i: str) -> str:
    """SQL for the counter-based uniform."""
    return f"((CAST('0x' || substr(md5('{seed}:{stream}:' || CAST({i} AS VARCHAR)), 1, 13) AS BIGINT)::DOUBLE + 0.5) / 4503599627370496.0::DOUBLE)"


def sql_laplace(u: str, lam: str) -> str:
    return f"(-({lam}) * sign(({u}) - 0.5) * ln(1 - 2 * abs(({u}) - 0.5)))"


#: lineitem's features and derived label in SQL.
SQL_LINEITEM = """(SELECT l_orderkey * 8 + l_linenumber AS row_id,
  [greatest(0.0::DOUBLE, least(1.0::DOUBLE, l_quantity / 50.0::DOUBLE)), greatest(0.0::DOUBLE, least(1.0::DOUBLE, l_extendedprice / 105000.0::DOUBLE)),
   greatest(0.0::DOUBLE, least(1.0::DOUBLE, l_discount / 0.1::DOUBLE)), greatest(0.0::DOUBLE, least(1.0::DOUBLE, l_tax / 0.08::DOUBLE))] AS x,
  CASE WHEN l_extendedprice * (1 - l_discount) > 50000 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM lineitem)"""
SQL_EMBEDDINGS = """(SELECT vec_id AS row_id, list_transform(e, lambda v: v * CASE WHEN nrm > 1 THEN 1 / nrm ELSE 1.0::DOUBLE END) AS x, CASE WHEN label < 5 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y
  FROM (SELECT vec_id, label, embedding::DOUBLE[] AS e, sqrt(list_sum(list_transform(embedding::DOUBLE[], lambda v: v * v))) AS nrm FROM embeddings))"""
