"""Kernels, frequencies, feature maps and randomness."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions import rng
from ..functions import vectors as v
from ..operators import blocks
from ..operators.measure import kernel_error_blocks
from ..sources import examples
from ..sources.tables import load
from .base import SQL_EMBEDDINGS, SQL_LINEITEM, query, sql_laplace, sql_u

_PAIRS = f"(SELECT a.row_id AS i, b.row_id AS j, a.x AS x, b.x AS z FROM {SQL_EMBEDDINGS} a, {SQL_EMBEDDINGS} b WHERE a.row_id <> b.row_id)"
_DIFF = "list_transform(list_zip(x, z), lambda p: p[1] - p[2])"
_ROWS = "SELECT i, count(*) AS others, round(sum(k), 6) AS total, round(min(k), 9) AS least, round(max(k), 9) AS most FROM (SELECT i, {} AS k FROM {}) GROUP BY i".format


def _rows(spark, sf_dir, matrix):
    """Every row with every other, in blocks: a row of the kernel matrix as its sum, least and largest entry besides the diagonal's."""
    m = blocks.row_measures(examples.embeddings(spark, sf_dir), matrix)
    return m.select("i", "others", F.round("total", 6).alias("total"), F.round("least", 9).alias("least"), F.round("most", 9).alias("most"))


def _kernel(kernel):
    return lambda spark, sf_dir: _rows(spark, sf_dir, lambda x, z: blocks.gram(x, z, kernel))


query("kernel_rbf_rows", _ROWS(f"exp(-list_sum(list_transform({_DIFF}, lambda t: t * t)) / 2)", _PAIRS))(_kernel(K.rbf()))
query("kernel_laplacian_rows", _ROWS(f"exp(-list_sum(list_transform({_DIFF}, lambda t: abs(t))))", _PAIRS))(_kernel(K.laplacian()))
query("kernel_cauchy_rows", _ROWS(f"list_product(list_transform({_DIFF}, lambda t: 1 / (1 + t * t)))", _PAIRS))(_kernel(K.cauchy_kernel()))
_TRIANGLE = K.translation_invariant("triangle", lambda x, z: F.greatest(F.lit(0.0), 1 - v.sup(F.zip_with(x, z, lambda a, b: a - b))), lambda t: np.maximum(0.0, 1 - np.abs(t).max(-1)), None, float("inf"))
query("kernel_custom", _ROWS(f"greatest(0.0::DOUBLE, 1 - list_max(list_transform({_DIFF}, lambda t: abs(t))))", _PAIRS))(_kernel(_TRIANGLE))

SEED, DIM, M = 7, 4, 16
_NORMAL = f"sqrt(-2 * ln({sql_u(SEED, 'fa', 'i')})) * cos(2 * pi() * {sql_u(SEED, 'fb', 'i')})"


def _freq_sql(rho: str, digits: int = 9) -> str:
    """Frequencies, and the mean of each one's two features over lineitem."""
    freq = f"(SELECT i // {DIM} AS j, i % {DIM} AS coord, {rho} AS rho FROM range({M * DIM}) AS t(i))"
    rows = f"SELECT j, {' + '.join(f'x[{k}] * r[{k}]' for k in range(1, DIM + 1))} AS p FROM {SQL_LINEITEM}, (SELECT j, list(rho ORDER BY coord) AS r FROM {freq} GROUP BY j)"
    return f"SELECT j, coord, round(rho, {digits}) AS rho, mean_cos, mean_sin FROM {freq} JOIN (SELECT j, round(avg(cos(p)), 7) AS mean_cos, round(avg(sin(p)), 7) AS mean_sin FROM ({rows}) GROUP BY j) USING (j)"


def _freq(kernel, digits=9):
    """The kernel's frequencies for lineitem's features, and what each one's two features are on average over the table: one pass."""

    def run(spark, sf_dir):
        phase = [v.dot_literal(F.col("x"), r) for r in K.frequency_matrix(spark, kernel, DIM, M, SEED)]
        means = [F.struct(F.lit(j).cast("long").alias("j"), F.round(F.avg(F.cos(p)), 7).alias("mean_cos"), F.round(F.avg(F.sin(p)), 7).alias("mean_sin")) for j, p in enumerate(phase)]
        seen = examples.lineitem(spark, sf_dir).agg(F.array(*means).alias("m")).select(F.inline("m"))
        return K.sample_frequencies(spark, kernel, DIM, M, SEED).join(F.broadcast(seen), "j").select("j", "coord", F.round("rho", digits).alias("rho"), "mean_cos", "mean_sin")

    return run


query("freq_rbf", _freq_sql(f"{_NORMAL} / 0.5"))(_freq(K.rbf(0.5)))
query("freq_laplacian", _freq_sql(f"tan(pi() * ({sql_u(SEED, 'fa', 'i')} - 0.5))", 6))(_freq(K.laplacian(), 6))
query("freq_cauchy", _freq_sql(sql_laplace(sql_u(SEED, "fa", "i"), "1.0")))(_freq(K.cauchy_kernel()))

# random features of embeddings: frequencies of 64 dimensions
_F64 = f"(SELECT i // 64 AS f, list(sqrt(-2 * ln({sql_u(SEED, 'fa', 'i')})) * cos(2 * pi() * {sql_u(SEED, 'fb', 'i')}) ORDER BY i) AS rho FROM range({{m}} * 64) AS t(i) GROUP BY 1)"


@query("rff_map_embeddings", f"""SELECT row_id, 2 * f + part AS pos, round(CASE WHEN part = 0 THEN cos(p) ELSE sin(p) END / sqrt(8), 9) AS value
FROM (SELECT row_id, f, list_dot_product(x, rho) AS p FROM {SQL_EMBEDDINGS}, {_F64.format(m=8)}), (SELECT unnest([0, 1]) AS part)""")
def rff_map_embeddings(spark, sf_dir):
    rho = K.frequency_matrix(spark, K.rbf(), 64, 8, SEED)
    e = examples.embeddings(spark, sf_dir)
    return e.select("row_id", F.posexplode(K.trig_map(F.col("x"), rho)).alias("pos", "value")).select("row_id", F.col("pos").cast("long").alias("pos"), F.round("value", 9).alias("value"))


@query("approx_kernel_rows", _ROWS("khat", f"(SELECT i, j, avg(cos(list_dot_product(rho, {_DIFF}))) AS khat FROM {_PAIRS}, {_F64.format(m=16)} GROUP BY i, j)"))
def approx_kernel_rows(spark, sf_dir):
    rho = K.frequency_matrix(spark, K.rbf(), 64, 16, SEED)
    return _rows(spark, sf_dir, lambda x, z: blocks.gram(x, z, None, rho))


_KERR = " UNION ALL ".join(
    f"""SELECT {m}::BIGINT AS m, count(*) AS pairs, round(max(e), 6) AS max_error, round(avg(e), 6) AS mean_error FROM (SELECT abs(any_value(exp(-list_sum(list_transform({_DIFF}, lambda t: t * t)) / 2)) - avg(cos(list_dot_product(rho, {_DIFF})))) AS e
FROM {_PAIRS}, {_F64.format(m=m)} WHERE i < j GROUP BY i, j)"""
    for m in (16, 64)
)


def _errors(spark, sf_dir, sizes):
    rhos = [K.frequency_matrix(spark, K.rbf(), 64, m, SEED) for m in sizes]
    e = kernel_error_blocks(examples.embeddings(spark, sf_dir), K.rbf(), rhos)
    return e.select("m", "pairs", F.round("max_error", 6).alias("max_error"), F.round("mean_error", 6).alias("mean_error"))


@query("kernel_error_embeddings", _KERR)
def kernel_error_embeddings(spark, sf_dir):
    """The uniform kernel error over all pairs of the table, in blocks, as the number of frequencies grows."""
    return _errors(spark, sf_dir, (16, 64))


@query("kernel_error_wide")
def kernel_error_wide(spark, sf_dir):
    """The same for more frequencies than SQL would take; a test holds it against all pairs in numpy."""
    return _errors(spark, sf_dir, (256, 1024))


@query("rng_uniform", f"SELECT i, round({sql_u(7, 'lap', 'i')}, 12) AS u FROM range(1000) AS t(i)")
def rng_uniform(spark, sf_dir):
    return spark.range(1000).select(F.col("id").alias("i"), F.round(rng.uniform(7, "lap", F.col("id")), 12).alias("u"))


@query("laplace_noise_table", f"SELECT i AS pos, round({sql_laplace(sql_u(7, 'lap', 'i'), '0.5')}, 9) AS mu FROM range(256) AS t(i)")
def laplace_noise_table(spark, sf_dir):
    return rng.laplace_vector(spark, 256, 0.5, 7).select("pos", F.round("mu", 9).alias("mu"))


def _exploded(df, digits=9):
    return df.select("row_id", F.posexplode("x").alias("pos", "value")).select("row_id", F.col("pos").cast("long").alias("pos"), (F.round("value", digits) if digits else F.col("value")).alias("value"))


@query("map_box", f"SELECT row_id, unnest([0, 1, 2, 3]::BIGINT[]) AS pos, round(unnest(x), 9) AS value FROM {SQL_LINEITEM}")
def map_box(spark, sf_dir):
    return _exploded(examples.lineitem(spark, sf_dir))


@query("map_clip", "SELECT row_id, p - 1 AS pos, round(x[p], 9) AS value FROM (SELECT vec_id AS row_id, list_transform(e, lambda q: q * CASE WHEN n > 0.5 THEN 0.5 / n ELSE 1.0 END) AS x FROM (SELECT vec_id, embedding::DOUBLE[] AS e, sqrt(list_sum(list_transform(embedding::DOUBLE[], lambda q: q * q))) AS n FROM embeddings)), range(1, 65) AS t(p)")
def map_clip(spark, sf_dir):
    e = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), v.clip_ball(F.col("embedding").cast("array<double>"), 0.5).alias("x"))
    return _exploded(e)


@query("map_poly2", f"SELECT row_id, (a - 1) * 4 + b - 1 AS pos, x[a] * x[b] AS value FROM {SQL_LINEITEM}, range(1, 5) AS s(a), range(1, 5) AS t(b)")
def map_poly2(spark, sf_dir):
    return _exploded(examples.lineitem(spark, sf_dir).select("row_id", v.outer(F.col("x")).alias("x")), None)


@query("map_onehot", "SELECT s_suppkey AS row_id, k AS pos, CASE WHEN s_nationkey = k THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END AS value FROM supplier, range(25) AS t(k)")
def map_onehot(spark, sf_dir):
    return _exploded(examples.supplier(spark, sf_dir))


@query("map_hash_text", """SELECT doc_id, CAST('0x' || substr(md5(w), 1, 7) AS BIGINT) % 64 AS bucket, count(*) AS n FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[ \n]+')) AS w FROM documents) WHERE w <> '' GROUP BY 1, 2""")
def map_hash_text(spark, sf_dir):
    d = load(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), "[ \n]+")).alias("w")).where("w <> ''")
    return d.groupBy("doc_id", (F.conv(F.substring(F.md5(F.col("w").cast("binary")), 1, 7), 16, 10).cast("long") % 64).alias("bucket")).agg(F.count("*").alias("n"))


@query("array_dot", f"SELECT row_id, round(list_dot_product(x, x), 9) AS dot FROM {SQL_EMBEDDINGS}")
def array_dot(spark, sf_dir):
    return examples.embeddings(spark, sf_dir).select("row_id", F.round(v.dot(F.col("x"), F.col("x")), 9).alias("dot"))


@query("array_norms", f"SELECT row_id, round(list_sum(list_transform(x, lambda q: abs(q))), 6) AS l1, round(sqrt(list_sum(list_transform(x, lambda q: q * q))), 9) AS l2, round(list_max(list_transform(x, lambda q: abs(q))), 9) AS sup FROM {SQL_EMBEDDINGS}")
def array_norms(spark, sf_dir):
    x = F.col("x")
    return examples.embeddings(spark, sf_dir).select("row_id", F.round(v.norm1(x), 6).alias("l1"), F.round(v.norm2(x), 9).alias("l2"), F.round(v.sup(x), 9).alias("sup"))
