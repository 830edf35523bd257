"""Work over all pairs of rows, at more rows than the reference machine's matrix takes (5,000), and in small blocks."""

import numpy as np
import pytest

from dp_margin.queries import QUERIES

#: More rows than DUAL_ROWS.
MANY = 5_200


def brute(x, name, spark):
    from dp_margin.functions import kernels as K

    d = lambda i: x[i] - x
    of = {
        "kernel_rbf_rows": lambda i: np.exp(-(d(i) ** 2).sum(-1) / 2),
        "kernel_laplacian_rows": lambda i: np.exp(-np.abs(d(i)).sum(-1)),
        "kernel_cauchy_rows": lambda i: np.prod(1 / (1 + d(i) ** 2), axis=-1),
        "kernel_custom": lambda i: np.maximum(0, 1 - np.abs(d(i)).max(-1)),
    }
    rho = K.frequency_matrix(spark, K.rbf(), 64, 16, 7)
    of["approx_kernel_rows"] = lambda i: np.cos(d(i) @ rho.T).mean(-1)
    return of[name]


@pytest.fixture(scope="session")
def many(spark, tmp_path_factory):
    """A folder whose embeddings are MANY unit vectors with labels 0 to 9, and the vectors."""
    r = np.random.default_rng(11)
    x = r.normal(size=(MANY, 64)) + np.eye(64)[r.integers(0, 8, MANY)] * 3
    x = (x / np.linalg.norm(x, axis=1)[:, None]).astype("f4")
    folder = str(tmp_path_factory.mktemp("many"))
    import pandas as pd

    pd.DataFrame({"vec_id": np.arange(MANY), "embedding": list(x), "label": (np.arange(MANY) % 10).astype("i4")}).to_parquet(f"{folder}/embeddings.parquet")
    x = x.astype(float)
    return folder, x / np.maximum(1, np.linalg.norm(x, axis=1))[:, None]


@pytest.mark.parametrize("name", ["kernel_rbf_rows", "kernel_laplacian_rows", "kernel_cauchy_rows", "kernel_custom", "approx_kernel_rows"])
def test_rows_of_the_kernel_matrix_at_any_size(spark, many, name):
    folder, x = many
    got = {r.i: r for r in QUERIES[name](spark, folder).collect()}
    assert len(got) == MANY and {r.others for r in got.values()} == {MANY - 1}
    of = brute(x, name, spark)
    for i in (0, 1, 17, MANY - 1):
        k = np.delete(of(i), i)
        assert (got[i].total, got[i].least, got[i].most) == (pytest.approx(k.sum(), abs=2e-6), pytest.approx(k.min(), abs=2e-9), pytest.approx(k.max(), abs=2e-9))


def test_row_measures_in_small_blocks_with_nulls_and_shared_ids(spark):
    from dp_margin.operators import blocks

    x = np.random.default_rng(2).normal(size=(40, 3))
    rows = [(i // 2 if i < 6 else i, None if i == 9 else v.tolist()) for i, v in enumerate(x)]
    got = {r.i: r for r in blocks.row_measures(spark.createDataFrame(rows, "row_id long, x array<double>"), lambda a, b: a @ b.T, 7).collect()}
    ids = np.array([r[0] for r in rows])
    for i in set(ids.tolist()):
        own, other = ids == i, ids != i
        k = (x[own] @ x[other & (np.arange(40) != 9)].T).ravel()
        if i == 9:
            assert (got[i].others, got[i].total, got[i].least) == (39, None, None)
        else:
            assert got[i].others == own.sum() * other.sum()
            assert (got[i].total, got[i].least, got[i].most) == (pytest.approx(k.sum()), pytest.approx(k.min()), pytest.approx(k.max()))
    assert blocks.row_measures(spark.createDataFrame(rows[:1], "row_id long, x array<double>"), lambda a, b: a @ b.T).count() == 0


@pytest.mark.parametrize("how", ["linear", "rbf", "random"])
def test_dual_in_a_table_equals_the_driver(spark, how):
    from dp_margin.functions import kernels as K
    from dp_margin.operators import solvers

    r = np.random.default_rng(4)
    x, kind = r.normal(size=(150, 3)), {"linear": {}, "rbf": {"kernel": K.rbf()}, "random": {"rho": r.normal(size=(9, 3))}}[how]
    y = np.where(x[:, 0] + 0.5 * r.normal(size=150) > 0, 1.0, -1.0)
    df = spark.createDataFrame([(i, v.tolist(), float(s), 1.0 + i % 2) for i, (v, s) in enumerate(zip(x, y, strict=True))], "row_id long, x array<double>, y double, weight double").repartition(4)
    small = solvers.reference(df, 20.0, tol=1e-9, **kind)
    big = solvers.reference_table(df, 20.0, tol=1e-8, working=60, **kind)
    a = np.array([q.alpha for q in sorted(big.frame(spark).collect(), key=lambda q: q.row_id)])
    assert 0 <= big.gap <= 1e-8 and abs(big.objective - small.objective) < 2e-8
    top = 20.0 / 225 * (1 + np.arange(150) % 2)
    assert (a >= 0).all() and (a <= top + 1e-12).all() and (a < top / 2).sum() > 20
    f = solvers.gram(x, x, kind.get("kernel"), kind.get("rho")) @ (a * y)
    assert 0.5 * (a * y) @ f + top @ np.maximum(0, 1 - y * f) == pytest.approx(small.objective, abs=2e-8)


def test_perturbation_chain_in_blocks_equals_the_driver(spark, sf):
    from dp_margin.functions import kernels as K
    from dp_margin.operators import measure, solvers
    from dp_margin.sources import examples

    e, rho = examples.embeddings(spark, sf), K.frequency_matrix(spark, K.rbf(), 64, 64, 7)
    a, b = solvers.reference(e, 100.0, K.rbf(), tol=1e-6), solvers.reference(e, 100.0, rho=rho, tol=1e-6)
    want, got = measure.perturbation_chain(a.x, a.y, a, b, 100.0), measure.perturbation_chain_table(e, a.frame(spark), b.frame(spark), K.rbf(), rho, 100.0)
    assert set(want) == set(got) and want["hilbert"] > 0.01
    assert {k: got[k] for k in want} == {k: pytest.approx(w, abs=1e-7) for k, w in want.items()}


BEYOND = [
    "perturbation_chain",
    "dual_scores",
    "primal_equals_dual",
    "ref_dual_box",
    "swap_space_scores",
    "ref_dual_objective",
    "primal_from_dual",
    "naive_disclosure",
    "dual_l1",
]


@pytest.mark.parametrize("name", BEYOND)
def test_duals_beyond_the_driver(spark, many, name):
    import duckdb

    from dp_margin.queries import ORACLES

    folder, _ = many
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW embeddings AS SELECT * FROM read_parquet('{folder}/embeddings.parquet')")
    got, want = QUERIES[name](spark, folder).toPandas(), duck.execute(ORACLES[name]).df()
    key = want.columns[0]
    got, want = (d.sort_values(key).reset_index(drop=True)[list(want.columns)] for d in (got, want))
    assert len(got) == len(want)
    for c in want.columns:
        assert all(a == b or a == pytest.approx(b, abs=2e-9) for a, b in zip(got[c], want[c], strict=True))
