"""Small tests of what the findings of round 2 changed."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from dp_margin.queries import QUERIES
from dp_margin.sources import examples


def test_certified_workloads_are_fitted_once_on_stored_features(spark, sf, monkeypatch):
    from dp_margin.operators import solvers

    fits, fit = [], solvers.fit
    monkeypatch.setattr(solvers, "fit", lambda df, *a, **k: (fits.append(df._jdf.queryExecution().optimizedPlan().toString()), fit(df, *a, **k))[1])
    rows = QUERIES["release_workloads_certified"](spark, sf).collect()
    assert len(rows) == len(fits) == 12 and not any("regexp_replace" in p or "Join" in p for p in fits)
    assert all(r.sup_distance <= r.sup_bound + 1e-9 and r.lam > 0 for r in rows)


def test_a_given_fit_makes_the_same_release(spark, sf):
    from dp_margin.functions.rng import SeededRng
    from dp_margin.operators import mechanisms, solvers

    df = examples.part(spark, sf)
    a = mechanisms.release_finite(df, 2, 2**0.5, 10.0, beta=1.0, rng=SeededRng(7), tol=1e-4)
    b = mechanisms.release_finite(df, 2, 2**0.5, 10.0, beta=1.0, rng=SeededRng(7), tol=1e-4, fit=solvers.fit(df, 10.0, 2, 2**0.5, tol=1e-4))
    assert np.allclose(a.w, b.w, atol=1e-12) and (a.lam, a.gap_tolerance) == (b.lam, b.gap_tolerance)


def test_clip_takes_its_value_once(spark):
    from dp_margin.functions import vectors as v

    df = spark.createDataFrame([(None,), (float("nan"),), (-2.0,), (0.5,), (7.0,), (float("inf"),)], "a double").select(v.clip(F.col("a") * 1.0).alias("c"))
    assert [r.c for r in df.collect()] == [0.0, 0.0, 0.0, 0.5, 1.0, 1.0]
    assert str(v.clip(F.col("zz"))).count("zz") == 1


def test_event_seconds_round_halves_to_even_as_sql_does(spark, tmp_path):
    import duckdb

    from dp_margin.queries import ORACLES

    duck = duckdb.connect()
    duck.execute("CREATE TABLE events AS SELECT i AS event_id, TIMESTAMP '2024-01-01 00:00:00' + i * INTERVAL 500 MILLISECOND AS ts FROM range(8) AS t(i)")
    duck.execute(f"COPY events TO '{tmp_path}/events.parquet' (FORMAT parquet)")
    got = {r.event_id: (r.h, r.secs) for r in QUERIES["event_hours"](spark, str(tmp_path)).collect()}
    assert got == {a: (b, c) for a, b, c in duck.execute(f"SELECT event_id, h, secs FROM ({ORACLES['event_hours']})").fetchall()}
    assert len(got) == 8


READS = {
    "hard_pair_linear_rows": "customer",
    "freq_cauchy": "lineitem",
    "freq_laplacian": "lineitem",
    "freq_rbf": "lineitem",
    "group_privacy": "events",
    "freq_count_utility": "lineitem",
    "freq_count_kernel": "lineitem",
    "failure_probability_sweep": "events",
    "collapse_duplicates": "events",
    "hard_packing_gaps": "customer",
    "hard_packing_rows": "customer",
    "fig61_curve": "customer",
}


@pytest.mark.parametrize("name", READS)
def test_query_reads_its_table(spark, sf, name):
    assert any(f"/{READS[name]}.parquet" in f for f in QUERIES[name](spark, sf).inputFiles())
