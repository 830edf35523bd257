"""Closed forms, properties and worked examples."""

import hashlib
import math

import numpy as np
import pytest
from pyspark.sql.functions import lit
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from dp_margin.functions import calibrate as cal
from dp_margin.functions import kernels, losses, optimal, rng
from dp_margin.operators import adversarial, mechanisms, passes, scoring, solvers
from dp_margin.operators.ledger import spend
from dp_margin.plans import plan
from dp_margin.sources import examples
from dp_margin.sources.scratch import scratch

positive = st.floats(1e-3, 1e3)


@given(beta=positive, C=positive, n=st.integers(2, 10**9), F_=st.integers(1, 1000))
@settings(max_examples=50, deadline=None)
def test_noise_and_privacy_are_inverse(beta, C, n, F_):
    lam = cal.min_noise_finite(beta, n, C, 1.0, F_)
    assert math.isclose(cal.privacy_of(lam, n, C, 1.0, F_), beta, rel_tol=1e-9)
    assert cal.min_noise_finite(beta, 2 * n, C, 1.0, F_) < lam < cal.min_noise_finite(beta, n, 2 * C, 1.0, F_)


def test_golden_values():
    assert math.isclose(cal.min_noise_finite(1, 500, 1, 1, 64), 0.064)
    assert math.isclose(cal.min_noise_random(1, 500, 1, 256), 0.181019336, rel_tol=1e-8)
    assert math.isclose(cal.max_noise_finite(0.5, 0.05, 64), 0.005279034, rel_tol=1e-6)
    assert math.isclose(cal.max_noise_random(0.5, 0.05, 256), 0.002817764, rel_tol=1e-6)
    assert cal.frequencies_needed(cal.theta_hinge(0.5, 0.1), 4, 0.05, 4, 2) == pytest.approx(2185, abs=1)
    assert cal.erlang_quantile(64, 0.95) == pytest.approx(77.70, abs=0.01) and cal.erlang_quantile(512, 0.95) == pytest.approx(549.8, abs=0.05)
    assert rng.uniform_py(7, "lap", 1) == (4397005786530807 + 0.5) / 2**52
    assert int(hashlib.md5(b"7:lap:1").hexdigest()[:13], 16) == 4397005786530807
    assert np.allclose(rng.SeededRng(7).laplace(4, 0.5), [1.639112184, 1.52522968, 0.664233973, 0.680251039])


@pytest.mark.parametrize("sigma, size, bound", [(0.25, 13, 5.4293), (0.5, 6, 4.5539), (0.8, 4, 4.0431)])
def test_packing(sigma, size, bound):
    assert optimal.packing_size(sigma) == size
    assert math.isclose(math.log(0.95 * (size - 1) / 0.05), bound, abs_tol=1e-4)
    assert adversarial.packing_separation(2, 20, sigma) >= 2 / 40


def test_packing_dual_against_brute_force(spark):
    for C, n, gamma in ((2.0, 20, 0.1), (19.0, 20, 0.5), (30.0, 20, 0.1), (0.5, 20, 0.3)):
        a, b, _ = adversarial.packing_dual(F.lit(C), F.lit(float(n)), F.lit(gamma))
        got = spark.range(1).select(a.alias("a"), b.alias("b")).first()
        g = np.linspace(0, C / n, 2001)
        x, y = np.meshgrid(g, g)
        m = n - 1
        value = m * x + y - 0.5 * (m * m * x * x - 2 * gamma * m * x * y + y * y)
        best = value.max()
        here = m * got.a + got.b - 0.5 * (m * m * got.a**2 - 2 * gamma * m * got.a * got.b + got.b**2)
        assert here >= best - 1e-5


def test_unbounded_spectrum():
    with pytest.raises(kernels.UnboundedSpectrum):
        cal.frequencies_needed(0.5, 4, 0.05, kernels.laplacian().second_moment(4), 2)


def test_paper_scale_of_the_cauchy_kernel():
    assert kernels.cauchy_kernel(True).numpy(np.zeros((1, 3)))[0] == 8 and kernels.cauchy_kernel().numpy(np.zeros((1, 3)))[0] == 1


def test_map_has_unit_norm_and_approximates(spark):
    rho = kernels.frequency_matrix(spark, kernels.rbf(), 4, 2048, 3)
    x = np.random.default_rng(0).normal(size=(6, 4))
    p = kernels.trig_batch(x, rho)
    assert np.allclose((p * p).sum(1), 1)
    assert np.abs(p @ p.T - kernels.rbf().numpy(x[:, None] - x[None])).max() < 0.1


def test_hard_pair_minimisers_differ_by_twice_eps(spark):
    p = adversarial.hard_pair_linear(spark, 10, 1.0, 0.02)
    w = [solvers.fit_hinge_1d(p.where(F.col("db") == d).select("row_id", F.array("x").alias("x"), "y"), 1.0).first().w for d in (1, 2)]
    assert w == pytest.approx([0.34, 0.38]) and adversarial.hard_pair_weights(10, 1.0, 0.02) == pytest.approx((0.34, 0.38))


@pytest.mark.parametrize("C", [0.5, 5.0, 50.0])
def test_one_feature_solver_against_the_dual(spark, C):
    r = np.random.default_rng(1)
    rows = [(i, [float(x)], float(y)) for i, (x, y) in enumerate(zip(r.uniform(-1, 1, 60), r.choice([-1, 1], 60)))]
    df = spark.createDataFrame(rows, "row_id long, x array<double>, y double")
    m = solvers.reference(df, C, tol=1e-11)
    for ranges in (1, 7):
        assert solvers.fit_hinge_1d(df, C, ranges).first().w == pytest.approx(float(((m.alpha * m.y) @ m.x)[0]), abs=1e-4)


def test_solvers_agree(spark, sf):
    e = examples.embeddings(spark, sf).where("row_id < 200")
    m, p = solvers.reference(e, 10.0, tol=1e-10), solvers.cutting_plane(e, 10.0, 64, tol=1e-9)
    assert p.objective == pytest.approx(m.objective, abs=1e-6) and p.gap <= 1e-9
    w = solvers.newton(e, 5.0, 64, losses.Logistic, solvers.logistic_curvature)
    assert solvers.certificate(e, w.w, 5.0, losses.Logistic) < 1e-15
    assert solvers.choose(losses.Hinge, 1.0, 1.0, 64) == "saturated" and solvers.choose(losses.Hinge, 10.0, 1.0, 64) == "cutting_plane"


def test_weighted_rows_stand_for_copies(spark):
    rows = [(i, [1.0, 0.5], 1.0) for i in range(5)] + [(9, [-0.3, 1.0], -1.0)]
    df = spark.createDataFrame(rows, "row_id long, x array<double>, y double")
    small = examples.collapse_duplicates(df)
    assert small.count() == 2
    assert np.allclose(solvers.cutting_plane(df, 8.0, 2).w, solvers.cutting_plane(small, 8.0, 2).w, atol=1e-5)


def test_unconverged_fit_raises(spark, sf):
    with pytest.raises(solvers.NotConverged):
        solvers.cutting_plane(examples.embeddings(spark, sf), 100.0, 64, tol=1e-12, most=2)


def test_release_holds_no_secret_and_counts_are_checked(spark, sf):
    df = examples.lineitem(spark, sf)
    r = mechanisms.release_finite(df, 4, 2.0, 0.25, beta=1.0)
    assert set(mechanisms.RELEASE.names).isdisjoint({"alpha", "support", "noise_seed", "accuracy"})
    assert r.frame(spark).count() == 1 and scoring.score(df, r).columns[-1] == "score"
    with pytest.raises(ValueError):
        mechanisms.release_finite(df, 4, 2.0, 0.25)
    with pytest.raises(ValueError):
        mechanisms.release_finite(df.limit(1), 4, 2.0, 0.25, beta=1.0)


def test_budget_is_refused_beyond_the_cap(spark):
    path = scratch(spark)
    spend(spark, path, "d", "r1", 0.75, 1.0)
    with pytest.raises(PermissionError):
        spend(spark, path, "d", "r2", 0.5, 1.0)


def test_plan_says_how_many_rows_it_needs():
    p = plan(500, 64, 1.0, 1.0, 1.0, 1.0, 0.5, 0.05)
    assert not p.feasible and plan(p.rows_needed, 64, 1.0, 1.0, 1.0, 1.0, 0.5, 0.05).feasible


def test_scan_reads_only_the_needed_columns(spark, sf):
    from dp_margin.operators import measure

    text = measure.risk(examples.lineitem(spark, sf), (0, 0, 0, 0), 1.0)._jdf.queryExecution().executedPlan().toString()
    assert "l_returnflag" not in text and "l_comment" not in text and "CartesianProduct" not in text


def test_kernel_error_over_all_pairs_in_blocks(spark, sf):
    from dp_margin.functions import kernels as K
    from dp_margin.operators.measure import kernel_error_blocks
    from dp_margin.queries import QUERIES
    from dp_margin.sources import examples

    e = examples.embeddings(spark, sf)
    rows = sorted(e.collect(), key=lambda r: r.row_id)
    x, rho = np.array([r.x for r in rows]), K.frequency_matrix(spark, K.rbf(), 64, 16, 7)
    d = x[:, None, :] - x[None, :, :]
    err = np.abs(np.exp(-(d * d).sum(-1) / 2) - np.cos(d @ rho.T).mean(-1))[np.triu_indices(len(x), 1)]
    got = kernel_error_blocks(e, K.rbf(), [rho], 37).first()
    assert got.pairs == len(err) == len(x) * (len(x) - 1) // 2 > 1770
    assert abs(got.max_error - err.max()) < 1e-9 and abs(got.mean_error - err.mean()) < 1e-9
    wide = {r.m: r for r in QUERIES["kernel_error_wide"](spark, sf).collect()}
    assert {m: r.pairs for m, r in wide.items()} == dict.fromkeys((256, 1024), len(err))
    rho = K.frequency_matrix(spark, K.rbf(), 64, 256, 7)
    err = np.abs(np.exp(-(d * d).sum(-1) / 2) - np.cos(d @ rho.T).mean(-1))[np.triu_indices(len(x), 1)]
    assert abs(wide[256].max_error - err.max()) < 1e-6 and abs(wide[256].mean_error - err.mean()) < 1e-6


def test_measures_read_all_rows(spark, sf, monkeypatch):
    from dp_margin.operators import measure
    from dp_margin.queries import QUERIES

    n, rows, seen = examples.embeddings(spark, sf).count(), examples.lineitem(spark, sf).count(), []
    sens, use, ref = measure.measured_sensitivity_saturated, measure.usefulness, solvers.reference
    monkeypatch.setattr(measure, "measured_sensitivity_saturated", lambda e, other, C: (seen.append(other.count()), sens(e, other, C))[1])
    monkeypatch.setattr(measure, "usefulness", lambda s, probes, *a: (seen.append(probes.count()), use(s, probes, *a))[1])
    monkeypatch.setattr(solvers, "reference", lambda e, *a, **k: (seen.append(e.count()), ref(e, *a, **k))[1])
    for name in ("measured_sensitivity", "usefulness_rff", "perturbation_chain", "swap_space_scores", "usefulness_finite"):
        assert all(v for r in QUERIES[name](spark, sf).collect() for v in r)
    assert n > 200 and seen == [n, rows, n, n, n, n, n, rows]


def test_usefulness_against_direct_products(spark, sf):
    from dp_margin.functions import rng as R
    from dp_margin.operators import measure
    from pyspark.sql import functions as F

    e = examples.embeddings(spark, sf)
    x = np.array([r.x for r in e.collect()])
    got = measure.usefulness(spark, e, 64, 0.05, 0.5, 40, 5).first().useful
    mu = np.array([r[0] for r in spark.range(40 * 64).orderBy("id").select(R.laplace(R.uniform(5, "use", F.col("id")), 0.05)).collect()]).reshape(40, 64)
    assert got == (np.abs(x @ mu.T).max(axis=0) <= 0.5).mean()


def test_ledger_replay_agrees_with_spending(spark):
    from dp_margin.operators.ledger import balance

    path, asked, granted = scratch(spark), [0.5, 0.25, 0.5, 0.25, 0.125], []
    for k, b in enumerate(asked):
        try:
            spend(spark, path, "d", f"r{k}", b, 1.0)
            granted.append(True)
        except PermissionError:
            granted.append(False)
    rows = spark.createDataFrame([("d", "", f"r{k}", b, k) for k, b in enumerate(asked)], "dataset string, stratum string, release_id string, beta double, ts int")
    assert [r.granted for r in balance(rows, 1.0).orderBy("ts").collect()] == granted == [True, True, False, True, False]


def test_a_held_ledger_is_waited_for(spark):
    from pathlib import Path

    path = scratch(spark)
    spend(spark, path, "d", "r1", 0.5, 1.0)
    lock = Path(path.removeprefix("file:").replace("///", "/"), "_lock") if "://" in path or path.startswith("file:") else Path(path, "_lock")
    lock.touch()
    with pytest.raises(TimeoutError):
        spend(spark, path, "d", "r2", 0.25, 1.0, patience=0.2)
    lock.unlink()
    spend(spark, path, "d", "r2", 0.25, 1.0)


def test_window_releases_hide_counts_and_stop_at_the_cap(spark, sf):
    from dp_margin.streaming import streams

    events = streams.stream_events(spark, sf)
    out, ledger = scratch(spark), scratch(spark)
    streams.release_per_window(events, "7 days", 1, 1.0, 0.5, out, ledger, 0.5, scratch(spark)).awaitTermination()
    r = streams.read_batches(spark, out, streams.RELEASED).collect()
    assert len(r) >= 1 and all(x.n != int(x.n) for x in r) and spark.read.parquet(ledger).count() == len(r)
    # a second run over the same windows finds their levels spent
    streams.release_per_window(events, "7 days", 1, 1.0, 0.5, again := scratch(spark), ledger, 0.5, scratch(spark)).awaitTermination()
    assert streams.read_batches(spark, again, streams.RELEASED).count() == 0


def test_late_rows_are_dropped_by_the_stream(spark, tmp_path):
    from datetime import datetime, timedelta

    from dp_margin.streaming import streams

    day = datetime(2024, 1, 1)
    schema = "event_id long, user_id long, event_type string, value double, ts timestamp"
    for k, days in enumerate(([0, 1, 20], [21], [2, 22], [40])):  # the third file's first row lies behind the watermark of the first; it holds from the batch after next
        spark.createDataFrame([(k * 10 + i, 1, "view", 50.0, day + timedelta(days=d)) for i, d in enumerate(days)], schema).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    events = streams.prepared(spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(f"{tmp_path}/in")).withColumn("score", lit(1.0))
    got = streams.run_to_table(streams.windows(events, "tumbling", "7 days"), scratch(spark)).orderBy("start").collect()
    assert [r.n for r in got] == [2, 3]  # days 0 and 1 without the late 2; days 20 to 22; day 40 is open


def test_support_vectors_are_counted_before_they_are_broadcast(spark, sf, monkeypatch):
    e = examples.embeddings(spark, sf)
    monkeypatch.setattr(scoring, "DUAL_ROWS", 10)
    with pytest.raises(ValueError):
        scoring.score_dual(e, e, e.selectExpr("row_id", "1.0D AS alpha"))


def test_bounds_are_for_one_kernel():
    from dp_margin.functions import calibrate as cal

    # eps = 0.5, C = 1, four dimensions, diameter 2: published sizes of the frequencies
    p = cal.plan_release_random(1.0, 0.5, 0.05, 1.0, 60_000, 4, 4.0, 2.0)
    assert p["m"] == pytest.approx(3.63e7, rel=1e-2) and not p["feasible"]
    n = p["rows_needed"]
    assert n == pytest.approx(4.56e9, rel=1e-2) and cal.plan_release_random(1.0, 0.5, 0.05, 1.0, n, 4, 4.0, 2.0)["feasible"]


def test_bracket_holds(spark, sf):
    from dp_margin.queries import QUERIES

    rows = QUERIES["privacy_bracket"](spark, sf).collect()
    assert all(r.holds for r in rows) and {r.kernel for r in rows if r.lower is not None} == {"linear", "rbf"}


def test_one_vs_rest_in_one_pass_equals_single_releases(spark):
    r = np.random.default_rng(3)
    rows = [(i, (x / max(1.0, np.linalg.norm(x))).tolist(), [0, 1, 2, None, 9][i % 5]) for i, x in enumerate(r.normal(size=(60, 3)))]
    df = spark.createDataFrame(rows, "row_id long, x array<double>, label int")
    made = mechanisms.release_one_vs_rest(df, [0, 1, 2], 3, 1.0, 1.0, 3.0, rng=rng.SeededRng(4))
    noise = rng.SeededRng(4).laplace(9, made[0].lam).reshape(3, 3)
    for k in (0, 1, 2):
        one = df.withColumn("y", F.when(F.col("label") == k, 1.0).otherwise(-1.0))
        assert made[k].w - noise[k] == pytest.approx(solvers.saturated(one, 1.0, 3).w, abs=1e-12)
        assert (made[k].n, made[k].beta) == (60, 1.0) and made[k].lam == pytest.approx(cal.min_noise_finite(1.0, 60, 1.0, 1.0, 3))
    fitted = mechanisms.release_one_vs_rest(df, [0, 1], 3, 1.0, 10.0, 2.0, rng=rng.SeededRng(4), tol=1e-6)
    assert set(fitted) == {0, 1} and all(x.gap_tolerance == 1e-6 for x in fitted.values())
    with pytest.raises(ValueError):
        mechanisms.release_one_vs_rest(df.limit(0), [0, 1], 3, 1.0, 1.0, 2.0)


def test_one_feature_path_equals_single_solutions(spark, sf):
    df = examples.events(spark, sf)
    path = {r.C: r.w for r in solvers.hinge_1d_path(df, [1.0, 10.0, 100.0]).collect()}
    assert path == {C: pytest.approx(solvers.fit_hinge_1d(df, C).first().w, abs=1e-12) for C in (1.0, 10.0, 100.0)}
    assert solvers.hinge_1d_path(df.limit(0), [1.0]).count() == 0


def test_large_sums_travel_as_blocks(spark):
    x = np.random.default_rng(5).normal(size=(300, 100))
    data = spark.createDataFrame([(i % 2 * 2.0 - 1, r.tolist()) for i, r in enumerate(x)], "y double, x array<double>").repartition(7)
    gram = passes.sum_pass(data, 10_000, lambda a, y, k: (a.T @ a).ravel())
    assert 10_000 > passes.BLOCK and np.allclose(gram.reshape(100, 100), x.T @ x)
    assert not passes.sum_pass(data.where("y > 5"), 10_000, lambda a, y, k: (a.T @ a).ravel()).any()
    fit = solvers.ridge(data, 2.0, 100)
    y = np.array([i % 2 * 2.0 - 1 for i in range(300)])
    assert np.allclose(fit.w + 2.0 / 300 * x.T @ losses.Square.slope_np(y, x @ fit.w), 0, atol=1e-8)
