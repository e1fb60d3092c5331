import numpy as np
import pytest
from pyspark.sql import functions as F

from privsurv.functions import basis
from privsurv.operators import audit, baseline, chain, cox, fit, metrics, noise, predict, prep, private, sensitivity, solver
from privsurv.operators.estimator import PrivateSurvivalRegression
from privsurv.operators.ledger import Ledger, Overspent
from privsurv.operators.objective import Data, Objective
from privsurv.sources.planted import planted

ALPHA, BETA = [-4.0, 1.0, -1.0], [0.8, -0.5, 0.3]


@pytest.fixture(scope="module")
def records(spark):
    df = planted(spark, 1500, ALPHA, BETA, 20).persist()
    df.count()
    return df


@pytest.mark.parametrize("q,e,bound,tight", [(200, 3, 469.785331, 467.223594), (20, 3, 50.525932, 47.964194), (10, 3, 27.237029, 24.675292), (200, 5, 472.888758, 470.212182)])
def test_gradient_bounds(q, e, bound, tight):
    a = basis.matrix(q, e)
    assert abs(sensitivity.gradient(a) - bound) < 1e-6 and abs(sensitivity.gradient(a, "tight") - tight) < 1e-6


@pytest.mark.parametrize("mode,want", [("printed", (3110.4143, 194.2173, 48.4076)), ("one_sided", (2437.6032, 152.0553, 37.7786)), ("squared", (4875.52, 304.425, 75.8706))])
def test_ridge_roots(mode, want):
    a = basis.matrix(200, 3)
    for eps, m in zip((0.1, 1.6, 6.4), want, strict=True):
        extra, left = sensitivity.extra_ridge(a, 1.0, 1e-9, eps, mode)
        assert abs(extra - m) < 6e-3 * max(1, m / 1000) and left == eps / 2
        assert abs(sensitivity.jacobian_charge(a, extra + 1e-9, mode) - eps / 2) < 1e-9


def test_no_extra_ridge_where_the_charge_is_small():
    a = basis.matrix(20, 3)
    extra, left = sensitivity.extra_ridge(a, 1000, 10.0, 1.0)
    assert extra == 0 and abs(left + sensitivity.jacobian_charge(a, 1e4) - 1.0) < 1e-12 and left >= 0.5


def test_random_pairs_stay_below_the_bound():
    assert 0.2 < audit.gradient_looseness(basis.matrix(20, 3), 3, 500) <= 1


def test_neighbours_optima_stay_within_the_sensitivity(spark, records):
    small = records.where("subject_id < 60")
    d1, lam = Data(small, basis.matrix(20, 3)), 0.05
    new = small.where("subject_id = 5").withColumn("t", F.lit(20)).withColumn("y", -F.col("y"))
    f1, f2 = fit.ridge(d1, lam), fit.ridge(Data(audit.swapped(small, 5, new), basis.matrix(20, 3)), lam)
    assert 0 < np.linalg.norm(f1 - f2) <= sensitivity.minimizer(d1.a, d1.n, lam)


def test_noise_law():
    draws = np.array([noise.gamma_sphere(4, 0.5) for _ in range(4000)])
    length = np.linalg.norm(draws, axis=1)
    assert abs(length.mean() - 2) < 0.1 and abs(length.var() - 1) < 0.15 and np.abs(draws.mean(axis=0)).max() < 0.1
    assert np.array_equal(noise.gamma_sphere(4, 0.5, "s"), noise.gamma_sphere(4, 0.5, "s"))


def test_solvers_agree_and_find_planted_effects(records):
    o = Objective(Data(records, basis.matrix(20, 3)), 1e-3)
    a, b, c = solver.newton(o), solver.bfgs(o), solver.lbfgs(o)
    assert np.allclose(a, b, atol=1e-4) and np.allclose(a, c, atol=1e-4)
    assert solver.certificate(o, a) < 1e-4
    m = fit.mle(o.data)
    assert np.abs(m[3:] - BETA).max() < 0.45


def test_result_does_not_depend_on_partitions_or_compression(records):
    flat = records.withColumn("x1", F.round("x1", 0)).withColumn("x2", F.round("x2", 0)).withColumn("x3", F.round("x3", 0))
    f = np.array([*ALPHA, *BETA])
    a = Data(flat.repartition(7), basis.matrix(20, 3)).sums([f])[0]
    b = Data(prep.compress(flat, ["x1", "x2", "x3"]).coalesce(1), basis.matrix(20, 3)).sums([f])[0]
    assert np.allclose(a, b)


def test_private_methods_refuse_bad_input(records):
    d = Data(records, basis.matrix(20, 3), "cloglog")
    with pytest.raises(ValueError, match="slope"):
        private.output_noise_fit(d, 1.0, 0.1)
    d = Data(records, basis.matrix(20, 3))
    for eps, lam in ((0.0, 0.1), (1.0, 0.0), (-1, 0.1)):
        with pytest.raises(ValueError):
            private.output_noise_fit(d, eps, lam)
    with pytest.raises(ValueError):
        chain.Config(1, 1, 1, 10, tau=0.4)


def test_ledger_refuses_overspending(spark, records):
    led = Ledger(spark, 1.0)
    led.charge("a", "u", 0.4, 2)
    with pytest.raises(Overspent):
        private.output_noise_fit(Data(records, basis.matrix(20, 3)), 0.3, 0.1, ledger=led, unit="u")
    assert led.spent("u") == 0.8 and led.spent("other") == 0


def test_output_noise_error_falls_with_ridge_until_bias(records):
    d = Data(records, basis.matrix(20, 3))
    star, errors = fit.mle(d), {}
    for lam in (1e-4, 1e-3, 1e-2, 100.0):
        f = fit.ridge(d, lam)
        errors[lam] = np.mean([np.linalg.norm(np.array(private.output_noise_fit(d, 6.4, lam, seed=s, fitted=f).f) - star) / np.linalg.norm(star) for s in range(20)])
    assert 7 < errors[1e-4] / errors[1e-3] < 13
    assert 0.95 < errors[100.0] < 1.01


def test_sampler_beats_noise_at_a_high_budget(spark, records):
    d = Data(records, basis.matrix(20, 3))
    star, v = fit.mle(d), private.default_bound(d.n)
    runs = {e: chain.Config(float(e), v, private.default_prior(v, float(e)), 4000, burn_in=2000, every=10, seed=1, step_scale=0.01) for e in ("0.1", "6.4")}
    got = {r["chain_id"]: r["mre"] for r in metrics.mre(chain.sample(d, runs), star.tolist(), ["chain_id"]).collect()}
    f = fit.ridge(d, 0.01)
    noisy = np.mean([np.linalg.norm(np.array(private.output_noise_fit(d, 6.4, 0.01, seed=s, fitted=f).f) - star) / np.linalg.norm(star) for s in range(10)])
    assert got["6.4"] < got["0.1"] and got["6.4"] < noisy


def test_noise_temperature():
    assert abs(chain.gaussian_chain(0.05, 60_000, "calibrated") - 1) < 0.12
    assert abs(chain.gaussian_chain(0.05, 60_000, "printed") - 0.5) < 0.07
    assert chain.Config(1, 1, 1, 1, temperature="printed").charged == 2


def test_metropolis_agrees_with_the_exact_grid(spark):
    g = np.random.default_rng(3)
    t, y = g.integers(1, 6, 120), g.choice([-1, 1], 120)
    x = np.zeros((120, 0))
    a = basis.matrix(5, 2)
    c = chain.Config(3.0, 5.0, 0.1, 6000, k=None, sampler="metropolis", step_scale=2.0, burn_in=1000, seed=2)
    _, trace = chain.run_chain(a, "logit", x, t, y, c)
    got = np.mean([f for _, f in trace], axis=0)
    f1, f2 = np.meshgrid(np.linspace(-4, 3, 71), np.linspace(-5, 5, 101), indexing="ij")
    eta = f1[..., None] + f2[..., None] * a[:, 1]
    soft = np.cumsum(np.maximum(eta, 0) + np.log1p(np.exp(-np.abs(eta))), axis=-1)
    logp = -0.5 * 0.1 * (f1**2 + f2**2)
    for ti, yi in zip(t, y, strict=True):
        logp = logp - 5 * np.tanh((soft[..., ti - 1] - (yi == 1) * eta[..., ti - 1]) / 5)
    p = np.exp(0.3 * logp - (0.3 * logp).max())
    p /= p.sum()
    assert abs(got[0] - (p * f1).sum()) < 0.25 and abs(got[1] - (p * f2).sum()) < 0.4


def test_prefetched_chain_is_replayable(spark, records):
    d = Data(records, basis.matrix(20, 3))
    rows = prep.row_ids(records, "subject_id")
    v = private.default_bound(d.n)
    c = chain.Config(1.0, v, private.default_prior(v, 1.0), 20, k=50, seed=4)
    a, b = chain.sample_prefetched(d, rows, "r", c, block=8), chain.sample_prefetched(d, rows.repartition(3), "r", c, block=8)
    assert np.allclose(a, b) and np.isfinite(a).all()
    ids = chain.minibatch_ids(spark, "r", 4, 1, 5, 50, 1500)
    assert ids.groupBy("step").agg(F.countDistinct("row_id").alias("n")).where("n <> 50").isEmpty()


def test_cox_against_risk_sets_written_out(spark, records):
    df = records.where("subject_id < 200")
    rows = df.toPandas()
    x, t, y = rows[["x1", "x2", "x3"]].to_numpy(), rows["t"].to_numpy(), rows["y"].to_numpy()
    beta = np.array([0.5, -0.2, 0.1])
    z = x @ beta
    breslow = sum(z[i] - np.log(np.exp(z[t >= t[i]]).sum()) for i in range(len(t)) if y[i] == 1)
    efron = 0.0
    for at in np.unique(t[y == 1]):
        own, risk = (t == at) & (y == 1), np.exp(z[t >= at]).sum()
        efron += z[own].sum() - sum(np.log(risk - k / own.sum() * np.exp(z[own]).sum()) for k in range(own.sum()))
    assert abs(cox.partial_likelihood(df, ["x1", "x2", "x3"], beta)[0] - breslow) < 1e-8
    assert abs(cox.partial_likelihood(df, ["x1", "x2", "x3"], beta, "efron")[0] - efron) < 1e-8


def test_cox_paths_agree_on_value_gradient_and_hessian(spark, records):
    """The numpy path of intervals and the column path of raw times, with few and with many ties."""
    beta, x = [0.5, -0.2, 0.1], ["x1", "x2", "x3"]
    for df in (records, records.withColumn("t", F.ceil(F.col("t") / 5).cast("int"))):
        for ties in ("breslow", "efron"):
            a = cox.partial_likelihood(df, x, beta, ties)
            b = cox.partial_likelihood(df.withColumn("raw", F.col("t") * 1.5), x, beta, ties, "raw")
            assert all(np.allclose(u, v, rtol=1e-8, atol=1e-7) for u, v in zip(a, b, strict=True))
            up, down = (cox.partial_likelihood(df, x, np.array(beta) + s * 1e-4, ties)[0] for s in (np.eye(3)[0], -np.eye(3)[0]))
            assert abs((up - down) / 2e-4 - a[1][0]) < 1e-3


def test_tied_events_in_closed_form():
    m, r0, c = np.array([40.0, 500.0, 33.0]), np.array([1000.0, 500.5, 1e6]), np.array([1.3, 1.0, 0.7])
    far = lambda few, many: many
    got = cox._efron(m, r0, c * m, np.log, (lambda *a: (None,) * 3, far))
    for i in range(3):
        left = r0[i] - np.arange(int(m[i])) * c[i]
        assert np.allclose([g[i] for g in got], [np.log(left).sum(), (1 / left).sum(), (1 / left**2).sum()], rtol=1e-6)


def test_releases_refuse_covariates_outside_the_ball_and_stopped_solvers(spark, records):
    far = Data(records.withColumn("x1", F.col("x1") + 50), basis.matrix(20, 3))
    for release in (private.output_noise_fit, private.objective_noise_fit):
        with pytest.raises(ValueError, match="unit ball"):
            release(far, 1.0, 0.1)
    d = Data(records, basis.matrix(20, 3))
    with pytest.raises(ValueError, match="gradient norm"):
        private.output_noise_fit(d, 1.0, 0.1, fitted=np.ones(d.d))
    a, b = (private.output_noise_fit(d, 1.0, 0.1) for _ in range(2))
    assert a.run_id != b.run_id and a.f != b.f


def test_ledger_table_survives_and_a_retried_run_is_charged_once(spark, tmp_path):
    path = str(tmp_path / "ledger")
    led = Ledger(spark, 1.0, path=path)
    led.charge("batch-0", "u", 0.6)
    again = Ledger(spark, 1.0, path=path)
    again.charge("batch-0", "u", 0.6)
    assert again.spent("u") == 0.6 and Ledger(spark, 1.0, path=path).spent("u") == 0.6
    with pytest.raises(Overspent):
        again.charge("batch-1", "u", 0.6)
    with pytest.raises(ValueError):
        again.charge("batch-0", "u", 0.5)


def test_likelihood_without_a_maximiser_is_refused(spark):
    rows = [(i, 2, 1 if i % 2 else -1, 1.0 if i % 2 else -1.0, 1) for i in range(40)]
    d = Data(spark.createDataFrame(rows, "subject_id int, t int, y int, x1 double, w int"), np.ones((4, 1)))
    with pytest.raises(fit.Unbounded):
        fit.mle(d)
    assert fit.optimum(d)[1] > 0


def test_a_fit_scans_its_source_once(spark, records):
    d = Data(records, basis.matrix(20, 3))
    with d.hold():
        plan = d.df.where("t > 0")._jdf.queryExecution().executedPlan().toString()
    assert "InMemoryTableScan" in plan


def test_discrete_effects_are_near_cox(records):
    d = Data(records, basis.matrix(20, 3), "cloglog")
    b, star = fit.mle(d, tolerance=1e-6)[3:], cox.fit(records, "efron")
    assert np.linalg.norm(b - star) / np.linalg.norm(star) < 0.15


def test_worked_vectors():
    b, star = np.array([0.0122443, -0.849823, -0.239539]), np.array([0.0585478, -0.790977, -0.23906])
    assert abs(np.linalg.norm(b - star) / np.linalg.norm(star) - 0.09039338) < 1e-7


def test_predecessors_and_zero(records):
    d = baseline.plain(records)
    r = baseline.logistic_objective(d, 0.5, 1e-4, "s")
    assert r.params["extra"] > 0 and r.params["noise_budget"] == 0.25
    assert np.linalg.norm(baseline.zero(d)) == 0


def test_estimator(spark, records):
    for method in ("ridge", "output_noise", "sampler"):
        m = PrivateSurvivalRegression(method=method, epsilon=6.4, lam=0.01, q=20, steps=200).fit(records)
        assert m.transform(records).where("z is null").isEmpty()
        assert m.release.exact == (method != "sampler")


def test_curves(spark, records):
    c = predict.curves(records.where("subject_id < 3"), ALPHA, BETA, ["x1", "x2", "x3"], 20)
    total = c.groupBy("subject_id").agg(F.sum("density").alias("d"), F.min("survival").alias("s")).collect()
    assert all(abs(r["d"] + r["s"] - 1) < 1e-9 for r in total)


def test_preparation_edges(spark):
    df = spark.createDataFrame([(1, 1, 0.0, 1, None), (2, 1, 9.0, 0, 2.0), (3, 2, 99.0, 1, float("nan"))], "subject_id long, unit_id long, duration double, event int, x1 double")
    d = prep.discretize(df, 10, 10.0)
    assert [r["t"] for r in d.orderBy("subject_id").collect()] == [1, 9, 10]
    with pytest.raises(ValueError):
        prep.nulls(d, ["x1"])
    assert prep.nulls(d, ["x1"], "drop").count() == 1 and prep.nulls(d, ["x1"], "impute_mean").where("x1 = 2").count() == 3
    row = prep.validate(d, ["x1"], 10).first()
    assert (row.bad_x, row.outside, row.repeated) == (2, 1, 0)
    empty = d.where("false")
    assert prep.validate(empty, ["x1"], 10).first().n == 0
    assert Data(empty.withColumn("w", F.lit(1)), basis.matrix(10, 2)).sums([np.zeros(3)])[0].sum() == 0


def test_bounded_plans(spark, records):
    """No person-period rows and no cross product in the distributed sums."""
    from privsurv.sources.tables import table

    text = records.mapInPandas(lambda f: f, records.schema)._jdf.queryExecution().toString()
    assert "Generate" not in text and "Cartesian" not in text
    del table


def test_tabulated_losses_stay_within_their_bound(records):
    from privsurv.functions.loss import SumOfLogistic
    from privsurv.operators import tabulated

    f, a, x = [*ALPHA, *BETA], basis.matrix(20, 3), ["x1", "x2", "x3"]
    rows = tabulated.losses(records, a, np.array(f), x, 33).toPandas()
    exact = SumOfLogistic(a).losses(np.array(f), rows[x].to_numpy(), rows["t"].to_numpy(), rows["y"].to_numpy())
    assert np.abs(rows["loss"] - exact).max() <= tabulated.error_bound(20, np.linalg.norm(BETA) + 1e-9, 33) + 1e-12


def test_choices(spark, records):
    from privsurv.plans import choose

    assert choose.evaluator(records, ["x1", "x2", "x3"], 20).name == "kernel"
    assert choose.evaluator(records, ["x1", "x2", "x3"], 200, 1e-6).name == "table"
    assert choose.evaluator(records.select("t", "y"), [], 20).name == "cells"
    assert choose.feeding(1e9, 3, 1000, 200).name == "prefetch" and "MB" in choose.feeding(1e9, 3, 1000, 200).explain()


def test_laplace_vector_has_the_spread_of_its_sensitivity():
    draws = np.array([noise.laplace_vector(np.array([1.0, -2.0, 3.0]), 0.5, 2.0, seed=i) for i in range(4000)]) - [1, -2, 3]
    length = np.linalg.norm(draws, axis=1)  # Gamma of shape three and scale one quarter
    assert abs(length.mean() - 0.75) < 0.03 and abs(length.var() - 3 / 16) < 0.02
    assert np.abs((draws / length[:, None]).mean(axis=0)).max() < 0.04
    with pytest.raises(ValueError):
        noise.laplace_vector(np.zeros(2), 1.0, 0.0)


def test_step_lengths_put_injected_noise_above_minibatch_noise():
    for n in (500, 20_000, 10**7):
        v = private.default_bound(n)
        rms = (6.4 / (2 * v)) / 200**0.5  # of a minibatch gradient, per unit of a record's
        h = chain.stable_scale(n, 6.4, v) * 10_000**-0.51
        assert (h * n) ** 2 <= 0.2 * (2 * h / rms)
