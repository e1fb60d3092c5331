"""Sums of logistic terms, fits per group, kept models, samples and the ball's mechanism."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from privsurv.functions import basis
from privsurv.functions.loss import SumOfLogistic
from privsurv.operators import chain, fit, prep, private, sampling, sensitivity, terms
from privsurv.operators.estimator import PrivateSurvivalRegression, SurvivalModel
from privsurv.operators.ledger import Ledger, Overspent
from privsurv.operators.objective import Data, Objective
from privsurv.sources.planted import planted

ALPHA, BETA = [-4.0, 1.0, -1.0], [0.8, -0.5, 0.3]
X = ["x1", "x2", "x3"]


@pytest.fixture(scope="module")
def records(spark):
    df = planted(spark, 900, ALPHA, BETA, 20).persist()
    df.count()
    return df


def _terms(records):
    return terms.terms(prep.person_period(records), basis.matrix(20, 3), X, "subject_id", "s", "fails")


def test_terms_sum_to_records(records):
    a, f = basis.matrix(20, 3), np.array([*ALPHA, *BETA])
    whole, parts = Data(records, a), _terms(records)
    assert parts.n == whole.n == 900
    assert np.allclose(whole.sums([f], hessian=True), parts.sums([f], hessian=True))
    assert np.allclose(fit.ridge(whole, 0.01), fit.ridge(parts, 0.01), atol=1e-7)


def test_noise_bounds_hold_for_changing_covariates():
    """Gradients of two subjects whose covariates change within the ball differ by no more than the bound."""
    g, a = np.random.default_rng(3), basis.matrix(20, 3)
    kernel, bound, worst = terms.TermLoss(a), sensitivity.gradient(a), 0.0
    for _ in range(300):
        f, grads = g.standard_normal(6) * g.choice([0.5, 5, 20]), []
        for _ in range(2):
            t, y = int(g.integers(1, 21)), g.choice([-1, 1])
            x = g.standard_normal((t, 3))
            x /= np.linalg.norm(x, axis=1, keepdims=True)
            ends = np.full(t, -1)
            ends[-1] = y
            grads.append(kernel.sums(f, x, np.arange(1, t + 1), ends, np.ones(t))[1:])
        worst = max(worst, float(np.linalg.norm(grads[0] - grads[1])))
    assert worst <= bound


def test_repeated_places_and_long_covariates_are_refused(spark, records):
    a = basis.matrix(20, 3)
    rows = prep.person_period(records.where("subject_id < 20"))
    with pytest.raises(terms.Repeated):
        terms.terms(rows.unionByName(rows), a, X, "subject_id", "s", "fails")
    long = terms.terms(rows.withColumn("x1", F.col("x1") + 3), a, X, "subject_id", "s", "fails")
    assert long.radius > 1 and long.n == 20
    with pytest.raises(ValueError):
        private.output_noise_fit(long, 1.0, 0.1)


def test_terms_of_null_places_and_empty_tables(spark):
    rows = spark.createDataFrame([(1, 1, 0, 0.1), (1, None, 1, 0.2), (2, 1, None, 0.3)], "id long, s int, event int, x1 double")
    d = terms.terms(rows, basis.matrix(4, 2), ["x1"])
    assert d.n == 1 and d.df.count() == 1
    empty = terms.terms(rows.where("false"), basis.matrix(4, 2), ["x1"])
    assert empty.sums([np.zeros(3)])[0].sum() == 0


def test_groups_equal_fits_alone(spark, records):
    """Also for a group of null, and one that holds most rows."""
    a = basis.matrix(20, 3)
    df = records.withColumn("g", F.when(F.col("subject_id") % 10 == 0, F.lit("a")).when(F.col("subject_id") % 10 == 1, F.lit(None)).otherwise(F.lit("b")))
    fits = terms.grouped_ridge(df, "g", a, 0.05, X)
    assert set(fits) == {"a", None, "b"}
    for g, f in fits.items():
        assert np.allclose(f, fit.ridge(Data(df.where(F.col("g").eqNullSafe(F.lit(g))).drop("g"), a), 0.05), atol=1e-7)
    with pytest.raises(ValueError):
        terms.grouped_ridge(df, "subject_id", a, 0.05, X, most_groups=50)
    assert terms.grouped_ridge(df.where("false"), "g", a, 0.05, X) == {}


def test_cells_equal_records(records):
    coarse = prep.compress(records.withColumn("x1", F.round("x1", 0)), ["x1"])
    a = basis.matrix(20, 3)
    cells = terms.from_cells(prep.risk_cells(coarse, ["x1"]), a, ["x1"])
    assert cells.n == 900 and np.allclose(fit.ridge(cells, 0.02), fit.ridge(Data(coarse, a), 0.02), atol=1e-7)


def test_models_are_kept(spark, records, tmp_path):
    m = PrivateSurvivalRegression(method="ridge", lam=0.01, q=20, link="cloglog").fit(records)
    m.save(spark, str(tmp_path / "m"))
    back = SurvivalModel.load(spark, str(tmp_path / "m"))
    assert back.release == m.release and back.x == X and back.release.link == "cloglog"
    few = records.where("subject_id < 4")
    assert back.transform(few).select("z").collect() == m.transform(few).select("z").collect()
    assert back.curves(few).count() == 80


def test_estimator_charges_its_ledger(spark, records):
    ledger = Ledger(spark, 2.0)
    e = PrivateSurvivalRegression(method="output_noise", epsilon=1.5, lam=0.1, q=20, unit="people").charging(ledger)
    e.fit(records)
    assert ledger.spent("people") == 1.5
    with pytest.raises(Overspent):
        e.fit(records)


def test_ball_mechanism(records):
    d = Data(records, basis.matrix(20, 3))
    r = chain.bounded_sampler_fit(d, 1.0, steps=50, bound="none", radius=2.0, seed=1)
    assert np.linalg.norm(r.f) <= 2 + 1e-9 and r.params["v"] == sensitivity.ball_bound(d.a, 2.0)
    g, kernel = np.random.default_rng(0), SumOfLogistic(d.a)
    for _ in range(200):
        f, x = g.standard_normal(6), g.standard_normal((1, 3))
        f, x = 2 * f / np.linalg.norm(f), x / np.linalg.norm(x)
        assert kernel.losses(f, x, np.array([20]), g.choice([-1, 1], 1))[0] <= r.params["v"]
    for wrong in ({"bound": "none"}, {"bound": "none", "radius": 2.0, "v": 1.0}):
        with pytest.raises(ValueError):
            chain.bounded_sampler_fit(d, 1.0, steps=5, **wrong)


def test_model_functions_refuse_other_links(spark):
    with pytest.raises(ValueError):
        private.Release("ridge", 1.0, [0.0] * 4, 8, 3, link="probit").register(spark, "m")
    with pytest.raises(ValueError):
        private.Release("ridge", 1.0, [0.0] * 4, 8, 3).register(spark, "m; drop")


def test_samples_hold_their_shares(spark):
    df = spark.range(20_000).withColumn("g", F.when(F.col("id") % 2 == 0, F.lit("a")).when(F.col("id") % 3 == 0, F.lit(None)).otherwise(F.lit("b")))
    assert abs(sampling.bernoulli(df, "id", 0.3).count() / 20_000 - 0.3) < 0.02
    got = {r[0]: r[1] for r in sampling.stratified(df, "g", "id", {"a": 0.5, "b": 0.1}).groupBy("g").count().collect()}
    assert set(got) == {"a", "b"} and abs(got["a"] / 10_000 - 0.5) < 0.03 and "Exchange" not in sampling.stratified(df, "g", "id", {"a": 0.5})._jdf.queryExecution().executedPlan().toString()
