"""Experiments cover what they are named for: workloads, budgets and repetitions, run here with short chains."""

import numpy as np

from privsurv.functions import basis
from privsurv.operators import chain, prep, private
from privsurv.operators.objective import Data
from privsurv.plans import q_chains, q_fits
from privsurv.plans.all_queries import QUERIES
from privsurv.sources.planted import planted

ALL = {"s1", "s2", "s3", "s4"}


def test_tradeoff_has_all_workloads_budgets_and_equal_repetitions(spark, sf, monkeypatch):
    monkeypatch.setattr(q_chains, "DRAWS", 2)
    monkeypatch.setattr(q_chains, "STEPS", 20)
    rows = QUERIES["privacy_tradeoff"](spark, sf).collect()
    assert {r["dataset"] for r in rows} == ALL and len(rows) == 4 * 3 * 7
    assert {round(r["epsilon"], 9) for r in rows} == {0.1, 0.2, 0.4, 0.8, 1.6, 3.2, 6.4}
    assert all(r["draws"] == 2 for r in rows) and all(np.isfinite(r["mre"]) for r in rows)


def test_objective_noise_together_is_as_one_by_one(spark):
    d = Data(planted(spark, 300, [-4.0, 1.0, -1.0], [0.8, -0.5, 0.3], 20).persist(), basis.matrix(20, 3))
    many = private.objective_noise_fits(d, [(0.4, "a"), (6.4, "b")], 0.1, tolerance=1e-8)
    for r, (eps, seed) in zip(many, [(0.4, "a"), (6.4, "b")], strict=True):
        one = private.objective_noise_fit(d, eps, 0.1, seed=seed, tolerance=1e-8)
        assert np.allclose(r.f, one.f, atol=1e-5) and r.params == one.params


def test_ridge_sweep_has_all_workloads(spark, sf):
    rows = QUERIES["lambda_sweep"](spark, sf).collect()
    assert {r["dataset"] for r in rows} == ALL and len(rows) == 24


def test_cox_comparison_has_all_workloads_and_all_their_covariates(spark, sf, monkeypatch):
    monkeypatch.setattr(q_fits.cox, "fit", lambda df, ties: np.ones(len(prep.covariates(df))))
    monkeypatch.setattr(q_fits.fit, "optimum", lambda d: (np.ones(d.d), 0.0))
    rows = QUERIES["cox_vs_discrete"](spark, sf).collect()
    assert {(r["dataset"], r["ties"]) for r in rows} == {(name, ties) for name in ALL for ties in ("breslow", "efron")}
    assert all(len(r["cox"]) == len(r["discrete"]) == (8 if r["dataset"] == "s1" else 3) for r in rows)


def test_chain_queries_run_both_workloads_at_their_own_intervals(spark, sf, monkeypatch):
    seen, whole = [], chain.sample
    short = lambda c: chain.variants(c, steps=6, burn_in=2, every=1)
    monkeypatch.setattr(chain, "sample", lambda d, runs: (seen.append(d.a.shape[0]), whole(d, {k: short(c) for k, c in runs.items()}))[1])
    monkeypatch.setattr(q_fits.fit, "optimum", lambda d: (np.ones(d.d), 0.0))
    for name in ("sampler_release", "density_s2", "mre_epochs_s4", "ablation_precondition"):
        assert {r["dataset"] for r in QUERIES[name](spark, sf).select("dataset").distinct().collect()} == {"s2", "s4"}, name
    assert seen == [200] * 12


def test_large_pools_run_by_joins_with_all_options(spark, monkeypatch):
    d = Data(planted(spark, 300, [-4.0, 1.0, -1.0], [0.8, -0.5, 0.3], 20).persist(), basis.matrix(20, 3))
    base = chain.Config(2.0, 4.0, 0.05, 6, k=20, seed=3, step_scale=0.01, burn_in=1, every=2)
    full = chain.variants(base, k=None, replay=True, steps=3, burn_in=0, every=1)
    whole = {"full": full, "metropolis": chain.variants(base, sampler="metropolis", steps=3, burn_in=0, every=1)}
    state = lambda df: {(r["chain_id"], r["step"]): r["f"] for r in df.collect()}
    want = state(chain.sample(d, whole))
    monkeypatch.setattr(chain, "POOL", 100)
    runs = {"base": base, "thermostat": chain.variants(base, sampler="thermostat"), "drift": chain.variants(base, drift_correction=True), "ball": chain.variants(base, radius=0.01), "again": chain.variants(base, with_replacement=True)}
    got = state(chain.sample(d, runs | whole))
    assert {k for k in got if k[0] not in whole} == {(name, s) for name in runs for s in (3, 5, 6)}
    assert all(np.allclose(got[k], v) for k, v in want.items()) and np.linalg.norm(got["ball", 6]) <= 0.01 + 1e-12
    assert len(chain.bounded_sampler_fit(d, 2.0, steps=3).f) == 6


def test_chains_by_epoch_run_all_epochs_of_any_number_of_records(spark, monkeypatch):
    d = Data(planted(spark, 900, [-4.0, 1.0, -1.0], [0.8, -0.5, 0.3], 20).persist(), basis.matrix(20, 3))
    seen, whole = [], chain.sample
    short = lambda c: chain.variants(c, steps=6, burn_in=2, every=1)
    monkeypatch.setattr(chain, "sample", lambda d, runs: (seen.extend((c.steps, c.burn_in) for c in runs.values()), whole(d, {k: short(c) for k, c in runs.items()}))[1])
    monkeypatch.setattr(q_chains, "_held", lambda *_: d)
    assert {r["dataset"] for r in QUERIES["mre_epochs_s4"](spark, None).select("dataset").distinct().collect()} == {"s2", "s4"}
    assert len(QUERIES["density_s2"](spark, None).collect()) > 0
    assert seen == [(10_000 + 250 * 900, 10_000)] * 8


def test_traces_come_in_pieces(monkeypatch):
    g = np.random.default_rng(3)
    a, x, t, y = basis.matrix(20, 3), g.uniform(-0.5, 0.5, (60, 3)), g.integers(1, 21, 60), np.where(g.random(60) < 0.5, 1, -1)
    c = chain.Config(2.0, 4.0, 0.05, 47, k=20, step_scale=0.01, burn_in=8, every=3)
    f, trace = chain.run_chain(a, "logit", x, t, y, c)
    monkeypatch.setattr(chain, "PIECE", 4)
    pieces = list(chain._traced("c", c, a, "logit", x, t, y, np.ones(60, dtype=int)))
    assert len(pieces) > 2 and all(len(p) <= 5 for p in pieces)
    got = [(int(s), v) for p in pieces for s, v in zip(p["step"], p["f"], strict=True)]
    assert got == [(s, v.tolist()) for s, v in trace] and (got[-1][0], got[-1][1]) == (47, f.tolist())
    assert [bool(v) for p in pieces for v in p["last"]] == [False] * (len(got) - 1) + [True]


def test_tradeoff_chains_run_all_epochs_after_the_burn_in(spark, sf, monkeypatch):
    seen, whole = [], chain.sample
    short = lambda c: chain.variants(c, steps=6, burn_in=2, every=1)
    monkeypatch.setattr(q_chains, "DRAWS", 1)
    monkeypatch.setattr(chain, "sample", lambda d, runs: (seen.extend((c.steps, c.burn_in, d.n) for c in runs.values()), whole(d, {k: short(c) for k, c in runs.items()}))[1])
    assert {r["dataset"] for r in QUERIES["privacy_tradeoff"](spark, sf).collect()} == ALL
    assert len(seen) == 28 and all((steps, burn_in) == (10_000 + 250 * n, 10_000) for steps, burn_in, n in seen)
