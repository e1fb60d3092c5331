"""Bounded losses summed through sums of products equal those summed record by record, and Metropolis chains use them."""

import numpy as np
import pytest

from privsurv.functions import basis
from privsurv.functions.loss import SumOfLogistic
from privsurv.functions.moments import Moments
from privsurv.operators import chain
from privsurv.operators.objective import Data
from privsurv.sources.planted import planted


def records(n, p, seed=1):
    g = np.random.default_rng(seed)
    x = g.uniform(-1, 1, (n, p)) / np.sqrt(p)
    return basis.matrix(50, 3), x, g.integers(1, 51, n), g.choice((-1, 1), n), g.integers(1, 4, n)


@pytest.mark.parametrize("p", [1, 2, 3])
@pytest.mark.parametrize("bound", ["tanh", "none"])
def test_totals_equal_sums_of_records(p, bound):
    a, x, t, y, w = records(3000, p)
    m, g = Moments(a, np.abs(x).max(axis=0)).take(x, t, y, w), np.random.default_rng(2)
    held = chain.Held(a, "logit", x, t, y, chain.Config(1.0, 16.0, 0.1, 1, bound=bound), w=w)
    for f in [np.zeros(3 + p), *(np.concatenate(([-4.0, 0.5, -0.5], 0.4 * g.standard_normal(p))) for _ in range(5))]:
        want = chain.bounded_gradient(held.kernel, f, x, t, y, 16.0, bound, w.astype(float))[1]
        assert np.isclose(m.total(f, 16.0, bound), want, rtol=1e-13, atol=0) and np.isclose(held.total(f), want, rtol=1e-13, atol=0)


def test_where_a_polynomial_does_not_settle_records_are_summed():
    a, x, t, y, _ = records(3000, 3)
    m, far = Moments(a, np.abs(x).max(axis=0)).take(x, t, y), np.array([-4.0, 0.5, -0.5, 9.0, -9.0, 9.0])
    assert m.total(far, 16.0, "tanh") is None and m.total(np.zeros(6), 16.0, "clip") is None
    held = chain.Held(a, "logit", x, t, y, chain.Config(1.0, 16.0, 0.1, 1))
    assert held.total(far) == chain.bounded_gradient(held.kernel, far, x, t, y, 16.0, "tanh")[1]


def test_metropolis_steps_read_no_record(monkeypatch):
    a, x, t, y, _ = records(3000, 3)
    c = chain.Config(6.4, 16.0, 0.1, 50, sampler="metropolis", step_scale=0.1)
    want = chain.run_chain(a, "logit", x, t, y, chain.variants(c, steps=3))[0]
    with monkeypatch.context() as only:
        only.setattr(chain.Moments, "pays", staticmethod(lambda *_: False))
        assert np.allclose(chain.run_chain(a, "logit", x, t, y, chain.variants(c, steps=3))[0], want, rtol=0, atol=1e-12)
    monkeypatch.setattr(chain, "bounded_gradient", lambda *_: pytest.fail("a pass over the records"))
    assert np.isfinite(chain.run_chain(a, "logit", x, t, y, c)[0]).all()


def test_metropolis_over_distributed_records_takes_one_pass(spark, monkeypatch):
    d = Data(planted(spark, 2500, [-4.0, 1.0, -1.0], [0.8, -0.5, 0.3], 20).persist(), basis.matrix(20, 3))
    c = chain.Config(2.0, 16.0, 0.05, 40, sampler="metropolis", step_scale=0.1, seed=4)
    want = chain.sample(d, {"m": c}).where("last").first()["f"]
    monkeypatch.setattr(chain, "POOL", 100)
    monkeypatch.setattr(chain.Spread, "_sums", lambda *_: pytest.fail("a pass a step"))
    assert np.allclose(chain.sample(d, {"m": c}).where("last").first()["f"], want, rtol=0, atol=1e-9)


def test_close_effects_share_terms_and_sums_stay():
    a, x, t, y, _ = records(400, 3)
    kernel, slope = SumOfLogistic(a), lambda own: 1 - np.tanh(own / 16) ** 2
    for f in (np.zeros(6), np.array([-4.0, 0.5, -0.5, 0.3, -0.2, 0.1]), np.array([1.0, 0.5, -0.5, 0.0, 0.0, 0.4])):
        loss, grad = kernel.gradients(f, x, t, y)
        with pytest.MonkeyPatch.context() as only:
            shared = kernel._shared
            only.setattr(kernel, "_shared", lambda *own: (used.append(1), shared(*own))[1])
            used = []
            got = kernel.weighted(f, x, t, y, slope)
        assert used and np.allclose(got[0], loss, rtol=1e-12, atol=0) and np.allclose(got[1], slope(loss) @ grad, rtol=1e-10, atol=1e-10)


def test_larger_pools_are_sent_to_tasks_with_the_same_chains(spark, monkeypatch):
    d = Data(planted(spark, 300, [-4.0, 1.0, -1.0], [0.8, -0.5, 0.3], 20).persist(), basis.matrix(20, 3))
    base = chain.Config(2.0, 4.0, 0.05, 30, k=20, step_scale=0.01, burn_in=1, every=7)
    runs = {f"{s}": chain.variants(base, seed=s) for s in range(5)}
    state = lambda df: {(r["chain_id"], r["step"], r["last"]): r["f"] for r in df.collect()}
    want = state(chain.sample(d, runs))
    assert chain.sample(d, runs).rdd.glom().map(len).filter(bool).count() == 5  # a task each
    monkeypatch.setattr(chain, "POOL", 1000)
    monkeypatch.setattr(chain, "_run_large", lambda *_: pytest.fail("joins for each block of steps"))
    got = state(chain.sample(d, runs))
    assert got.keys() == want.keys() and all(np.allclose(got[k], v, rtol=0, atol=1e-12) for k, v in want.items())
