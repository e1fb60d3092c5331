"""Chains whose steps take all records count equal ones once, by weight."""

import numpy as np
from pyspark.sql import functions as F

from privsurv.functions.loss import SumOfLogistic
from privsurv.operators import chain
from privsurv.operators.objective import Data


def test_weights_stand_for_equal_records(spark):
    a = np.stack((np.ones(8), np.arange(1, 9) / 8), axis=1)
    t, y, w = np.array([1, 3, 8]), np.array([1, -1, 1]), np.array([4, 1, 3])
    x, f = np.zeros((3, 0)), np.array([-1.0, 0.5])
    for bound in ("tanh", "clip", "none"):
        got = chain.bounded_gradient(SumOfLogistic(a), f, x, t, y, 2.0, bound, w)
        want = chain.bounded_gradient(SumOfLogistic(a), f, np.zeros((8, 0)), np.repeat(t, w), np.repeat(y, w), 2.0, bound)
        assert np.allclose(got[0], want[0]) and np.isclose(got[1], want[1])
    cells = spark.createDataFrame([(int(i), int(j), int(k)) for i, j, k in zip(t, y, w)], "t int, y int, w long")
    each = cells.select("t", "y", F.explode(F.sequence(F.lit(1), F.col("w"))).alias("k")).select("t", "y", F.lit(1).cast("long").alias("w"))
    base = chain.Config(2.0, 4.0, 0.4, 20, k=None, seed=5, step_scale=0.1)
    runs = {"metropolis": chain.variants(base, sampler="metropolis"), "full": base, "small": chain.variants(base, k=2)}
    state = lambda df: {(r["chain_id"], r["step"]): r["f"] for r in chain.sample(Data(df, a), runs).collect()}
    got, want = state(cells), state(each)
    assert got.keys() == want.keys() and all(np.allclose(got[k], want[k]) for k in got)


def test_states_are_counted_at_their_nearest_point_of_the_grid(spark):
    from privsurv.plans import q_chains

    df = spark.createDataFrame([(-5.01,), (-5.07,), (4.95,), (4.93,)], "v double")
    assert [r[0] for r in df.select(F.floor(q_chains.nearest(F.col("v")))).collect()] == [-5, -6, 5, 4]


def test_sums_by_products_of_odds_equal_sums_by_terms():
    g = np.random.default_rng(0)
    from privsurv.functions import basis

    for q in (1, 7, 200):
        k, n = SumOfLogistic(basis.matrix(q, 3)), 700
        x, t, w = g.normal(size=(n, 2)), g.integers(1, q + 1, n), g.integers(0, 4, n).astype(float)
        y, f = np.where(g.random(n) < 0.4, 1, -1), np.array([-2.0, 1.0, -1.0, 0.8, -0.5])
        eta = (k.a @ f[:3])[None, :] + (x @ f[3:])[:, None]
        alive, fails = np.arange(1, q + 1) <= t[:, None], (np.arange(1, q + 1) == t[:, None]) & (y == 1)[:, None]
        z = np.concatenate((np.broadcast_to(k.a, (n, q, 3)), np.broadcast_to(x[:, None], (n, q, 2))), axis=2)
        p = 1 / (1 + np.exp(-eta))
        r, c = w[:, None] * (p * alive - fails), w[:, None] * p * (1 - p) * alive
        want = [(w[:, None] * (np.logaddexp(0, eta) * alive - eta * fails)).sum(), *np.einsum("ns,nsi->i", r, z), *np.einsum("ns,nsi,nsj->ij", c, z, z)[np.triu_indices(5)]]
        assert np.allclose(k._odds_sums(np.exp(k.a @ f[:3]), np.exp(x @ f[3:]), f, x, t, y, w, True), want)
        assert np.allclose(k.sums(f, x, t, y, w, True), want) and np.allclose(k.sums(f, x, t, y, w), want[:6])
        assert np.isfinite(k.sums(1000 * f, x, t, y, w, True)).all()  # odds beyond the limit are summed by terms
