import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from privsurv.functions import basis, links, loss, rng, udfs
from privsurv.functions import sql as sql_functions
from privsurv.functions.loss import SumOfLogistic


def random_records(n=60, q=12, p=3, seed=0):
    g = np.random.default_rng(seed)
    x = g.standard_normal((n, p))
    x /= np.maximum(1, np.linalg.norm(x, axis=1, keepdims=True))
    return x, g.integers(1, q + 1, n), g.choice([-1, 1], n)


def test_basis_ends_and_knots():
    a = basis.matrix(200, 3)
    assert np.allclose(a[-1], [1, 1, 0.75])
    u = np.arange(1, 201) / 200
    assert np.allclose(a[:, 2], u**3 - 2 * np.maximum(u - 0.5, 0) ** 3)
    assert np.allclose(basis.matrix(10, 2)[:, 1], np.arange(1, 11) / 10)
    with pytest.raises(ValueError):
        basis.knots(1)


def test_basis_frame_equals_matrix(spark):
    for e, grid in ((3, "right"), (5, "mid")):
        rows = basis.natural_spline(spark, 30, e, grid).orderBy("s").collect()
        assert np.allclose([r["a"] for r in rows], basis.matrix(30, e, grid))


@pytest.mark.parametrize("link", links.LINKS)
def test_gradient_is_the_slope_of_the_loss(link):
    x, t, y = random_records()
    k, f = SumOfLogistic(basis.matrix(12, 3), link, chunk=17), np.array([-0.5, 0.4, -0.3, 0.2, -0.1, 0.3])
    _, grad = k.gradients(f, x, t, y)
    for i in range(6):
        h = np.zeros(6)
        h[i] = 1e-5
        slope = (k.losses(f + h, x, t, y) - k.losses(f - h, x, t, y)) / 2e-5
        assert np.allclose(slope, grad[:, i], atol=2e-3 if link == "probit" else 1e-6)


def test_hessian_is_positive_and_matches_gradient_slopes():
    x, t, y = random_records()
    k, f, w = SumOfLogistic(basis.matrix(12, 3)), np.array([-0.5, 0.4, -0.3, 0.2, -0.1, 0.3]), np.ones(60)
    s = k.sums(f, x, t, y, w, hessian=True)
    h = np.zeros((6, 6))
    h[np.triu_indices(6)] = s[7:]
    h = h + h.T - np.diag(np.diag(h))
    assert np.linalg.eigvalsh(h).min() > -1e-9
    for i in range(6):
        d = np.zeros(6)
        d[i] = 1e-5
        assert np.allclose((k.sums(f + d, x, t, y, w)[1:7] - k.sums(f - d, x, t, y, w)[1:7]) / 2e-5, h[i], atol=1e-4)


def test_zero_coefficients_cost_ln2_per_interval():
    x = np.zeros((3, 1))
    t, y = np.array([1, 3, 5]), np.array([1, -1, 1])
    assert np.allclose(SumOfLogistic(basis.matrix(5, 3)).losses(np.zeros(4), x, t, y), t * math.log(2))


def test_one_interval_is_plain_logistic():
    x, _, y = random_records()
    got = SumOfLogistic(np.ones((1, 1))).losses(np.array([0.3, 1, -1, 0.5]), x, np.ones(60, int), y)
    assert np.allclose(got, np.log1p(np.exp(-y * (0.3 + x @ [1, -1, 0.5]))))


def test_columns_equal_kernels(spark):
    x, t, y = random_records()
    f = [-0.5, 0.4, -0.3, 0.2, -0.1, 0.3]
    df = spark.createDataFrame([(int(a), int(b), *map(float, c)) for a, b, c in zip(t, y, x, strict=True)], "t int, y int, x1 double, x2 double, x3 double")
    z = loss.dot([F.col(f"x{i}") for i in (1, 2, 3)], f[3:])
    for link in links.LINKS:
        got = [r[0] for r in df.select(loss.record_loss(F.col("t"), F.col("y"), z, f[:3], 12, link)).collect()]
        assert np.allclose(got, SumOfLogistic(basis.matrix(12, 3), link).losses(np.array(f), x, t, y), atol=1e-6)
    arrow = udfs.record_loss_arrow(f, 12, 3)
    got = [r[0] for r in df.select(arrow("t", "y", F.array("x1", "x2", "x3"))).collect()]
    assert np.allclose(got, SumOfLogistic(basis.matrix(12, 3)).losses(np.array(f), x, t, y))


def test_sanitizer_values(spark):
    want = {1: 0.999167, 5: 4.898373, 10: 9.242343, 20: 15.231883, 40: 19.280552}
    df = spark.createDataFrame([(float(k),) for k in want], "x double")
    got = {r[0]: r[1] for r in df.select("x", loss.sanitize(F.col("x"), 20)).collect()}
    assert all(abs(got[k] - v) < 1e-6 for k, v in want.items())


def test_links_agree_for_small_hazards(spark):
    row = spark.range(1).select(links.score(F.lit(0.001)).alias("a"), links.score(F.lit(0.001), "cloglog").alias("b"), links.normal_cdf(F.lit(1.3)).alias("c")).first()
    assert abs(row["a"] - row["b"]) < 1e-3
    assert abs(row["c"] - 0.5 * (1 + math.erf(1.3 / math.sqrt(2)))) < 2e-7
    assert abs(links.normal_quantile(row["c"]) - 1.3) < 1e-5


def test_random_columns_equal_python(spark):
    row = spark.range(1).select(rng.uniform("a", "1").alias("u"), rng.normal("a", "2").alias("n")).first()
    assert row["u"] == rng.value("a", 1) and abs(row["n"] - rng.normal_value("a", 2)) < 1e-12
    assert int(rng.value("a", 1) * 2**52) == 236542418672621


def test_sql_functions(spark):
    sql_functions.register(spark)
    row = spark.sql("SELECT vec_dot(array(1D, 2D), array(3D, 4D)) d, vec_norm(array(3D, 4D)) n, vec_norm(vec_clip_ball(array(3D, 4D), 1D)) c, vec_axpy(2D, array(1D), array(1D)) a, sanitize_loss(10D, 20D) s, logit_hazard(0D) h, spline_value(1D) b").first()
    assert (row.d, row.n, row.a, row.h, row.b) == (11, 5, [3], 0.5, [1, 1, 0.75]) and abs(row.c - 1) < 1e-12 and abs(row.s - 9.242343) < 1e-6
