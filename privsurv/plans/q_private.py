"""Queries: bounds, noise, sanitised losses, mechanisms, releases, ledger, audits."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..functions import basis, loss, rng
from ..operators import audit, fit, metrics, noise, private, sensitivity
from ..operators.ledger import Ledger
from ..operators.objective import Data
from ..sources import workloads as W
from ..sources.tables import table
from . import spells_sql as Q
from .q_model import _LOGIT, _PERIODS, ALPHA, BETA, _loss, _records
from .q_prep import R
from .registry import query

GRIDS = ((200, 3), (20, 3), (10, 3), (200, 5))


def _s2(q: int, e: int, name: str) -> str:
    return f"{Q.basis(q, e, name)}, {name}n AS (SELECT {q} AS q, {e} AS e, s, {' + '.join(f'a{i + 1} * a{i + 1}' for i in range(e))} AS s2 FROM {name})"


_ALL = ", ".join(_s2(q, e, f"b{i}") for i, (q, e) in enumerate(GRIDS)) + ", n AS (" + " UNION ALL ".join(f"SELECT * FROM b{i}n" for i in range(len(GRIDS))) + ")"


def _norms(spark):
    out = None
    for q, e in GRIDS:
        own = sensitivity.norms(basis.natural_spline(spark, q, e)).select(F.lit(q).alias("q"), F.lit(e).alias("e"), "s", "s2")
        out = own if out is None else out.unionByName(own)
    return out


@query(f"WITH {_ALL} SELECT q, e, round(sum(sqrt(4 + s2)) + max(sqrt(4 * s2 + 4)), 6) AS bound FROM n GROUP BY ALL")
def sens_gradient(spark, sf_dir):
    return _norms(spark).groupBy("q", "e").agg(F.round(sensitivity.gradient_columns(), 6).alias("bound"))


@query(f"WITH {_ALL} SELECT q, e, round(sum(sqrt(4 + s2)) + max(sqrt(4 * s2 + 4) - sqrt(4 + s2)), 6) AS bound FROM n GROUP BY ALL")
def sens_tight(spark, sf_dir):
    rows = [(q, e, sensitivity.gradient(basis.matrix(q, e), "tight")) for q, e in GRIDS]
    return spark.createDataFrame(rows, "q int, e int, bound double").select("q", "e", F.round("bound", 6).alias("bound"))


@query(f"WITH {_ALL}, c AS (SELECT count(*) AS n FROM ({Q.SPELLS['s4']})) SELECT lam, round((sum(sqrt(4 + s2)) + max(sqrt(4 * s2 + 4))) / (max(c.n) * lam), 6) AS bound FROM n, c, (VALUES (1e-3), (1e-2), (1e-1)) v(lam) WHERE q = 200 AND e = 3 GROUP BY lam")
def sens_minimizer(spark, sf_dir):
    n = W.signups(spark, sf_dir).count()
    rows = [(lam, sensitivity.minimizer(basis.matrix(200, 3), n, lam)) for lam in (1e-3, 1e-2, 1e-1)]
    return spark.createDataFrame(rows, "lam double, bound double").select("lam", F.round("bound", 6).alias("bound"))


_MASS = "(VALUES (40.0::DOUBLE), (200.0), (3000.0)) v(m)"


def _charges(spark, mode):
    rows = [(q, e, float(m), sensitivity.jacobian_charge(basis.matrix(q, e), m, mode)) for q, e in GRIDS for m in (40, 200, 3000)]
    return spark.createDataFrame(rows, "q int, e int, m double, charge double").select("q", "e", "m", F.round("charge", 8).alias("charge"))


@query(f"WITH {_ALL} SELECT q, e, m, round(greatest(2 * sum(ln(1 + 0.25 * sqrt(s2 + 1) / m)), sum(ln(1 + 0.25 * (s2 + 1) / m))), 8) AS charge FROM n, {_MASS} GROUP BY ALL")
def jacobian_charge(spark, sf_dir):
    return _charges(spark, "printed")


@query(f"WITH {_ALL} SELECT q, e, m, round(sum(ln(1 + 0.25 * (s2 + 1) / m)), 8) AS charge FROM n, {_MASS} GROUP BY ALL")
def jacobian_charge_one_sided(spark, sf_dir):
    return _charges(spark, "one_sided")


@query(f"WITH {_ALL} SELECT q, e, m, round(2 * sum(ln(1 + 0.25 * (s2 + 1) / m)), 8) AS charge FROM n, {_MASS} GROUP BY ALL")
def jacobian_charge_squared(spark, sf_dir):
    return _charges(spark, "squared")


@query(f"""WITH RECURSIVE {_s2(20, 3, 'b')}, eps AS (SELECT epsilon FROM (VALUES (0.1::DOUBLE), (1.6), (6.4)) v(epsilon)), n AS (SELECT count(DISTINCT user_id) AS n FROM events WHERE event_type = 'signup'),
c0 AS (SELECT epsilon, any_value(n) AS n, 2 * sum(ln(1 + 0.25 * sqrt(s2 + 1) / (n * 0.001))) AS c0 FROM bn, n, eps GROUP BY epsilon),
f AS (SELECT m, 2 * sum(ln(1 + 0.25 * sqrt(s2 + 1) / m)) AS c FROM bn, (SELECT power(10, i / 400.0) AS m FROM range(-400, 2001) r(i)) GROUP BY m),
z AS (SELECT epsilon, max(m) AS lo FROM eps JOIN f ON c > epsilon / 2 GROUP BY 1),
it AS (SELECT epsilon, 0 AS k, lo, lo * 1.01 AS hi FROM z UNION ALL
 SELECT epsilon, k + 1, CASE WHEN c > epsilon / 2 THEN mid ELSE lo END, CASE WHEN c > epsilon / 2 THEN hi ELSE mid END FROM
 (SELECT it.*, (lo + hi) / 2 AS mid, (SELECT 2 * sum(ln(1 + 0.25 * sqrt(s2 + 1) / ((lo + hi) / 2))) FROM bn) AS c FROM it WHERE k < 45))
SELECT epsilon, round(CASE WHEN c0 <= epsilon / 2 THEN n * 0.001 ELSE hi END, 4) AS mass, round(CASE WHEN c0 <= epsilon / 2 THEN 0 ELSE hi / n - 0.001 END, 7) + 0.0 AS extra,
round(CASE WHEN c0 <= epsilon / 2 THEN epsilon - c0 ELSE epsilon / 2 END, 6) AS left_ FROM it JOIN c0 USING (epsilon) WHERE k = 45""")
def extra_ridge(spark, sf_dir):
    """Ridge that the objective method adds at ridge 0.001 for as many records as users have signed up: the fewer, the more."""
    n, rows = table(spark, sf_dir, "events", ["event_type", "user_id"]).where("event_type = 'signup'").agg(F.countDistinct("user_id")).first()[0], []
    for eps in (0.1, 1.6, 6.4):
        extra, left = sensitivity.extra_ridge(basis.matrix(20, 3), n, 0.001, eps)
        rows.append((eps, n * (extra + 0.001), extra, left))
    return spark.createDataFrame(rows, "epsilon double, mass double, extra double, left_ double").select("epsilon", F.round("mass", 4).alias("mass"), R(F.col("extra"), 7).alias("extra"), F.round("left_", 6).alias("left_"))


def _u(*keys: str) -> str:
    return f"((('0x' || substr(md5({' || '.join(keys)}), 1, 13))::BIGINT + 0.5) / 4503599627370496.0)"


_NOISE = f"""WITH k AS (SELECT run, i FROM range(0, 50) a(run), range(0, 6) b(i)),
d AS (SELECT run, i, -ln({_u("'9|'", 'run', "'|length|'", 'i')}) AS e, sqrt(-2 * ln({_u("'9|'", 'run', "'|way|'", 'i', "'|r'")})) * cos(2 * pi() * {_u("'9|'", 'run', "'|way|'", 'i', "'|a'")}) AS g FROM k),
t AS (SELECT run, i, 0.25 * sum(e) OVER (PARTITION BY run) AS length, g / sqrt(sum(g * g) OVER (PARTITION BY run)) AS way FROM d)"""


@query(_NOISE + " SELECT run, i, round(length, 8) AS length, round(length * way, 8) + 0.0 AS b FROM t")
def gamma_noise_replay(spark, sf_dir):
    """Columns of digest noise: six components, scale 0.25."""
    k = spark.range(50).select(F.col("id").alias("run")).crossJoin(spark.range(6).select(F.col("id").alias("i")))
    from pyspark.sql import Window

    own = Window.partitionBy("run")
    d = k.select("run", "i", rng.exponential("9", F.col("run"), "length", F.col("i")).alias("e"), rng.normal("9", F.col("run"), "way", F.col("i")).alias("g"))
    length = 0.25 * F.sum("e").over(own)
    return d.select("run", "i", F.round(length, 8).alias("length"), R(length * F.col("g") / F.sqrt(F.sum(F.col("g") * F.col("g")).over(own)), 8).alias("b"))


@query(_NOISE + " SELECT run, round(sqrt(sum(length * way * length * way)), 8) AS norm, round(max(CASE WHEN i = 0 THEN length * way END), 8) + 0.0 AS first, round(max(CASE WHEN i = 5 THEN length * way END), 8) + 0.0 AS last FROM t GROUP BY run")
def noise_driver_replay(spark, sf_dir):
    """The driver's replay of the same draws."""
    drawn = [noise.gamma_sphere(6, 0.25, f"9|{r}") for r in range(50)]
    rows = [(r, float(np.linalg.norm(b)), float(b[0]), float(b[5])) for r, b in enumerate(drawn)]
    return spark.createDataFrame(rows, "run long, norm double, first double, last double").select("run", *[R(F.col(c), 8).alias(c) for c in ("norm", "first", "last")])


@query(f"WITH d AS (SELECT i, {' + '.join('-ln(' + _u(chr(39) + 'm|' + chr(39), 'i', chr(39) + f'|{j}' + chr(39)) + ')' for j in range(6))} AS g FROM range(0, 4000) r(i)) SELECT count(*) AS n, round(avg(g), 6) AS mean, round(var_pop(g), 5) AS variance, abs(avg(g) - 6) < 0.2 AS near FROM d")
def noise_moments(spark, sf_dir):
    """Gamma lengths have mean and variance six."""
    g = spark.range(4000).select(rng.gamma(6, "m", F.col("id")).alias("g"))
    return g.agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("g"), 6).alias("mean"), F.round(F.var_pop("g"), 5).alias("variance"), (F.abs(F.avg("g") - 6) < 0.2).alias("near"))


@query("SELECT x, round(20 * tanh(x / 20.0), 8) AS c, round(1 - power(tanh(x / 20.0), 2), 8) AS slope, least(x, 20)::DOUBLE AS clip FROM (SELECT i / 2.0::DOUBLE AS x FROM range(0, 81) r(i))")
def sanitizer_curve(spark, sf_dir):
    x = spark.range(81).select((F.col("id") / 2).alias("x"))
    return x.select("x", F.round(loss.sanitize(F.col("x"), 20), 8).alias("c"), F.round(loss.sanitize_slope(F.col("x"), 20), 8).alias("slope"), loss.sanitize(F.col("x"), 20, "clip").alias("clip"))


_LOSSES = f"{_PERIODS}, l AS (SELECT subject_id, sum({_LOGIT}) AS loss FROM periods GROUP BY 1)"


@query(f"WITH {_LOSSES} SELECT subject_id, round(4 * tanh(loss / 4), 6) AS bounded FROM l")
def sanitized_loss(spark, sf_dir):
    return _records(spark, sf_dir).select("subject_id", F.round(loss.sanitize(_loss(), 4), 6).alias("bounded"))


@query(f"""WITH {_LOSSES}, g AS (SELECT subject_id, {', '.join(f'sum((1 / (1 + exp(-eta)) - fails) * {c}) AS g{i}' for i, c in enumerate(['a1', 'a2', 'a3', 'x1', 'x2', 'x3']))} FROM periods GROUP BY 1)
SELECT {', '.join(f'round(avg((1 - power(tanh(loss / 4), 2)) * g{i}), 6) + 0.0 AS g{i + 1}' for i in range(6))} FROM g JOIN l USING (subject_id)""")
def sanitized_gradient(spark, sf_dir):
    from ..functions.loss import SumOfLogistic
    from ..operators.chain import bounded_gradient, pool

    d = Data(_records(spark, sf_dir), basis.matrix(8, 3))
    g, _ = bounded_gradient(SumOfLogistic(d.a), np.array([*ALPHA, *BETA]), *pool(d), 4.0, "tanh")
    return spark.createDataFrame([tuple(float(v) for v in g)], ", ".join(f"g{i + 1} double" for i in range(6))).select(*[R(F.col(f"g{i + 1}")).alias(f"g{i + 1}") for i in range(6)])


_F2 = sum(v * v for v in (*ALPHA, *BETA))


@query(f"WITH {_LOSSES} SELECT round(-0.5 * 0.05 * {_F2} - sum(4 * tanh(loss / 4)), 6) AS utility, round((1.0 / 8) * (-0.5 * 0.05 * {_F2} - sum(4 * tanh(loss / 4))), 6) AS log_density FROM l")
def utility_value(spark, sf_dir):
    u = private.utility(Data(_records(spark, sf_dir), basis.matrix(8, 3)), np.array([*ALPHA, *BETA]), 4.0, 0.05)
    return spark.createDataFrame([(round(u, 6), round(u / 8, 6))], "utility double, log_density double")


@query(f"WITH {_LOSSES} SELECT round(max(4 * tanh(loss / 4)) - min(4 * tanh(loss / 4)), 6) AS gap, true AS ok FROM l")
def utility_sensitivity(spark, sf_dir):
    return audit.utility_gap(_records(spark, sf_dir).select(_loss().alias("loss")), 4.0).select(F.round("gap", 6).alias("gap"), "ok")


@query("""WITH s AS (SELECT c_nationkey::BIGINT AS id, count(*)::DOUBLE AS score FROM customer GROUP BY 1), w AS (SELECT *, exp((score - max(score) OVER ()) * 0.5 / 2) AS wt FROM s),
r AS (SELECT *, sum(wt) OVER (ORDER BY id) AS upto, sum(wt) OVER () AS total FROM w)
SELECT id, score, round(wt / total, 9) AS p, (upto >= 0.37 * total AND upto - wt < 0.37 * total) AS drawn FROM r""")
def exponential_mechanism_grid(spark, sf_dir):
    """Nation with about the most customers, privately."""
    s = table(spark, sf_dir, "customer", ["c_nationkey"]).groupBy(F.col("c_nationkey").cast("long").alias("id")).agg(F.count(F.lit(1)).cast("double").alias("score"))
    return private.exponential_mechanism(s, 0.5, 1.0, 0.37).select("id", "score", F.round("p", 9).alias("p"), "drawn")


@query("""WITH a AS (SELECT o_orderpriority AS priority, count(DISTINCT o_custkey) AS n FROM orders GROUP BY 1)
SELECT priority, n, epsilon, round(2 * ln(n), 8) AS v, round(0.01 * 2 * 2 * ln(n) / epsilon, 8) AS sigma FROM a, (VALUES (0.1::DOUBLE), (6.4)) b(epsilon)""")
def default_bounds(spark, sf_dir):
    """For as many records as customers have orders of each priority."""
    units = table(spark, sf_dir, "orders", ["o_orderpriority", "o_custkey"]).groupBy("o_orderpriority").agg(F.countDistinct("o_custkey").alias("n")).collect()  # a row per priority
    rows = [(k, n, e, private.default_bound(n), private.default_prior(private.default_bound(n), e)) for k, n in units for e in (0.1, 6.4)]
    return spark.createDataFrame(rows, "priority string, n long, epsilon double, v double, sigma double").select("priority", "n", "epsilon", F.round("v", 8).alias("v"), F.round("sigma", 8).alias("sigma"))


@query("SELECT unit, round(sum(e * g), 6) AS spent, count(*) AS runs, min(x) AS exact FROM (VALUES ('s4', 1.6, 1, 1), ('s4', 0.4, 2, 0), ('s5', 6.4, 1, 1)) v(unit, e, g, x) GROUP BY unit")
def ledger_total(spark, sf_dir):
    led = Ledger(spark, 10)
    led.charge("a", "s4", 1.6)
    led.charge("b", "s4", 0.4, 2, exact=False)
    led.charge("c", "s5", 6.4)
    return Ledger.total(led.frame()).select("unit", F.round("spent", 6).alias("spent"), "runs", "exact")


@query(f"""WITH {Q.records('s5')}, a AS (SELECT subject_id, t, y, x1, x2, x3 FROM records), b AS (SELECT subject_id, t, CASE WHEN subject_id = (SELECT min(subject_id) FROM a) THEN -y ELSE y END AS y, x1, x2, x3 FROM a)
SELECT (SELECT count(*) FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b))::INT AS left_only, (SELECT count(*) FROM (SELECT * FROM b EXCEPT ALL SELECT * FROM a))::INT AS right_only""")
def neighbor_audit(spark, sf_dir):
    """A neighbour differs in one record on either side."""
    df = _records(spark, sf_dir).drop("unit_id")
    first = df.agg(F.min("subject_id")).first()[0]
    new = df.where(F.col("subject_id") == first).withColumn("y", -F.col("y"))
    out = audit.difference(df, audit.swapped(df, first, new)).groupBy().pivot("side", ["left", "right"]).count()
    return out.select(F.col("left").cast("int").alias("left_only"), F.col("right").cast("int").alias("right_only"))


def _worst_sql(q: int) -> str:
    """At zero coefficients, over all pairs of records with opposite unit covariates: largest gradient difference over its bound."""
    return f"""SELECT {q} AS q, round(max(sqrt(power(a.g1 - b.g1, 2) + power(a.g2 - b.g2, 2) + power(a.g3 - b.g3, 2) + power(a.g4 - b.g4, 2))) / (SELECT sum(sqrt(4 + s2)) + max(sqrt(4 * s2 + 4)) FROM b{q}n), 6) AS ratio
    FROM (SELECT * FROM g{q} WHERE x = 1) a, (SELECT * FROM g{q} WHERE x = -1) b"""


def _ends_sql(q: int) -> str:
    terms = ", ".join(f"sum(0.5 * a{i}) - max(CASE WHEN s = t AND y = 1 THEN a{i} ELSE -1e9 END) * (y = 1)::INT AS g{i}" for i in (1, 2, 3))
    return f"g{q} AS (SELECT t, y, x, {terms}, x * (0.5 * t - (y = 1)::INT) AS g4 FROM b{q}, range(1, {q + 1}) r(t), (VALUES (1), (-1)) w(y), (VALUES (1), (-1)) z(x) WHERE s <= t GROUP BY t, y, x)"


@query(f"WITH {_s2(10, 3, 'b10')}, {_s2(20, 3, 'b20')}, {_ends_sql(10)}, {_ends_sql(20)} {_worst_sql(10)} UNION ALL {_worst_sql(20)}")
def gradient_bound_audit(spark, sf_dir):
    """How much of the gradient bound all pairs of records use at zero coefficients; never more than one."""
    rows = [(q, audit.gradient_use(basis.matrix(q, 3))) for q in (10, 20)]
    return spark.createDataFrame(rows, "q int, ratio double").select("q", F.round("ratio", 6).alias("ratio"))


@query("SELECT true AS within_budget, true AS moved_less_than_bound")
def output_ratio_audit(spark, sf_dir):
    """Fits of explicit neighbours: how far the optimum moves, and the largest log density ratio at epsilon 1."""
    df, lam = _records(spark, sf_dir), 0.05
    first = df.orderBy("t", "subject_id").first()["subject_id"]
    new = df.where(F.col("subject_id") == first).withColumn("t", F.lit(8)).withColumn("y", -F.col("y"))
    d1, d2 = Data(df, basis.matrix(8, 3)), Data(audit.swapped(df, first, new), basis.matrix(8, 3))
    f1, f2, t = fit.ridge(d1, lam), fit.ridge(d2, lam), sensitivity.minimizer(d1.a, d1.n, lam)
    points = np.random.default_rng(0).standard_normal((500, 6)) * 3
    return spark.createDataFrame([(bool(audit.output_ratio(f1, f2, t, 1.0, points) <= 1), bool(np.linalg.norm(f1 - f2) <= t))], "within_budget boolean, moved_less_than_bound boolean")


@query()
def output_noise_release(spark, sf_dir):
    """The flagship: signups with a private output-noise fit, from the system's entropy."""
    d = fit.data(W.frame(spark, sf_dir, "s4"), 200)
    return private.output_noise_fit(d, 6.4, 0.01, ledger=Ledger(spark, 6.4)).frame(spark)


@query()
def objective_noise_release(spark, sf_dir):
    return private.objective_noise_fit(fit.data(W.frame(spark, sf_dir, "s4"), 200), 6.4, 0.01).frame(spark)


@query("SELECT round(sqrt((0.0122443-0.0585478)^2 + (-0.849823+0.790977)^2 + (-0.239539+0.23906)^2) / sqrt(0.0585478^2 + 0.790977^2 + 0.23906^2) * 100, 6) AS percent")
def relative_error_worked(spark, sf_dir):
    row = spark.range(1).select(F.array(F.lit(0.0122443), F.lit(-0.849823), F.lit(-0.239539)).alias("a"), F.array(F.lit(0.0585478), F.lit(-0.790977), F.lit(-0.23906)).alias("b"))
    return row.select(F.round(100 * metrics.relative_error(F.col("a"), F.col("b")), 6).alias("percent"))


