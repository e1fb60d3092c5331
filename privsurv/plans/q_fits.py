"""Queries: fits, Cox regression, life tables, and their comparison."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..functions import basis, rng
from ..operators import baseline, cox, fit, metrics, prep, solver
from ..operators.objective import Data, Objective
from ..sources import workloads as W
from . import spells_sql as Q
from .q_model import S, _records
from .q_prep import R
from .registry import query


def _linear(spark, sf_dir, lam=0.1, **more) -> Objective:
    """S5 with a linear baseline and the raw opening flag: three coefficients."""
    df = prep.discretize(W.dialogues(spark, sf_dir), 8, 8.0).select("subject_id", "t", "y", "x1", F.lit(1).cast("long").alias("w"))
    return Objective(Data(prep.compress(df, ["x1"]), basis.matrix(8, 2)), lam, **more)


_CELLS = f"""cells AS (SELECT s / 8.0 AS u, x1, count(*)::DOUBLE AS n, sum((t = s AND y = 1)::INT)::DOUBLE AS m FROM
(SELECT x1, greatest(1, least(8, ceil(duration / 8.0 * 8)))::INT AS t, 2 * event - 1 AS y FROM ({Q.SPELLS['s5']})) JOIN range(1, 9) r(s) ON s <= t GROUP BY ALL),
size AS (SELECT count(*)::DOUBLE AS n FROM ({Q.SPELLS['s5']}))"""


def _descent(iterations: int, step: float, lam: float = 0.1, extra: str = "", linear: tuple = (0, 0, 0), before: str = "") -> str:
    """Gradient steps on the risk cells, as a recursive query."""
    eta = "(d.f1 + d.f2 * c.u + d.f3 * c.x1)"
    g = f"(c.n / (1 + exp(-{eta})) - c.m)"
    return f"""WITH RECURSIVE {_CELLS}, {before}d AS (SELECT 0 AS k, 0.0::DOUBLE AS f1, 0.0::DOUBLE AS f2, 0.0::DOUBLE AS f3 UNION ALL
    SELECT k + 1, f1 - {step} * (g1 / n + {lam} * f1 + {linear[0]} / n), f2 - {step} * (g2 / n + {lam} * f2 + {linear[1]} / n), f3 - {step} * (g3 / n + {lam} * f3 + {linear[2]} / n)
    FROM (SELECT d.*, (SELECT n FROM size) AS n, (SELECT sum({g}) FROM cells c) AS g1, (SELECT sum({g} * c.u) FROM cells c) AS g2, (SELECT sum({g} * c.x1) FROM cells c) AS g3 FROM d WHERE k < {iterations})){extra}"""


def _row(spark, f, n=4):
    return spark.createDataFrame([tuple(float(v) for v in f)], ", ".join(f"f{i + 1} double" for i in range(len(f)))).select(*[R(F.col(f"f{i + 1}"), n).alias(f"f{i + 1}") for i in range(len(f))])


_FINAL = "SELECT round(f1, 4) + 0.0 AS f1, round(f2, 4) + 0.0 AS f2, round(f3, 4) + 0.0 AS f3 FROM d WHERE k = "


@query(_descent(400, 0.4) + " " + _FINAL + "400")
def ridge_s5(spark, sf_dir):
    """Newton optimum, against descent in the oracle."""
    return _row(spark, solver.newton(_linear(spark, sf_dir)))


#: The same descent on S6: fifty intervals of document length, events if toxic, the quality flag as covariate.
_CELLS_S6 = _CELLS.replace("s / 8.0", "s / 50.0").replace("least(8, ceil(duration / 8.0 * 8))", "least(50, ceil(duration / 50000.0 * 50))").replace("range(1, 9)", "range(1, 51)").replace(Q.SPELLS["s5"], Q.SPELLS["s6"])


@query(_descent(1500, 0.3).replace(_CELLS, _CELLS_S6) + " " + _FINAL + "1500")
def ridge_s6(spark, sf_dir):
    """Lengths of labelled documents, fitted on compressed records."""
    df = prep.discretize(W.lengths(spark, sf_dir), 50, 50_000.0).select("subject_id", "t", "y", "x1", F.lit(1).cast("long").alias("w"))
    return _row(spark, fit.ridge(Data(prep.compress(df, ["x1"]), basis.matrix(50, 2)), 0.1))


@query(_descent(400, 0.4) + " " + _FINAL + "400")
def ridge_s5_bfgs(spark, sf_dir):
    return _row(spark, solver.bfgs(_linear(spark, sf_dir)))


@query(_descent(400, 0.4) + " " + _FINAL + "400")
def ridge_s5_lbfgs(spark, sf_dir):
    return _row(spark, solver.lbfgs(_linear(spark, sf_dir)))


@query(_descent(3000, 1.2, 0.0) + " SELECT round(f1, 3) + 0.0 AS f1, round(f2, 3) + 0.0 AS f2, round(f3, 3) + 0.0 AS f3 FROM d WHERE k = 3000")
def mle_s5(spark, sf_dir):
    """No penalty."""
    return _row(spark, fit.mle(_linear(spark, sf_dir).data), 3)


@query(_descent(12, 0.4) + " SELECT k::BIGINT AS k, round(f1, 8) + 0.0 AS f1, round(f2, 8) + 0.0 AS f2, round(f3, 8) + 0.0 AS f3 FROM d")
def gd_trajectory(spark, sf_dir):
    rows = [(k, *map(float, f)) for k, f in enumerate(solver.descend(_linear(spark, sf_dir), 0.4, 12))]
    return spark.createDataFrame(rows, "k long, f1 double, f2 double, f3 double").select("k", *[R(F.col(f"f{i}"), 8).alias(f"f{i}") for i in (1, 2, 3)])


@query(_descent(400, 0.4) + """, p AS (SELECT f1 + 0.3 AS f1, f2 - 0.2 AS f2, f3 + 0.1 AS f3 FROM d WHERE k = 400),
h AS (SELECT (c.n / (1 + exp(-(p.f1 + p.f2 * c.u + p.f3 * c.x1))) - c.m) AS g, c.u, c.x1, p.* FROM cells c, p),
g AS (SELECT sum(g) / any_value(n) + 0.1 * any_value(f1) AS g1, sum(g * u) / any_value(n) + 0.1 * any_value(f2) AS g2, sum(g * x1) / any_value(n) + 0.1 * any_value(f3) AS g3 FROM h, size)
SELECT round(sqrt(g1 * g1 + g2 * g2 + g3 * g3) / 0.1, 3) AS bound, sqrt(0.09 + 0.04 + 0.01) <= sqrt(g1 * g1 + g2 * g2 + g3 * g3) / 0.1 AS covers FROM g""")
def certificate_s5(spark, sf_dir):
    """Strong convexity bounds how far a point is from the optimum, here one that was moved away from it."""
    o = _linear(spark, sf_dir)
    f, away = solver.newton(o), np.array([0.3, -0.2, 0.1])
    bound = solver.certificate(o, f + away)
    return spark.createDataFrame([(bound, bool(np.linalg.norm(away) <= bound))], "bound double, covers boolean").select(F.round("bound", 3).alias("bound"), "covers")


@query(_descent(500, 0.5, 0.1, linear=(3.0, -2.0, 1.0)) + " " + _FINAL + "500")
def perturbed_fit_s5(spark, sf_dir):
    """An objective with a linear term, which is how objective noise enters."""
    return _row(spark, solver.newton(_linear(spark, sf_dir, b=np.array([3.0, -2.0, 1.0]))))


LENGTH = "length"


def _gamma_sql(key: str, d: int, scale: float) -> list[str]:
    """Replayed noise components as SQL expressions."""
    u = lambda *k: "((('0x' || substr(md5('" + "|".join(map(str, k)) + "'), 1, 13))::BIGINT + 0.5) / 4503599627370496.0)"
    length = f"({scale!r} * ({' + '.join(f'-ln({u(key, LENGTH, i)})' for i in range(d))}))"
    g = [f"(sqrt(-2 * ln({u(key, 'way', i, 'r')})) * cos(2 * pi() * {u(key, 'way', i, 'a')}))" for i in range(d)]
    norm = f"sqrt({' + '.join(f'{x} * {x}' for x in g)})"
    return [f"({length} * {x} / {norm})" for x in g]


_B8 = f"{Q.basis(8, 2, 'b8')}, sn AS (SELECT sum(sqrt(4 + a1 * a1 + a2 * a2)) + max(sqrt(4 * (a1 * a1 + a2 * a2) + 4)) AS g FROM b8)"
_N = _gamma_sql("replay", 3, 1.0)


@query(_descent(400, 0.4, 0.1, f", {_B8}") + f""" SELECT {', '.join(f"round(f{i + 1} + (g / (size.n * 0.1) + 2e-9 / 0.1) / 3.2 * {_N[i]}, 4) + 0.0 AS f{i + 1}" for i in range(3))} FROM d, sn, size WHERE k = 400""")
def output_noise_replay(spark, sf_dir):
    """Output noise with digest noise, so that the release itself can be compared (test mode, not private)."""
    from ..operators.private import output_noise_fit

    o = _linear(spark, sf_dir)
    return _row(spark, output_noise_fit(o.data, 3.2, 0.1, seed="replay").f)


_LEFT_S5 = "(SELECT 3.2 - greatest(2 * sum(ln(1 + 0.25 * sqrt(a1 * a1 + a2 * a2 + 1) / ((SELECT n FROM size) * 0.5))), sum(ln(1 + 0.25 * (a1 * a1 + a2 * a2 + 1) / ((SELECT n FROM size) * 0.5)))) FROM b8)"


@query(_descent(300, 0.4, 0.5, linear=tuple(f"((SELECT g FROM sn) / {_LEFT_S5} * {b})" for b in _N), before=f"{_B8}, ") + " " + _FINAL + "300")
def objective_noise_replay(spark, sf_dir):
    """Objective noise with digest noise; here the ridge suffices and none is added."""
    from ..operators.private import objective_noise_fit

    return _row(spark, objective_noise_fit(_linear(spark, sf_dir, 0.5).data, 3.2, 0.5, seed="replay", slack_share=0).f)


POINTS = ((0.0, 0.0, 0.0), (-2.0, 1.0, 0.5), (1.5, -3.0, 2.0), (-6.0, 4.0, -4.0))


def _ratio_sql() -> str:
    """Log density ratio of objective noise at some points, for S5 and a neighbour whose first record ends the other way."""
    points = " UNION ALL ".join(f"SELECT {i} AS point, {a}::DOUBLE AS f1, {b}::DOUBLE AS f2, {c}::DOUBLE AS f3" for i, (a, b, c) in enumerate(POINTS))
    cells = f"""r0 AS (SELECT subject_id, x1, greatest(1, least(8, ceil(duration / 8.0 * 8)))::INT AS t, 2 * event - 1 AS y FROM ({Q.SPELLS['s5']})),
    r AS (SELECT 0 AS side, * FROM r0 UNION ALL SELECT 1, subject_id, x1, t, CASE WHEN subject_id = (SELECT min(subject_id) FROM r0) THEN -y ELSE y END FROM r0),
    c AS (SELECT side, s / 8.0 AS u, x1, count(*)::DOUBLE AS n, sum((t = s AND y = 1)::INT)::DOUBLE AS m FROM r JOIN range(1, 9) g(s) ON s <= t GROUP BY ALL),
    size AS (SELECT count(*)::DOUBLE AS n FROM r0)"""
    h = lambda v: f"sum(c.n * p * (1 - p) * {v})"
    return f"""WITH {cells}, pt AS ({points}),
    e AS (SELECT point, side, f1, f2, f3, u, x1, n, m, 1 / (1 + exp(-(f1 + f2 * u + f3 * x1))) AS p FROM pt, c),
    k AS (SELECT point, side, any_value(f1) AS f1, any_value(f2) AS f2, any_value(f3) AS f3, sum(c.n * p - m) AS g1, sum((c.n * p - m) * u) AS g2, sum((c.n * p - m) * x1) AS g3,
      {h('1')} AS a, {h('u')} AS b, {h('x1')} AS d, {h('u * u')} AS e, {h('u * x1')} AS f, {h('x1 * x1')} AS i FROM e c GROUP BY ALL),
    m AS (SELECT point, side, sqrt(power(g1 + l * f1, 2) + power(g2 + l * f2, 2) + power(g3 + l * f3, 2)) AS b,
      ln((a + l) * ((e + l) * (i + l) - f * f) - b * (b * (i + l) - f * d) + d * (b * f - (e + l) * d)) AS logdet FROM (SELECT *, (SELECT n FROM size) * 0.5 AS l FROM k)),
    {_B8}, v AS (SELECT max(g) / {_LEFT_S5} AS scale FROM sn)
    SELECT x.point, round((z.b - x.b) / (SELECT scale FROM v) + x.logdet - z.logdet, 5) + 0.0 AS log_ratio, abs((z.b - x.b) / (SELECT scale FROM v) + x.logdet - z.logdet) <= 3.2 AS within
    FROM m x JOIN m z ON x.point = z.point WHERE x.side = 0 AND z.side = 1"""


@query(_ratio_sql())
def objective_ratio_audit(spark, sf_dir):
    """Objective noise on neighbours: log density ratio of the release at some points, with the change of variables, at epsilon 3.2."""
    from ..operators import audit, sensitivity

    df = prep.discretize(W.dialogues(spark, sf_dir), 8, 8.0).select("subject_id", "t", "y", "x1", F.lit(1).cast("long").alias("w"))
    first = df.agg(F.min("subject_id")).first()[0]
    new = df.where(F.col("subject_id") == first).withColumn("y", -F.col("y"))
    a = basis.matrix(8, 2)
    one, two = (Data(prep.compress(x, ["x1"]), a) for x in (df, audit.swapped(df, first, new)))
    extra, left = sensitivity.extra_ridge(a, one.n, 0.5, 3.2)
    ratios = audit.objective_ratios(Objective(one, 0.5, extra), Objective(two, 0.5, extra), sensitivity.gradient(a) / left, np.array(POINTS))
    rows = [(i, float(r), bool(abs(r) <= 3.2)) for i, r in enumerate(ratios)]
    return spark.createDataFrame(rows, "point int, log_ratio double, within boolean").select("point", R(F.col("log_ratio"), 5).alias("log_ratio"), "within")


def _plain_logistic(spark, sf_dir):
    df = prep.discretize(W.lengths(spark, sf_dir), 50, 50_000).select("subject_id", F.lit(1).alias("t"), "y", "x1", "x2", F.lit(1).cast("long").alias("w"))
    return baseline.plain(prep.compress(df, ["x1", "x2"]))


def _logistic_descent(iterations: int, step: float, lam: float, linear=("0", "0", "0")) -> str:
    eta = "(d.f1 + d.f2 * c.x1 + d.f3 * c.x2)"
    g = f"(c.n / (1 + exp(-{eta})) - c.m)"
    return f"""WITH RECURSIVE cells AS (SELECT x1, x2, count(*)::DOUBLE AS n, sum(event)::DOUBLE AS m FROM ({Q.SPELLS['s6']}) GROUP BY ALL), size AS (SELECT sum(n) AS n FROM cells),
    d AS (SELECT 0 AS k, 0.0::DOUBLE AS f1, 0.0::DOUBLE AS f2, 0.0::DOUBLE AS f3 UNION ALL
    SELECT k + 1, f1 - {step} * (g1 / n + {lam} * f1 + {linear[0]} / n), f2 - {step} * (g2 / n + {lam} * f2 + {linear[1]} / n), f3 - {step} * (g3 / n + {lam} * f3 + {linear[2]} / n)
    FROM (SELECT d.*, (SELECT n FROM size) AS n, (SELECT sum({g}) FROM cells c) AS g1, (SELECT sum({g} * c.x1) FROM cells c) AS g2, (SELECT sum({g} * c.x2) FROM cells c) AS g3 FROM d WHERE k < {iterations}))"""


@query(_logistic_descent(900, 1.0, 0.05) + " " + _FINAL + "900")
def plain_logistic_fit(spark, sf_dir):
    """One interval: the predecessor's regularised logistic regression."""
    return _row(spark, fit.ridge(_plain_logistic(spark, sf_dir), 0.05))


@query(_logistic_descent(900, 1.0, 0.05) + f" SELECT {', '.join(f'round(f{i + 1} + 2 / (size.n * 0.05 * 3.2) * {_N[i]}, 4) + 0.0 AS f{i + 1}' for i in range(3))} FROM d, size WHERE k = 900")
def logistic_output_replay(spark, sf_dir):
    return _row(spark, baseline.logistic_output(_plain_logistic(spark, sf_dir), 3.2, 0.05, "replay").f)


_LEFT = "(3.2 - ln(1 + 0.5 / ((SELECT n FROM size) * 0.05) + 0.0625 / (((SELECT n FROM size) * 0.05) * ((SELECT n FROM size) * 0.05))))"


@query(_logistic_descent(900, 1.0, 0.05, tuple(f"(2 / {_LEFT} * {b})" for b in _N)) + " " + _FINAL + "900")
def logistic_objective_replay(spark, sf_dir):
    return _row(spark, baseline.logistic_objective(_plain_logistic(spark, sf_dir), 3.2, 0.05, "replay").f)


@query()
def link_fits(spark, sf_dir):
    """The three links on dialogues: like fits where hazards are small."""
    rows = []
    for link in ("logit", "cloglog", "probit"):
        f = fit.ridge(fit.data(_records(spark, sf_dir), 8, link=link), 0.01, tolerance=1e-6)
        rows.append((link, *[round(float(v), 4) for v in f]))
    return spark.createDataFrame(rows, "link string, " + ", ".join(f"f{i + 1} double" for i in range(6)))


# --- Cox -------------------------------------------------------------------------------------------------------------

_B = [0.4, -0.3, 0.2]
_RISK = f"""WITH {Q.records('s2')}, z AS (SELECT *, {' + '.join(f'{b} * x{i + 1}' for i, b in enumerate(_B))} AS z FROM records),
pairs AS (SELECT a.subject_id, a.t, a.z, sum(exp(b.z)) AS r0, {', '.join(f'sum(exp(b.z) * b.x{i}) AS r{i}' for i in (1, 2, 3))}, any_value(a.x1) AS x1, any_value(a.x2) AS x2, any_value(a.x3) AS x3
FROM z a JOIN z b ON b.t >= a.t WHERE a.y = 1 GROUP BY ALL)"""


@query(_RISK + " SELECT round(sum(z - ln(r0)), 5) AS loglik FROM pairs")
def cox_loglik_breslow(spark, sf_dir):
    v, _, _ = cox.partial_likelihood(W.frame(spark, sf_dir, "s2"), S, _B)
    return spark.createDataFrame([(round(v, 5),)], "loglik double")


@query(_RISK + " SELECT " + ", ".join(f"round(sum(x{i} - r{i} / r0), 5) + 0.0 AS g{i}" for i in (1, 2, 3)) + " FROM pairs")
def cox_gradient(spark, sf_dir):
    _, g, _ = cox.partial_likelihood(W.frame(spark, sf_dir, "s2"), S, _B)
    return _row(spark, g, 5).withColumnsRenamed({f"f{i}": f"g{i}" for i in (1, 2, 3)})


@query(f"""WITH {Q.records('s2')}, z AS (SELECT *, {' + '.join(f'{b} * x{i + 1}' for i, b in enumerate(_B))} AS z FROM records),
e AS (SELECT t, sum(z) AS bx, sum(exp(z)) AS own, count(*) AS m FROM z WHERE y = 1 GROUP BY t), r AS (SELECT e.t, sum(exp(b.z)) AS r0 FROM e JOIN z b ON b.t >= e.t GROUP BY 1)
SELECT round(sum(bx) - sum(s), 5) AS loglik FROM (SELECT e.t, any_value(bx) AS bx, sum(ln(r0 - k * own / m)) AS s FROM e JOIN r USING (t), range(0, 1000) g(k) WHERE k < m GROUP BY 1)""")
def cox_loglik_efron(spark, sf_dir):
    v, _, _ = cox.partial_likelihood(W.frame(spark, sf_dir, "s2"), S, _B, "efron")
    return spark.createDataFrame([(round(v, 5),)], "loglik double")


_RAW = f"""WITH z AS (SELECT duration AS t, 2 * event - 1 AS y, 0.4 * x1 / 1e4 - 0.3 * x2 + 0.2 * x3 / 5e5 AS z FROM ({Q.SPELLS['s2']})),
e AS (SELECT t, sum(z) AS bx, sum(exp(z)) AS own, count(*) AS m FROM z WHERE y = 1 GROUP BY t), r AS (SELECT e.t, sum(exp(b.z)) AS r0 FROM e JOIN z b ON b.t >= e.t GROUP BY 1),
s AS (SELECT e.t, any_value(bx) AS bx, any_value(m) * ln(any_value(r0)) AS breslow, sum(ln(r0 - k * own / m)) AS efron FROM e JOIN r USING (t), range(0, 1000) g(k) WHERE k < m GROUP BY 1)"""


@query(_RAW + " SELECT round(sum(bx) - sum(breslow), 5) AS breslow, round(sum(bx) - sum(efron), 5) AS efron FROM s")
def cox_loglik_raw(spark, sf_dir):
    """On durations as they are, not cut into intervals."""
    scaled = [F.col("x1") / 1e4, F.col("x2"), F.col("x3") / 5e5]
    df = W.SPELLS["s2"](spark, sf_dir).select("duration", (2 * F.col("event") - 1).alias("y"), *[c.alias(f"x{i + 1}") for i, c in enumerate(scaled)], F.lit(1).alias("w"))
    values = [cox.partial_likelihood(df, S, _B, ties, "duration")[0] for ties in ("breslow", "efron")]
    return spark.createDataFrame([tuple(round(v, 5) for v in values)], "breslow double, efron double")


@query(f"""WITH {Q.records('s5')}, z AS (SELECT *, 0.4 * x1 - 0.3 * x2 + 0.2 * x3 AS z FROM records)
SELECT a.subject_id, count(*) AS at_risk, round(sum(exp(b.z)), 6) AS weight FROM z a JOIN z b ON b.t >= a.t WHERE a.y = 1 GROUP BY 1""")
def risk_set_bruteforce(spark, sf_dir):
    """The range join that running totals replace; a check on small data."""
    df = _records(spark, sf_dir).withColumn("z", 0.4 * F.col("x1") - 0.3 * F.col("x2") + 0.2 * F.col("x3"))
    a, b = df.where("y = 1").select("subject_id", "t"), df.select(F.col("t").alias("t2"), "z")
    return a.join(F.broadcast(b), F.col("t2") >= F.col("t")).groupBy("subject_id").agg(F.count(F.lit(1)).alias("at_risk"), F.round(F.sum(F.exp("z")), 6).alias("weight"))


@query(f"""WITH RECURSIVE s AS (SELECT greatest(1, least(8, ceil(duration / 8.0 * 8)))::INT AS t, 2 * event - 1 AS y, x1 FROM ({Q.SPELLS['s5']})),
e AS (SELECT t, count(*)::DOUBLE AS m, sum(x1) AS sx FROM s WHERE y = 1 GROUP BY t), r AS (SELECT e.t, any_value(m) AS m, any_value(sx) AS sx, sum((s.x1 = 0)::INT)::DOUBLE AS n0, sum((s.x1 = 1)::INT)::DOUBLE AS n1 FROM e JOIN s ON s.t >= e.t GROUP BY 1),
it AS (SELECT 0 AS k, 0.0::DOUBLE AS b UNION ALL SELECT k + 1, b + (SELECT sum(sx - m * n1 * exp(b) / (n0 + n1 * exp(b))) FROM r) / (SELECT sum(m * (n1 * exp(b) / (n0 + n1 * exp(b))) * (n0 / (n0 + n1 * exp(b)))) FROM r) FROM it WHERE k < 25)
SELECT round(b, 5) + 0.0 AS beta FROM it WHERE k = 25""")
def cox_fit_1d(spark, sf_dir):
    df = prep.discretize(W.dialogues(spark, sf_dir), 8, 8.0).select("t", "y", "x1", F.lit(1).alias("w"))
    return spark.createDataFrame([(float(cox.fit(df)[0]),)], "b double").select(R(F.col("b"), 5).alias("beta"))


@query(f"""WITH {Q.records('s2')}, z AS (SELECT *, 0.4 * x1 - 0.3 * x2 + 0.2 * x3 AS z FROM records), e AS (SELECT t, count(*) AS m FROM z WHERE y = 1 GROUP BY t),
r AS (SELECT e.t, any_value(m) / sum(exp(b.z)) AS step FROM e JOIN z b ON b.t >= e.t GROUP BY 1) SELECT t AS time, round(sum(step) OVER (ORDER BY t), 7) AS cumulative FROM r""")
def cox_baseline(spark, sf_dir):
    return cox.baseline(W.frame(spark, sf_dir, "s2"), _B).select("time", F.round("cumulative", 7).alias("cumulative"))


_LIFE = f"""WITH {Q.records('s4')}, g AS (SELECT s, count(t) FILTER (t >= s) AS at_risk, count(t) FILTER (t = s AND y = 1) AS events, count(t) FILTER (t = s AND y = -1) AS censored FROM range(1, 201) r(s), records GROUP BY s),
h AS (SELECT *, CASE WHEN at_risk > 0 THEN events / at_risk ELSE 0 END AS hazard FROM g),
c AS (SELECT *, CASE WHEN min(1 - hazard) OVER w <= 0 THEN 0 ELSE exp(sum(ln(greatest(1 - hazard, 1e-300))) OVER w) END AS survival, sum(hazard) OVER w AS cumulative FROM h WINDOW w AS (ORDER BY s))"""


def _life(spark, sf_dir):
    return baseline.life_table(W.frame(spark, sf_dir, "s4"), 200).withColumn("s", F.col("s").cast("long"))


@query(_LIFE + " SELECT s, at_risk, events, censored, round(hazard, 8) AS hazard FROM c")
def life_table(spark, sf_dir):
    return _life(spark, sf_dir).select("s", "at_risk", "events", "censored", F.round("hazard", 8).alias("hazard"))


@query(_LIFE + " SELECT s, round(survival, 7) AS survival FROM c")
def kaplan_meier(spark, sf_dir):
    return _life(spark, sf_dir).select("s", F.round("survival", 7).alias("survival"))


@query(_LIFE + " SELECT s, round(cumulative, 7) AS cumulative FROM c")
def nelson_aalen(spark, sf_dir):
    return _life(spark, sf_dir).select("s", F.round("cumulative", 7).alias("cumulative"))


_M = [[rng.normal_value(3, "project", i, j) / 2**0.5 for j in range(2)] for i in range(3)]


@query(f"WITH {Q.records('s5')} SELECT subject_id, " + ", ".join(f"round({' + '.join(f'x{i + 1} * ({_M[i][j]!r})' for i in range(3))}, 6) + 0.0 AS x{j + 1}" for j in range(2)) + " FROM records")
def projected_covariates(spark, sf_dir):
    return cox.projected(_records(spark, sf_dir), 2, 3).select("subject_id", R(F.col("x1")).alias("x1"), R(F.col("x2")).alias("x2"))


@query()
def cox_vs_discrete(spark, sf_dir):
    """Relative error of the discrete model's covariate effects against Cox, for both tie rules; no penalty, not private."""
    rows = []
    for name in ("s1", "s2", "s3", "s4"):
        df = W.frame(spark, sf_dir, name, scale="zscore_radius")
        df = prep.compress(df, prep.covariates(df)).persist()
        f, _ = fit.optimum(fit.data(df, 200))
        for ties in ("breslow", "efron"):
            rows.append((name, ties, f[3:].tolist(), cox.fit(df, ties).tolist()))
        df.unpersist()
    out = spark.createDataFrame(rows, "dataset string, ties string, discrete array<double>, cox array<double>")
    return out.withColumn("error", metrics.relative_error(F.col("discrete"), F.col("cox")))


@query()
def aft(spark, sf_dir):
    """An outside method on the same records."""
    beta, intercept, scale = baseline.aft(_records(spark, sf_dir))
    return spark.createDataFrame([(*[float(b) for b in beta], float(intercept), float(scale))], "x1 double, x2 double, x3 double, intercept double, scale double")

