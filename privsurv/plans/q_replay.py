"""Queries: releases and experiments with replayed noise, so that SQL can compute them too; ablations of bounds."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F

from ..functions import basis, loss
from ..operators import fit, metrics, noise, prep, private, sensitivity
from ..operators.objective import Data
from ..sources import workloads as W
from ..sources.tables import table
from . import spells_sql as Q
from .q_fits import _B8, _CELLS, _N, _gamma_sql, _linear, _row
from .q_prep import R
from .registry import query

BUDGETS = [0.1 * 2**j for j in range(7)]
SEEDS = [f"s{i}" for i in range(5)]
RIDGES = (0.01, 0.1, 1.0)
_G8 = "(SELECT sum(sqrt(4 + a1 * a1 + a2 * a2)) + max(sqrt(4 * (a1 * a1 + a2 * a2) + 4)) FROM b8)"


def _cases_sql(cases: str, iterations: int, step: str, before: str = "") -> str:
    """Gradient steps of several cases (lam and a linear term b1 to b3) at once, as a recursive query in d."""
    sums = ", ".join(f"sum((c.n / (1 + exp(-(d.f1 + d.f2 * c.u + d.f3 * c.x1))) - c.m) * {x}) AS g{i}" for i, x in ((1, "1"), (2, "c.u"), (3, "c.x1")))
    steps = ", ".join(f"f{i} - {step} * (g{i} / z.n + lam * f{i} + b{i} / z.n) AS f{i}" for i in (1, 2, 3))
    return f"""WITH RECURSIVE {_CELLS}, {Q.basis(8, 2, 'b8')}, {before}cases AS ({cases}),
    d AS (SELECT name, 0 AS k, 0.0::DOUBLE AS f1, 0.0::DOUBLE AS f2, 0.0::DOUBLE AS f3 FROM cases UNION ALL
    SELECT name, k + 1, {steps} FROM (SELECT d.name, d.k, d.f1, d.f2, d.f3, {sums} FROM d, cells c WHERE d.k < {iterations} GROUP BY ALL) q JOIN cases USING (name), size z)"""


def _noise_rows(scale: str) -> str:
    """Replayed noise of each seed, of length scale ``scale``."""
    rows = []
    for s in SEEDS:
        n = _gamma_sql(s, 3, 1.0)
        rows.append(f"SELECT '{s}' AS seed, " + ", ".join(f"{n[i]} AS z{i + 1}" for i in range(3)))
    return f"noise AS ({' UNION ALL '.join(rows)}), scale AS ({scale})"


_ERROR = "sqrt((power(f.f1 + c * z1 - o.f1, 2) + power(f.f2 + c * z2 - o.f2, 2) + power(f.f3 + c * z3 - o.f3, 2)) / (o.f1 * o.f1 + o.f2 * o.f2 + o.f3 * o.f3))"
_SWEEP = _cases_sql(" UNION ALL ".join(f"SELECT '{lam}' AS name, {lam}::DOUBLE AS lam, 0.0::DOUBLE AS b1, 0.0::DOUBLE AS b2, 0.0::DOUBLE AS b3" for lam in (0, *RIDGES)), 3000, "1.2 / (1 + 1.2 * lam)")


def _released(spark, d: Data, cases: list[tuple]) -> object:
    """Errors against the optimum of output-noise releases: one row per name, epsilon and ridge, mean over seeds."""
    star, _ = fit.optimum(d)
    rows = []
    for lam in sorted({c[1] for c in cases}):
        f = fit.ridge(d, lam)
        for eps in (c[0] for c in cases if c[1] == lam):
            rows += [(eps, lam, private.output_noise_fit(d, eps, lam, seed=s, fitted=f, certified=True).f) for s in SEEDS]
    draws = spark.createDataFrame(rows, "epsilon double, lambda double, f array<double>")
    return metrics.mre(draws, star.tolist(), ["epsilon", "lambda"])


@query(_SWEEP + ", " + _noise_rows(f"SELECT f.name, ({_G8} / (z.n * lam) + 2e-9 / lam) / 6.4 AS c, lam FROM cases f, size z WHERE lam > 0") + f"""
SELECT lam AS lambda, round(avg({_ERROR}), 3) AS mre, count(*) AS draws FROM (SELECT * FROM d WHERE k = 3000) f JOIN scale USING (name), noise, (SELECT * FROM d WHERE k = 3000 AND name = '0') o GROUP BY lam""")
def lambda_sweep_s5(spark, sf_dir):
    """Error of output noise against the ridge at budget 6.4, with five replayed draws for each."""
    return _released(spark, _linear(spark, sf_dir).data, [(6.4, lam) for lam in RIDGES]).select("lambda", F.round("mre", 3).alias("mre"), "draws")


_EPS = ", ".join(f"({e!r}::DOUBLE)" for e in BUDGETS)


@query(_SWEEP + ", " + _noise_rows(f"SELECT epsilon, ({_G8} / (z.n * 0.1) + 2e-9 / 0.1) / epsilon AS c FROM size z, (VALUES {_EPS}) v(epsilon)") + f"""
SELECT round(epsilon, 4) AS epsilon, round(avg({_ERROR}), 3) AS mre, count(*) AS draws FROM (SELECT * FROM d WHERE k = 3000 AND name = '0.1') f, scale, noise, (SELECT * FROM d WHERE k = 3000 AND name = '0') o GROUP BY epsilon""")
def privacy_tradeoff_s5(spark, sf_dir):
    """Error of output noise against the budget at ridge 0.1, with five replayed draws for each."""
    out = _released(spark, _linear(spark, sf_dir).data, [(e, 0.1) for e in BUDGETS])
    return out.select(F.round("epsilon", 4).alias("epsilon"), F.round("mre", 3).alias("mre"), "draws")


_CHARGE = "(SELECT 2 * sum(ln(1 + 0.25 * sqrt(a1 * a1 + a2 * a2 + 1) / ({m}))) FROM b8)"
_ROOT = f"""it AS (SELECT 0 AS j, 1e-6::DOUBLE AS lo, 1e6::DOUBLE AS hi UNION ALL
  SELECT j + 1, CASE WHEN c > 0.2 THEN mid ELSE lo END, CASE WHEN c > 0.2 THEN hi ELSE mid END FROM
  (SELECT it.*, sqrt(lo * hi) AS mid, {_CHARGE.format(m='sqrt(lo * hi)')} AS c FROM it WHERE j < 120)), root AS (SELECT hi AS m FROM it WHERE j = 120),
  """


@query(_cases_sql(f"SELECT 'a' AS name, m / z.n AS lam, {', '.join(f'{_G8} / 0.2 * {_N[i]} AS b{i + 1}' for i in range(3))} FROM root, size z", 600, "1.2 / (1 + 1.2 * lam)", _ROOT)
       + " SELECT round(m, 4) AS mass, round(f1, 4) + 0.0 AS f1, round(f2, 4) + 0.0 AS f2, round(f3, 4) + 0.0 AS f3 FROM d, root WHERE k = 600")
def objective_extra_replay(spark, sf_dir):
    """Objective noise at a budget that needs more ridge than is asked for, replayed."""
    d = _linear(spark, sf_dir).data
    r = private.objective_noise_fit(d, 0.4, 1e-5, seed="replay", slack_share=0)
    mass = d.n * (r.params["lambda"] + r.params["extra"])
    return _row(spark, [mass, *r.f]).withColumnsRenamed({"f1": "mass", "f2": "f1", "f3": "f2", "f4": "f3"})


_LV = _gamma_sql("vector", 3, 0.25)


@query(f"SELECT {', '.join(f'round({v} + {_LV[i]}, 8) AS f{i + 1}' for i, v in enumerate((1.0, 2.0, 3.0)))}")
def laplace_vector_replay(spark, sf_dir):
    """Any vector of known sensitivity with noise of the same family."""
    return _row(spark, noise.laplace_vector(np.array([1.0, 2.0, 3.0]), 0.5, 2.0, "vector"), 8)


_RADII = """v AS (SELECT avg(value) AS m, stddev_pop(value) AS sd FROM events), radii AS (SELECT event_type, max(abs(value - m)) / any_value(sd) AS r FROM events, v GROUP BY 1)"""


@query(" UNION ALL ".join(f"""(WITH {Q.basis(q)}, s AS (SELECT sqrt(a1 * a1 + a2 * a2 + a3 * a3 + 1) AS l FROM basis), {_RADII} SELECT event_type, {q} AS q, round(r, 6) AS radius, round(sum({Q.softplus('r * l')}), 5) AS bound
FROM s, radii GROUP BY event_type, r)""" for q in (20, 200)))
def ball_bounds(spark, sf_dir):
    """What a ball of coefficients, as wide as the standardised values of a kind of event, bounds a record's loss by: far above the sanitized bound of 2 ln n."""
    values = table(spark, sf_dir, "events", ["event_type", "value"])
    scale = values.agg(F.avg("value").alias("m"), F.stddev_pop("value").alias("sd"))
    radii = values.crossJoin(F.broadcast(scale)).groupBy("event_type").agg((F.max(F.abs(F.col("value") - F.col("m"))) / F.first("sd")).alias("r")).collect()  # a row per kind
    rows = [(k, q, r, sensitivity.ball_bound(basis.matrix(q, 3), r)) for q in (20, 200) for k, r in radii]
    return spark.createDataFrame(rows, "event_type string, q int, radius double, bound double").select("event_type", "q", F.round("radius", 6).alias("radius"), F.round("bound", 5).alias("bound"))


_S2 = "a1 * a1 + a2 * a2 + a3 * a3"


@query(f"""WITH {Q.basis(200)}, b AS (SELECT {_S2} AS s2 FROM basis), g AS (SELECT sum(sqrt(4 + s2)) + max(sqrt(4 * s2 + 4)) AS printed, sum(sqrt(4 + s2)) + max(sqrt(4 * s2 + 4) - sqrt(4 + s2)) AS tight FROM b),
c AS (SELECT o_orderstatus AS status, count(DISTINCT o_custkey) AS n FROM orders GROUP BY 1)
SELECT status, n, 'gradient' AS bound, 'tight' AS mode, round(tight / printed, 8) AS ratio FROM g, c
UNION ALL SELECT status, n, 'jacobian', 'squared', round(sum(2 * ln(1 + 0.25 * (s2 + 1) / (n * 0.01))) / greatest(sum(2 * ln(1 + 0.25 * sqrt(s2 + 1) / (n * 0.01))), sum(ln(1 + 0.25 * (s2 + 1) / (n * 0.01)))), 8) FROM b, c GROUP BY status, n
UNION ALL SELECT status, n, 'jacobian', 'one_sided', round(sum(ln(1 + 0.25 * (s2 + 1) / (n * 0.01))) / greatest(sum(2 * ln(1 + 0.25 * sqrt(s2 + 1) / (n * 0.01))), sum(ln(1 + 0.25 * (s2 + 1) / (n * 0.01)))), 8) FROM b, c GROUP BY status, n""")
def ablation_sensitivity(spark, sf_dir):
    """Noise of other bounds over that of the published ones, for the customers with orders of each status: their sensitivity, or the budget that the Jacobian costs."""
    a, rows = basis.matrix(200, 3), []
    units = table(spark, sf_dir, "orders", ["o_orderstatus", "o_custkey"]).groupBy("o_orderstatus").agg(F.countDistinct("o_custkey").alias("n"))
    for status, n in units.collect():  # a row per status
        rows.append((status, n, "gradient", "tight", sensitivity.gradient(a, "tight") / sensitivity.gradient(a)))
        for mode in ("squared", "one_sided"):
            rows.append((status, n, "jacobian", mode, sensitivity.jacobian_charge(a, n * 0.01, mode) / sensitivity.jacobian_charge(a, n * 0.01)))
    return spark.createDataFrame(rows, "status string, n long, bound string, mode string, ratio double").withColumn("ratio", F.round("ratio", 8))


@query(f"""WITH {Q.records('s4')}, {Q.basis(200)}, e AS (SELECT subject_id, (s = t AND y = 1)::INT AS fails, -4.0 * a1 + 1.0 * a2 - 1.0 * a3 + 0.8 * x1 - 0.5 * x2 + 0.3 * x3 AS eta FROM records JOIN basis ON s <= t),
l AS (SELECT sum({Q.softplus('CASE WHEN fails = 1 THEN -eta ELSE eta END')}) AS l FROM e GROUP BY subject_id), v AS (SELECT 2 * ln(count(*)) AS v FROM l)
SELECT bound, round(sum(CASE bound WHEN 'tanh' THEN v * tanh(l / v) WHEN 'clip' THEN least(l, v) ELSE l END), 4) AS total, sum((l > v)::INT)::BIGINT AS above, round(max(CASE bound WHEN 'tanh' THEN v * tanh(l / v) WHEN 'clip' THEN least(l, v) ELSE l END), 6) AS largest
FROM l, v, (VALUES ('tanh'), ('clip'), ('none')) b(bound) GROUP BY bound""")
def ablation_bounds(spark, sf_dir):
    """What the three kinds of bounds make of the same losses."""
    df = W.frame(spark, sf_dir, "s4")
    z = loss.dot([F.col(c) for c in ("x1", "x2", "x3")], [0.8, -0.5, 0.3])
    own = df.select(loss.record_loss(F.col("t"), F.col("y"), z, [-4.0, 1.0, -1.0], 200).alias("l"))
    v = private.default_bound(df.count())
    kinds = F.explode(F.array(*[F.struct(F.lit(k).alias("bound"), loss.sanitize(F.col("l"), v, k).alias("b")) for k in ("tanh", "clip", "none")])).alias("e")
    out = own.select("l", kinds).groupBy("e.bound").agg(F.sum("e.b").alias("total"), F.sum((F.col("l") > v).cast("long")).alias("above"), F.max("e.b").alias("largest"))
    return out.select("bound", F.round("total", 4).alias("total"), "above", F.round("largest", 6).alias("largest"))
