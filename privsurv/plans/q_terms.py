"""Queries: covariates that change over time, fits per group and from cells, many coefficients, held-out quality, SQL access to models."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import basis, loss, udfs
from ..operators import cox, fit, metrics, predict, prep, private, solver, terms
from ..operators.objective import Data, Objective
from ..sources import workloads as W
from ..sources.tables import table
from . import spells_sql as Q
from .q_fits import _CELLS, _CELLS_S6, _FINAL, _M, _descent, _gamma_sql, _row
from .q_model import ALPHA, BETA, S, _records
from .q_prep import R
from .registry import query

#: Text length and the speaker of each turn, inside the unit ball.
_TURNS = """turns AS (SELECT conv_id AS id, turn + 1 AS s, (turn + 1) / 8.0 AS u,
  (turn = max(turn) OVER (PARTITION BY conv_id) AND role = 'assistant')::INT AS m,
  0.7 * least(length(text) / 2000.0, 1.0) AS c1, CASE WHEN role = 'user' THEN 0.7 ELSE 0.0 END AS c2 FROM conversations),
  size AS (SELECT count(DISTINCT id)::DOUBLE AS n FROM turns)"""


def _turns(spark, sf_dir) -> terms.Terms:
    last = F.max("turn").over(Window.partitionBy("conv_id"))
    rows = table(spark, sf_dir, "conversations").select(
        F.col("conv_id").alias("id"), (F.col("turn") + 1).alias("s"), ((F.col("turn") == last) & (F.col("role") == "assistant")).cast("int").alias("event"),
        (0.7 * F.least(F.length("text") / 2000, F.lit(1.0))).alias("c1"), F.when(F.col("role") == "user", 0.7).otherwise(0.0).alias("c2"))
    return terms.terms(rows, basis.matrix(8, 2), ["c1", "c2"])


def _rounds(rows: str, names: list[str], iterations: int, step: float, lam: float, by: str = "") -> str:
    """Gradient steps over joined rows ``cells`` (n at risk, m failures), per group ``by`` if given, as a recursive query in d."""
    f = [f"f{i + 1}" for i in range(len(names))]
    eta = " + ".join(f"d.{a} * {c}" for a, c in zip(f, names, strict=True))
    sums = ", ".join(f"sum((c.n / (1 + exp(-({eta}))) - c.m) * {c}) AS g{i + 1}" for i, c in enumerate(names))
    steps = ", ".join(f"{a} - {step} * (g{i + 1} / z.n + {lam} * {a}) AS {a}" for i, a in enumerate(f))
    group, using = (f"{by}, ", f"USING ({by})") if by else ("", "ON true")
    zeros = ", ".join(f"0.0::DOUBLE AS {a}" for a in f)
    return f"""WITH RECURSIVE {rows}, d AS (SELECT {group}0 AS k, {zeros} FROM size UNION ALL
    SELECT {group}k + 1 AS k, {steps} FROM (SELECT {group and 'd.' + group}d.k, {', '.join('d.' + a for a in f)}, {sums} FROM d JOIN cells c {using} WHERE d.k < {iterations} GROUP BY ALL) q JOIN size z {using})"""


def _shown(f: list[str], n: int = 4) -> str:
    return ", ".join(f"round({a}, {n}) + 0.0 AS f{i + 1}" for i, a in enumerate(f))


_TURN_FIT = _rounds(f"{_TURNS}, cells AS (SELECT u, c1, c2, count(*)::DOUBLE AS n, sum(m)::DOUBLE AS m FROM turns GROUP BY ALL)", ["1", "c.u", "c.c1", "c.c2"], 700, 0.3, 0.1)
_F4 = [f"f{i}" for i in (1, 2, 3, 4)]


@query(f"{_TURN_FIT} SELECT {_shown(_F4)} FROM d WHERE k = 700")
def time_varying_fit(spark, sf_dir):
    """Ridge fit with covariates of each turn, by Newton steps over terms."""
    return _row(spark, fit.ridge(_turns(spark, sf_dir), 0.1))


_BOUND = "(SELECT sum(sqrt(4 + 1 + u * u)) + max(sqrt(4 * (1 + u * u) + 4)) FROM (SELECT s / 8.0 AS u FROM range(1, 9) r(s)))"
_TURN_NOISE = _gamma_sql("turns", 4, 1.0)


@query(f"{_TURN_FIT} SELECT " + _shown([f"{a} + ({_BOUND} / (size.n * 0.1) + 2e-9 / 0.1) / 3.2 * {_TURN_NOISE[i]}" for i, a in enumerate(_F4)]) + " FROM d, size WHERE k = 700")
def time_varying_release(spark, sf_dir):
    """Output noise on that fit, replayed: a subject has one term at most in each interval, so the bounds are those of records."""
    return _row(spark, private.output_noise_fit(_turns(spark, sf_dir), 3.2, 0.1, seed="turns").f)


_GROUPS = f"""recs AS (SELECT subject_id % 3 AS grp, x1, greatest(1, least(8, ceil(duration)))::INT AS t, 2 * event - 1 AS y FROM ({Q.SPELLS['s5']})),
  cells AS (SELECT grp, s / 8.0 AS u, x1, count(*)::DOUBLE AS n, sum((t = s AND y = 1)::INT)::DOUBLE AS m FROM recs JOIN range(1, 9) r(s) ON s <= t GROUP BY ALL),
  size AS (SELECT grp, count(*)::DOUBLE AS n FROM recs GROUP BY grp)"""


@query(_rounds(_GROUPS, ["1", "c.u", "c.x1"], 500, 0.4, 0.1, "grp") + f" SELECT grp, {_shown(['f1', 'f2', 'f3'])} FROM d WHERE k = 500")
def grouped_ridge_s5(spark, sf_dir):
    """A fit per group of dialogues, all groups in the same passes."""
    df = prep.discretize(W.dialogues(spark, sf_dir), 8, 8.0).withColumn("grp", F.col("subject_id") % 3).withColumn("w", F.lit(1).cast("long"))
    fits = terms.grouped_ridge(df, "grp", basis.matrix(8, 2), 0.1, ["x1"])
    rows = [(g, *map(float, f)) for g, f in fits.items()]
    return spark.createDataFrame(rows, "grp long, f1 double, f2 double, f3 double").select("grp", *[R(F.col(f"f{i}"), 4).alias(f"f{i}") for i in (1, 2, 3)])


@query(_descent(1500, 0.3).replace(_CELLS, _CELLS_S6) + " " + _FINAL + "1500")
def ridge_s6_cells(spark, sf_dir):
    """The fit of ``ridge_s6`` from its risk cells: passes then cost cells, not records."""
    df = prep.discretize(W.lengths(spark, sf_dir), 50, 50_000.0).select("subject_id", "t", "y", "x1", F.lit(1).cast("long").alias("w"))
    return _row(spark, fit.ridge(terms.from_cells(prep.risk_cells(df, ["x1"]), basis.matrix(50, 2), ["x1"]), 0.1))


_X64 = [f"x{i}" for i in range(1, 65)]
_S7 = f"""recs AS ({Q.SPELLS['s7']}), cells AS (SELECT s / 9.0 AS u, (s = duration AND event = 1)::INT::DOUBLE AS m, 1.0::DOUBLE AS n, {', '.join(_X64)} FROM recs JOIN range(1, 10) r(s) ON s <= duration),
  size AS (SELECT count(*)::DOUBLE AS n FROM recs)"""


@query(_rounds(_S7, ["1", "c.u", *[f"c.{x}" for x in _X64]], 160, 0.25, 0.5) + f""" SELECT {_shown(['f1', 'f2', 'f3', 'f66'])},
round(sqrt({' + '.join(f'f{i} * f{i}' for i in range(3, 67))}), 4) AS length FROM d WHERE k = 160""")
def ridge_s7_lbfgs(spark, sf_dir):
    """Sixty-four covariates by the solver that keeps no matrix."""
    df = W.frame(spark, sf_dir, "s7").withColumn("w", F.lit(1).cast("long"))
    f = solver.lbfgs(Objective(Data(df, basis.matrix(9, 2)), 0.5))
    return _row(spark, [f[0], f[1], f[2], f[65], float(np.linalg.norm(f[2:]))]).withColumnRenamed("f5", "length")


_SPLIT = "(('0x' || substr(md5('11|split|' || subject_id), 1, 13))::BIGINT + 0.5) / 4503599627370496.0 < 0.3"
_HELD = f"""recs AS (SELECT {_SPLIT} AS held, x1, greatest(1, least(8, ceil(duration)))::INT AS t, 2 * event - 1 AS y, row_number() OVER () AS id FROM ({Q.SPELLS['s5']})),
  pp AS (SELECT held, id, t, y, x1, s, s / 8.0 AS u, (t = s AND y = 1)::INT AS fails FROM recs JOIN range(1, 9) r(s) ON s <= t),
  cells AS (SELECT u, x1, count(*)::DOUBLE AS n, sum(fails)::DOUBLE AS m FROM pp WHERE NOT held GROUP BY ALL), size AS (SELECT count(*)::DOUBLE AS n FROM recs WHERE NOT held)"""
_ETA = "(f1 + f2 * u + f3 * x1)"


@query(_rounds(_HELD, ["1", "c.u", "c.x1"], 500, 0.4, 0.1) + f""", b AS (SELECT f1, f2, f3 FROM d WHERE k = 500),
o AS (SELECT id, sum({Q.softplus(f'CASE WHEN fails = 1 THEN -{_ETA} ELSE {_ETA} END')}) AS l FROM pp, b WHERE held GROUP BY id),
p AS (SELECT r.id, any_value(r.t) AS t, any_value(r.y) AS y, exp(-sum(ln(1 + exp(f1 + f2 * g.s / 8.0 + f3 * x1)))) AS alive FROM recs r, b, range(1, 5) g(s) WHERE held GROUP BY r.id)
SELECT (SELECT count(*) FROM o) AS n, (SELECT round(2 * sum(l), 3) FROM o) AS deviance, (SELECT round(avg(power((t > 4)::INT - alive, 2)), 5) FROM p WHERE t > 4 OR y = 1) AS brier""")
def holdout_quality(spark, sf_dir):
    """Deviance and Brier score of a fit on records that it did not see."""
    df = prep.discretize(W.dialogues(spark, sf_dir), 8, 8.0).withColumn("w", F.lit(1).cast("long"))
    df = prep.split(df, "subject_id", 0.3, 11).select("t", "y", "w", "x1", "holdout")
    f = fit.ridge(Data(prep.compress(df.where("NOT holdout"), ["x1"]), basis.matrix(8, 2)), 0.1).tolist()
    held, z = df.where("holdout"), F.col("x1") * f[2]
    own = loss.record_loss(F.col("t"), F.col("y"), z, f[:2], 8)
    alive = F.exp(-sum((F.log1p(F.exp(loss.baseline(F.lit(s), f[:2], 8) + z)) for s in range(1, 5)), F.lit(0.0)))
    n = held.agg(F.count(F.lit(1)).alias("n"))
    quality = metrics.fit_quality(held, own, 3).select(F.round("deviance", 3).alias("deviance"))
    return n.crossJoin(quality).crossJoin(metrics.brier(held, alive, 4).select(F.round("brier", 5).alias("brier")))  # one row each


_PROJECTED = ", ".join(f"{' + '.join(f'x{i + 1} * ({_M[i][j]!r})' for i in range(3))} AS p{j + 1}" for j in range(2))


@query(f"""WITH {Q.records('s2')}, z AS (SELECT *, 0.5 * p1 - 0.4 * p2 AS z FROM (SELECT subject_id, t, y, {_PROJECTED} FROM records)),
pairs AS (SELECT a.subject_id, a.z, a.p1, a.p2, sum(exp(b.z)) AS r0, sum(exp(b.z) * b.p1) AS r1, sum(exp(b.z) * b.p2) AS r2 FROM z a JOIN z b ON b.t >= a.t WHERE a.y = 1 GROUP BY ALL)
SELECT round(sum(z - ln(r0)), 5) AS loglik, round(sum(p1 - r1 / r0), 5) + 0.0 AS g1, round(sum(p2 - r2 / r0), 5) + 0.0 AS g2 FROM pairs""")
def cox_projected(spark, sf_dir):
    """Cox partial likelihood and gradient on randomly projected covariates, the informal predecessor."""
    v, g, _ = cox.partial_likelihood(cox.projected(W.frame(spark, sf_dir, "s2"), 2, 3), ["x1", "x2"], [0.5, -0.4])
    return _row(spark, [v, *g], 5).withColumnsRenamed({"f1": "loglik", "f2": "g1", "f3": "g2"})


_GAMMA = "-2.0 * a1 + 1.0 * a2 - 1.5 * a3"


@query(f"""WITH {Q.records('s5')}, {Q.basis(8)}, h AS (SELECT subject_id, s, 1 / (1 + exp(-({_GAMMA} + 0.8 * x1 - 0.5 * x2 + 0.3 * x3))) AS h FROM records, basis)
SELECT subject_id, s::INT AS s, round(h, 8) AS hazard, round(exp(sum(ln(1 - h)) OVER (PARTITION BY subject_id ORDER BY s)), 8) AS survival FROM h""")
def survival_curve_udtf(spark, sf_dir):
    """Curves by a table function in a lateral join."""
    udfs.register(spark)
    predict.scored(_records(spark, sf_dir), BETA, S).createOrReplaceTempView("privsurv_scored")
    alpha = ", ".join(f"{a}D" for a in ALPHA)
    return spark.sql(f"SELECT subject_id, s, round(hazard, 8) AS hazard, round(survival, 8) AS survival FROM privsurv_scored, LATERAL survival_curve(z, array({alpha}), 8)")


@query(f"WITH {Q.basis(20)} SELECT s::INT AS s, round(a1, 9) + 0.0 AS a1, round(a2, 9) + 0.0 AS a2, round(a3, 9) + 0.0 AS a3 FROM basis")
def spline_basis_udtf(spark, sf_dir):
    udfs.register(spark)
    return spark.sql("SELECT s, round(a[0], 9) + 0D AS a1, round(a[1], 9) + 0D AS a2, round(a[2], 9) + 0D AS a3 FROM spline_basis(20, 3)")


@query(f"""WITH {Q.records('s5')}, {Q.basis(8)}, z AS (SELECT subject_id, 0.8 * x1 - 0.5 * x2 + 0.3 * x3 AS z FROM records)
SELECT subject_id, round(z, 8) + 0.0 AS risk, round(1 / (1 + exp(-((SELECT {_GAMMA} FROM basis WHERE s = 3) + z))), 8) AS hazard,
  round(exp(-(SELECT sum(ln(1 + exp({_GAMMA} + z))) FROM basis WHERE s <= 5)), 8) AS survival FROM z""")
def model_in_sql(spark, sf_dir):
    """A released model as a view and SQL functions of risk, hazard and survival."""
    private.Release("ridge", float("inf"), [*ALPHA, *BETA], 8, 3).register(spark, "privsurv_model")
    _records(spark, sf_dir).createOrReplaceTempView("privsurv_records")
    x = "array(x1, x2, x3)"
    return spark.sql(f"""SELECT subject_id, round(privsurv_model_risk({x}), 8) + 0D AS risk, round(privsurv_model_hazard(3, {x}), 8) AS hazard,
        round(privsurv_model_survival(5, {x}), 8) AS survival FROM privsurv_records""")
