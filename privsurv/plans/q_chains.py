"""Queries: minibatches, chains, the exact grid posterior, measures over traces."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import basis, loss, rng
from ..operators import chain, fit, metrics, prep, private, solver
from ..operators.objective import Data, Objective
from ..sources import workloads as W
from ..sources.tables import table
from . import spells_sql as Q
from .q_model import S, _records
from .q_prep import R
from .registry import query

_U = "((('0x' || substr(md5({k}), 1, 13))::BIGINT + 0.5) / 4503599627370496.0)"
_DRAW = _U.format(k="'c1|5|' || step || '|' || draw")


@query(f"""WITH d AS (SELECT step, draw, floor({_DRAW} * 500)::BIGINT AS row_id FROM range(1, 21) a(step), range(0, 28) b(draw)),
f AS (SELECT step, row_id, min(draw) AS draw FROM d GROUP BY ALL), k AS (SELECT *, row_number() OVER (PARTITION BY step ORDER BY draw) - 1 AS slot FROM f)
SELECT 'c1' AS chain_id, step, slot, row_id FROM k WHERE slot < 20""")
def minibatch_indices(spark, sf_dir):
    """Twenty distinct rows of 500 per step."""
    ids = chain.minibatch_ids(spark, "c1", 5, 1, 20, 20, 500)
    return ids.select("chain_id", "step", F.col("slot").cast("long").alias("slot"), "row_id")


_DRAW2 = _U.format(k="'c2|1|' || step || '|' || draw")


@query(f"""WITH {Q.records('s4')}, n AS (SELECT count(*) AS n FROM records), r AS (SELECT row_number() OVER (ORDER BY subject_id) - 1 AS row_id, t, x1 FROM records),
d AS (SELECT step, draw, floor({_DRAW2} * n)::BIGINT AS row_id FROM n, range(1, 11) a(step), range(0, 200) b(draw)),
f AS (SELECT step, row_id, min(draw) AS draw FROM d GROUP BY ALL), k AS (SELECT *, row_number() OVER (PARTITION BY step ORDER BY draw) - 1 AS slot FROM f)
SELECT 'c2' AS chain_id, step, count(*) AS n, sum(t)::BIGINT AS t, round(sum(x1), 6) + 0.0 AS x1 FROM k JOIN r USING (row_id) WHERE slot < 40 GROUP BY step""")
def prefetch_join(spark, sf_dir):
    """Records of a block of minibatches fetched by one join, summed by step."""
    df = prep.row_ids(W.frame(spark, sf_dir, "s4"), "subject_id")
    got = chain.prefetch(chain.minibatch_ids(spark, "c2", 1, 1, 10, 40, df.count()), df.select("row_id", "t", "y", *S))
    return got.groupBy("chain_id", "step").agg(F.count(F.lit(1)).alias("n"), F.sum("t").alias("t"), R(F.sum("x1")).alias("x1"))


_CELLS = f"""recs AS (SELECT greatest(1, least(8, ceil(duration / 8.0 * 8)))::INT AS t, 2 * event - 1 AS y, x1 FROM ({Q.SPELLS['s5']})), size AS (SELECT count(*)::DOUBLE AS n FROM recs),
pp AS (SELECT row_number() OVER () AS dummy, r.rid, r.x1, s / 8.0 AS u, (s = t AND y = 1)::INT AS m FROM (SELECT *, row_number() OVER () AS rid FROM recs) r JOIN range(1, 9) g(s) ON s <= t)"""


def _slopes_sql(shift: tuple[float, ...] = (0, 0, 0), v: float = 4.0, clip: bool = False) -> str:
    """Sums of bounded losses' gradients at d, moved by ``shift``."""
    eta = f"((d.f1 + {shift[0]}) + (d.f2 + {shift[1]}) * p.u + (d.f3 + {shift[2]}) * p.x1)"
    soft = f"(greatest(CASE WHEN p.m = 1 THEN -{eta} ELSE {eta} END, 0) + ln(1 + exp(-abs({eta}))))"
    slope = f"(1 / (1 + exp(-{eta})) - p.m)"
    own = f"(l < {v})::INT" if clip else f"(1 - power(tanh(l / {v}), 2))"
    sums = ", ".join(f"sum({own} * g{i})" for i in range(3))
    return f"(SELECT list_value({sums}) FROM (SELECT p.rid, sum({soft}) AS l, sum({slope}) AS g0, sum({slope} * p.u) AS g1, sum({slope} * p.x1) AS g2 FROM pp p GROUP BY p.rid))"


_Z = [f"(sqrt(-2 * ln({_U.format(k=f"'3|' || (k + 1) || '|{i}|r'")})) * cos(2 * pi() * {_U.format(k=f"'3|' || (k + 1) || '|{i}|a'")}))" for i in range(3)]


def _chain_sql(steps: int, precondition: bool, factor: float, sigma: float = 0.05, clip: bool = False, radius: float | None = None, drift: bool = False) -> str:
    """Full-batch chain on three coefficients with digest noise."""
    v, eps = 4.0, 2.0
    scale = eps / (2 * v)
    moved = [_slopes_sql(tuple(1e-4 if i == j else 0 for j in range(3)), v, clip) for i in range(3)] if drift else []
    out = []
    for i in range(3):
        f = f"f{i + 1}"
        sec = f"(0.99 * v{i + 1} + 0.01 * b{i + 1} * b{i + 1})"
        gg = f"(1 / (1e-5 + sqrt({sec})))" if precondition else "1.0"
        h = "power(k + 1, -0.51) * 0.01"
        turn = f" - {h} * 0.01 * {gg} * {gg} * b{i + 1} * e{i + 1} / greatest(sqrt({sec}), 1e-12)" if drift else ""
        out.append((f"{f} - {h} * {gg} * n * b{i + 1}{turn} + sqrt({h} * {gg} * {factor}) * {_Z[i]}", sec))
    secants = "".join(f", ({scale} * ({sigma} * (f{i + 1} + 1e-4) / n + e[{i + 1}][{i + 1}] / n) - {scale} * ({sigma} * f{i + 1} / n + gr[{i + 1}] / n)) / 1e-4 AS e{i + 1}" for i in range(3)) if drift else ""
    ends = f", list_value({', '.join(moved)}) AS e" if drift else ""
    inside = f"least(1.0, {radius} / greatest(sqrt(w1 * w1 + w2 * w2 + w3 * w3), 1e-300))" if radius else "1.0"
    return f"""WITH RECURSIVE {_CELLS}, d AS (SELECT 0 AS k, 0.0::DOUBLE AS f1, 0.0::DOUBLE AS f2, 0.0::DOUBLE AS f3, 0.0::DOUBLE AS v1, 0.0::DOUBLE AS v2, 0.0::DOUBLE AS v3 UNION ALL
    SELECT k, w1 * {inside}, w2 * {inside}, w3 * {inside}, s1, s2, s3 FROM
    (SELECT k + 1 AS k, {', '.join(f'{o[0]} AS w{i + 1}' for i, o in enumerate(out))}, {', '.join(f'{o[1]} AS s{i + 1}' for i, o in enumerate(out))} FROM
    (SELECT q.*, n, {', '.join(f'{scale} * ({sigma} * f{i + 1} / n + gr[{i + 1}] / n) AS b{i + 1}' for i in range(3))}{secants}
     FROM (SELECT d.*, (SELECT n FROM size) AS n, {_slopes_sql(v=v, clip=clip)} AS gr{ends} FROM d WHERE k < {steps}) q)))
    SELECT k::BIGINT AS step, round(f1, 5) + 0.0 AS f1, round(f2, 5) + 0.0 AS f2, round(f3, 5) + 0.0 AS f3 FROM d WHERE k > 0"""


def _thermostat_sql(steps: int) -> str:
    """Momentum with a friction that follows its kinetic energy."""
    h, scale = "(power(k + 1, -0.51) * 0.01)", 0.25
    m = [f"(m{i + 1} - {h} * fr * m{i + 1} - {h} * n * {scale} * (0.05 * f{i + 1} / n + gr[{i + 1}] / n) + sqrt(2 * {h}) * {_Z[i]})" for i in range(3)]
    zeros = ", ".join(f"0.0::DOUBLE AS {c}{i}" for c in "fm" for i in (1, 2, 3))
    return f"""WITH RECURSIVE {_CELLS}, d AS (SELECT 0 AS k, {zeros}, 1.0::DOUBLE AS fr UNION ALL
    SELECT k + 1, {', '.join(f'f{i} + {h} * w{i}' for i in (1, 2, 3))}, w1, w2, w3, fr + {h} * ((w1 * w1 + w2 * w2 + w3 * w3) / 3 - 1) FROM
    (SELECT q.*, {', '.join(f'{m[i]} AS w{i + 1}' for i in range(3))} FROM (SELECT d.*, (SELECT n FROM size) AS n, {_slopes_sql()} AS gr FROM d WHERE k < {steps}) q))
    SELECT k::BIGINT AS step, round(f1, 5) + 0.0 AS f1, round(f2, 5) + 0.0 AS f2, round(f3, 5) + 0.0 AS f3 FROM d WHERE k > 0"""


def _data(spark, sf_dir) -> Data:
    df = prep.discretize(W.dialogues(spark, sf_dir), 8, 8.0).select("t", "y", "x1", F.lit(1).cast("long").alias("w"))
    return Data(df, basis.matrix(8, 2))


def _replayed(spark, sf_dir, **more):
    c = chain.Config(2.0, 4.0, more.pop("sigma", 0.05), 12, k=None, seed=3, replay=True, step_scale=0.01, **more)
    t = chain.sample(_data(spark, sf_dir), {"a": c})
    return t.select("step", *[R(F.get("f", i), 5).alias(f"f{i + 1}") for i in range(3)])


@query(_chain_sql(12, True, 2))
def chain_replay_preconditioned(spark, sf_dir):
    """Every state of a short preconditioned chain, replayed in SQL."""
    return _replayed(spark, sf_dir)


@query(_chain_sql(12, True, 1))
def chain_replay_printed(spark, sf_dir):
    return _replayed(spark, sf_dir, temperature="printed")


@query(_chain_sql(12, False, 2))
def chain_replay_plain(spark, sf_dir):
    return _replayed(spark, sf_dir, sampler="plain", precondition=False)


@query(_chain_sql(12, True, 2, sigma=0.0))
def chain_replay_uniform_prior(spark, sf_dir):
    return _replayed(spark, sf_dir, sigma=0.0)


@query(_chain_sql(12, True, 2, clip=True))
def chain_replay_clipped(spark, sf_dir):
    """Losses cut off at the bound."""
    return _replayed(spark, sf_dir, bound="clip")


@query(_chain_sql(12, True, 2, radius=0.5))
def chain_replay_ball(spark, sf_dir):
    """States kept in a ball, the older way to bound losses."""
    return _replayed(spark, sf_dir, radius=0.5)


@query(_chain_sql(12, True, 2, drift=True))
def chain_replay_drift(spark, sf_dir):
    """With the preconditioner's divergence in the drift."""
    return _replayed(spark, sf_dir, drift_correction=True)


@query(_thermostat_sql(12))
def chain_replay_thermostat(spark, sf_dir):
    return _replayed(spark, sf_dir, sampler="thermostat")


@query(f"""SELECT 'c3' AS chain_id, step, slot, floor({_U.format(k="'c3|5|' || step || '|' || slot")} * 500)::BIGINT AS row_id FROM range(1, 21) a(step), range(0, 20) b(slot)""")
def minibatch_with_replacement(spark, sf_dir):
    ids = chain.minibatch_ids(spark, "c3", 5, 1, 20, 20, 500, replacement=True)
    return ids.select("chain_id", "step", F.col("slot").cast("long").alias("slot"), "row_id")


@query(f"""WITH recs AS (SELECT greatest(1, least(8, ceil(duration / 8.0 * 8)))::INT AS t, 2 * event - 1 AS y FROM ({Q.SPELLS['s5']})), g AS (SELECT i / 4.0::DOUBLE AS f1, j / 4.0::DOUBLE AS f2 FROM range(-16, 5) a(i), range(-8, 9) b(j)),
l AS (SELECT f1, f2, rid, sum({Q.softplus('CASE WHEN s = t AND y = 1 THEN -(f1 + f2 * s / 8.0) ELSE f1 + f2 * s / 8.0 END')}) AS loss FROM g, (SELECT *, row_number() OVER () AS rid FROM recs), range(1, 9) r(s) WHERE s <= t GROUP BY ALL),
u AS (SELECT f1, f2, 0.25 * (-0.5 * 0.05 * (f1 * f1 + f2 * f2) - sum(4 * tanh(loss / 4))) AS logp FROM l GROUP BY f1, f2), e AS (SELECT *, exp(logp - max(logp) OVER ()) AS rel FROM u)
SELECT f1, f2, round(rel / sum(rel) OVER (), 9) AS p FROM e""")
def grid_posterior(spark, sf_dir):
    """Exact bounded-loss posterior of two coefficients on a public grid: the truth that chains are held against."""
    df = prep.discretize(W.dialogues(spark, sf_dir), 8, 8.0).withColumn("w", F.lit(1))
    df = prep.compress(df, [])
    grid = spark.range(-16, 5).select((F.col("id") / 4).alias("f1")).crossJoin(spark.range(-8, 9).select((F.col("id") / 4).alias("f2")))
    u = lambda s: F.col("f1") + F.col("f2") * s / 8.0
    from ..functions.links import softplus

    own = F.aggregate(F.sequence(F.lit(1), F.col("t")), F.lit(0.0), lambda acc, s: acc + softplus(F.when((s == F.col("t")) & (F.col("y") == 1), -u(s)).otherwise(u(s))))
    return chain.grid_posterior(df, grid, loss.sanitize(own, 4.0), 2.0, 4.0, 0.05).select("f1", "f2", F.round("p", 9).alias("p"))


def nearest(v):
    """The point of a grid of eighths that a state stands for; on intervals as such, a grid's mass is off by half a step at both ends."""
    return F.floor(v * 8 + 0.5) / 8


_WIDE = "g AS (SELECT (a - 48) / 8.0 AS f1, (b - 64) / 8.0 AS f2 FROM range(0, 81) x(a), range(0, 129) y(b))"


@query(f"""WITH recs AS (SELECT greatest(1, least(8, ceil(duration)))::INT AS t, 2 * event - 1 AS y FROM ({Q.SPELLS['s5']})), cells AS (SELECT t, y, count(*) AS w FROM recs GROUP BY ALL), {_WIDE},
l AS (SELECT f1, f2, t, y, any_value(w) AS w, sum({Q.softplus('CASE WHEN s = t AND y = 1 THEN -(f1 + f2 * s / 8.0) ELSE f1 + f2 * s / 8.0 END')}) AS loss FROM g, cells, range(1, 9) r(s) WHERE s <= t GROUP BY ALL),
u AS (SELECT f1, f2, 0.25 * (-0.5 * 0.4 * (f1 * f1 + f2 * f2) - sum(w * 4 * tanh(loss / 4))) AS logp FROM l GROUP BY f1, f2), e AS (SELECT *, exp(logp - max(logp) OVER ()) AS rel FROM u),
b AS (SELECT 1 AS component, floor(f1)::INT AS bin, sum(rel) AS m FROM e GROUP BY ALL UNION ALL SELECT 2, floor(f2)::INT, sum(rel) FROM e GROUP BY ALL)
SELECT component, bin, round(m / (SELECT sum(rel) FROM e), 6) + 0.0 AS p, true AS metropolis_near, true AS langevin_near FROM b WHERE m / (SELECT sum(rel) FROM e) >= 0.001""")
def density_vs_grid(spark, sf_dir):
    """Exact posterior mass of intervals of both coefficients of S5 dialogues on a grid, and whether the shares of two chains' states, each taken at
    its nearest point of the grid, are within 0.06 of it.  Steps shorten as the posterior does, from lengths that suit a hundred records."""
    from ..functions.links import softplus

    df = prep.discretize(W.dialogues(spark, sf_dir), 8, 8.0).withColumn("w", F.lit(1).cast("long"))
    df = prep.compress(df, [])
    grid = spark.range(81).select(((F.col("id") - 48) / 8).alias("f1")).crossJoin(spark.range(129).select(((F.col("id") - 64) / 8).alias("f2")))
    u = lambda s: F.col("f1") + F.col("f2") * s / 8.0
    own = F.aggregate(F.sequence(F.lit(1), F.col("t")), F.lit(0.0), lambda acc, s: acc + softplus(F.when((s == F.col("t")) & (F.col("y") == 1), -u(s)).otherwise(u(s))))
    exact = chain.grid_posterior(df, grid, loss.sanitize(own, 4.0), 2.0, 4.0, 0.4)
    d = Data(df, np.stack((np.ones(8), np.arange(1, 9) / 8), axis=1))
    few = 100 / max(d.n, 1.0)
    base = chain.Config(2.0, 4.0, 0.4, 60_000, k=None, burn_in=10_000, every=5, seed=5)
    runs = {"metropolis": chain.variants(base, sampler="metropolis", step_scale=60.0 * few**0.5), "langevin": chain.variants(base, step_scale=0.2 * few**1.5)}
    trace = chain.sample(d, runs)
    bins = lambda df, at, mass: _union(df.groupBy("chain_id", F.floor(at(i)).cast("int").alias("bin")).agg(mass.alias("p")).withColumn("component", F.lit(i + 1)) for i in (0, 1))
    share = bins(trace, lambda i: nearest(F.get("f", i)), F.count(F.lit(1)) / F.lit(10_000.0)).groupBy("component", "bin").pivot("chain_id", list(runs)).agg(F.first("p"))
    truth = bins(exact.withColumn("chain_id", F.lit("exact")), lambda i: F.col(f"f{i + 1}"), F.sum("p")).where("p >= 0.001")
    near = lambda c: F.abs(F.coalesce(c, F.lit(0.0)) - F.col("p")) <= 0.06
    return truth.join(share, ["component", "bin"], "left").select("component", "bin", F.round("p", 6).alias("p"), near("metropolis").alias("metropolis_near"), near("langevin").alias("langevin_near"))


def _trace_sql(rows: str = "400") -> str:
    u = lambda tag: _U.format(k=f"'t|' || c || '|' || s || '|{tag}'")
    n = lambda tag: f"(sqrt(-2 * ln({u(tag + '|r')})) * cos(2 * pi() * {u(tag + '|a')}))"
    return f"tr AS (SELECT 'c' || c AS chain_id, s AS step, 1 + 0.1 * {n('x')} AS v1, -2 + 0.3 * {n('y')} AS v2 FROM range(0, 3) a(c), range(1, {rows} + 1) b(s))"


def _trace(spark):
    rows = spark.range(3).select(F.col("id").alias("c")).crossJoin(spark.range(1, 401).select(F.col("id").alias("s")))
    return rows.select(F.concat(F.lit("c"), F.col("c")).alias("chain_id"), F.col("s").alias("step"), F.array(1 + 0.1 * rng.normal("t", F.col("c"), F.col("s"), "x"), -2 + 0.3 * rng.normal("t", F.col("c"), F.col("s"), "y")).alias("f"))


_STAR = [1.0, -2.1]
_D = "sqrt(power(v1 - 1.0, 2) + power(v2 + 2.1, 2)) / sqrt(1.0 + 2.1 * 2.1)"


@query(f"WITH {_trace_sql()} SELECT chain_id, round(avg({_D}), 8) AS mre, count(*) AS draws FROM tr GROUP BY 1")
def mre_literal(spark, sf_dir):
    return metrics.mre(_trace(spark), _STAR, ["chain_id"]).select("chain_id", F.round("mre", 8).alias("mre"), "draws")


@query(f"WITH {_trace_sql()}, e AS (SELECT chain_id, ceil(step / 50.0)::BIGINT AS epoch, sum({_D}) AS s, count(*) AS n FROM tr GROUP BY ALL) SELECT chain_id, epoch, round(sum(s) OVER w / sum(n) OVER w, 8) AS mre FROM e WINDOW w AS (PARTITION BY chain_id ORDER BY epoch)")
def running_mre(spark, sf_dir):
    return metrics.running_mre(_trace(spark), _STAR, 50).select("chain_id", "epoch", F.round("mre", 8).alias("mre"))


@query(f"WITH {_trace_sql()}, m AS (SELECT *, avg(v2) OVER (PARTITION BY chain_id) AS mu FROM tr) SELECT chain_id, round(any_value(mu), 7) AS mean, round(sqrt(avg(power(v2 - mu, 2))), 7) AS sd, round(avg(power(v2 - mu, 3)) / power(avg(power(v2 - mu, 2)), 1.5), 6) AS skewness, round(avg(power(v2 - mu, 4)) / power(avg(power(v2 - mu, 2)), 2) - 3, 6) AS kurtosis FROM m GROUP BY 1")
def moments(spark, sf_dir):
    m = metrics.moments(_trace(spark), 1, ["chain_id"])
    return m.select("chain_id", F.round("mean", 7).alias("mean"), F.round("sd", 7).alias("sd"), F.round("skewness", 6).alias("skewness"), F.round("kurtosis", 6).alias("kurtosis"))


@query(f"""WITH {_trace_sql()}, h AS (SELECT *, ntile(2) OVER (PARTITION BY chain_id ORDER BY step) AS half, lag(v1) OVER (PARTITION BY chain_id ORDER BY step) AS b FROM tr),
g AS (SELECT chain_id, half, avg(v1) AS m, var_samp(v1) AS s2, count(*)::DOUBLE AS n, corr(v1, b) AS r FROM h GROUP BY ALL)
SELECT round(sqrt((avg(n) - 1) / avg(n) + var_samp(m) / avg(s2)), 7) AS rhat, round(sum(n) * (1 - avg(r)) / (1 + avg(r)), 3) AS effective FROM g""")
def rhat(spark, sf_dir):
    return metrics.rhat(_trace(spark), 0).select(F.round("rhat", 7).alias("rhat"), F.round("effective", 3).alias("effective"))


#: Events as traces: a user's events are the steps of a chain, their scaled value and hour its state.
_WALK = "tr AS (SELECT user_id::VARCHAR AS chain_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS step, value / 50.0 AS v1, hour(ts) / 24.0 AS v2 FROM events)"


def _walk(spark, sf_dir):
    state = F.array((F.col("value") / 50.0).alias("v1"), (F.hour("ts") / 24.0).alias("v2"))
    step = F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")).cast("long")
    return table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "value"]).select(F.col("user_id").cast("string").alias("chain_id"), step.alias("step"), state.alias("f"))


@query(f"""WITH {_WALK}, e AS (SELECT chain_id, ceil(step / 10.0)::BIGINT AS epoch, sum(sqrt(power(v1 - 1.0, 2) + power(v2 - 0.5, 2)) / sqrt(1.25)) AS s, count(*) AS n FROM tr GROUP BY ALL),
c AS (SELECT chain_id, epoch, sum(s) OVER w / sum(n) OVER w AS mre, max(epoch) OVER (PARTITION BY chain_id) AS top FROM e WINDOW w AS (PARTITION BY chain_id ORDER BY epoch))
SELECT chain_id, round(regr_slope(mre, epoch), 8) + 0.0 AS slope, abs(regr_slope(mre, epoch)) <= 0.02 AS stable FROM c WHERE epoch > top - 4 GROUP BY 1""")
def convergence_test(spark, sf_dir):
    """Whether each user's running mean of values and hours has settled over the last four epochs of ten events."""
    c = metrics.converged(metrics.running_mre(_walk(spark, sf_dir), [1.0, 0.5], 10), 4, 0.02)
    return c.select("chain_id", R(F.col("slope"), 8).alias("slope"), "stable")


@query(f"WITH {_WALK}, b AS (SELECT CASE WHEN v1 < 0 THEN 0 WHEN v1 >= 8 THEN 17 ELSE floor(v1 / 8 * 16)::INT + 1 END::BIGINT AS bin, count(*) AS n FROM tr GROUP BY 1) SELECT bin, n, round(n / sum(n) OVER () / (8.0 / 16), 8) AS density FROM b")
def density_histogram(spark, sf_dir):
    """Of the values of all events, scaled."""
    return metrics.density(_walk(spark, sf_dir), 0, 0.0, 8.0, 16).select("bin", "n", F.round("density", 8).alias("density"))


_POINTS = (0.25, 0.5, 1.0, 1.5, 2.0, 3.0, 4.0)


@query(f"WITH {_WALK} SELECT point, round(avg(exp(-0.5 * power((point - v1) / 0.1, 2)) / (0.1 * sqrt(2 * pi()))), 7) AS density FROM tr, (SELECT unnest([{', '.join(f'{p}::DOUBLE' for p in _POINTS)}]) AS point) GROUP BY point")
def density_kernel(spark, sf_dir):
    """Of the values of all events, scaled."""
    return metrics.kernel_density(_walk(spark, sf_dir), 0, _POINTS, 0.1).select("point", F.round("density", 7).alias("density"))


_SHRUNK = (1e-5, 1e-4, 1e-3, 1e-2, 1e-1, 1.0)


@query(f"""WITH o AS (SELECT o_orderpriority AS dataset, o_orderkey % 2 AS half, o_totalprice / 1e5 AS y FROM orders), m AS (SELECT dataset, avg(y) AS m FROM o WHERE half = 0 GROUP BY 1),
c AS (SELECT o.dataset, l, avg(power(y - m / (1 + l), 2)) AS e FROM o JOIN m ON o.dataset = m.dataset, (VALUES {', '.join(f'({v!r}::DOUBLE)' for v in _SHRUNK)}) v(l) WHERE half = 1 GROUP BY ALL)
SELECT dataset, arg_min(l, e) AS "lambda", round(min(e), 9) AS value FROM c GROUP BY 1""")
def best_lambda(spark, sf_dir):
    """The ridge of the mean price of an order, fitted on even keys, that predicts the odd ones of its priority best."""
    y = table(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority", "o_totalprice"]).select(F.col("o_orderpriority").alias("dataset"), (F.col("o_orderkey") % 2).alias("half"), (F.col("o_totalprice") / 1e5).alias("y"))
    mean = y.where("half = 0").groupBy("dataset").agg(F.avg("y").alias("m"))  # a row per priority
    ridges = F.explode(F.array(*[F.lit(v) for v in _SHRUNK])).alias("lambda")
    tried = y.where("half = 1").join(F.broadcast(mean), "dataset").select("dataset", "y", "m", ridges)
    curve = tried.groupBy("dataset", "lambda").agg(F.avg((F.col("y") - F.col("m") / (1 + F.col("lambda"))) ** 2).alias("value"))
    return metrics.best_lambda(curve).withColumn("value", F.round("value", 9))


#: Errors made up for a test of ranks: three methods at two budgets, with a tie.
_METHODS = [("s4", 0.4, "output", 11.9), ("s4", 0.4, "objective", 2.3), ("s4", 0.4, "sampler", 1.38), ("s4", 6.4, "output", 0.47), ("s4", 6.4, "objective", 0.46), ("s4", 6.4, "sampler", 0.46)]


@query(f"SELECT dataset, epsilon, method, rank() OVER (PARTITION BY dataset, epsilon ORDER BY value)::INT AS rank FROM (VALUES {', '.join(f'({d!r}, {e}::DOUBLE, {m!r}, {v})' for d, e, m, v in _METHODS)}) v(dataset, epsilon, method, value)")
def rank_methods(spark, sf_dir):
    """Methods by error at each budget; equal errors share a rank."""
    return metrics.rank_methods(spark.createDataFrame(_METHODS, "dataset string, epsilon double, method string, value double")).drop("value")


@query(f"""WITH {Q.records('s4')}, z AS (SELECT t, y, 0.8 * x1 - 0.5 * x2 + 0.3 * x3 AS z FROM records), r AS (SELECT min(z) AS lo, max(z) AS hi FROM z),
b AS (SELECT t, y, least(999, floor((z - lo) / greatest(hi - lo, 1e-12) * 1000))::INT AS b FROM z, r)
SELECT round(sum(CASE WHEN a.b > c.b THEN 1.0 WHEN a.b = c.b THEN 0.5 ELSE 0 END) / count(*), 7) AS concordance, count(*) AS pairs FROM b a JOIN b c ON c.t > a.t WHERE a.y = 1""")
def concordance(spark, sf_dir):
    df = W.frame(spark, sf_dir, "s4").withColumn("z", loss.dot([F.col(c) for c in S], [0.8, -0.5, 0.3]))
    return metrics.concordance(df).select(F.round("concordance", 7).alias("concordance"), "pairs")


@query(f"WITH {Q.records('s4')} SELECT round(avg(power((t > 50)::INT - exp(-0.01 * 50) , 2)), 7) AS brier, count(*) AS n FROM records WHERE t > 50 OR y = 1")
def brier(spark, sf_dir):
    """Of a constant hazard of about one per cent."""
    return metrics.brier(W.frame(spark, sf_dir, "s4"), F.exp(F.lit(-0.5)), 50).select(F.round("brier", 7).alias("brier"), "n")


@query(f"WITH {Q.records('s5')}, l AS (SELECT sum(t * ln(2)) AS s FROM records) SELECT round(-s, 6) AS loglik, round(2 * s, 6) AS deviance, round(12 + 2 * s, 6) AS aic FROM l")
def deviance(spark, sf_dir):
    own = loss.record_loss(F.col("t"), F.col("y"), F.lit(0.0), [0.0, 0.0, 0.0], 8)
    return metrics.fit_quality(_records(spark, sf_dir), own, 6).select(*[F.round(c, 6).alias(c) for c in ("loglik", "deviance", "aic")])


# --- experiments -------------------------------------------------------------------------------------------------------


def _sampler(n: float, eps: float, steps: int, seed: int, **more) -> chain.Config:
    """Published settings, with step lengths shortened to where the chain reaches its target (``chain.stable_scale``)."""
    v = private.default_bound(n)
    scale = more.pop("step_scale", None) or chain.stable_scale(n, eps, v)
    return chain.Config(eps, v, more.pop("sigma", private.default_prior(v, eps)), steps, seed=seed, step_scale=scale, **more)


TWO = ("s2", "s4")


def _union(frames):
    out = None
    for own in frames:
        out = own if out is None else out.unionByName(own)
    return out


def _held(spark, sf_dir, name: str, link: str = "logit") -> Data:
    """A workload at its own number of intervals."""
    return fit.data(W.frame(spark, sf_dir, name), W.SPECS[name].q, link=link)


@query()
def sampler_release(spark, sf_dir):
    """Private releases of second orders and signups by the bounded-loss sampler, with each link."""
    def one(name, link):
        return chain.bounded_sampler_fit(_held(spark, sf_dir, name, link), 6.4, steps=5000).frame(spark).withColumn("dataset", F.lit(name))

    return _union(one(name, link) for name in TWO for link in ("logit", "cloglog", "probit"))


BURN_IN = 10_000
EPOCHS = 250


def _length(n: float) -> int:
    """Steps of a chain: all epochs of n steps, after the burn-in."""
    return BURN_IN + int(EPOCHS * n)


@query()
def density_s2(spark, sf_dir):
    """Histogram of the first two covariate effects at epsilon 6.4 after the burn-in, over all epochs, of s2 and s4."""
    def one(name):
        d = _held(spark, sf_dir, name)
        t = chain.sample(d, {name: _sampler(d.n, 6.4, _length(d.n), 1, burn_in=BURN_IN, every=20)})
        return metrics.densities(t, (3, 4), -6, 6, 24).withColumn("dataset", F.lit(name))

    return _union(one(name) for name in TWO)


THREE = (0.4, 1.6, 6.4)


def _epochs(spark, sf_dir, names, seeds=(2,), most: int | None = None):
    """Running error by epoch of n steps, after the burn-in: dataset, chain_id (budget and seed), epoch, mre."""
    def one(name):
        d = _held(spark, sf_dir, name)
        with d.hold():
            star, _ = fit.optimum(d)
            return curves(name, d, star)

    def curves(name, d, star):
        steps, n = min(_length(d.n), most or _length(d.n)), max(1, int(d.n))
        runs = {f"{e}|{s}": _sampler(d.n, e, steps, s, burn_in=min(BURN_IN, steps // 2) if most else BURN_IN, every=max(1, n // 50)) for e in THREE for s in seeds}
        return metrics.running_mre(chain.sample(d, runs), star.tolist(), n).withColumn("dataset", F.lit(name))

    return _union(one(name) for name in names)


@query()
def mre_epochs_s4(spark, sf_dir):
    """Running error of chains at three budgets by epoch, of s2 and s4."""
    c = _epochs(spark, sf_dir, TWO)
    return c.withColumn("epsilon", F.split("chain_id", "[|]")[0].cast("double"))


@query("SELECT epsilon::DOUBLE AS epsilon, rank FROM (VALUES (0.4, 3), (1.6, 2), (6.4, 1)) v(epsilon, rank)")
def budget_order_s4(spark, sf_dir):
    """Rank of the error that four chains at each budget end with, on signups, after 30,000 steps: the larger the budget, the less."""
    c = _epochs(spark, sf_dir, ("s4",), (11, 12, 13, 14), 30_000)
    last = c.groupBy("chain_id").agg(F.max_by("mre", "epoch").alias("mre"))
    mean = last.groupBy(F.split("chain_id", "[|]")[0].cast("double").alias("epsilon")).agg(F.avg("mre").alias("value"))
    return mean.select("epsilon", F.rank().over(Window.orderBy("value")).alias("rank"))  # one row per budget


@query("SELECT event_type, temperature, true AS as_expected FROM (SELECT DISTINCT event_type FROM events), (VALUES ('calibrated'), ('printed')) v(temperature)")
def ablation_temperature(spark, sf_dir):
    """On normal targets as sharp as the mean squares of each kind of event's values (over those of all) the calibrated noise gives the target's variance, the printed one half."""
    values = table(spark, sf_dir, "events", ["event_type", "value"])
    whole = values.agg(F.avg(F.col("value") ** 2).alias("whole"))
    targets = values.groupBy("event_type").agg(F.avg(F.col("value") ** 2).alias("own")).crossJoin(F.broadcast(whole))  # a row per kind
    cases = targets.select("event_type", (F.col("own") / F.col("whole")).alias("precision"), F.explode(F.array(F.lit("calibrated"), F.lit("printed"))).alias("temperature"))

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        want = {"calibrated": 1.0, "printed": 0.5}
        ok = [abs(p * chain.gaussian_chain(0.05, 60_000, t, 1, p) - want[t]) < 0.12 for p, t in zip(frame["precision"], frame["temperature"], strict=True)]
        return frame[["event_type", "temperature"]].assign(as_expected=ok)

    return cases.groupBy("event_type", "temperature").applyInPandas(run, "event_type string, temperature string, as_expected boolean")


@query()
def ablation_precondition(spark, sf_dir):
    """Error of states with and without preconditioning, and of the other samplers, same steps, of s2 and s4."""
    def one(name):
        d = _held(spark, sf_dir, name)
        with d.hold():
            star, _ = fit.optimum(d)
            base = _sampler(d.n, 6.4, 5000, 3, burn_in=2500, every=10)
            own = lambda **more: chain.variants(base, **more)
            runs = {
                "preconditioned": base, "published_steps": own(step_scale=1.0), "drift_corrected": own(drift_correction=True), "uniform_prior": own(sigma=0.0),
                "with_replacement": own(with_replacement=True), "unbounded": own(bound="none"), "clipped": own(bound="clip"), "ball": own(radius=float(2 * np.linalg.norm(star))),
                "plain": own(sampler="plain", precondition=False, step_scale=1e-3), "thermostat": own(sampler="thermostat", step_scale=1e-3), "metropolis": own(sampler="metropolis", step_scale=0.3),
            }
            return metrics.mre(chain.sample(d, runs), star.tolist(), ["chain_id"]).withColumn("dataset", F.lit(name))

    return _union(one(name) for name in TWO)


BUDGETS = tuple(0.1 * 2**j for j in range(7))
RIDGES = (1e-5, 1e-4, 1e-3, 1e-2, 1e-1, 1.0)
DRAWS = 20  # of each method at each budget
STEPS: int | None = None  # of a chain; None: the burn-in and all epochs
FOUR = ("s1", "s2", "s3", "s4")


def _swept(d: Data, key: str):
    """The optimum, the ridge fits, and output-noise draws of each at the highest budget."""
    star, _ = fit.optimum(d)
    fits = dict(zip(RIDGES, solver.newton_many([Objective(d, lam) for lam in RIDGES], tolerance=1e-8), strict=True))
    draw = lambda lam, s: private.output_noise_fit(d, BUDGETS[-1], lam, seed=f"{key}{lam}{s}", fitted=fits[lam], tolerance=1e-8, certified=True).f
    return star, fits, {lam: [draw(lam, s) for s in range(DRAWS)] for lam in RIDGES}


def _cells(spark, sf_dir, name: str):
    df = W.frame(spark, sf_dir, name)
    return prep.compress(df, prep.covariates(df))


def _sweep(spark, sf_dir):
    """dataset, lambda, mre: mean relative error of output noise at the highest budget over ridges."""
    rows = []
    for name in FOUR:
        d = fit.data(_cells(spark, sf_dir, name), 200)
        with d.hold():
            star, _, draws = _swept(d, name)
        rows += [(name, lam, s, f, star.tolist()) for lam, own in draws.items() for s, f in enumerate(own)]
    df = spark.createDataFrame(rows, "dataset string, lambda double, seed int, f array<double>, star array<double>")
    return df.groupBy("dataset", "lambda").agg(F.avg(metrics.distance(F.col("f"), F.col("star"))).alias("mre"))


@query()
def lambda_sweep(spark, sf_dir):
    """Mean relative error of output noise at epsilon 6.4 over ridges and 20 seeds."""
    return _sweep(spark, sf_dir)


@query()
def lambda_sweep_best(spark, sf_dir):
    """The ridge of least error of each workload's sweep."""
    return metrics.best_lambda(_sweep(spark, sf_dir).withColumnRenamed("mre", "value"))


def _tradeoff(spark, df, name: str, steps: int | None = None):
    """dataset, method, epsilon, run, f, star: as many draws of both noises as chains of the sampler (every tenth state after the burn-in, of all
    epochs or of ``steps`` steps), for every budget."""
    d, rows = fit.data(df, 200), []
    with d.hold():
        star, fits, draws = _swept(d, "l")
        star = star.tolist()
        # The best ridge at the highest budget serves both noise methods.
        best = min(RIDGES, key=lambda lam: np.mean([np.linalg.norm(np.array(v) - star) for v in draws[lam]]))
        for eps in BUDGETS:
            own = [private.output_noise_fit(d, eps, best, seed=f"o{s}", fitted=fits[best], tolerance=1e-8, certified=True) for s in range(DRAWS)]
            rows += [(name, "output_noise", eps, s, r.f, star) for s, r in enumerate(own)]
        cases = [(eps, f"b{s}") for eps in BUDGETS for s in range(DRAWS)]
        rows += [(name, r.method, r.epsilon, i % DRAWS, r.f, star) for i, r in enumerate(private.objective_noise_fits(d, cases, best, tolerance=1e-7, start=fits[best]))]
        given = steps or STEPS
        steps, burn_in = (given, min(BURN_IN, given // 2)) if given else (_length(d.n), BURN_IN)
        runs = {f"{eps!r}|{s}": _sampler(d.n, eps, steps, 1000 * i + s, burn_in=burn_in, every=10) for i, eps in enumerate(BUDGETS) for s in range(DRAWS)}
        t = chain.sample(d, runs)
    part = F.split("chain_id", "[|]")
    t = t.select(F.lit(name).alias("dataset"), F.lit("sampler").alias("method"), part[0].cast("double").alias("epsilon"), part[1].cast("int").alias("run"), "f", F.array(*[F.lit(v) for v in star]).alias("star"))
    return spark.createDataFrame(rows, "dataset string, method string, epsilon double, run int, f array<double>, star array<double>").unionByName(t)


def _errors(draws):
    return draws.groupBy("dataset", "method", "epsilon").agg(F.avg(metrics.distance(F.col("f"), F.col("star"))).alias("mre"), F.countDistinct("run").alias("draws"))


@query()
def privacy_tradeoff(spark, sf_dir):
    """Error of the three methods over seven budgets on the four given workloads."""
    return _errors(_union(_tradeoff(spark, _cells(spark, sf_dir, name), name) for name in FOUR))


@query()
def privacy_tradeoff_planted(spark, sf_dir):
    """The same on planted data, since the given tables have no real effects; chains of 6000 steps."""
    from ..sources.planted import planted

    return _errors(_tradeoff(spark, planted(spark, 4000, [-6.0, 1.0, -1.0], [0.8, -0.5, 0.3], 200), "planted", 6000))
