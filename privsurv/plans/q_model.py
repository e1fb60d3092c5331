"""Queries: links, bases, losses, gradients, curves, scores."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions import basis, links, loss, udfs
from ..functions import sql as sql_functions
from ..operators import predict, prep, tabulated
from ..operators.objective import Data
from ..sources import workloads as W
from ..sources.tables import table
from . import spells_sql as Q
from .q_prep import R
from .registry import query

ALPHA, BETA, S = [-2.0, 1.0, -1.5], [0.8, -0.5, 0.3], ["x1", "x2", "x3"]
_ERF = "(1 - t * (0.254829592 + t * (-0.284496736 + t * (1.421413741 + t * (-1.453152027 + t * 1.061405429)))) * exp(-z * z))"


def _grid(spark):
    return spark.range(-60, 61).select((F.col("id") / 10).alias("eta"))


_GRID_SQL = "FROM (SELECT i / 10.0::DOUBLE AS eta FROM range(-60, 61) r(i))"


@query(f"SELECT eta, round(1 / (1 + exp(-eta)), 9) AS h, round(ln((1 / (1 + exp(-eta))) / (1 - 1 / (1 + exp(-eta)))), 6) + 0.0 AS back {_GRID_SQL}")
def link_logit(spark, sf_dir):
    h = links.hazard(F.col("eta"))
    return _grid(spark).select("eta", F.round(h, 9).alias("h"), R(links.score(h)).alias("back"))


@query(f"SELECT eta, round(1 - exp(-exp(eta)), 9) AS h {_GRID_SQL}")
def link_cloglog(spark, sf_dir):
    return _grid(spark).select("eta", F.round(links.hazard(F.col("eta"), "cloglog"), 9).alias("h"))


@query(f"""SELECT eta, round(CASE WHEN eta >= 0 THEN 0.5 * (1 + {_ERF}) ELSE 0.5 * (1 - {_ERF}) END, 8) AS h
FROM (SELECT *, 1 / (1 + 0.3275911 * z) AS t FROM (SELECT *, abs(eta) / sqrt(2) AS z {_GRID_SQL}))""")
def link_probit(spark, sf_dir):
    return _grid(spark).select("eta", F.round(links.hazard(F.col("eta"), "probit"), 8).alias("h"))


@query("SELECT h, round(ln(h / (1 - h)), 6) + 0.0 AS logit, round(ln(-ln(1 - h)), 6) + 0.0 AS cloglog, round(ln(h / (1 - h)) - ln(-ln(1 - h)), 6) + 0.0 AS gap FROM (SELECT i / 200.0::DOUBLE AS h FROM range(1, 200) r(i))")
def link_grid(spark, sf_dir):
    """The two links nearly coincide for small hazards."""
    h = spark.range(1, 200).select((F.col("id") / 200).alias("h"))
    a, b = links.score(F.col("h")), links.score(F.col("h"), "cloglog")
    return h.select("h", R(a).alias("logit"), R(b).alias("cloglog"), R(a - b).alias("gap"))


def _basis(e: int, q: int, grid: str):
    cols = ", ".join(f"round(a{i + 1}, 9) + 0.0 AS a{i + 1}" for i in range(e))
    off = basis.GRIDS[grid]

    def run(spark, sf_dir):
        b = basis.natural_spline(spark, q, e, grid)
        return b.select(F.col("s").cast("long").alias("s"), *[R(F.get("a", i), 9).alias(f"a{i + 1}") for i in range(e)])

    query(f"WITH {Q.basis(q, e, grid=off)} SELECT s, {cols} FROM basis", f"spline_basis_e{e}" + (f"_{grid}" if grid != "right" else ""))(run)


for _e, _q, _g in ((2, 40, "right"), (3, 200, "right"), (4, 50, "mid"), (5, 200, "right"), (3, 20, "left")):
    _basis(_e, _q, _g)


@query(f"""WITH rec AS (SELECT greatest(1, least(8, ceil(duration / 6.0 * 8)))::INT AS t FROM ({Q.SPELLS['s4']}))
SELECT s, sum((s = t)::INT)::BIGINT AS total, count(*) AS n FROM rec, range(1, 9) r(s) GROUP BY s""")
def dummy_basis(spark, sf_dir):
    """Signups by their last of eight intervals: sums of the dummies of their rows of the basis, and of the constant."""
    rows = basis.dummies(spark, 8).join(basis.constant(spark, 8).withColumnRenamed("a", "c"), "s").select(F.col("s").alias("t"), "a", "c")
    own = prep.discretize(W.signups(spark, sf_dir), 8, 6.0).select("t").join(F.broadcast(rows), "t")  # eight rows
    at = own.select(F.posexplode("a").alias("k", "v"), F.get("c", 0).alias("c"))
    return at.groupBy((F.col("k") + 1).cast("long").alias("s")).agg(F.sum("v").cast("long").alias("total"), F.sum("c").cast("long").alias("n"))


def _records(spark, sf_dir, name="s5"):
    return W.frame(spark, sf_dir, name)


def _loss(link="logit", q=8):
    return loss.record_loss(F.col("t"), F.col("y"), loss.dot([F.col(c) for c in S], BETA), ALPHA, q, link)


_PERIODS = f"{Q.records('s5')}, {Q.basis(8)}, {Q.periods(ALPHA, BETA)}"
_LOGIT = f"{Q.softplus('CASE WHEN fails = 1 THEN -eta ELSE eta END')}"


@query(f"WITH {Q.records('s5')} SELECT subject_id, round(t * ln(2), 8) AS loss FROM records")
def record_loss_zero(spark, sf_dir):
    """At zero coefficients every interval costs ln 2."""
    z = loss.record_loss(F.col("t"), F.col("y"), F.lit(0.0), [0.0, 0.0, 0.0], 8)
    return _records(spark, sf_dir).select("subject_id", F.round(z, 8).alias("loss"))


@query(f"WITH {_PERIODS} SELECT subject_id, round(sum({_LOGIT}), 6) AS loss FROM periods GROUP BY 1")
def record_loss_fixed_f(spark, sf_dir):
    return _records(spark, sf_dir).select("subject_id", F.round(_loss(), 6).alias("loss"))


@query(f"""WITH {Q.records('s4')}, {Q.basis(200)}, {Q.periods(ALPHA, BETA)} SELECT subject_id, round(sum({_LOGIT}), 6) AS loss FROM periods GROUP BY 1""")
def record_loss_kernel(spark, sf_dir):
    """The Arrow kernel on 200 intervals."""
    f = udfs.record_loss_arrow([*ALPHA, *BETA], 200, 3)
    return _records(spark, sf_dir, "s4").select("subject_id", F.round(f("t", "y", F.array(*S)), 6).alias("loss"))


@query(f"""WITH {Q.records('s4')}, {Q.basis(200)}, {Q.periods(ALPHA, BETA)} SELECT subject_id, round(sum({_LOGIT}), 5) AS loss FROM periods GROUP BY 1""")
def record_loss_tabulated(spark, sf_dir):
    """By one lookup per record in place of up to 200 terms."""
    out = tabulated.losses(_records(spark, sf_dir, "s4"), basis.matrix(200, 3), [*ALPHA, *BETA], S, 257)
    return out.select("subject_id", F.round("loss", 5).alias("loss"))


@query("SELECT 's5' AS dataset, 'columns' AS evaluator, 'broadcast' AS feeding UNION ALL SELECT 's6', 'kernel', 'broadcast'")
def physical_choices(spark, sf_dir):
    from . import choose

    rows = []
    for name in ("s5", "s6"):
        df = _records(spark, sf_dir, name)
        x = prep.covariates(df)
        rows.append((name, choose.evaluator(df, x, W.SPECS[name].q).name, choose.feeding(df.count(), len(x), 1000, 200).name))
    return spark.createDataFrame(rows, "dataset string, evaluator string, feeding string")


@query(f"WITH {_PERIODS} SELECT subject_id, round(sum({_LOGIT}), 6) AS loss FROM periods GROUP BY 1")
def record_loss_sql(spark, sf_dir):
    """By the temporary SQL functions."""
    sql_functions.register(spark)
    return _records(spark, sf_dir).selectExpr("subject_id", f"round(record_loss(t, y, vec_dot(array(x1, x2, x3), array({', '.join(f'{b}D' for b in BETA)})), array({', '.join(f'{a}D' for a in ALPHA)}), 8), 6) AS loss")


@query(f"""WITH {_PERIODS}, h AS (SELECT *, 1 / (1 + exp(-eta)) AS h FROM periods)
SELECT subject_id, round(-sum(CASE WHEN fails = 1 THEN ln(h) ELSE ln(1 - h) END), 6) AS loss FROM h GROUP BY 1""")
def loss_hazard_form(spark, sf_dir):
    z = loss.dot([F.col(c) for c in S], BETA)
    event = ((F.col("y") + 1) / 2).cast("int")
    return _records(spark, sf_dir).select("subject_id", F.round(loss.hazard_loss(F.col("t"), event, z, ALPHA, 8), 6).alias("loss"))


@query(f"WITH {_PERIODS} SELECT subject_id, round(sum(CASE WHEN fails = 1 THEN -ln(1 - exp(-exp(eta))) ELSE exp(eta) END), 6) AS loss FROM periods GROUP BY 1")
def loss_cloglog(spark, sf_dir):
    return _records(spark, sf_dir).select("subject_id", F.round(_loss("cloglog"), 6).alias("loss"))


@query(f"""WITH {_PERIODS}, z AS (SELECT *, abs(eta) / sqrt(2) AS z FROM periods), tt AS (SELECT * EXCLUDE (t), 1 / (1 + 0.3275911 * z) AS t FROM z),
c AS (SELECT *, CASE WHEN eta >= 0 THEN 0.5 * (1 + {_ERF}) ELSE 0.5 * (1 - {_ERF}) END AS up, CASE WHEN -eta >= 0 THEN 0.5 * (1 + {_ERF}) ELSE 0.5 * (1 - {_ERF}) END AS down FROM tt)
SELECT subject_id, round(sum(CASE WHEN fails = 1 THEN -ln(greatest(up, 1e-12)) ELSE -ln(greatest(down, 1e-12)) END), 5) AS loss FROM c GROUP BY 1""")
def loss_probit(spark, sf_dir):
    return _records(spark, sf_dir).select("subject_id", F.round(_loss("probit"), 5).alias("loss"))


_A = ["a1", "a2", "a3", "x1", "x2", "x3"]
_SLOPE = "(1 / (1 + exp(-eta)) - fails)"


@query(f"WITH {Q.records('s4')}, {Q.basis(200)}, {Q.periods(ALPHA, BETA)} SELECT round(sum({_LOGIT}), 3) AS loss, " + ", ".join(f"round(sum({_SLOPE} * {c}), 3) + 0.0 AS g{i + 1}" for i, c in enumerate(_A)) + " FROM periods")
def gradient_sum_fixed_f(spark, sf_dir):
    """Distributed loss and gradient, no person-period rows."""
    d = Data(_records(spark, sf_dir, "s4"), basis.matrix(200, 3), n=1)
    s = d.sums([[*ALPHA, *BETA]])[0]
    return spark.createDataFrame([tuple(float(v) for v in s)], ", ".join(f"{c} double" for c in ["loss", *[f"g{i + 1}" for i in range(6)]])).select(F.round("loss", 3).alias("loss"), *[R(F.col(f"g{i + 1}"), 3).alias(f"g{i + 1}") for i in range(6)])


_PAIRS = [(i, j) for i in range(6) for j in range(i, 6)]


@query(f"WITH {_PERIODS}, p AS (SELECT *, 1 / (1 + exp(-eta)) AS h FROM periods) SELECT " + ", ".join(f"round(sum(h * (1 - h) * {_A[i]} * {_A[j]}), 4) + 0.0 AS h{i + 1}{j + 1}" for i, j in _PAIRS) + " FROM p")
def hessian_sum_fixed_f(spark, sf_dir):
    d = Data(_records(spark, sf_dir), basis.matrix(8, 3), n=1)
    s = d.sums([[*ALPHA, *BETA]], hessian=True)[0][7:]
    return spark.createDataFrame([tuple(float(v) for v in s)], ", ".join(f"h{i + 1}{j + 1} double" for i, j in _PAIRS)).select(*[R(F.col(f"h{i + 1}{j + 1}"), 4).alias(f"h{i + 1}{j + 1}") for i, j in _PAIRS])


@query(f"WITH {_PERIODS} SELECT (y = 1) AS event, " + ", ".join(f"round(sum({_SLOPE} * {c}), 4) + 0.0 AS g{i + 1}" for i, c in enumerate(_A)) + " FROM periods GROUP BY 1")
def grouped_gradient(spark, sf_dir):
    df = _records(spark, sf_dir).withColumn("event", F.col("y") == 1)
    return udfs.grouped_gradient(df, "event", [*ALPHA, *BETA], 8, 3, S).select("event", *[R(F.col(f"g{i + 1}"), 4).alias(f"g{i + 1}") for i in range(6)])


_LONG = """long AS (SELECT conv_id AS id, (turn + 1)::INT AS s, (turn = max(turn) OVER (PARTITION BY conv_id) AND role = 'assistant')::INT AS event, length(text) / 1000.0::DOUBLE AS c1, (role = 'user')::INT::DOUBLE AS c2 FROM conversations)"""


@query(f"""WITH {_LONG}, {Q.basis(8)}, e AS (SELECT id, event, -2.0 * a1 + 1.0 * a2 - 1.5 * a3 + 0.8 * c1 - 0.5 * c2 AS eta FROM long JOIN basis USING (s))
SELECT id, round(sum({Q.softplus('CASE WHEN event = 1 THEN -eta ELSE eta END')}), 6) AS loss FROM e GROUP BY 1""")
def time_varying_loss(spark, sf_dir):
    """Covariates that change each turn."""
    from pyspark.sql import Window

    c = table(spark, sf_dir, "conversations")
    long = c.select(F.col("conv_id").alias("id"), (F.col("turn") + 1).cast("int").alias("s"), ((F.col("turn") == F.max("turn").over(Window.partitionBy("conv_id"))) & (F.col("role") == "assistant")).cast("int").alias("event"), (F.length("text") / 1000).alias("c1"), (F.col("role") == "user").cast("double").alias("c2"))
    return loss.from_long(long, [0.8, -0.5], ALPHA, 8, ["c1", "c2"]).select("id", F.round("loss", 6).alias("loss"))


@query("""WITH g AS (SELECT l_linenumber AS k, count(*) FILTER (l_returnflag = 'R') / count(*) FILTER (l_returnflag <> 'R') AS odds FROM lineitem GROUP BY 1), o AS (SELECT odds AS first FROM g WHERE k = 1)
SELECT 'line_' || k AS name, round(ln(odds / first), 8) + 0.0 AS beta, round(odds / first, 8) AS ratio, 'odds' AS kind FROM g, o WHERE k > 1""")
def effects_table(spark, sf_dir):
    """Of a line's number in its order on its return, against first lines; the fit of one dummy a number is the log odds ratio."""
    returned = F.col("l_returnflag") == "R"
    g = table(spark, sf_dir, "lineitem", ["l_linenumber", "l_returnflag"]).groupBy("l_linenumber").agg(F.sum(returned.cast("long")).alias("yes"), F.sum((~returned).cast("long")).alias("no"))
    odds = {k: yes / no for k, yes, no in g.collect()}  # a row per line number
    rest = sorted(k for k in odds if k > 1)
    out = predict.effects(spark, [math.log(odds[k] / odds[1]) for k in rest], [f"line_{k}" for k in rest])
    return out.select("name", R(F.col("beta"), 8).alias("beta"), F.round("ratio", 8).alias("ratio"), "kind")


_CURVES = f"""{Q.records('s5')}, {Q.basis(8)}, h AS (SELECT subject_id, s, 1 / (1 + exp(-(-2.0 * a1 + a2 - 1.5 * a3 + 0.8 * x1 - 0.5 * x2 + 0.3 * x3))) AS h FROM records, basis),
c AS (SELECT *, exp(sum(ln(1 - h)) OVER (PARTITION BY subject_id ORDER BY s)) AS survival, sum(h) OVER (PARTITION BY subject_id ORDER BY s) AS cumulative FROM h)"""


@query(f"""WITH {_CURVES} SELECT subject_id, s, round(h, 7) AS hazard, round(survival, 7) AS survival, round(coalesce(lag(survival) OVER (PARTITION BY subject_id ORDER BY s), 1.0) * h, 7) AS density, round(cumulative, 7) AS cumulative FROM c""")
def survival_curves(spark, sf_dir):
    c = predict.curves(_records(spark, sf_dir), ALPHA, BETA, S, 8)
    return c.select("subject_id", F.col("s").cast("long").alias("s"), *[F.round(n, 7).alias(n) for n in ("hazard", "survival", "density", "cumulative")])


@query(f"WITH {_CURVES} SELECT subject_id, coalesce(min(CASE WHEN survival <= 0.5 THEN s END), -1)::BIGINT AS quantile, round(1 + sum(survival), 6) AS expected FROM c GROUP BY 1")
def survival_quantiles(spark, sf_dir):
    c = predict.quantile_time(predict.curves(_records(spark, sf_dir), ALPHA, BETA, S, 8))
    return c.select("subject_id", F.coalesce(F.col("quantile").cast("long"), F.lit(-1)).alias("quantile"), F.round("expected", 6).alias("expected"))


@query(f"WITH {Q.records('s2')} SELECT subject_id, round(0.8 * x1 - 0.5 * x2 + 0.3 * x3, 6) + 0.0 AS z, ntile(10) OVER (ORDER BY 0.8 * x1 - 0.5 * x2 + 0.3 * x3, subject_id)::INT AS decile FROM records")
def risk_score_ntiles(spark, sf_dir):
    """Exact deciles by a global order (for reports); ``predict.deciles`` uses cut points at scale."""
    from pyspark.sql import Window

    df = predict.scored(_records(spark, sf_dir, "s2"), BETA, S)
    return df.select("subject_id", R(F.col("z")).alias("z"), F.ntile(10).over(Window.orderBy("z", "subject_id")).alias("decile"))


@query(f"""WITH {Q.records('s4')}, z AS (SELECT subject_id, 0.8 * x1 - 0.5 * x2 + 0.3 * x3 AS z FROM records),
c AS (SELECT (SELECT z FROM (SELECT z, row_number() OVER (ORDER BY z) AS k FROM z) WHERE k = ceil(round(i * (SELECT count(*) FROM z) / 10.0, 6))) AS cut FROM range(1, 10) r(i))
SELECT subject_id, (1 + (SELECT count(*) FROM c WHERE c.cut < z.z))::INT AS decile FROM z""")
def risk_score_deciles(spark, sf_dir):
    """Groups by cut points, which are exact ranks."""
    return predict.deciles(predict.scored(_records(spark, sf_dir, "s4"), BETA, S)).select("subject_id", "decile")


@query(f"WITH {_PERIODS} SELECT sum(fails)::BIGINT AS fails, count(*) AS n FROM periods")
def person_period_udtf(spark, sf_dir):
    """The same rows by a table function and a lateral join."""
    udfs.register(spark)
    _records(spark, sf_dir).createOrReplaceTempView("privsurv_records")
    return spark.sql("SELECT CAST(sum(fails) AS BIGINT) AS fails, count(*) AS n FROM privsurv_records, LATERAL person_periods(t, y)")


