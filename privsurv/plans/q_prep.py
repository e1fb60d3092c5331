"""Queries: workloads and preparation."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import prep
from ..sources import workloads as W
from ..sources.tables import table
from . import spells_sql as Q
from .registry import query

R = lambda c, n=6: (F.round(c, n) + 0.0)


def _prep(name: str):
    p = Q.SIZE[name][2]
    x = [f"x{i + 1}" for i in range(p)]
    sql = ", ".join(f"round({c}, 6) + 0.0 AS {c}" for c in x)
    if name == "s7":
        sql = f"round(sqrt({' + '.join(f'{c} * {c}' for c in x)}), 6) + 0.0 AS norm, round(x1, 6) + 0.0 AS x1, round(x64, 6) + 0.0 AS x64"

    def run(spark, sf_dir):
        cols = [R(prep.norm(x)).alias("norm"), R(F.col("x1")).alias("x1"), R(F.col("x64")).alias("x64")] if name == "s7" else [R(F.col(c)).alias(c) for c in x]
        return W.frame(spark, sf_dir, name).select(F.col("subject_id").cast("string").alias("subject_id"), F.col("unit_id").cast("long").alias("unit_id"), "t", "y", *cols)

    query(f"WITH {Q.records(name)} SELECT subject_id::VARCHAR AS subject_id, unit_id::BIGINT AS unit_id, t, y, {sql} FROM records", f"prep_{name}")(run)


for _name in W.SPECS:
    _prep(_name)


@query(" UNION ALL ".join(f"SELECT '{n}' AS dataset, count(*) AS n, sum(event)::BIGINT AS uncensored, {Q.SIZE[n][2]}::BIGINT AS p FROM ({Q.SPELLS[n]})" for n in sorted(Q.SIZE)))
def dataset_stats(spark, sf_dir):
    """Records, events and covariates of each workload."""
    out = None
    for n in sorted(W.SPECS):
        own = prep.stats(W.SPELLS[n](spark, sf_dir), W.SPECS[n].p).select(F.lit(n).alias("dataset"), "n", "uncensored", "p")
        out = own if out is None else out.unionByName(own)
    return out


@query("""SELECT o_custkey, row_number() OVER w AS k, epoch_us(o_orderdate) AS begin_us, coalesce(epoch_us(lead(o_orderdate) OVER w), -1) AS next_us
FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)""")
def gap_spells(spark, sf_dir):
    us = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    return prep.gap_spells(table(spark, sf_dir, "orders"), "o_custkey", ["o_orderdate", "o_orderkey"], "o_orderdate").select("o_custkey", F.col("k").cast("long").alias("k"), us("begin").alias("begin_us"), F.coalesce(us("next"), F.lit(-1)).alias("next_us"))


@query("""SELECT event_id, user_id, coalesce(epoch_us(bought), -1) AS closed_us FROM (SELECT *, min(CASE WHEN event_type = 'purchase' THEN ts END) OVER (PARTITION BY user_id ORDER BY ts, event_id
ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) AS bought FROM events WHERE event_type IN ('signup', 'purchase')) WHERE event_type = 'signup'""")
def next_event_spells(spark, sf_dir):
    out = prep.next_event_spells(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], "event_type", "signup", "purchase", "ts")
    return out.select("event_id", "user_id", F.coalesce(F.unix_micros(F.col("closed").cast("timestamp")), F.lit(-1)).alias("closed_us"))


@query(f"WITH s AS ({Q.SPELLS['s4']}) SELECT greatest(1, least(40, ceil(duration / 6.0 * 40)))::INT AS t, 2 * event - 1 AS y, count(*) AS n FROM s GROUP BY ALL")
def discretize(spark, sf_dir):
    return prep.discretize(W.signups(spark, sf_dir), 40, 6.0).groupBy("t", "y").agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH s AS ({Q.SPELLS['s5']}) SELECT greatest(1, least(8, ceil(duration / (SELECT max(duration) FROM s) * 8)))::INT AS t, count(*) AS n FROM s GROUP BY ALL")
def discretize_observed(spark, sf_dir):
    return prep.discretize(W.dialogues(spark, sf_dir), 8).groupBy("t").agg(F.count(F.lit(1)).alias("n"))


_X4 = ["x1", "x2", "x3"]


@query(f"WITH s AS ({Q.SPELLS['s4']}) SELECT subject_id, " + ", ".join(f"round({c} - avg({c}) OVER (), 4) + 0.0 AS {c}" for c in _X4) + " FROM s")
def center(spark, sf_dir):
    return prep.center(W.signups(spark, sf_dir), _X4).select("subject_id", *[R(F.col(c), 4).alias(c) for c in _X4])


@query(f"WITH {Q.records('s2')} SELECT count(*) AS n, round(max(sqrt(x1*x1+x2*x2+x3*x3)), 6) AS top, round(avg(sqrt(x1*x1+x2*x2+x3*x3)), 6) AS mean FROM records")
def unit_ball(spark, sf_dir):
    return W.frame(spark, sf_dir, "s2").agg(F.count(F.lit(1)).alias("n"), F.round(F.max(prep.norm(_X4)), 6).alias("top"), F.round(F.avg(prep.norm(_X4)), 6).alias("mean"))


_CLIP = "least(1.0, 1 / greatest(sqrt(x1*x1+x2*x2+x3*x3), 1e-300))"


@query(f"WITH s AS ({Q.SPELLS['s5']}) SELECT subject_id, " + ", ".join(f"round({c} * {_CLIP}, 6) AS {c}" for c in _X4) + " FROM s")
def clip_ball(spark, sf_dir):
    return prep.unit_ball(W.dialogues(spark, sf_dir), _X4, "clip").select("subject_id", *[F.round(c, 6).alias(c) for c in _X4])


@query(f"WITH s AS ({Q.SPELLS['s5']}) SELECT subject_id, " + ", ".join(f"round(greatest(-1.0, least(1.0, {c} / {b})) / sqrt(3), 6) + 0.0 AS {c}" for c, b in zip(_X4, (1.0, 500.0, 4.0), strict=True)) + " FROM s")
def public_bounds_ball(spark, sf_dir):
    return prep.unit_ball(W.dialogues(spark, sf_dir), _X4, "public_bounds", [1, 500, 4]).select("subject_id", *[R(F.col(c)).alias(c) for c in _X4])


@query(f"""WITH s AS ({Q.SPELLS['s5']}), c AS (SELECT subject_id, """ + ", ".join(f"({c} - avg({c}) OVER ()) / coalesce(nullif(stddev_pop({c}) OVER (), 0), 1.0) AS {c}" for c in _X4)
       + " FROM s) SELECT subject_id, " + ", ".join(f"round({c} / max(sqrt(x1*x1+x2*x2+x3*x3)) OVER (), 5) + 0.0 AS {c}" for c in _X4) + " FROM c")
def zscore_ball(spark, sf_dir):
    df = prep.unit_ball(prep.center(W.dialogues(spark, sf_dir), _X4), _X4, "zscore_radius")
    return df.select("subject_id", *[R(F.col(c), 5).alias(c) for c in _X4])


@query("SELECT doc_id, (lang = 'en')::INT AS lang_en, (lang = 'es')::INT AS lang_es, (lang = 'fr')::INT AS lang_fr FROM documents")
def encode_dummies(spark, sf_dir):
    return prep.encode(table(spark, sf_dir, "documents", ["doc_id", "lang"]), "lang", ["de", "en", "es", "fr"]).drop("lang")


@query("SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")
def props_json(spark, sf_dir):
    return table(spark, sf_dir, "events", ["event_id", "props"]).select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query(f"""WITH s AS ({Q.SPELLS['s4']}) SELECT subject_id, unit_id FROM (SELECT *, row_number() OVER (PARTITION BY unit_id ORDER BY md5('0|' || subject_id), subject_id) AS k FROM s) WHERE k <= 2""")
def contribution_bound(spark, sf_dir):
    return prep.bound_contribution(W.signups(spark, sf_dir), 2).select("subject_id", "unit_id")


@query(f"WITH {Q.records('s5')} SELECT s, sum((s = t AND y = 1)::INT)::BIGINT AS fails, count(*) AS n FROM records JOIN range(1, 9) r(s) ON s <= t GROUP BY s")
def person_period(spark, sf_dir):
    return prep.person_period(W.frame(spark, sf_dir, "s5")).groupBy(F.col("s").cast("long").alias("s")).agg(F.sum("fails").cast("long").alias("fails"), F.count(F.lit(1)).alias("n"))


_S6 = ["x1", "x2", "x3", "x4"]


def _s6_cells(spark, sf_dir):
    return prep.discretize(W.lengths(spark, sf_dir), 50, 50_000).withColumn("w", F.lit(1))


_S6_SQL = f"s AS ({Q.SPELLS['s6']}), r AS (SELECT *, greatest(1, least(50, ceil(duration / 50000.0 * 50)))::INT AS t, 2 * event - 1 AS y FROM s)"


@query(f"WITH {_S6_SQL} SELECT t, y, x1, x2, x3, x4, count(*) AS w FROM r GROUP BY ALL")
def compress_cells(spark, sf_dir):
    return prep.compress(_s6_cells(spark, sf_dir), _S6)


@query(f"""WITH {_S6_SQL} SELECT x1, x2, x3, x4, s::INT AS s, count(*) AS at_risk, sum((t = s AND y = 1)::INT)::BIGINT AS failed FROM r JOIN range(1, 51) g(s) ON s <= t GROUP BY ALL""")
def risk_cells(spark, sf_dir):
    return prep.risk_cells(_s6_cells(spark, sf_dir), _S6)


@query("""SELECT c_custkey, (('0x' || substr(md5('7|split|' || c_custkey), 1, 13))::BIGINT + 0.5) / 4503599627370496.0 < 0.25 AS holdout FROM customer""")
def holdout_split(spark, sf_dir):
    return prep.split(table(spark, sf_dir, "customer", ["c_custkey"]), "c_custkey", 0.25, 7)


@query(f"WITH {Q.records('s3')} SELECT count(*) AS n, 0::BIGINT AS bad_t, 0::BIGINT AS bad_y, 0::BIGINT AS bad_x, sum((sqrt(x1*x1+x2*x2+x3*x3) > 1 + 1e-12)::INT)::BIGINT AS outside, count(*) - count(DISTINCT subject_id) AS repeated FROM records")
def validate_counts(spark, sf_dir):
    return prep.validate(W.frame(spark, sf_dir, "s3"), _X4, 200)


@query("SELECT count(*) AS n, count(DISTINCT o_orderkey) AS ids, (sum(rn) - 0)::BIGINT AS total, max(rn) AS top FROM (SELECT o_orderkey, row_number() OVER (ORDER BY o_orderkey) - 1 AS rn FROM orders)")
def row_ids(spark, sf_dir):
    out = prep.row_ids(table(spark, sf_dir, "orders", ["o_orderkey"]), "o_orderkey", rows_each=2_000)
    return out.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("row_id").alias("ids"), F.sum("row_id").alias("total"), F.max("row_id").alias("top"))


@query(f"WITH s AS ({Q.SPELLS['s4']}) SELECT count(*) FILTER (x2 IS NOT NULL) AS kept, round(avg(x2), 6) AS mean FROM s")
def null_policies(spark, sf_dir):
    """Rows kept by dropping, and the mean that imputation keeps."""
    df = W.signups(spark, sf_dir)
    return prep.nulls(df, ["x2"], "drop").agg(F.count(F.lit(1)).alias("kept")).crossJoin(prep.nulls(df, ["x2"], "impute_mean").agg(F.round(F.avg("x2"), 6).alias("mean")))


@query("""WITH s AS (SELECT o_custkey, o_orderkey, o_orderdate, coalesce(min(l_shipdate), NULL) AS shipped FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY ALL)
SELECT o_orderkey AS subject_id, o_custkey AS unit_id, coalesce(shipped <= TIMESTAMP '1998-01-01', false)::INT AS event,
round((epoch_us(CASE WHEN coalesce(shipped <= TIMESTAMP '1998-01-01', false) THEN shipped ELSE TIMESTAMP '1998-01-01' END) - epoch_us(o_orderdate)) / 86400e6, 6) AS duration FROM s""")
def survival_frame(spark, sf_dir):
    """Order to first shipment, censored at a public date."""
    ship_ = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_shipdate"]).groupBy("l_orderkey").agg(F.min("l_shipdate").alias("shipped"))
    df = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate"]).join(ship_, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    out = prep.survival_frame(df, "o_orderkey", F.col("o_orderdate"), F.col("shipped"), F.lit("1998-01-01").cast("timestamp_ntz"), [], "o_custkey")
    return out.select("subject_id", "unit_id", "event", F.round("duration", 6).alias("duration"))
