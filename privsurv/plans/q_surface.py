"""Queries: the relational, window and function surface around the methods, each with a survival use."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..sources.tables import table
from .q_prep import R
from . import spells_sql as Q
from .registry import query

T = table


@query("SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey WHERE l_shipdate > o_orderdate AND l_discount BETWEEN 0.02 AND 0.06 AND p_brand IS NOT NULL GROUP BY 1")
def join_inner(spark, sf_dir):
    li = T(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_extendedprice", "l_discount", "l_shipdate"]).where(F.col("l_discount").between(0.02, 0.06))
    o, p = T(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority", "o_orderdate"]), T(spark, sf_dir, "part", ["p_partkey", "p_brand"]).where("p_brand is not null")
    df = li.join(o, li.l_orderkey == o.o_orderkey).join(p, li.l_partkey == p.p_partkey).where("l_shipdate > o_orderdate")
    return df.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@query("SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey AND o_orderdate < TIMESTAMP '1995-07-01' GROUP BY 1")
def join_left(spark, sf_dir):
    o = T(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate"]).where("o_orderdate < timestamp_ntz '1995-07-01'")
    c = T(spark, sf_dir, "customer", ["c_custkey"])
    return c.join(o, c.c_custkey == o.o_custkey, "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.doc_id IS NOT NULL AS in_docs, l.doc_id IS NOT NULL AS in_labels FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def join_full(spark, sf_dir):
    d, x = T(spark, sf_dir, "documents", ["doc_id"]), T(spark, sf_dir, "labels", ["doc_id"]).withColumnRenamed("doc_id", "other")
    return d.join(x, d.doc_id == x.other, "full").select(F.coalesce("doc_id", "other").alias("doc_id"), F.col("doc_id").isNotNull().alias("in_docs"), F.col("other").isNotNull().alias("in_labels"))


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
def join_semi(spark, sf_dir):
    o = T(spark, sf_dir, "orders", ["o_custkey", "o_totalprice"]).where("o_totalprice > 200000")
    c = T(spark, sf_dir, "customer", ["c_custkey"])
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_anti(spark, sf_dir):
    c = T(spark, sf_dir, "customer", ["c_custkey"])
    return c.join(T(spark, sf_dir, "orders", ["o_custkey"]), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@query("SELECT r_regionkey::BIGINT AS r, s, round(r_regionkey + s / 10.0, 6) AS u FROM region, range(1, 11) g(s)")
def join_cross(spark, sf_dir):
    """Profiles times a small grid of intervals."""
    r = T(spark, sf_dir, "region", ["r_regionkey"]).select(F.col("r_regionkey").cast("long").alias("r"))
    return r.crossJoin(F.broadcast(spark.range(1, 11).withColumnRenamed("id", "s"))).select("r", "s", F.round(F.col("r") + F.col("s") / 10.0, 6).alias("u"))


@query("SELECT b.k AS bucket, count(*) AS n FROM orders JOIN (SELECT k, k * 50000 AS lo, (k + 1) * 50000 AS hi FROM range(0, 20) r(k)) b ON o_totalprice >= lo AND o_totalprice < hi GROUP BY 1")
def join_range(spark, sf_dir):
    """Values against ranges: the few ranges are broadcast, so the non-equal join streams."""
    b = spark.range(20).select(F.col("id").alias("bucket"), (F.col("id") * 50000).alias("lo"), ((F.col("id") + 1) * 50000).alias("hi"))
    o = T(spark, sf_dir, "orders", ["o_totalprice"])
    return o.join(F.broadcast(b), (o.o_totalprice >= b.lo) & (o.o_totalprice < b.hi)).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


@query("""SELECT s.event_id, coalesce(p.event_id, -1) AS last_view FROM (SELECT * FROM events WHERE event_type = 'signup') s ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY ALL) p ON s.user_id = p.user_id AND s.ts >= p.ts""")
def join_asof(spark, sf_dir):
    """The user's last view before each signup, by one window instead of a join."""
    e = T(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type"]).where("event_type in ('signup', 'view')")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    seen = e.withColumn("last_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.where("event_type = 'signup'").select("event_id", F.coalesce("last_view", F.lit(-1)).alias("last_view"))


@query("SELECT a.event_id AS signup, count(b.event_id) AS purchases FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 DAY WHERE a.event_type = 'signup' GROUP BY 1")
def join_interval(spark, sf_dir):
    e = T(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type"])
    a, b = e.where("event_type = 'signup'").select(F.col("event_id").alias("signup"), "user_id", "ts"), e.where("event_type = 'purchase'").select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    on = (F.col("user_id") == F.col("u2")) & (F.col("t2") > F.col("ts")) & (F.col("t2") <= F.col("ts") + F.expr("INTERVAL 6 DAYS"))
    return a.join(b, on, "left").groupBy("signup").agg(F.count("t2").alias("purchases"))


_SEG = "customer JOIN nation ON c_nationkey = n_nationkey"


def _seg(spark, sf_dir):
    c, n = T(spark, sf_dir, "customer", ["c_custkey", "c_nationkey", "c_mktsegment", "c_acctbal"]), T(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).select("c_mktsegment", F.col("n_regionkey").cast("long").alias("region"), "c_acctbal")


_AGG = "count(*) AS n, sum(round(c_acctbal * 100)::BIGINT)::BIGINT AS cents"


def _aggs():
    return [F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("c_acctbal") * 100).cast("long")).alias("cents")]


def _filled(df):
    return df.select(F.coalesce("c_mktsegment", F.lit("all")).alias("segment"), F.coalesce("region", F.lit(-1)).alias("region"), "n", "cents")


_FILL = "coalesce(c_mktsegment, 'all') AS segment, coalesce(n_regionkey, -1)::BIGINT AS region"


@query(f"SELECT {_FILL}, {_AGG} FROM {_SEG} GROUP BY ROLLUP (c_mktsegment, n_regionkey)")
def agg_rollup(spark, sf_dir):
    return _filled(_seg(spark, sf_dir).rollup("c_mktsegment", "region").agg(*_aggs()))


@query(f"SELECT {_FILL}, {_AGG} FROM {_SEG} GROUP BY CUBE (c_mktsegment, n_regionkey)")
def agg_cube(spark, sf_dir):
    return _filled(_seg(spark, sf_dir).cube("c_mktsegment", "region").agg(*_aggs()))


@query(f"SELECT {_FILL}, {_AGG} FROM {_SEG} GROUP BY GROUPING SETS ((c_mktsegment), (n_regionkey), ())")
def agg_grouping_sets(spark, sf_dir):
    df = _seg(spark, sf_dir)
    return _filled(df.groupingSets([["c_mktsegment"], ["region"], []], "c_mktsegment", "region").agg(*_aggs()))


@query("SELECT event_type, count(DISTINCT user_id) AS users, count(*) AS n, count(*) FILTER (value > 50) AS high FROM events GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return T(spark, sf_dir, "events", ["event_type", "user_id", "value"]).groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.count(F.lit(1)).alias("n"), F.count_if(F.col("value") > 50).alias("high"))


@query("SELECT event_type, true AS near FROM events GROUP BY 1")
def agg_approx_distinct(spark, sf_dir):
    """The sketch is within six per cent of the exact count."""
    df = T(spark, sf_dir, "events", ["event_type", "user_id"]).groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.countDistinct("user_id").alias("b"))
    return df.select("event_type", (F.abs(F.col("a") - F.col("b")) <= 0.06 * F.col("b") + 2).alias("near"))


@query("SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS median, round(quantile_cont(l_quantity, 0.9), 6) AS p90, round(stddev_samp(l_discount), 8) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r, min(l_quantity) AS lo, max(l_quantity) AS hi FROM lineitem GROUP BY 1")
def agg_percentile(spark, sf_dir):
    df = T(spark, sf_dir, "lineitem", ["l_returnflag", "l_quantity", "l_discount", "l_extendedprice"]).groupBy("l_returnflag")
    return df.agg(F.round(F.median("l_quantity"), 6).alias("median"), F.round(F.percentile("l_quantity", 0.9), 6).alias("p90"), F.round(F.stddev_samp("l_discount"), 8).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"))


@query("SELECT o_custkey, arg_min(o_orderkey, (o_orderdate, o_orderkey)) AS first_order, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS last_order FROM orders GROUP BY 1")
def agg_min_by(spark, sf_dir):
    k = F.struct("o_orderdate", "o_orderkey")
    return T(spark, sf_dir, "orders", ["o_custkey", "o_orderkey", "o_orderdate"]).groupBy("o_custkey").agg(F.min_by("o_orderkey", k).alias("first_order"), F.max_by("o_orderkey", k).alias("last_order"))


@query("SELECT dataset, max(v) FILTER (lam = 'low') AS low, max(v) FILTER (lam = 'high') AS high FROM (SELECT o_orderstatus AS dataset, CASE WHEN o_totalprice < 150000 THEN 'low' ELSE 'high' END AS lam, count(*) AS v FROM orders GROUP BY ALL) GROUP BY 1")
def pivot_lambda(spark, sf_dir):
    """Long results as a table of one column per level."""
    o = T(spark, sf_dir, "orders", ["o_orderstatus", "o_totalprice"]).select(F.col("o_orderstatus").alias("dataset"), F.when(F.col("o_totalprice") < 150000, "low").otherwise("high").alias("lam"))
    return o.groupBy("dataset").pivot("lam", ["low", "high"]).agg(F.count(F.lit(1)))


@query("SELECT l_returnflag, name, value FROM (UNPIVOT (SELECT l_returnflag, sum(round(l_discount * 100)::BIGINT)::BIGINT AS discount, sum(round(l_tax * 100)::BIGINT)::BIGINT AS tax FROM lineitem GROUP BY 1) ON discount, tax INTO NAME name VALUE value)")
def unpivot(spark, sf_dir):
    df = T(spark, sf_dir, "lineitem", ["l_returnflag", "l_discount", "l_tax"]).groupBy("l_returnflag").agg(F.sum(F.round(F.col("l_discount") * 100).cast("long")).alias("discount"), F.sum(F.round(F.col("l_tax") * 100).cast("long")).alias("tax"))
    return df.unpivot("l_returnflag", ["discount", "tax"], "name", "value")


@query("""SELECT s_suppkey, rank() OVER w AS r, dense_rank() OVER w AS d, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey) AS n, round(percent_rank() OVER w, 8) AS p, round(cume_dist() OVER w, 8) AS c, ntile(4) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey) AS q
FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal)""")
def win_rank(spark, sf_dir):
    w, u = Window.partitionBy("s_nationkey").orderBy("s_acctbal"), Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")
    big = lambda c: c.cast("long")
    return T(spark, sf_dir, "supplier").select("s_suppkey", big(F.rank().over(w)).alias("r"), big(F.dense_rank().over(w)).alias("d"), big(F.row_number().over(u)).alias("n"), F.round(F.percent_rank().over(w), 8).alias("p"), F.round(F.cume_dist().over(w), 8).alias("c"), big(F.ntile(4).over(u)).alias("q"))


@query("""SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before, coalesce(lead(event_id, 2) OVER w, -1) AS later, first_value(event_id) OVER w AS first, coalesce(nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), -1) AS second
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""")
def win_lag_lead(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    z = lambda c: F.coalesce(c, F.lit(-1))
    return T(spark, sf_dir, "events", ["event_id", "user_id", "ts"]).select("event_id", z(F.lag("event_id").over(w)).alias("before"), z(F.lead("event_id", 2).over(w)).alias("later"), F.first("event_id").over(w).alias("first"), z(F.nth_value("event_id", 2).over(whole)).alias("second"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS moving FROM events")
def win_frame_rows(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return T(spark, sf_dir, "events", ["event_id", "user_id", "ts", "value"]).select("event_id", F.round(F.avg("value").over(w), 6).alias("moving"))


@query("SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderstatus ORDER BY o_custkey RANGE BETWEEN 10 PRECEDING AND 10 FOLLOWING) AS near FROM orders")
def win_frame_range(spark, sf_dir):
    w = Window.partitionBy("o_orderstatus").orderBy("o_custkey").rangeBetween(-10, 10)
    return T(spark, sf_dir, "orders", ["o_orderkey", "o_orderstatus", "o_custkey"]).select("o_orderkey", F.count(F.lit(1)).over(w).alias("near"))


@query("SELECT c_mktsegment, c_custkey, c_acctbal FROM customer QUALIFY row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) <= 3")
def topk(spark, sf_dir):
    w = Window.partitionBy("c_mktsegment").orderBy(F.desc("c_acctbal"), "c_custkey")
    return T(spark, sf_dir, "customer", ["c_mktsegment", "c_custkey", "c_acctbal"]).withColumn("k", F.row_number().over(w)).where("k <= 3").drop("k")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def sort_limit(spark, sf_dir):
    return T(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("SELECT c_nationkey::BIGINT AS k FROM customer UNION SELECT s_nationkey::BIGINT FROM supplier")
def set_union(spark, sf_dir):
    a, b = T(spark, sf_dir, "customer").select(F.col("c_nationkey").cast("long").alias("k")), T(spark, sf_dir, "supplier").select(F.col("s_nationkey").cast("long").alias("k"))
    return a.unionByName(b).distinct()


@query("SELECT o_custkey AS k FROM orders INTERSECT SELECT c_custkey FROM customer")
def set_intersect(spark, sf_dir):
    return T(spark, sf_dir, "orders").select(F.col("o_custkey").alias("k")).intersect(T(spark, sf_dir, "customer").select("c_custkey"))


@query("SELECT k FROM (SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders)")
def set_except(spark, sf_dir):
    return T(spark, sf_dir, "customer").select(F.col("c_custkey").alias("k")).subtract(T(spark, sf_dir, "orders").select("o_custkey"))


@query("SELECT n, count(*) AS rows FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL EXCEPT ALL SELECT user_id, event_type, count(*) FROM events WHERE user_id % 2 = 0 GROUP BY ALL) GROUP BY 1")
def set_except_all(spark, sf_dir):
    e = T(spark, sf_dir, "events", ["user_id", "event_type"])
    g = lambda d: d.groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    return g(e).exceptAll(g(e.where("user_id % 2 = 0"))).groupBy("n").agg(F.count(F.lit(1)).alias("rows"))


@query("SELECT conv_id, s FROM (SELECT conv_id, count(*) AS t FROM conversations GROUP BY 1), LATERAL (SELECT s FROM range(1, 100) r(s) WHERE s <= t)")
def lateral_expand(spark, sf_dir):
    c = T(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.count(F.lit(1)).alias("t"))
    return c.select("conv_id", F.explode(F.sequence(F.lit(1).cast("long"), F.col("t"))).alias("s"))


@query("WITH RECURSIVE r AS (SELECT 1 AS s, 0.97::DOUBLE AS survival UNION ALL SELECT s + 1, survival * (1 - 0.03 - 0.001 * s) FROM r WHERE s < 50) SELECT s, round(survival, 9) AS survival FROM r")
def recursive_cte(spark, sf_dir):
    """Survival as a recursion."""
    return spark.sql("WITH RECURSIVE r(s, survival) AS (SELECT 1, 0.97D UNION ALL SELECT s + 1, survival * (1 - 0.03D - 0.001D * s) FROM r WHERE s < 50) SELECT s, round(survival, 9) AS survival FROM r")


@query("SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders i WHERE i.o_orderstatus = o.o_orderstatus) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')")
def subqueries(spark, sf_dir):
    T(spark, sf_dir, "orders").createOrReplaceTempView("privsurv_orders")
    T(spark, sf_dir, "customer").createOrReplaceTempView("privsurv_customer")
    return spark.sql("SELECT o_orderkey FROM privsurv_orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM privsurv_orders i WHERE i.o_orderstatus = o.o_orderstatus) AND o_custkey IN (SELECT c_custkey FROM privsurv_customer WHERE c_mktsegment = 'BUILDING')")


@query("SELECT c_custkey FROM customer QUALIFY row_number() OVER (ORDER BY md5('s|' || c_custkey), c_custkey) <= 50")
def sample_exact(spark, sf_dir):
    """Exactly fifty rows, the same everywhere, by order of a digest."""
    return T(spark, sf_dir, "customer", ["c_custkey"]).orderBy(F.md5(F.concat_ws("|", F.lit("s"), F.col("c_custkey").cast("string")).cast("binary")), "c_custkey").limit(50)


@query("SELECT doc_id, upper(substr(lang, 1, 1)) || ':' || lower(source) AS tag, length(text) AS n, md5(lang) AS digest, regexp_extract(source, '([0-9]+)', 1) AS num, trim(concat(' ', lang, ' ')) AS t, split_part(concat(lang, '-', source), '-', 2) AS part FROM documents")
def fn_string(spark, sf_dir):
    c = F.col
    return T(spark, sf_dir, "documents").select("doc_id", F.concat(F.upper(F.substring("lang", 1, 1)), F.lit(":"), F.lower("source")).alias("tag"), F.length("text").cast("long").alias("n"), F.md5(c("lang").cast("binary")).alias("digest"), F.regexp_extract("source", "([0-9]+)", 1).alias("num"), F.trim(F.concat(F.lit(" "), c("lang"), F.lit(" "))).alias("t"), F.element_at(F.split(F.concat("lang", F.lit("-"), "source"), "-"), 2).alias("part"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, hour(o_orderdate) AS h, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS d, epoch_us(date_trunc('month', o_orderdate)) AS month_us, epoch_us(o_orderdate + INTERVAL 3 DAY) AS later FROM orders")
def fn_date(spark, sf_dir):
    us = lambda e: F.unix_micros(F.expr(e).cast("timestamp"))
    return T(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.hour("o_orderdate").cast("long").alias("h"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).cast("long").alias("d"), us("date_trunc('month', o_orderdate)").alias("month_us"), us("o_orderdate + INTERVAL 3 DAYS").alias("later"))


@query("SELECT x, round(exp(-x), 9) AS e, round(ln(1 + x), 9) AS l, round(tanh(x), 9) AS t, round(sqrt(x), 9) AS s, round(power(x, 1.5), 8) AS p, floor(x)::BIGINT AS f, ceil(x)::BIGINT AS c, greatest(x, 1.0) AS g, least(x, 1.0) AS m, round(cos(x), 9) + 0.0 AS co FROM (SELECT DISTINCT l_quantity / 8.0 AS x FROM lineitem)")
def fn_math(spark, sf_dir):
    x = T(spark, sf_dir, "lineitem", ["l_quantity"]).distinct().select((F.col("l_quantity") / 8).alias("x"))
    return x.select("x", F.round(F.exp(-F.col("x")), 9).alias("e"), F.round(F.log1p("x"), 9).alias("l"), F.round(F.tanh("x"), 9).alias("t"), F.round(F.sqrt("x"), 9).alias("s"), F.round(F.pow("x", F.lit(1.5)), 8).alias("p"), F.floor("x").alias("f"), F.ceil("x").alias("c"), F.greatest("x", F.lit(1.0)).alias("g"), F.least("x", F.lit(1.0)).alias("m"), R(F.cos("x"), 9).alias("co"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding::DOUBLE[], lambda v: v * v)), 6) AS norm2, round(list_sum(embedding[1:8]::DOUBLE[]), 6) + 0.0 AS head, len(list_filter(embedding, lambda v: v > 0)) AS positive, list_position(embedding, list_max(embedding))::BIGINT AS top FROM embeddings")
def fn_array(spark, sf_dir):
    e = F.transform("embedding", lambda v: v.cast("double"))
    add = lambda c: F.aggregate(c, F.lit(0.0), lambda a, v: a + v)
    return T(spark, sf_dir, "embeddings").select("vec_id", F.round(add(F.transform(e, lambda v: v * v)), 6).alias("norm2"), R(add(F.slice(e, 1, 8))).alias("head"), F.size(F.filter("embedding", lambda v: v > 0)).cast("long").alias("positive"), F.array_position("embedding", F.array_max("embedding")).alias("top"))


@query("SELECT event_type, round(avg(value), 6) AS mean, 2 AS entries FROM events GROUP BY 1")
def fn_map(spark, sf_dir):
    """A released parameter map and back."""
    g = T(spark, sf_dir, "events").groupBy("event_type").agg(F.avg("value").alias("m"))
    m = g.select("event_type", F.map_from_arrays(F.array(F.lit("mean"), F.lit("one")), F.array("m", F.lit(1.0))).alias("params"))
    return m.select("event_type", F.round(F.element_at("params", "mean"), 6).alias("mean"), F.size(F.map_keys("params")).alias("entries"))


@query("SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k, json_extract_string(props, '$.k') AS again FROM events")
def fn_json(spark, sf_dir):
    e = T(spark, sf_dir, "events", ["event_id", "props"])
    parsed = F.from_json("props", "struct<k: bigint>")
    return e.select("event_id", parsed["k"].alias("k"), F.get_json_object(F.to_json(parsed), "$.k").alias("again"))


@query("SELECT event_id, coalesce(nullif(event_type, 'view'), 'none') AS kind, coalesce(CASE WHEN value > 50 THEN value END, 0.0) AS v FROM events")
def fn_null(spark, sf_dir):
    e = T(spark, sf_dir, "events", ["event_id", "event_type", "value"])
    return e.select("event_id", F.coalesce(F.nullif(F.col("event_type"), F.lit("view")), F.lit("none")).alias("kind"), F.coalesce(F.nanvl(F.when(F.col("value") > 50, F.col("value")), F.lit(0.0)), F.lit(0.0)).alias("v"))


@query("SELECT c_custkey, c_acctbal FROM customer WHERE c_mktsegment LIKE 'B%' AND c_acctbal IS NOT NULL AND c_mktsegment IN ('BUILDING', 'MACHINERY') AND regexp_matches(c_mktsegment, 'ING$')")
def filter_pushdown(spark, sf_dir):
    """Filters and columns reach the scan."""
    return T(spark, sf_dir, "customer", ["c_custkey", "c_acctbal", "c_mktsegment"]).where(F.col("c_mktsegment").like("B%") & F.col("c_acctbal").isNotNull() & F.col("c_mktsegment").isin("BUILDING", "MACHINERY") & F.col("c_mktsegment").rlike("ING$")).select("c_custkey", "c_acctbal")


def _planted_sql(n: int, q: int) -> str:
    """The planted law with digest numbers: an event when the cumulative hazard passes an exponential threshold, uniform censoring."""
    u = lambda tag: f"((('0x' || substr(md5('1|{tag}|' || i), 1, 13))::BIGINT + 0.5) / 4503599627370496.0)"
    x = ", ".join(f"(2 * {u(f'x{j}')} - 1) / sqrt(3) AS x{j + 1}" for j in range(3))
    return f"""WITH {Q.basis(q)}, r AS (SELECT i, {x}, -ln({u('event')}) AS e, least({q}, ceil({u('censor')} * {q}))::INT AS cut FROM range(0, {n}) g(i)),
h AS (SELECT i, s, e, sum({Q.softplus('-4.0 * a1 + 1.0 * a2 - 1.0 * a3 + 0.8 * x1 - 0.5 * x2 + 0.3 * x3')}) OVER (PARTITION BY i ORDER BY s) AS c FROM r, basis),
t AS (SELECT i, min(s) AS t FROM h WHERE c >= e GROUP BY i)
SELECT i AS subject_id, least(coalesce(t, {q + 1}), cut)::INT AS t, CASE WHEN coalesce(t, {q + 1}) <= cut THEN 1 ELSE -1 END AS y, {', '.join(f'round(x{j}, 9) + 0.0 AS x{j}' for j in (1, 2, 3))}
FROM r LEFT JOIN t USING (i)"""


@query(_planted_sql(500, 20))
def planted_source(spark, sf_dir):
    """The Python data source of planted records."""
    from ..sources import planted

    planted.register(spark)
    df = spark.read.format("planted_survival").options(n="500", q="20").load()
    return df.select("subject_id", "t", "y", *[(F.round(c, 9) + 0.0).alias(c) for c in ("x1", "x2", "x3")])


@query(_planted_sql(500, 20))
def planted_columns(spark, sf_dir):
    """The same records by columns."""
    from ..sources.planted import planted

    df = planted(spark, 500, [-4.0, 1.0, -1.0], [0.8, -0.5, 0.3], 20)
    return df.select("subject_id", "t", "y", *[(F.round(c, 9) + 0.0).alias(c) for c in ("x1", "x2", "x3")])


_SAMPLE = "(('0x' || substr(md5('5|sample|' || c_custkey), 1, 13))::BIGINT + 0.5) / 4503599627370496.0"


@query(f"SELECT c_custkey FROM customer WHERE {_SAMPLE} < 0.2")
def sample_bernoulli(spark, sf_dir):
    """A fifth of the rows, by a digest."""
    from ..operators import sampling

    return sampling.bernoulli(T(spark, sf_dir, "customer", ["c_custkey"]), "c_custkey", 0.2, 5)


@query(f"SELECT c_mktsegment, c_custkey FROM customer WHERE {_SAMPLE} < CASE c_mktsegment WHEN 'BUILDING' THEN 0.5 WHEN 'MACHINERY' THEN 0.1 ELSE 0 END")
def sample_stratified(spark, sf_dir):
    """A share of its own for each stratum."""
    from ..operators import sampling

    rows = T(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"])
    return sampling.stratified(rows, "c_mktsegment", "c_custkey", {"BUILDING": 0.5, "MACHINERY": 0.1}, 5)
