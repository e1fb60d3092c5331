"""Survival workloads on the given tables, as raw spells: subject_id, unit_id, duration, event, x1..xp.

Horizons and cutoffs are public constants.  ``frame`` turns spells into records: interval t, y = +-1, covariates centred and fitted
into the unit ball.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import prep
from .tables import table

CUTOFF = "1995-07-01"


@dataclass(frozen=True)
class Spec:
    q: int
    horizon: float
    p: int


SPECS = {"s1": Spec(200, 2500, 8), "s2": Spec(200, 181, 3), "s3": Spec(200, 181, 3), "s4": Spec(200, 6, 3), "s5": Spec(8, 8, 3), "s6": Spec(50, 50_000, 4), "s7": Spec(9, 9, 64)}


def days(a: Column, b: Column) -> Column:
    """Days from a to b, of timestamps of either kind."""
    micros = lambda c: F.unix_micros(c.cast("timestamp"))
    return (micros(b) - micros(a)) / F.lit(86_400e6)


def returns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """S1: order to shipment of a line, event if returned.  Covariates: eight of line, order and part."""
    line = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"])
    orders = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_totalprice", "o_orderdate"])
    part = table(spark, sf_dir, "part", ["p_partkey", "p_size", "p_retailprice"])
    df = line.join(orders, line.l_orderkey == orders.o_orderkey).join(part, line.l_partkey == part.p_partkey).where("l_shipdate > o_orderdate")
    x = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", (F.col("l_linestatus") == "F").cast("double"), "p_size", "p_retailprice", "o_totalprice"]
    cols = [(F.col(c) if isinstance(c, str) else c).cast("double").alias(f"x{i + 1}") for i, c in enumerate(x)]
    key = F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.date_format("l_shipdate", "yyyyMMdd"))
    return df.select(key.alias("subject_id"), F.col("o_custkey").alias("unit_id"), days(F.col("o_orderdate"), F.col("l_shipdate")).alias("duration"), (F.col("l_returnflag") == "R").cast("int").alias("event"), *cols)


def _spells(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate", "o_totalprice"]).where(F.col("o_orderdate") < F.lit(CUTOFF).cast("timestamp_ntz"))
    return orders.withColumn("k", F.row_number().over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")))


def next_order(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """S2 (k = 1) and S3 (k = 2): from a customer's k-th order to the next, censored at the cutoff."""
    rows = _spells(spark, sf_dir).where(F.col("k") <= k + 1)
    customer = table(spark, sf_dir, "customer", ["c_custkey", "c_acctbal", "c_mktsegment"])
    at = lambda i, c: F.max(F.when(F.col("k") == i, F.col(c)))
    wide = rows.groupBy("o_custkey").agg(*[at(i, c).alias(f"{n}{i}") for i in range(1, k + 2) for n, c in (("date", "o_orderdate"), ("price", "o_totalprice"))]).where(f"date{k} is not null")
    end = F.coalesce(f"date{k + 1}", F.lit(CUTOFF).cast("timestamp_ntz"))
    middle = (F.col("c_mktsegment") == "BUILDING").cast("double") if k == 1 else days(F.col(f"date{k - 1}"), F.col(f"date{k}"))
    return wide.join(customer, wide.o_custkey == customer.c_custkey).select(
        F.col("o_custkey").alias("subject_id"), F.col("o_custkey").alias("unit_id"), days(F.col(f"date{k}"), end).alias("duration"), F.col(f"date{k + 1}").isNotNull().cast("int").alias("event"),
        F.col("c_acctbal").cast("double").alias("x1"), middle.alias("x2"), F.col(f"price{k}").cast("double").alias("x3"))


def signups(spark: SparkSession, sf_dir: str, window: float = 6.0) -> DataFrame:
    """S4: signup to the user's next purchase, censored after ``window`` days or at the end of the data."""
    end = table(spark, sf_dir, "events", ["ts"]).agg(F.max("ts").alias("data_end"))
    nxt = prep.next_event_spells(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], "event_type", "signup", "purchase", "ts")
    wait = days(F.col("ts"), F.col("closed"))
    event = F.coalesce(wait <= window, F.lit(False))
    left = F.least(F.lit(window), days(F.col("ts"), F.col("data_end")))
    return nxt.crossJoin(F.broadcast(end)).select(  # one row
        F.col("event_id").alias("subject_id"), F.col("user_id").alias("unit_id"), F.when(event, wait).otherwise(left).alias("duration"), event.cast("int").alias("event"),
        F.col("value").cast("double").alias("x1"), F.get_json_object("props", "$.k").cast("double").alias("x2"), F.hour("ts").cast("double").alias("x3"))


def dialogues(spark: SparkSession, sf_dir: str) -> DataFrame:
    """S5: number of turns; event if the assistant spoke last."""
    df = table(spark, sf_dir, "conversations")
    return df.groupBy("conv_id").agg(
        F.count(F.lit(1)).alias("turns"), F.max_by("role", "turn").alias("last"), F.min_by("role", "turn").alias("opening"), F.avg(F.length("text")).alias("x2"), F.countDistinct("role").alias("roles"),
    ).select(F.col("conv_id").alias("subject_id"), F.col("conv_id").alias("unit_id"), F.col("turns").cast("double").alias("duration"), (F.col("last") == "assistant").cast("int").alias("event"),
             (F.col("opening") == "system").cast("double").alias("x1"), "x2", F.col("roles").cast("double").alias("x3"))


def lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """S6: length of a labelled document; event if toxic."""
    docs, labels = table(spark, sf_dir, "documents", ["doc_id", "lang", "n_chars"]), table(spark, sf_dir, "labels")
    lang = [(F.col("lang") == x).cast("double").alias(f"x{i + 2}") for i, x in enumerate(("de", "es", "fr"))]
    return labels.join(docs, "doc_id").select(F.col("doc_id").alias("subject_id"), F.col("doc_id").alias("unit_id"), F.col("n_chars").cast("double").alias("duration"), F.col("toxic").cast("int").alias("event"), F.col("quality").cast("double").alias("x1"), *lang)


def stages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """S7: label of a vector as its stage; the embedding as covariates."""
    df = table(spark, sf_dir, "embeddings")
    return df.select(F.col("vec_id").alias("subject_id"), F.col("vec_id").alias("unit_id"), F.least(F.col("label") + 1, F.lit(9)).cast("double").alias("duration"), (F.col("label") < 9).cast("int").alias("event"), *[F.get("embedding", i).cast("double").alias(f"x{i + 1}") for i in range(64)])


SPELLS = {"s1": returns, "s2": lambda s, d: next_order(s, d, 1), "s3": lambda s, d: next_order(s, d, 2), "s4": signups, "s5": dialogues, "s6": lengths, "s7": stages}


def frame(spark: SparkSession, sf_dir: str, name: str, q: int | None = None, scale: str = "radius") -> DataFrame:
    """Records of a workload: subject_id, unit_id, t, y, x1..xp, w."""
    spec = SPECS[name]
    df = SPELLS[name](spark, sf_dir)
    df = prep.discretize(df, q or spec.q, spec.horizon)
    x = prep.covariates(df)
    if name != "s7" or scale != "radius":  # embeddings are in the unit ball already
        df = prep.unit_ball(prep.center(df, x), x, scale)
    return df.select("subject_id", "unit_id", "t", "y", *x, F.lit(1).cast("long").alias("w"))
