from pyspark.sql import functions as F

from privsurv.operators import private
from privsurv.operators.ledger import Ledger, Overspent
from privsurv.sources import planted, tables
from privsurv.streaming import spells


def test_formats_round_trip(spark, tmp_path):
    df = spark.range(5).select(F.col("id").alias("t"), (F.col("id") * 0.5).alias("x1"))
    for kind in ("csv", "json", "orc", "parquet"):
        path = str(tmp_path / kind)
        df.write.format(kind).option("header", "true").save(path)
        got = tables.load(spark, path, kind, "t long, x1 double", **({"header": "true"} if kind == "csv" else {}))
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, df.collect()))


def test_partitioned_and_model_sinks(spark, tmp_path):
    df = spark.range(10).select(F.col("id").alias("subject_id"), (F.col("id") % 2).alias("y"))
    tables.save_frame(df, str(tmp_path / "f"), ["y"])
    assert spark.read.parquet(str(tmp_path / "f")).where("y = 1").count() == 5
    r = private.Release("ridge", 1.0, [1.0, 2.0], 5, 1)
    tables.append_model(r.frame(spark), str(tmp_path / "m"))
    tables.append_model(r.frame(spark), str(tmp_path / "m"))
    assert spark.read.parquet(str(tmp_path / "m")).count() == 2
    assert '"epsilon"' in tables.model_json({"epsilon": 1.0})


def test_views_and_planted_source(spark, sf):
    tables.register_views(spark, sf, ["orders"])
    assert spark.sql("SELECT count(*) FROM orders").first()[0] > 0
    planted.register(spark)
    rows = spark.read.format("planted_survival").options(n="200", partitions="3").load()
    assert rows.count() == 200 and rows.where("t < 1 OR y NOT IN (-1, 1)").isEmpty()


def test_refit_charges_before_it_runs(spark, tmp_path):
    path = str(tmp_path / "in")
    spark.range(4).write.parquet(path)
    led, seen = Ledger(spark, 1.0), []
    stream = spark.readStream.schema("id long").parquet(path)
    q = spells.refit(stream, lambda batch, n: seen.append(batch.count()), led, "u", 0.6).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert seen == [4] and led.spent("u") == 0.6
    try:
        led.charge("more", "u", 0.6)
        raise AssertionError("overspent")
    except Overspent:
        pass


def test_bucketed_tables_join_without_a_shuffle(spark):
    df = spark.range(200).select(F.col("id").alias("user_id"), (F.col("id") % 7).alias("v"))
    limit = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        for name in ("bucketed_a", "bucketed_b"):
            tables.save_bucketed(df, name, "user_id", 4, "overwrite")
        joined = spark.table("bucketed_a").join(spark.table("bucketed_b"), "user_id")
        assert joined.count() == 200 and "Exchange hashpartitioning(user_id" not in joined._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", limit)
        for name in ("bucketed_a", "bucketed_b"):
            spark.sql(f"DROP TABLE IF EXISTS {name}")
