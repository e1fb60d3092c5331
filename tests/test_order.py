"""Row ids in the order of their key, and ranks found by them."""

from pyspark.sql import functions as F

from privsurv.operators import prep


def test_row_ids_follow_the_key_over_many_ranges(spark):
    df = spark.range(5000).select((F.col("id") * 7919 % 5003 * 3 - 4000).alias("k"))
    got = prep.row_ids(df.repartition(5), "k", rows_each=200).orderBy("k").toPandas()
    assert got["row_id"].tolist() == list(range(5000))
    pairs = df.select(F.struct((F.col("k") % 10).alias("a"), "k").alias("key"))
    got = prep.row_ids(pairs, "key", rows_each=200).orderBy("key").toPandas()
    assert got["row_id"].tolist() == list(range(5000))
    assert prep.row_ids(df.limit(0), "k").count() == 0


def test_deciles_are_exact_ranks_whatever_the_number_of_records(spark):
    from privsurv.operators import predict

    df = spark.range(60_001).select((F.col("id") * 7919 % 60_001).cast("double").alias("z"))
    got = {r["decile"]: (r["lo"], r["n"]) for r in predict.deciles(df).groupBy("decile").agg(F.min("z").alias("lo"), F.count(F.lit(1)).alias("n")).collect()}
    assert got == {i + 1: (float(-(-i * 60_001 // 10)), -(-(i + 1) * 60_001 // 10) - -(-i * 60_001 // 10)) for i in range(10)}
    few = spark.createDataFrame([(1.0,), (2.0,), (None,)], "z double")
    assert {(r["z"], r["decile"]) for r in predict.deciles(few).collect()} == {(1.0, 1), (2.0, 6), (None, 1)}
    assert predict.deciles(few.limit(0)).count() == 0
