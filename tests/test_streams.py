from pyspark.sql import functions as F

from privsurv.streaming import runner, spells

DAY = 86_400


def write(spark, path, rows):
    df = spark.createDataFrame(rows, "event_id long, sec long, user_id long, event_type string, value double, props string")
    df.select("event_id", F.timestamp_seconds("sec").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", "value", "props").coalesce(1).write.mode("append").parquet(path)


def test_spells_close_expire_and_drop_late_rows(spark, tmp_path):
    path, base = str(tmp_path / "events"), 1_700_000_000
    e = lambda i, day, user, kind: (i, base + int(day * DAY), user, kind, 1.0, "{}")
    write(spark, path, [e(1, 0, 1, "signup"), e(2, 1, 1, "purchase"), e(3, 0, 2, "signup"), e(4, 0.5, 3, "view")])
    stream = runner.events_stream(spark, path, 1)
    write(spark, path, [e(5, 20, 9, "signup")])  # moves the watermark past user 2's deadline
    write(spark, path, [e(7, 21, 9, "purchase")])
    write(spark, path, [e(6, 2, 4, "signup"), e(8, 40, 8, "view"), e(9, 40, 8, "signup")])  # the first is late
    got = {(r.user_id, r.subject_id): (round(r.duration, 3), r.event) for r in runner.finish(spells.build(stream)).collect()}
    assert got[(1, 1)] == (1.0, 1) and got[(2, 3)] == (6.0, 0) and got[(9, 5)] == (1.0, 1)
    assert (4, 6) not in got


def test_duplicates_are_dropped(spark, tmp_path):
    path = str(tmp_path / "events")
    write(spark, path, [(1, 1_700_000_000, 1, "view", 1.0, "{}")] * 3 + [(2, 1_700_000_100, 1, "view", 1.0, "{}")])
    assert runner.finish(spells.deduplicated(runner.events_stream(spark, path))).count() == 2


def test_a_retried_refit_is_charged_once(spark, tmp_path):
    """A new query over the same events, as after a crash before its checkpoint, meets the charge that the ledger's table keeps."""
    from privsurv.operators.ledger import Ledger

    path, seen = str(tmp_path / "events"), []
    write(spark, path, [(1, 1_700_000_000, 1, "signup", 1.0, "{}")])
    for attempt in range(2):
        ledger = Ledger(spark, 1.0, path=str(tmp_path / "ledger"))
        stream = runner.events_stream(spark, path)
        query = spells.refit(stream, lambda batch, number: seen.append(number), ledger, "u", 0.7).option("checkpointLocation", str(tmp_path / f"c{attempt}")).trigger(availableNow=True).start()
        query.awaitTermination()
    assert seen == [0, 0] and Ledger(spark, 1.0, path=str(tmp_path / "ledger")).spent("u") == 0.7
