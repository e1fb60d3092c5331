"""Queries: streams over the events table, held against batch SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..streaming import runner, spells
from . import spells_sql as Q
from .registry import query


def _events(spark, sf_dir):
    return runner.events_stream(spark, f"{sf_dir}/[e]vents.parquet")  # a pattern, so that a table may be one file or a folder


@query(f"""SELECT subject_id, unit_id AS user_id, round(duration, 6) AS duration FROM ({Q.SPELLS['s4']}) WHERE event = 1""")
def stream_spells(spark, sf_dir):
    """Spells that a purchase closes (those that a timer or the end of data censors come later or never)."""
    out = runner.finish(spells.build(_events(spark, sf_dir)))
    return out.where("event = 1").select("subject_id", "user_id", F.round("duration", 6).alias("duration"))


@query("SELECT epoch(date_trunc('day', ts))::BIGINT AS begin, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, sf_dir):
    return runner.finish(spells.tumbling(_events(spark, sf_dir)), "complete")


@query("""SELECT begin, count(*) AS n, sum((event_type = 'purchase')::INT)::BIGINT AS bought FROM (SELECT epoch(date_trunc('day', ts))::BIGINT - 86400 * k AS begin, event_type FROM events, range(0, 2) r(k)) GROUP BY 1""")
def stream_sliding(spark, sf_dir):
    return runner.finish(spells.sliding(_events(spark, sf_dir)), "complete")


@query("""WITH g AS (SELECT *, (ts - lag(ts) OVER w >= INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL)::INT AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM g) SELECT floor(epoch(min(ts)))::BIGINT AS begin, user_id, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_session(spark, sf_dir):
    return runner.finish(spells.sessions(_events(spark, sf_dir)), "complete")


@query("SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1")
def stream_dedup(spark, sf_dir):
    """Each event sent twice, kept once."""
    twice = _events(spark, sf_dir).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    return runner.finish(spells.deduplicated(twice)).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("""SELECT event_id, round(0.8 * value / 1000.0 - 0.5 * hour(ts) / 24.0, 8) + 0.0 AS z, round(1 / (1 + exp(-(-2.0 + 1.0 * 0.05 - 1.5 * power(0.05, 3) + 0.8 * value / 1000.0 - 0.5 * hour(ts) / 24.0))), 8) AS hazard FROM events WHERE event_type = 'signup'""")
def stream_scoring(spark, sf_dir):
    out = runner.finish(spells.scored(_events(spark, sf_dir), [-2.0, 1.0, -1.5], [0.8, -0.5], 20))
    return out.select("event_id", (F.round("z", 8) + 0.0).alias("z"), F.round("hazard", 8).alias("hazard"))


@query("SELECT a.event_id AS signup_id, b.event_id AS purchase_id, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'signup' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 DAY")
def stream_interval_join(spark, sf_dir):
    return runner.finish(spells.interval_join(_events(spark, sf_dir)))


_MARKS = """w AS (SELECT epoch(date_trunc('day', ts))::BIGINT AS begin, event_type, event_id % 3 AS part FROM events),
m AS (SELECT floor(max(epoch_us(ts)) FILTER (event_id % 3 = 0) / 1000 - 432000000) AS one, floor(max(epoch_us(ts)) / 1000 - 432000000) AS two FROM events)"""


@query(f"""WITH {_MARKS} SELECT begin, event_type, count(*) AS n FROM w, m WHERE (part < 2 OR (begin + 86400) * 1000 > one) AND (begin + 86400) * 1000 <= two GROUP BY ALL""")
def stream_late(spark, sf_dir):
    """Three batches of the same month: the third loses events whose window has gone by the watermark of the first (the engine drops
    late rows one batch after it moves the watermark).  Windows that the last watermark has not passed are not given out."""
    from ..sources.tables import table

    folder = f"{runner.shared_dir(spark)}/late-{uuid.uuid4().hex}"
    events = table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type", "value", "props"])
    for part in (0, 1, 2):  # each becomes one batch, in the order written
        events.where(F.col("event_id") % 3 == part).coalesce(1).write.mode("append").parquet(folder)
    return runner.finish(spells.tumbling(runner.events_stream(spark, folder, 1), delay="5 days"))
