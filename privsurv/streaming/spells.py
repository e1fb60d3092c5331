"""Survival spells over event streams: an opening event starts one, a closing event ends it, a timer censors it.

State per user is the list of open spells.  Rows of a batch are taken in (ts, event_id) order; rows older than the watermark are
late and dropped by the engine.  A timer fires when the watermark passes the earliest deadline.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

OUT = "user_id long, subject_id long, duration double, event int"
STATE = "ids array<long>, starts array<double>"
DAY = 86_400.0


def build(events: DataFrame, opens: str = "signup", closes: str = "purchase", days: float = 6.0, delay: str = "1 day") -> DataFrame:
    limit = days * DAY

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ids, starts = (list(v) for v in state.get) if state.exists else ([], [])
        out: list[tuple] = []
        if state.hasTimedOut:
            now = state.getCurrentWatermarkMs() / 1000
        else:
            rows = pd.concat(list(frames)).sort_values(["sec", "event_id"])
            for sec, event_id, kind in zip(rows["sec"], rows["event_id"], rows["event_type"], strict=True):
                late = [i for i, s in enumerate(starts) if s + limit < sec]
                out += [(key[0], ids[i], days, 0) for i in late]
                ids, starts = ([v for i, v in enumerate(x) if i not in set(late)] for x in (ids, starts))
                if kind == closes:
                    out += [(key[0], i, (sec - s) / DAY, 1) for i, s in zip(ids, starts, strict=True)]
                    ids, starts = [], []
                elif kind == opens:
                    ids.append(int(event_id))
                    starts.append(float(sec))
            now = state.getCurrentWatermarkMs() / 1000
        over = [i for i, s in enumerate(starts) if s + limit < now]
        out += [(key[0], ids[i], days, 0) for i in over]
        ids, starts = ([v for i, v in enumerate(x) if i not in set(over)] for x in (ids, starts))
        if ids:
            state.update((ids, starts))
            state.setTimeoutTimestamp(max(int((min(starts) + limit) * 1000) + 1, state.getCurrentWatermarkMs() + 1))
        elif state.exists:
            state.remove()
        yield pd.DataFrame(out, columns=["user_id", "subject_id", "duration", "event"])

    rows = events.withWatermark("ts", delay).where(F.col("event_type").isin(opens, closes)).select("user_id", "event_id", "event_type", "ts", (F.unix_micros("ts") / 1e6).alias("sec"))
    return rows.groupBy("user_id").applyInPandasWithState(step, OUT, STATE, "append", GroupStateTimeout.EventTimeTimeout)


def tumbling(events: DataFrame, width: str = "1 day", delay: str = "1 day") -> DataFrame:
    """Events by type per window."""
    return events.withWatermark("ts", delay).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("begin"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day", delay: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.window("ts", width, step).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.when(F.col("event_type") == "purchase", 1).otherwise(0)).cast("long").alias("bought")).select(F.unix_seconds("w.start").alias("begin"), "n", "bought")


def sessions(events: DataFrame, gap: str = "6 hours", delay: str = "1 day") -> DataFrame:
    """Sessions per user: runs of events less than a gap apart."""
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("begin"), "user_id", "n")


def deduplicated(events: DataFrame, delay: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def scored(events: DataFrame, alpha: list[float], beta: list[float], q: int) -> DataFrame:
    """Risk of each signup with a released model: expressions only, no state."""
    from ..functions import links, loss

    z = loss.dot([F.col("value") / 1000.0, F.hour("ts") / 24.0], beta)
    first = loss.baseline(F.lit(1), alpha, q) + z
    return events.where("event_type = 'signup'").select("event_id", z.alias("z"), links.hazard(first).alias("hazard"))


def interval_join(events: DataFrame, days: int = 6, delay: str = "1 day") -> DataFrame:
    """Signups with purchases of the same user within some days after, both sides with a watermark."""
    left = events.where("event_type = 'signup'").select(F.col("event_id").alias("signup_id"), "user_id", F.col("ts").alias("ts1")).withWatermark("ts1", delay)
    right = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("user2"), F.col("ts").alias("ts2")).withWatermark("ts2", delay)
    on = (F.col("user_id") == F.col("user2")) & (F.col("ts2") > F.col("ts1")) & (F.col("ts2") <= F.col("ts1") + F.expr(f"INTERVAL {days} DAYS"))
    return left.join(right, on).select("signup_id", "purchase_id", "user_id")


def refit(stream: DataFrame, fit, ledger, unit: str, epsilon: float, name: str = "batch"):
    """A private fit per batch: each is charged before it runs, and once if it is retried (a restarted query keeps batch numbers
    and, with a ledger that has a path, the charge)."""

    def one(batch: DataFrame, number: int) -> None:
        if not batch.isEmpty():
            ledger.charge(f"{name}-{number}", unit, epsilon)
            fit(batch, number)

    return stream.writeStream.foreachBatch(one)
