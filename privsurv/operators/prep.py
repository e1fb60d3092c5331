"""From raw tables to survival records.

A record has subject_id, unit_id (whom privacy protects), t in 1..q, y = +1 (event) or -1 (censored), covariates x1..xp inside
the unit ball, and a weight w.  Empty tables give empty records; null covariates are rejected unless a policy says otherwise.
"""

from __future__ import annotations

import re
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.window import WindowSpec

from ..functions import rng


def covariates(df: DataFrame) -> list[str]:
    return sorted((c for c in df.columns if re.fullmatch(r"x\d+", c)), key=lambda c: int(c[1:]))


def survival_frame(df: DataFrame, id_: str, start: Column, end: Column, censor: Column, x: Sequence[Column], unit: str | None = None) -> DataFrame:
    """Durations in days from origin, end (null if not seen) and censoring times; the earlier of the two counts."""
    micros = lambda c: F.unix_micros(c.cast("timestamp"))
    event = F.coalesce(end <= censor, F.lit(False))
    return df.select(F.col(id_).alias("subject_id"), F.col(unit or id_).alias("unit_id"), ((micros(F.when(event, end).otherwise(censor)) - micros(start)) / 86_400e6).alias("duration"), event.cast("int").alias("event"), *[c.cast("double").alias(f"x{i + 1}") for i, c in enumerate(x)])


def gap_spells(df: DataFrame, key: str, order: Sequence[str], time: str) -> DataFrame:
    """Every k-th to (k+1)-th gap of a recurrent event: key, k, begin, next (null if none)."""
    w = Window.partitionBy(key).orderBy(*order)
    return df.select(key, F.row_number().over(w).alias("k"), F.col(time).alias("begin"), F.lead(time).over(w).alias("next"))


def next_event_spells(df: DataFrame, key: str, order: Sequence[str], kind: str, opens: str, closes: str, time: str) -> DataFrame:
    """From each opening event to the key's next closing one."""
    closing = F.when(F.col(kind) == closes, F.col(time))
    return df.where(F.col(kind).isin(opens, closes)).withColumn("closed", F.min(closing).over(later(key, order))).where(F.col(kind) == opens)


def later(key: str, order: Sequence[str]) -> WindowSpec:
    """All later rows of a key.  Runs backwards, so that a running minimum serves: frames that end at the last row are evaluated anew
    for each row."""
    return Window.partitionBy(key).orderBy(*[F.col(c).desc() for c in order]).rowsBetween(Window.unboundedPreceding, -1)


def discretize(df: DataFrame, q: int, horizon: float | None = None) -> DataFrame:
    """Adds t and y.  Without a public ``horizon`` the largest duration is used, which reveals it."""
    if horizon is None:
        horizon = float(df.agg(F.max("duration")).first()[0] or 1.0)
    t = F.greatest(F.lit(1), F.least(F.lit(q), F.ceil(F.col("duration") / F.lit(float(horizon)) * q))).cast("int")
    return df.withColumn("t", t).withColumn("y", (2 * F.col("event") - 1).cast("int"))


def center(df: DataFrame, x: Sequence[str]) -> DataFrame:
    """Zero means: one aggregate of p numbers, broadcast back as a single row."""
    means = df.agg(*[F.avg(c).alias(f"m_{c}") for c in x])
    return df.crossJoin(F.broadcast(means)).withColumns({c: F.col(c) - F.col(f"m_{c}") for c in x}).drop(*[f"m_{c}" for c in x])


def norm(x: Sequence[str]) -> Column:
    out = F.lit(0.0)
    for c in x:
        out = out + F.col(c) * F.col(c)
    return F.sqrt(out)


def unit_ball(df: DataFrame, x: Sequence[str], mode: str = "radius", bounds: Sequence[float] | None = None) -> DataFrame:
    """Fits covariates into the unit ball.

    ``radius`` divides by the largest norm (as data-dependent as centring); ``clip`` shrinks only records outside;
    ``public_bounds`` divides each covariate by its public bound times the root of p; ``zscore_radius`` standardises first.
    """
    if mode == "clip":
        scale = F.least(F.lit(1.0), 1 / F.greatest(norm(x), F.lit(1e-300)))
        return df.withColumn("__s", scale).withColumns({c: F.col(c) * F.col("__s") for c in x}).drop("__s")
    if mode == "public_bounds":
        clipped = {c: F.greatest(F.lit(-1.0), F.least(F.lit(1.0), F.col(c) / F.lit(float(b)))) / F.lit(len(x) ** 0.5) for c, b in zip(x, bounds or [], strict=True)}
        return df.withColumns(clipped)
    if mode == "zscore_radius":
        sd = df.agg(*[F.stddev_pop(c).alias(f"s_{c}") for c in x])
        df = df.crossJoin(F.broadcast(sd)).withColumns({c: F.col(c) / F.when(F.col(f"s_{c}") > 0, F.col(f"s_{c}")).otherwise(1.0) for c in x}).drop(*[f"s_{c}" for c in x])
    elif mode != "radius":
        raise ValueError(f"unknown mode {mode!r}")
    top = df.agg(F.max(norm(x)).alias("__r"))
    return df.crossJoin(F.broadcast(top)).withColumns({c: F.col(c) / F.when(F.col("__r") > 0, F.col("__r")).otherwise(1.0) for c in x}).drop("__r")


def encode(df: DataFrame, column: str, levels: Sequence[str]) -> DataFrame:
    """One dummy per level after the first."""
    return df.withColumns({f"{column}_{v}": (F.coalesce(F.col(column), F.lit("")) == v).cast("int") for v in levels[1:]})


def nulls(df: DataFrame, x: Sequence[str], policy: str = "reject") -> DataFrame:
    bad = F.lit(False)
    for c in x:
        bad = bad | F.col(c).isNull() | F.isnan(c)
    if policy == "drop":
        return df.where(~bad)
    if policy == "impute_mean":
        means = df.agg(*[F.avg(F.when(~F.isnan(c), F.col(c))).alias(f"m_{c}") for c in x])
        return df.crossJoin(F.broadcast(means)).withColumns({c: F.when(F.col(c).isNull() | F.isnan(c), F.col(f"m_{c}")).otherwise(F.col(c)) for c in x}).drop(*[f"m_{c}" for c in x])
    if not df.where(bad).isEmpty():
        raise ValueError("null or NaN covariates")
    return df


def validate(df: DataFrame, x: Sequence[str], q: int) -> DataFrame:
    """One row of counts: rows, and rows with a bad interval, flag, covariate, norm, or a repeated subject."""
    null = F.lit(False)
    for c in x:
        null = null | F.col(c).isNull() | F.isnan(c)
    count = lambda c: F.sum(F.when(c, 1).otherwise(0)).cast("long")
    out = df.agg(F.count(F.lit(1)).alias("n"), count(~F.col("t").between(1, q) | F.col("t").isNull()).alias("bad_t"), count(~F.col("y").isin(-1, 1) | F.col("y").isNull()).alias("bad_y"), count(null).alias("bad_x"), count(~null & (norm(x) > 1 + 1e-12)).alias("outside"))
    twice = df.groupBy("subject_id").count().where("count > 1").agg(F.count(F.lit(1)).alias("repeated"))
    return out.crossJoin(F.broadcast(twice))


def bound_contribution(df: DataFrame, m: int, seed: int = 0) -> DataFrame:
    """At most m records per privacy unit, chosen by a digest: user-level budgets are then m times the record-level one."""
    order = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("subject_id").cast("string")).cast("binary"))
    w = Window.partitionBy("unit_id").orderBy(order, "subject_id")
    return df.withColumn("__k", F.row_number().over(w)).where(F.col("__k") <= m).drop("__k")


def person_period(df: DataFrame) -> DataFrame:
    """One row per survived or failed interval; ``fails`` is 1 in the last interval of an event."""
    return df.select("*", F.explode(F.sequence(F.lit(1), F.col("t"))).alias("s")).withColumn("fails", ((F.col("s") == F.col("t")) & (F.col("y") == 1)).cast("int"))


def compress(df: DataFrame, x: Sequence[str]) -> DataFrame:
    """Equal records as one with a weight; exact, and small for categorical covariates."""
    return df.groupBy("t", "y", *x).agg(F.sum("w").cast("long").alias("w"))


def risk_cells(df: DataFrame, x: Sequence[str]) -> DataFrame:
    """Per covariate cell and interval s: how many were at risk and how many failed.  The data term depends on these alone."""
    ends = df.groupBy(*x, "t").agg(F.sum("w").alias("n"), F.sum(F.when(F.col("y") == 1, F.col("w")).otherwise(0)).alias("failed"))
    # At risk in s: all that end at s or later.  Cells that end nowhere in between have rows only where someone ends,
    # so expand each end to the intervals since the previous one.
    w = Window.partitionBy(*x).orderBy(F.col("t").desc())
    back = Window.partitionBy(*x).orderBy("t")
    run = ends.withColumn("at_risk", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0))).withColumn("prev", F.coalesce(F.lag("t").over(back), F.lit(0)))
    wide = run.select(*x, "t", "failed", "at_risk", F.explode(F.sequence(F.col("prev") + 1, F.col("t"))).alias("s"))
    return wide.select(*x, "s", F.col("at_risk").cast("long").alias("at_risk"), F.when(F.col("s") == F.col("t"), F.col("failed")).otherwise(0).cast("long").alias("failed"))


def row_ids(df: DataFrame, order: str, seed: int = 0, rows_each: int = 100_000) -> DataFrame:
    """Dense ids 0..n-1 in the order of a column, without a global sort: counts of ranges of it, their running total, and a rank inside
    each range.  Bounds of ranges come from keys chosen by a digest, so each evaluation finds the same."""
    n = df.count()
    many = max(1, min(1 << 16, -(-n // rows_each)))
    each = 32  # keys per range
    chosen = df.where(F.pmod(F.xxhash64(F.lit(seed), F.col(order)), F.lit(max(1, n // (each * many)))) == 0) if many > 1 else df.limit(0)
    edges = chosen.agg(F.array_sort(F.collect_list(order)).alias("__keys"))
    edges = edges.select(F.filter("__keys", lambda _, i: (i + 1) % each == 0).alias("__edges"))
    steps = F.array(*[F.lit(1 << k) for k in range(17, -1, -1)])
    cell = F.aggregate(steps, F.lit(0), lambda at, s: F.when((at + s <= F.size("__edges")) & (F.get("__edges", at + s - 1) <= F.col(order)), at + s).otherwise(at))
    held = df.crossJoin(F.broadcast(edges)).withColumn("__cell", cell).drop("__edges")  # one row
    before = Window.partitionBy(F.lit(0)).orderBy("__cell").rowsBetween(Window.unboundedPreceding, -1)
    first = held.groupBy("__cell").count().select("__cell", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("__first"))  # cells only
    inside = Window.partitionBy("__cell").orderBy(order)
    return held.withColumn("__k", F.row_number().over(inside)).join(F.broadcast(first), "__cell").withColumn("row_id", (F.col("__first") + F.col("__k") - 1).cast("long")).drop("__cell", "__k", "__first")


def stats(df: DataFrame, p: int) -> DataFrame:
    return df.agg(F.count(F.lit(1)).alias("n"), F.sum("event").cast("long").alias("uncensored"), F.lit(p).cast("long").alias("p"))


def split(df: DataFrame, key: str, share: float, seed: int = 0) -> DataFrame:
    """Adds ``holdout`` by a digest of the key."""
    return df.withColumn("holdout", (rng.uniform(str(seed), "split", F.col(key).cast("string")) < share))
