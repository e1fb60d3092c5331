"""Scoring with a released model: curves, quantiles, expected lifetimes, risk groups, effects.  Post-processing costs no budget."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import basis, links, loss
from .prep import row_ids


def scored(df: DataFrame, beta: Sequence[float], x: Sequence[str]) -> DataFrame:
    return df.withColumn("z", loss.dot([F.col(c) for c in x], beta))


def curves(profiles: DataFrame, alpha: Sequence[float], beta: Sequence[float], x: Sequence[str], q: int, link: str = "logit") -> DataFrame:
    """subject_id, s, hazard, survival, density, cumulative hazard: q rows per profile."""
    spark = profiles.sparkSession
    b = basis.natural_spline(spark, q, len(alpha)).select("s", loss.dot(F.col("a"), alpha).alias("gamma"))
    rows = scored(profiles, beta, x).select("subject_id", "z").crossJoin(F.broadcast(b))  # q rows
    h = rows.withColumn("hazard", links.hazard(F.col("gamma") + F.col("z"), link))
    up = Window.partitionBy("subject_id").orderBy("s")
    h = h.withColumn("survival", F.exp(F.sum(F.log1p(-F.col("hazard"))).over(up.rowsBetween(Window.unboundedPreceding, 0))))
    before = F.coalesce(F.lag("survival").over(up), F.lit(1.0))
    return h.select("subject_id", "s", "hazard", "survival", (before * F.col("hazard")).alias("density"), F.sum("hazard").over(up.rowsBetween(Window.unboundedPreceding, 0)).alias("cumulative"))


def quantile_time(curve: DataFrame, level: float = 0.5) -> DataFrame:
    """First interval at which survival falls to the level (null if it never does), and expected intervals lived."""
    return curve.groupBy("subject_id").agg(F.min(F.when(F.col("survival") <= level, F.col("s"))).alias("quantile"), (1 + F.sum("survival")).alias("expected"))


def deciles(df: DataFrame, groups: int = 10) -> DataFrame:
    """Risk groups of equal size by exact cut points (``groups`` - 1 numbers), found by rank in ranges, so nothing is sorted in one task."""
    z = df.select("z").where("z is not null")
    n = z.count()
    ranks = [-(-i * n // groups) for i in range(1, groups)]
    at = {r["row_id"]: r["z"] for r in row_ids(z, "z").where(F.col("row_id").isin([k - 1 for k in ranks])).select("row_id", "z").collect()}
    cuts = F.array(*[F.lit(at[k - 1]) for k in ranks if k]).cast("array<double>")
    return df.withColumn("decile", (1 + F.size(F.filter(cuts, lambda c: c < F.col("z")))).cast("int"))


def effects(spark: SparkSession, beta: Sequence[float], names: Sequence[str], link: str = "logit") -> DataFrame:
    """exp(beta): odds ratios for the logit link, hazard ratios for the complementary log-log link."""
    rows = spark.createDataFrame([(n, float(b)) for n, b in zip(names, beta, strict=True)], "name string, beta double")
    return rows.withColumn("ratio", F.exp("beta")).withColumn("kind", F.lit({"logit": "odds", "cloglog": "hazard"}.get(link, "none")))
