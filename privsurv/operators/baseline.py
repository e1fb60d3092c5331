"""Comparators: predecessors for one logistic loss, life tables, the zero vector, accelerated failure times."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import noise
from .fit import ridge
from .objective import Data, Objective
from .prep import covariates
from .private import Release
from .solver import newton


def plain(df: DataFrame) -> Data:
    """One interval: the loss becomes a plain logistic loss of y (x has a constant before it)."""
    return Data(df.withColumn("t", F.lit(1)), np.ones((1, 1)))


def logistic_output(d: Data, epsilon: float, lam: float, seed: object = None) -> Release:
    """Published predecessor: sensitivity 2 / (n lam) of regularised logistic regression on the unit ball."""
    f = ridge(d, lam)
    return Release("logistic_output", epsilon, (f + noise.gamma_sphere(d.d, 2 / (d.n * lam * epsilon), seed)).tolist(), 1, 1, params={"lambda": lam})


def logistic_objective(d: Data, epsilon: float, lam: float, seed: object = None) -> Release:
    """Published predecessor with curvature bound one quarter."""
    c, n = 0.25, d.n
    left, extra = epsilon - np.log(1 + 2 * c / (n * lam) + c * c / (n * lam) ** 2), 0.0
    if left <= 0:
        extra, left = c / (n * np.expm1(epsilon / 4)) - lam, epsilon / 2
    b = noise.gamma_sphere(d.d, 2 / left, seed)
    return Release("logistic_objective", epsilon, newton(Objective(d, lam, extra, b)).tolist(), 1, 1, params={"lambda": lam, "extra": float(extra), "noise_budget": float(left)})


def life_table(df: DataFrame, q: int) -> DataFrame:
    """Per interval: at risk, events, censored, hazard, Kaplan-Meier survival, Nelson-Aalen cumulative hazard.  At most q rows."""
    ends = df.groupBy("t").agg(F.sum("w").alias("n"), F.sum(F.when(F.col("y") == 1, F.col("w")).otherwise(0)).alias("events"))
    grid = df.sparkSession.range(1, q + 1).select(F.col("id").cast("int").alias("s"))
    all_ = grid.join(F.broadcast(ends), F.col("s") == F.col("t"), "left").select("s", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("events", F.lit(0)).alias("events"))
    down = Window.partitionBy(F.lit(0)).orderBy(F.col("s").desc())
    up = Window.partitionBy(F.lit(0)).orderBy("s").rowsBetween(Window.unboundedPreceding, 0)
    run = all_.withColumn("at_risk", F.sum("n").over(down.rowsBetween(Window.unboundedPreceding, 0)))
    run = run.withColumn("hazard", F.when(F.col("at_risk") > 0, F.col("events") / F.col("at_risk")).otherwise(F.lit(0.0)))
    survival = F.when(F.min(1 - F.col("hazard")).over(up) <= 0, 0.0).otherwise(F.exp(F.sum(F.log(F.greatest(1 - F.col("hazard"), F.lit(1e-300)))).over(up)))
    return run.select("s", F.col("at_risk").cast("long").alias("at_risk"), F.col("events").cast("long").alias("events"), (F.col("n") - F.col("events")).cast("long").alias("censored"), "hazard", survival.alias("survival"), F.sum("hazard").over(up).alias("cumulative"))


def zero(d: Data) -> np.ndarray:
    """The limit of heavy ridge; its relative error is one."""
    return np.zeros(d.d)


def aft(df: DataFrame):
    """Accelerated failure time regression of the machine learning library, an outside check of signs."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import AFTSurvivalRegression

    x = covariates(df)
    rows = VectorAssembler(inputCols=x, outputCol="features").transform(df).select(F.col("t").cast("double").alias("label"), F.when(F.col("y") == 1, 1.0).otherwise(0.0).alias("censor"), "features")
    model = AFTSurvivalRegression().fit(rows)
    return model.coefficients.toArray(), model.intercept, model.scale
