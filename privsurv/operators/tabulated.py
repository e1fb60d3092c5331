"""Losses from a table: for given coefficients the sum over survived intervals depends on (t, x'beta) alone.

The table has one row per interval with values and slopes at equally spaced scores; a record's loss is a cubic interpolation in its row, one
broadcast lookup of q rows in place of up to q exponentials.  Scores lie in [-|beta|, |beta|], because covariates are in the unit ball.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import loss as loss_


def error_bound(q: int, radius: float, points: int) -> float:
    """Of cubic Hermite interpolation: the fourth derivative of one softplus term is at most one eighth."""
    h = 2 * radius / (points - 1)
    return q * 0.125 * h**4 / 384


def table(spark: SparkSession, a: np.ndarray, f: np.ndarray, points: int = 129) -> tuple[DataFrame, float, float]:
    """t, gamma, v (sums of survived terms), d (their slopes); radius and step."""
    e = a.shape[1]
    radius = float(np.linalg.norm(f[e:])) + 1e-9
    z, gamma = np.linspace(-radius, radius, points), a @ f[:e]
    eta = gamma[:, None] + z[None, :]
    v = np.cumsum(np.maximum(eta, 0) + np.log1p(np.exp(-np.abs(eta))), axis=0)
    d = np.cumsum(0.5 * (1 + np.tanh(0.5 * eta)), axis=0)
    rows = [(i + 1, float(gamma[i]), v[i].tolist(), d[i].tolist()) for i in range(len(a))]
    return spark.createDataFrame(rows, "__t int, __gamma double, __v array<double>, __d array<double>"), radius, 2 * radius / (points - 1)


def losses(df: DataFrame, a: np.ndarray, f: np.ndarray, x: list[str], points: int = 129) -> DataFrame:
    """Adds ``loss`` to records."""
    small, radius, h = table(df.sparkSession, a, np.asarray(f, float), points)
    z = loss_.dot([F.col(c) for c in x], f[a.shape[1] :])
    held = df.withColumn("__z", z).join(F.broadcast(small), F.col("t") == F.col("__t"))  # q rows
    at = F.least(F.lit(points - 2), F.greatest(F.lit(0), F.floor((F.col("__z") + radius) / h))).cast("int")
    held = held.withColumn("__i", at).withColumn("__u", (F.col("__z") + radius) / h - F.col("__i"))

    def part(name: str, off: int) -> Column:
        return F.get(name, F.col("__i") + off)

    u = F.col("__u")
    value = (1 + 2 * u) * (1 - u) ** 2 * part("__v", 0) + u * (1 - u) ** 2 * h * part("__d", 0) + u * u * (3 - 2 * u) * part("__v", 1) + u * u * (u - 1) * h * part("__d", 1)
    own = value - F.when(F.col("y") == 1, F.col("__gamma") + F.col("__z")).otherwise(0.0)
    return held.withColumn("loss", own).drop("__z", "__t", "__gamma", "__v", "__d", "__i", "__u")
