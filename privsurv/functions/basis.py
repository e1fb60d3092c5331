"""Baseline hazard bases: natural cubic splines on equally spaced knots, constants and interval dummies."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

GRIDS = {"right": 0.0, "mid": 0.5, "left": 1.0}  # what to subtract from s


def knots(e: int) -> list[float]:
    if e < 2:
        raise ValueError("a natural spline has two knots at least")
    return [j / (e - 1) for j in range(e)]


def spline_columns(u: Column, e: int, at: list[float] | None = None) -> list[Column]:
    """The e basis functions at u: constant, linear, and differences of truncated cubes."""
    k = at or knots(e)
    cube = lambda c: F.pow(F.greatest(u - c, F.lit(0.0)), F.lit(3.0))
    part = lambda j: (cube(k[j]) - cube(k[-1])) / (k[-1] - k[j])
    return [F.lit(1.0), u, *[part(j) - part(e - 2) for j in range(e - 2)]]


def natural_spline(spark: SparkSession, q: int, e: int = 3, grid: str = "right", at: list[float] | None = None) -> DataFrame:
    """s and a (array of e numbers) for s = 1..q."""
    u = (F.col("s") - GRIDS[grid]) / F.lit(float(q))
    return spark.range(1, q + 1).select(F.col("id").cast("int").alias("s")).select("s", F.array(*spline_columns(u, e, at)).alias("a"))


def constant(spark: SparkSession, q: int) -> DataFrame:
    return spark.range(1, q + 1).select(F.col("id").cast("int").alias("s"), F.array(F.lit(1.0)).alias("a"))


def dummies(spark: SparkSession, q: int) -> DataFrame:
    return spark.range(1, q + 1).select(F.col("id").cast("int").alias("s")).select("s", F.transform(F.sequence(F.lit(1), F.lit(q)), lambda i: (i == F.col("s")).cast("double")).alias("a"))


def matrix(q: int, e: int = 3, grid: str = "right", kind: str = "spline", at: list[float] | None = None) -> np.ndarray:
    """The same in numpy: q rows.  It has q * e numbers, whatever the data."""
    if kind == "constant":
        return np.ones((q, 1))
    if kind == "dummies":
        return np.eye(q)
    u, k = (np.arange(1, q + 1) - GRIDS[grid]) / q, at or knots(e)
    cube = lambda c: np.maximum(u - c, 0.0) ** 3
    part = lambda j: (cube(k[j]) - cube(k[-1])) / (k[-1] - k[j])
    return np.stack([np.ones(q), u, *[part(j) - part(e - 2) for j in range(e - 2)]], axis=1)
