"""Python functions for what columns cannot do at speed: long sums of logistic terms, grouped gradients, table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from . import basis
from .loss import SumOfLogistic


def record_loss_arrow(f: list[float], q: int, e: int, link: str = "logit"):
    """Scalar pandas function of t, y and an array of covariates."""
    a, f_ = basis.matrix(q, e), np.asarray(f, float)

    @pandas_udf("double")
    def run(t: pd.Series, y: pd.Series, x: pd.Series) -> pd.Series:
        return pd.Series(SumOfLogistic(a, link).losses(f_, np.stack(x.to_numpy()), t.to_numpy(), y.to_numpy()) if len(t) else np.zeros(0))

    return run


def grouped_gradient(df: DataFrame, by: str, f: list[float], q: int, e: int, x: list[str]) -> DataFrame:
    """Gradient sums per group.  Partial sums are made before the shuffle: Python aggregates have no partial stage."""
    a, f_, d = basis.matrix(q, e), np.asarray(f, float), len(f)

    def run(frames):
        kernel = SumOfLogistic(a)
        for g in frames:
            for name, own in g.groupby(by, dropna=False):
                s = kernel.sums(f_, own[x].to_numpy(float), own["t"].to_numpy(), own["y"].to_numpy(), own["w"].to_numpy(float))
                yield pd.DataFrame({by: [name], **{f"g{i + 1}": [s[1 + i]] for i in range(d)}})

    kind = dict(df.dtypes)[by]
    part = df.mapInPandas(run, f"{by} {kind}, " + ", ".join(f"g{i + 1} double" for i in range(d)))
    return part.groupBy(by).agg(*[F.sum(f"g{i + 1}").alias(f"g{i + 1}") for i in range(d)])


@udtf(returnType="s int, at double")
class SplineGrid:
    """Intervals and their places on (0, 1]."""

    def eval(self, q: int):
        for s in range(1, q + 1):
            yield s, s / q


@udtf(returnType="s int, fails int")
class PersonPeriods:
    """Intervals of one record, for lateral joins."""

    def eval(self, t: int, y: int):
        for s in range(1, t + 1):
            yield s, int(s == t and y == 1)


@udtf(returnType="s int, a array<double>")
class SplineBasis:
    """Basis rows of q intervals with e knots."""

    def eval(self, q: int, e: int):
        for s, row in enumerate(basis.matrix(q, e), 1):
            yield s, row.tolist()


@udtf(returnType="s int, hazard double, survival double")
class SurvivalCurve:
    """Hazard and survival of a record with covariate effect z, for lateral joins; null effects give no rows."""

    def eval(self, z: float, alpha: list, q: int):
        if z is None:
            return
        alive = 1.0
        for s, eta in enumerate(basis.matrix(q, len(alpha)) @ np.asarray(alpha, float) + z, 1):
            h = 0.5 * (1 + np.tanh(0.5 * eta))
            alive *= 1 - h
            yield s, float(h), float(alive)


def register(spark: SparkSession) -> None:
    spark.udtf.register("spline_grid", SplineGrid)
    spark.udtf.register("person_periods", PersonPeriods)
    spark.udtf.register("spline_basis", SplineBasis)
    spark.udtf.register("survival_curve", SurvivalCurve)


def norm(x: Column) -> Column:
    return F.sqrt(F.aggregate(x, F.lit(0.0), lambda acc, v: acc + v * v))
