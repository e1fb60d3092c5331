"""Empirical checks of privacy claims on explicit neighbours: data sets that differ in one record."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.loss import SumOfLogistic
from . import sensitivity
from .objective import Objective


def swapped(df: DataFrame, old_id: int, new: DataFrame) -> DataFrame:
    """The neighbour with one record replaced."""
    return df.where(F.col("subject_id") != old_id).unionByName(new)


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Records in one but not the other, repeats counted."""
    return a.exceptAll(b).withColumn("side", F.lit("left")).unionByName(b.exceptAll(a).withColumn("side", F.lit("right")))


def gradient_looseness(a: np.ndarray, p: int, pairs: int, seed: int = 0) -> float:
    """Largest gradient difference of random record pairs over its bound: never above one."""
    g, k = np.random.default_rng(seed), SumOfLogistic(a)
    q, e, worst = a.shape[0], a.shape[1], 0.0
    for _ in range(pairs):
        f = g.standard_normal(e + p) * g.choice([0.1, 1, 5, 20])
        x = g.standard_normal((2, p))
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        _, grad = k.gradients(f, x, g.integers(1, q + 1, 2), g.choice([-1, 1], 2))
        worst = max(worst, float(np.linalg.norm(grad[0] - grad[1])))
    return worst / sensitivity.gradient(a)


def gradient_use(a: np.ndarray) -> float:
    """Largest gradient difference at zero coefficients over its bound, of all pairs of times and ends with opposite covariates."""
    q, k = a.shape[0], SumOfLogistic(a)
    t, y = np.tile(np.arange(1, q + 1), 2), np.repeat([1, -1], q)
    f = np.zeros(a.shape[1] + 1)
    (_, one), (_, two) = (k.gradients(f, np.full((2 * q, 1), x), t, y) for x in (1.0, -1.0))
    return float(np.linalg.norm(one[:, None, :] - two[None, :, :], axis=2).max()) / sensitivity.gradient(a)


def output_ratio(f1: np.ndarray, f2: np.ndarray, t: float, epsilon: float, points: np.ndarray) -> float:
    """Largest log density ratio of the output-noise release between two neighbours' fits, over some outputs: at most epsilon."""
    return float(np.abs(np.linalg.norm(points - f1, axis=1) - np.linalg.norm(points - f2, axis=1)).max() * epsilon / t)


def objective_ratios(one: Objective, two: Objective, scale: float, points: np.ndarray) -> np.ndarray:
    """Log density ratios of the objective-noise release between two neighbours, at some outputs.

    An output is the optimum for exactly one linear term, minus the gradient of the rest; its density is the noise's density
    there times the Jacobian of that map, the determinant of the Hessian.  ``scale``: of the noise's length.
    """
    out = []
    for f in points:
        terms = []
        for o in (one, two):
            _, grad, h = o.second(f)
            terms.append(-o.data.n * float(np.linalg.norm(grad)) / scale + float(np.linalg.slogdet(o.data.n * h)[1]))
        out.append(terms[0] - terms[1])
    return np.array(out)


def utility_gap(losses: DataFrame, v: float) -> DataFrame:
    """Largest change of the bounded utility over all replacements of one record: the range of bounded losses, below v."""
    b = F.lit(v) * F.tanh(F.col("loss") / F.lit(v))
    return losses.agg((F.max(b) - F.min(b)).alias("gap")).withColumn("ok", F.col("gap") <= v)
