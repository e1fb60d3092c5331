"""Other sums of logistic losses: covariates that change over time, any problem given term by term, and fits per group.

A term is one row: its place s (a row of the basis), whether it fails, covariates and a weight.  Solvers, certificates and private
releases take ``Terms`` as they take records: the bounds need no more than at most one term of a subject at each place and
covariates in the unit ball.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.loss import SumOfLogistic
from .objective import Data, Objective
from .solver import newton_many


class TermLoss:
    """Numpy sums over single logistic terms."""

    def __init__(self, a: np.ndarray):
        self.a = a

    def sums(self, f: np.ndarray, x: np.ndarray, t: np.ndarray, y: np.ndarray, w: np.ndarray, hessian: bool = False) -> np.ndarray:
        """Loss, gradient and if asked for the upper triangle of the Hessian."""
        rows = np.concatenate((self.a[t.astype(np.int64) - 1], x), axis=1)
        eta = rows @ f
        fails = (y == 1).astype(float)
        value = w @ (np.maximum(eta, 0) + np.log1p(np.exp(-np.abs(eta))) - fails * eta)
        p = 0.5 * (1 + np.tanh(0.5 * eta))
        parts = [[value], rows.T @ (w * (p - fails))]
        if hessian:
            parts.append(((rows.T * (w * p * (1 - p))) @ rows)[np.triu_indices(len(f))])
        return np.concatenate(parts)


class Repeated(ValueError):
    """A subject has two terms at one place."""


@dataclass
class Terms(Data):
    """Terms as ``Data``: t is the place, n the number of subjects."""

    def kernel(self):
        return TermLoss(self.a)

    def _measure(self) -> None:
        squares = sum((F.col(c) * F.col(c) for c in self.x), F.lit(0.0))
        self.norm = float(self.df.agg(F.sqrt(F.max(squares))).first()[0] or 0)


def terms(df: DataFrame, a: np.ndarray, x: Sequence[str], id_: str = "id", s: str = "s", event: str = "event", w: str | None = None) -> Terms:
    """Terms of ``df``.  Rows with no place or no outcome are not terms; a subject with two terms at one place is refused, since the
    bounds would not hold.  The places of a subject are at most the rows of the basis."""
    rows = df.where(F.col(s).isNotNull() & F.col(event).isNotNull())
    each = rows.groupBy(id_).agg(F.count(F.lit(1)).alias("n"), F.count_distinct(s).alias("places"))
    n, wrong = each.agg(F.count(F.lit(1)), F.coalesce(F.sum((F.col("n") > F.col("places")).cast("long")), F.lit(0))).first()
    if wrong:
        raise Repeated(f"{wrong} subjects have several terms at one place")
    weight = F.col(w).cast("double") if w else F.lit(1.0)
    out = rows.select(F.col(s).cast("int").alias("t"), F.when(F.col(event) == 1, 1).otherwise(-1).alias("y"), weight.alias("w"), *[F.col(c).cast("double").alias(c) for c in x])
    return Terms(out, a, x=list(x), n=float(n) or 1e-300)


def from_cells(cells: DataFrame, a: np.ndarray, x: Sequence[str]) -> Terms:
    """Terms of ``prep.risk_cells``: those that failed in a cell, and those at risk that did not."""
    end = F.explode(F.array(F.struct(F.lit(1).alias("y"), F.col("failed").alias("w")), F.struct(F.lit(-1).alias("y"), (F.col("at_risk") - F.col("failed")).alias("w")))).alias("e")
    n = cells.where("s = 1").agg(F.sum("at_risk")).first()[0]  # all records are at risk in the first interval
    rows = cells.select(F.col("s").cast("int").alias("t"), *x, end).select("t", "e.y", F.col("e.w").cast("double").alias("w"), *x).where("w > 0")
    return Terms(rows, a, x=list(x), n=float(n or 0) or 1e-300)


@dataclass
class GroupObjective(Objective):
    group: int = 0


def grouped_ridge(df: DataFrame, by: str, a: np.ndarray, lam: float, x: Sequence[str], tolerance: float = 1e-9, most_groups: int = 10_000) -> dict[object, np.ndarray]:
    """Ridge fit of every group, all in the same passes: partitions send one short array per group they hold, so a group of any size
    is never in one task.  Refuses more than ``most_groups`` groups, since their coefficients stand on the driver; nulls are a group."""
    x, d = list(x), a.shape[1] + len(x)
    size = 1 + d + d * (d + 1) // 2
    sizes = df.groupBy(by).agg(F.sum("w").alias("n")).limit(most_groups + 1).collect()
    if len(sizes) > most_groups:
        raise ValueError(f"more than {most_groups} groups; fit a part of them at a time")
    if not sizes:
        return {}
    kind = df.schema[by].dataType.simpleString()
    index = df.sparkSession.createDataFrame([(r[0], i) for i, r in enumerate(sizes)], f"__by {kind}, __g int")
    rows = df.join(F.broadcast(index), df[by].eqNullSafe(index["__by"])).select("__g", "t", "y", "w", *x)  # at most most_groups rows

    def second(os: Sequence[GroupObjective], fs: Sequence[np.ndarray]) -> list[tuple[float, np.ndarray, np.ndarray]]:
        live = {o.group: np.asarray(f, float) for o, f in zip(os, fs, strict=True)}

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            kernel, held = SumOfLogistic(a), {}
            for frame in frames:
                for g, own in frame.groupby("__g"):
                    if g in live:
                        held[g] = held.get(g, 0) + kernel.sums(live[g], own[x].to_numpy(float), own["t"].to_numpy(), own["y"].to_numpy(), own["w"].to_numpy(float), True)
            for g, s in held.items():
                yield pd.DataFrame({"g": g, "k": np.arange(size), "v": s})

        sums = {g: np.zeros(size) for g in live}
        for g, k, v in rows.mapInPandas(run, "g int, k int, v double").groupBy("g", "k").agg(F.sum("v")).collect():  # groups x coefficients
            sums[g][k] = v
        out = []
        for o, f in zip(os, fs, strict=True):
            n, s = max(o.data.n, 1.0), sums[o.group]
            value, grad = o._whole(np.asarray(f, float), s[0] / n, s[1 : 1 + d] / n)
            h = np.zeros((d, d))
            h[np.triu_indices(d)] = s[1 + d :] / n
            out.append((value, grad, h + h.T - np.diag(np.diag(h)) + lam * np.eye(d)))
        return out

    rows.persist(StorageLevel.MEMORY_AND_DISK)
    try:
        os = [GroupObjective(Data(rows, a, x=x, n=float(r["n"])), lam, group=i) for i, r in enumerate(sizes)]
        fs = newton_many(os, tolerance=tolerance, second=second)
    finally:
        rows.unpersist()
    return {r[0]: f for r, f in zip(sizes, fs, strict=True)}
