"""Distributed value, gradient and Hessian of the data term.

Each partition sums its records' terms in numpy and returns one short array; Spark adds the arrays.  Traffic and driver memory depend on
the number of coefficients and of candidates, never on the number of records.  Several candidate vectors share one pass.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.loss import SumOfLogistic
from .prep import covariates


@dataclass
class Data:
    """Records with the basis they are fitted on."""

    df: DataFrame
    a: np.ndarray  # q rows of the time basis
    link: str = "logit"
    x: list[str] = field(default_factory=list)
    n: float = 0.0
    passes: int = 0
    norm: float | None = None  # longest covariate vector

    def __post_init__(self) -> None:
        self.x = self.x or covariates(self.df)
        self._held = self.df.is_cached  # then every pass reads the caller's copy
        self.df = self.df.select("t", "y", "w", *self.x)
        if not self.n:
            self._measure()

    def _measure(self) -> None:
        squares = sum((F.col(c) * F.col(c) for c in self.x), F.lit(0.0))
        n, norm = self.df.agg(F.sum("w"), F.sqrt(F.max(squares))).first()
        self.n, self.norm = float(n or 0), float(norm or 0)

    def kernel(self):
        """What sums the records of a partition."""
        return SumOfLogistic(self.a, self.link)

    @property
    def radius(self) -> float:
        """Length of the longest covariate vector."""
        if self.norm is None:
            self._measure()
        return self.norm

    @contextmanager
    def hold(self) -> Iterator[None]:
        """Keeps the pruned records while a solver passes over them: scans, windows and joins that made them run once.
        Partitions of lost executors are made again from the source."""
        if self._held:
            yield
            return
        self._held = True
        self.df.persist(StorageLevel.MEMORY_AND_DISK)
        try:
            yield
        finally:
            self.df.unpersist()
            self._held = False

    @property
    def d(self) -> int:
        return self.a.shape[1] + len(self.x)

    def sums(self, fs: Sequence[np.ndarray], hessian: bool = False) -> np.ndarray:
        """Per candidate: loss, gradient and if asked for the upper triangle of the Hessian, summed over records."""
        kernel, x, fs = self.kernel(), list(self.x), [np.asarray(f, dtype=float) for f in fs]
        d = self.d
        size = 1 + d + (d * (d + 1) // 2 if hessian else 0)

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            out = np.zeros((len(fs), size))
            for f in frames:
                if len(f):
                    cols = f[x].to_numpy(dtype=float)
                    t, y, w = f["t"].to_numpy(), f["y"].to_numpy(), f["w"].to_numpy(dtype=float)
                    for k, c in enumerate(fs):
                        out[k] += kernel.sums(c, cols, t, y, w, hessian)
            yield pd.DataFrame({"i": np.arange(out.size), "v": out.ravel()})

        rows = self.df.mapInPandas(run, "i int, v double").groupBy("i").agg(F.sum("v")).collect()  # candidates x coefficients
        self.passes += 1
        out = np.zeros(len(fs) * size)
        for i, v in rows:
            out[i] = v
        return out.reshape(len(fs), size)


@dataclass
class Objective:
    """Mean loss plus ridge ``lam`` (and ``extra``), plus a linear term b'f/n; only the mean loss needs the data."""

    data: Data
    lam: float = 0.0
    extra: float = 0.0
    b: np.ndarray | None = None

    def values(self, fs: Sequence[np.ndarray]) -> list[tuple[float, np.ndarray]]:
        out, n = [], max(self.data.n, 1.0)
        for f, s in zip(fs, self.data.sums(fs), strict=True):
            out.append(self._whole(np.asarray(f, float), s[0] / n, s[1 : 1 + len(f)] / n))
        return out

    def _whole(self, f: np.ndarray, value: float, grad: np.ndarray) -> tuple[float, np.ndarray]:
        ridge = self.lam + self.extra
        value, grad = value + 0.5 * ridge * float(f @ f), grad + ridge * f
        if self.b is not None:
            value, grad = value + float(self.b @ f) / max(self.data.n, 1.0), grad + self.b / max(self.data.n, 1.0)
        return value, grad

    def second(self, f: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        return second_many([self], [f])[0]


def second_many(os: Sequence[Objective], fs: Sequence[np.ndarray]) -> list[tuple[float, np.ndarray, np.ndarray]]:
    """Value, gradient and Hessian of several objectives on the same data, each at its own point, in one pass."""
    data, out = os[0].data, []
    n, d = max(data.n, 1.0), data.d
    for o, f, s in zip(os, fs, data.sums(fs, hessian=True), strict=True):
        value, grad = o._whole(np.asarray(f, float), s[0] / n, s[1 : 1 + d] / n)
        h = np.zeros((d, d))
        h[np.triu_indices(d)] = s[1 + d :] / n
        h = h + h.T - np.diag(np.diag(h))
        out.append((value, grad, h + (o.lam + o.extra) * np.eye(d)))
    return out
