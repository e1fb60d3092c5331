"""Non-private fits: maximum likelihood and ridge, with any link."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from ..functions import basis
from .objective import Data, Objective
from .solver import SOLVERS


def data(df: DataFrame, q: int, e: int = 3, link: str = "logit", kind: str = "spline", grid: str = "right") -> Data:
    return Data(df, basis.matrix(q, e, grid, kind), link)


def ridge(d: Data, lam: float, solver: str | None = None, tolerance: float = 1e-9) -> np.ndarray:
    """Newton for the logit link with few coefficients, quasi-Newton otherwise."""
    name = solver or ("newton" if d.link == "logit" and d.d <= 40 else "lbfgs" if d.d > 40 else "bfgs")
    with d.hold():
        return SOLVERS[name](Objective(d, lam), tolerance=tolerance)


class Unbounded(ValueError):
    """Maximum likelihood runs off to infinity."""


def mle(d: Data, solver: str | None = None, tolerance: float = 1e-9) -> np.ndarray:
    """No penalty.  Raises ``Unbounded`` where the likelihood has no finite maximiser (events are separated, or a coefficient is not
    identified): there a Newton step stays long however small the gradient gets.  Give ``ridge`` a small penalty then."""
    f = ridge(d, 0.0, solver, tolerance)
    if d.link == "logit":
        _, grad, h = Objective(d).second(f)
        away = np.linalg.norm(np.linalg.lstsq(h, grad, rcond=None)[0])
    else:
        grad, away = Objective(d).values([f])[0][1], 0.0
    if not np.isfinite(f).all() or np.linalg.norm(grad) > max(1e-6, 10 * tolerance) or away > 1e-3 * (1 + np.linalg.norm(f)):
        raise Unbounded("the likelihood has no finite maximiser; use ridge with a small penalty")
    return f


def optimum(d: Data, penalty: float = 1e-8) -> tuple[np.ndarray, float]:
    """What private fits are compared with, and the ridge that it took: none, or ``penalty`` where there is no finite maximiser."""
    try:
        with d.hold():
            return mle(d), 0.0
    except Unbounded:
        return ridge(d, penalty), penalty
