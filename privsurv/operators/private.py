"""Private releases: noise on the solution, noise on the objective, and draws from a bounded-loss posterior."""

from __future__ import annotations

import math
import uuid
from dataclasses import asdict, dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import basis
from ..functions import loss as loss_
from . import noise, sensitivity
from .fit import ridge
from .ledger import Ledger
from .objective import Data, Objective
from .solver import SOLVERS, gradient_norm, newton_many


@dataclass
class Release:
    """A released model.  ``exact`` says whether the guarantee holds as stated or only as the sampler converges."""

    method: str
    epsilon: float
    f: list[float]
    q: int
    e: int
    link: str = "logit"
    params: dict[str, float] = field(default_factory=dict)
    exact: bool = True
    run_id: str = ""

    def frame(self, spark: SparkSession) -> DataFrame:
        row = asdict(self)
        return spark.createDataFrame([tuple(row[c] for c in ("run_id", "method", "epsilon", "f", "q", "e", "link", "params", "exact"))], "run_id string, method string, epsilon double, f array<double>, q int, e int, link string, params map<string,double>, exact boolean")

    def register(self, spark: SparkSession, name: str) -> None:
        """SQL access: a view ``name`` of the model, and temporary functions name_risk(x), name_hazard(s, x) and name_survival(s, x) of an
        array of covariates.  They are expressions, compiled with the query that calls them."""
        if not name.isidentifier():
            raise ValueError("a model's name is an identifier")
        if self.link != "logit":
            raise ValueError("SQL functions are for the logit link")
        self.frame(spark).createOrReplaceTempView(name)
        number = lambda v: f"CAST('{float(v)!r}' AS DOUBLE)"
        places = "array(" + ", ".join(number(g) for g in basis.matrix(self.q, self.e) @ self.f[: self.e]) + ")"
        beta = "array(" + ", ".join(map(number, self.f[self.e :])) + ")"
        risk = f"aggregate(zip_with(x, {beta}, (a, b) -> a * b), 0D, (acc, v) -> acc + v)"
        make = "CREATE OR REPLACE TEMPORARY FUNCTION"
        spark.sql(f"{make} {name}_risk(x ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {risk}")
        spark.sql(f"{make} {name}_hazard(s INT, x ARRAY<DOUBLE>) RETURNS DOUBLE RETURN 1 / (1 + exp(-({places}[s - 1] + {risk})))")
        spark.sql(f"{make} {name}_survival(s INT, x ARRAY<DOUBLE>) RETURNS DOUBLE RETURN exp(-aggregate(slice({places}, 1, s), 0D, (acc, g) -> acc + log1p(exp(g + {risk}))))")


def _check(epsilon: float, lam: float | None = None) -> None:
    if not epsilon > 0:
        raise ValueError("epsilon is positive")
    if lam is not None and not lam > 0:
        raise ValueError("this method needs a positive ridge")


def run_name(method: str, seed: object) -> str:
    """A name of its own for every release; seeded ones (tests) repeat theirs."""
    return f"{method}-{uuid.uuid4().hex}" if seed is None else f"{method}-{seed}"


def require_ball(d: Data) -> None:
    """All bounds are for covariates in the unit ball."""
    if d.radius > 1 + 1e-9:
        raise ValueError(f"covariates reach a length of {d.radius:.6g}; scale or clip them to the unit ball first (prep.unit_ball, prep.clip_ball)")


def _certified(o: Objective, f: np.ndarray, tolerance: float) -> None:
    """Refuses a fit that is farther from the optimum than the slack that is charged for."""
    norm = gradient_norm(o, f)
    if not norm <= tolerance:
        raise ValueError(f"the solver stopped at a gradient norm of {norm:.3g}, above {tolerance:g}; raise the tolerance or use another solver")


def output_noise_fit(d: Data, epsilon: float, lam: float, seed: object = None, mode: str = "printed", tolerance: float = 1e-9, fitted: np.ndarray | None = None, ledger: Ledger | None = None, unit: str = "data", certified: bool = False) -> Release:
    """Ridge fit plus noise scaled to its sensitivity, and to how far a fit of that gradient norm may be off.

    ``certified`` says that the caller has checked ``fitted`` already (many draws of one fit).
    """
    sensitivity.require_bounded_gradient(d.link)
    _check(epsilon, lam)
    require_ball(d)
    run = run_name("output", seed)
    if ledger:
        ledger.charge(run, unit, epsilon)
    with d.hold():
        f = ridge(d, lam, tolerance=tolerance) if fitted is None else fitted
        if not certified:
            _certified(Objective(d, lam), f, tolerance)
    t = sensitivity.minimizer(d.a, d.n, lam, mode) + sensitivity.solver_slack(tolerance, lam)
    return Release("output_noise", epsilon, (f + noise.gamma_sphere(d.d, t / epsilon, seed)).tolist(), *d.a.shape, params={"lambda": lam, "sensitivity": t}, run_id=run)


def _masked(f: np.ndarray, ridge_: float, tolerance: float, epsilon: float, seed: object) -> np.ndarray:
    """A stopped fit with noise that hides how far it is from the optimum: both neighbours are within the slack of theirs."""
    if not epsilon:
        return f
    return f + noise.gamma_sphere(len(f), sensitivity.solver_slack(tolerance, ridge_) / epsilon, None if seed is None else f"{seed}|slack")


def objective_noise_fit(d: Data, epsilon: float, lam: float, seed: object = None, mode: str = "printed", tolerance: float = 1e-9, ledger: Ledger | None = None, unit: str = "data", solver: str = "newton", slack_share: float = 1e-3) -> Release:
    """Ridge fit with a random linear term and, where needed, more ridge.

    The guarantee is for the exact optimum.  ``slack_share`` of the budget pays for noise that covers what the stopped solver may be
    off; without it (zero, for comparisons) the release says ``exact=False``.
    """
    sensitivity.require_bounded_gradient(d.link)
    _check(epsilon)
    require_ball(d)
    run = run_name("objective", seed)
    if ledger:
        ledger.charge(run, unit, epsilon, exact=slack_share > 0)
    extra, left = sensitivity.extra_ridge(d.a, d.n, lam, epsilon * (1 - slack_share), mode)
    b = noise.gamma_sphere(d.d, sensitivity.gradient(d.a) / left, seed)
    o = Objective(d, lam, extra, b)
    with d.hold():
        f = SOLVERS[solver](o, tolerance=tolerance)
        _certified(o, f, tolerance)
    f = _masked(f, lam + extra, tolerance, epsilon * slack_share, seed)
    return Release("objective_noise", epsilon, f.tolist(), *d.a.shape, params={"lambda": lam, "extra": extra, "noise_budget": left}, exact=slack_share > 0, run_id=run)


def objective_noise_fits(d: Data, cases: list[tuple[float, object]], lam: float, mode: str = "printed", tolerance: float = 1e-9, start: np.ndarray | None = None, slack_share: float = 1e-3) -> list[Release]:
    """Objective noise for several (epsilon, seed), fitted together so that they share passes over the records.  For experiments: charges no ledger."""
    sensitivity.require_bounded_gradient(d.link)
    require_ball(d)
    bound, terms, parts = sensitivity.gradient(d.a), [], {}
    for epsilon, seed in cases:
        _check(epsilon)
        if epsilon not in parts:
            parts[epsilon] = sensitivity.extra_ridge(d.a, d.n, lam, epsilon * (1 - slack_share), mode)
        extra, left = parts[epsilon]
        terms.append(Objective(d, lam, extra, noise.gamma_sphere(d.d, bound / left, seed)))
    with d.hold():
        fs = newton_many(terms, start, tolerance)
    out = []
    for (e, seed), o, f in zip(cases, terms, fs, strict=True):
        f = _masked(f, lam + o.extra, tolerance, e * slack_share, seed)
        params = {"lambda": lam, "extra": o.extra, "noise_budget": parts[e][1]}
        out.append(Release("objective_noise", e, f.tolist(), *d.a.shape, params=params, exact=slack_share > 0, run_id=run_name("objective", seed)))
    return out


def default_bound(n: float) -> float:
    """Bound of a record's loss."""
    return 2 * math.log(max(n, 2))


def default_prior(v: float, epsilon: float) -> float:
    """Weight of the normal prior."""
    return 0.01 * 2 * v / epsilon


def utility(d: Data, f: np.ndarray, v: float, sigma: float, bound: str = "tanh") -> float:
    """Bounded utility in one pass of columns: minus prior minus sum of bounded losses."""
    e = d.a.shape[1]
    z = loss_.dot([F.col(c) for c in d.x], f[e:])
    own = loss_.sanitize(loss_.record_loss(F.col("t"), F.col("y"), z, f[:e], d.a.shape[0], d.link), v, bound)
    return -0.5 * sigma * float(f @ f) - float(d.df.agg(F.sum(F.col("w") * own)).first()[0] or 0.0)


def exponential_mechanism(scores: DataFrame, epsilon: float, sensitivity_: float, u: float) -> DataFrame:
    """Draws one of few candidates (id, score) with probability proportional to exp(epsilon score / 2 sensitivity).

    ``u`` is a uniform number.  The candidates are a public, bounded list, ordered by id.
    """
    weight = F.exp((F.col("score") - F.max("score").over(Window.partitionBy(F.lit(0)))) * epsilon / (2 * sensitivity_))
    run = scores.withColumn("weight", weight)
    up = Window.partitionBy(F.lit(0)).orderBy("id")
    run = run.withColumn("upto", F.sum("weight").over(up.rowsBetween(Window.unboundedPreceding, 0))).withColumn("total", F.sum("weight").over(Window.partitionBy(F.lit(0))))
    return run.withColumn("p", F.col("weight") / F.col("total")).withColumn("drawn", (F.col("upto") >= u * F.col("total")) & (F.col("upto") - F.col("weight") < u * F.col("total")))
