"""Estimator in the style of the machine learning library: fit a private or plain model, transform records to risks.

Models are kept as one-row tables (``save``, ``load``), which any engine can read.
"""

from __future__ import annotations

from pyspark import keyword_only
from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import basis
from . import predict, private
from .chain import bounded_sampler_fit
from .fit import mle, ridge
from .ledger import Ledger
from .objective import Data
from .prep import covariates


class SurvivalModel(Model):
    def __init__(self, release: private.Release | None = None, x: list[str] | None = None):
        super().__init__()
        self.release, self.x = release, x or []

    def _transform(self, dataset: DataFrame) -> DataFrame:
        return predict.scored(dataset, self.release.f[self.release.e :], self.x)

    def curves(self, dataset: DataFrame) -> DataFrame:
        """Hazard and survival per subject and interval."""
        r = self.release
        return predict.curves(dataset, r.f[: r.e], r.f[r.e :], self.x, r.q, r.link)

    def save(self, spark: SparkSession, path: str, mode: str = "errorifexists") -> None:
        names = F.array(*[F.lit(c) for c in self.x]) if self.x else F.array().cast("array<string>")
        self.release.frame(spark).withColumn("x", names).write.mode(mode).parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> SurvivalModel:
        row = spark.read.parquet(path).first().asDict()
        return cls(private.Release(**{k: v for k, v in row.items() if k != "x"}), list(row["x"]))


class PrivateSurvivalRegression(Estimator):
    """``method``: mle, ridge, output_noise, objective_noise or sampler.  ``link`` is for the methods that take one (not the two noise
    methods).  With a ledger every private fit is charged to ``unit`` before it runs."""

    method = Param(Params._dummy(), "method", "how to fit", TypeConverters.toString)
    epsilon = Param(Params._dummy(), "epsilon", "privacy budget", TypeConverters.toFloat)
    lam = Param(Params._dummy(), "lam", "ridge", TypeConverters.toFloat)
    q = Param(Params._dummy(), "q", "intervals", TypeConverters.toInt)
    e = Param(Params._dummy(), "e", "knots", TypeConverters.toInt)
    steps = Param(Params._dummy(), "steps", "steps of the sampler", TypeConverters.toInt)
    link = Param(Params._dummy(), "link", "logit, cloglog or probit", TypeConverters.toString)
    unit = Param(Params._dummy(), "unit", "whom the ledger charges", TypeConverters.toString)

    @keyword_only
    def __init__(self, *, method: str = "output_noise", epsilon: float = 1.0, lam: float = 0.01, q: int = 200, e: int = 3, steps: int = 2000, link: str = "logit", unit: str = "data"):
        super().__init__()
        self._setDefault(method="output_noise", epsilon=1.0, lam=0.01, q=200, e=3, steps=2000, link="logit", unit="data")
        self._set(**self._input_kwargs)
        self.ledger: Ledger | None = None

    def charging(self, ledger: Ledger) -> PrivateSurvivalRegression:
        """This estimator, with a ledger that its private fits are charged to."""
        self.ledger = ledger
        return self

    def _fit(self, dataset: DataFrame) -> SurvivalModel:
        get = self.getOrDefault
        d = Data(dataset, basis.matrix(get(self.q), get(self.e)), get(self.link), x=covariates(dataset))
        how, eps, lam, charge = get(self.method), get(self.epsilon), get(self.lam), {"ledger": self.ledger, "unit": get(self.unit)}
        if how == "output_noise":
            r = private.output_noise_fit(d, eps, lam, **charge)
        elif how == "objective_noise":
            r = private.objective_noise_fit(d, eps, lam, **charge)
        elif how == "sampler":
            r = bounded_sampler_fit(d, eps, steps=get(self.steps), **charge)
        elif how in ("mle", "ridge"):
            tolerance = 1e-9 if d.link == "logit" else 1e-6
            f = mle(d, tolerance=tolerance) if how == "mle" else ridge(d, lam, tolerance=tolerance)
            r = private.Release(how, float("inf"), f.tolist(), get(self.q), get(self.e), d.link)
        else:
            raise ValueError(f"unknown method {how!r}")
        return SurvivalModel(r, d.x)
