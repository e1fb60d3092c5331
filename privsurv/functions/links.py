"""Link functions of the hazard: logit, complementary log-log and probit, as columns and in numpy.

A score ``eta`` is the baseline effect plus covariate effect of one interval; the inverse link makes it the probability of an
event in the interval given none before.  Losses are negative log-likelihoods of surviving or failing one interval.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

LINKS = ("logit", "cloglog", "probit")
# Rational approximation of the error function, absolute error below 1.5e-7.
ERF_P = 0.3275911
ERF_A = (0.254829592, -0.284496736, 1.421413741, -1.453152027, 1.061405429)


def _check(link: str) -> None:
    if link not in LINKS:
        raise ValueError(f"link is one of {', '.join(LINKS)}, not {link!r}")


def softplus(u: Column) -> Column:
    """ln(1 + e^u) without overflow."""
    return F.greatest(u, F.lit(0.0)) + F.log1p(F.exp(-F.abs(u)))


def normal_cdf(x: Column) -> Column:
    z = F.abs(x) / F.lit(float(np.sqrt(2)))
    t = 1 / (1 + ERF_P * z)
    poly = t * (ERF_A[0] + t * (ERF_A[1] + t * (ERF_A[2] + t * (ERF_A[3] + t * ERF_A[4]))))
    erf = 1 - poly * F.exp(-z * z)
    return F.when(x >= 0, 0.5 * (1 + erf)).otherwise(0.5 * (1 - erf))


def hazard(eta: Column, link: str = "logit") -> Column:
    """Inverse link: probability of an event from a score."""
    _check(link)
    if link == "logit":
        return F.when(eta >= 0, 1 / (1 + F.exp(-eta))).otherwise(F.exp(eta) / (1 + F.exp(eta)))
    if link == "cloglog":
        return -F.expm1(-F.exp(eta))
    return normal_cdf(eta)


def score(h: Column, link: str = "logit") -> Column:
    """The link itself, of a probability strictly between 0 and 1 (probit by bisection-free inversion is numpy only)."""
    _check(link)
    if link == "logit":
        return F.log(h / (1 - h))
    if link == "cloglog":
        return F.log(-F.log1p(-h))
    raise ValueError("the probit score has no built-in expression; use normal_quantile")


def normal_quantile(p: float) -> float:
    """Inverse normal distribution function by Newton steps on the exact function."""
    from statistics import NormalDist

    return NormalDist().inv_cdf(p)


def loss_survive(eta: Column, link: str = "logit") -> Column:
    _check(link)
    if link == "logit":
        return softplus(eta)
    return F.exp(eta) if link == "cloglog" else -F.log(F.greatest(normal_cdf(-eta), F.lit(1e-12)))


def loss_fail(eta: Column, link: str = "logit") -> Column:
    _check(link)
    if link == "logit":
        return softplus(-eta)
    return -F.log(F.greatest(-F.expm1(-F.exp(eta)), F.lit(1e-12))) if link == "cloglog" else -F.log(F.greatest(normal_cdf(eta), F.lit(1e-12)))


def terms(eta: np.ndarray, link: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Numpy: losses of surviving and failing and their slopes in eta."""
    _check(link)
    if link == "logit":
        soft, p = np.maximum(eta, 0) + np.log1p(np.exp(-np.abs(eta))), 0.5 * (1 + np.tanh(0.5 * eta))
        return soft, soft - eta, p, p - 1
    if link == "cloglog":
        ex = np.exp(np.clip(eta, -50, 50))
        h = np.maximum(-np.expm1(-ex), 1e-300)
        return ex, -np.log(h), ex, -ex * np.exp(-ex) / h
    t = 1 / (1 + ERF_P * np.abs(eta) / np.sqrt(2))
    erf = 1 - t * (ERF_A[0] + t * (ERF_A[1] + t * (ERF_A[2] + t * (ERF_A[3] + t * ERF_A[4])))) * np.exp(-eta * eta / 2)
    cdf = np.where(eta >= 0, 0.5 * (1 + erf), 0.5 * (1 - erf))
    low, high, pdf = np.maximum(1 - cdf, 1e-12), np.maximum(cdf, 1e-12), np.exp(-eta * eta / 2) / np.sqrt(2 * np.pi)
    return -np.log(low), -np.log(high), pdf / low, -pdf / high
