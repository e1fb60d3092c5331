"""Losses of survival records, as columns for SQL-sized work and as numpy kernels for scale.

A record survives intervals 1..t-1; interval t fails if y = 1 and is survived too if y = -1.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import links
from .basis import GRIDS, spline_columns
from .moments import barycentric, needed


def dot(x: Sequence[Column] | Column, beta: Sequence[float]) -> Column:
    """Covariate effect of flat columns or of an array."""
    cols = [F.get(x, i) for i in range(len(beta))] if isinstance(x, Column) else list(x)
    out = F.lit(0.0)
    for c, b in zip(cols, beta, strict=True):
        out = out + c * F.lit(float(b))
    return out


def baseline(s: Column, alpha: Sequence[float], q: int, grid: str = "right") -> Column:
    parts = spline_columns((s - GRIDS[grid]) / F.lit(float(q)), len(alpha))
    return dot(parts, alpha)


def record_loss(t: Column, y: Column, z: Column, alpha: Sequence[float], q: int, link: str = "logit", grid: str = "right") -> Column:
    """Negative log-likelihood of a record with covariate effect ``z``."""
    survived = F.aggregate(F.sequence(F.lit(1), F.greatest(t, F.lit(1))), F.lit(0.0), lambda acc, s: acc + F.when(s < t, links.loss_survive(baseline(s, alpha, q, grid) + z, link)).otherwise(0.0))
    last = baseline(t, alpha, q, grid) + z
    return survived + F.when(y == 1, links.loss_fail(last, link)).otherwise(links.loss_survive(last, link))


def hazard_loss(t: Column, event: Column, z: Column, alpha: Sequence[float], q: int) -> Column:
    """The same from hazards: -(event ln h(t) + (1 - event) ln(1 - h(t)) + ln S(t - 1))."""
    h = lambda s: links.hazard(baseline(s, alpha, q) + z)
    before = F.aggregate(F.sequence(F.lit(1), F.greatest(t, F.lit(1))), F.lit(0.0), lambda acc, s: acc + F.when(s < t, F.log1p(-h(s))).otherwise(0.0))
    return -(before + F.when(event == 1, F.log(h(t))).otherwise(F.log1p(-h(t))))


def sanitize(loss: Column, v: float, bound: str = "tanh") -> Column:
    """Bounds a loss by v: smoothly, by clipping, or not at all (which is not private)."""
    if bound == "none":
        return loss
    return F.least(loss, F.lit(float(v))) if bound == "clip" else F.lit(float(v)) * F.tanh(loss / F.lit(float(v)))


def sanitize_slope(loss: Column, v: float) -> Column:
    th = F.tanh(loss / F.lit(float(v)))
    return 1 - th * th


def from_long(df: DataFrame, beta: Sequence[float], alpha: Sequence[float], q: int, covariates: Sequence[str]) -> DataFrame:
    """Loss per subject when covariates change over time: one row per subject and interval (id, s, event, covariates)."""
    eta = baseline(F.col("s"), alpha, q) + dot([F.col(c) for c in covariates], beta)
    return df.groupBy("id").agg(F.sum(F.when(F.col("event") == 1, links.loss_fail(eta)).otherwise(links.loss_survive(eta))).alias("loss"))


class SumOfLogistic:
    """Numpy kernel of a sum of logistic (or other link) losses over intervals; other problems may give their own basis rows."""

    def __init__(self, a: np.ndarray, link: str = "logit", chunk: int = 4096):
        self.a, self.link, self.chunk = a, link, chunk

    def parts(self, f: np.ndarray, x: np.ndarray, t: np.ndarray, y: np.ndarray):
        """Yields rows, loss of each, and slopes per interval, for pieces of the records in order of t."""
        e = self.a.shape[1]
        gamma, z = self.a @ f[:e], x @ f[e:]
        order = np.argsort(t, kind="stable")
        for lo in range(0, len(order), self.chunk):
            own = order[lo : lo + self.chunk]
            wide = int(t[own[-1]])
            s = np.arange(1, wide + 1)
            eta = gamma[None, :wide] + z[own][:, None]
            if self.link == "logit":  # failing instead of surviving takes eta from the loss and one from the slope
                small, past = np.exp(-np.abs(eta)), s[None, :] <= t[own][:, None]
                event, end = np.flatnonzero(y[own] == 1), t[own].astype(np.int64) - 1
                loss = ((np.maximum(eta, 0) + np.log1p(small)) * past).sum(axis=1)
                slope = np.where(eta >= 0, 1.0, small) / (1 + small) * past
                loss[event] -= eta[event, end[event]]
                slope[event, end[event]] -= 1
                yield own, loss, slope
                continue
            keep, fail, slope, slope_fail = links.terms(eta, self.link)
            before, at = s[None, :] < t[own][:, None], s[None, :] == t[own][:, None]
            event = at & (y[own] == 1)[:, None]
            alive = before | (at & ~event)
            yield own, (keep * alive + fail * event).sum(axis=1), slope * alive + slope_fail * event

    def losses(self, f: np.ndarray, x: np.ndarray, t: np.ndarray, y: np.ndarray) -> np.ndarray:
        out = np.zeros(len(t))
        for own, loss, _ in self.parts(f, x, t, y):
            out[own] = loss
        return out

    def gradients(self, f: np.ndarray, x: np.ndarray, t: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Loss and gradient of each record."""
        out, grad = np.zeros(len(t)), np.zeros((len(t), len(f)))
        for own, loss, r in self.parts(f, x, t, y):
            out[own] = loss
            grad[own] = np.concatenate((r @ self.a[: r.shape[1]], r.sum(axis=1, keepdims=True) * x[own]), axis=1)
        return out, grad

    def weighted(self, f: np.ndarray, x: np.ndarray, t: np.ndarray, y: np.ndarray, slope: Callable[[np.ndarray], np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """Losses, and the sum of the records' gradients, each times ``slope`` of its loss.

        Logit terms stand in one ragged row per record, so a record costs its own intervals and nothing else; many records whose
        effects are close share terms at a few effects (``_shared``).
        """
        t = np.asarray(t, dtype=np.int64)
        if self.link != "logit" or int(t.sum()) > self.chunk * 256:
            loss, grad = self.gradients(f, x, t, y)
            return loss, slope(loss) @ grad
        e = self.a.shape[1]
        gamma, z = self.a @ f[:e], x @ f[e:]
        low, high = float(np.minimum.reduce(z)), float(np.maximum.reduce(z))
        k = needed((high - low) / 2)
        if 3 * k * int(np.maximum.reduce(t)) <= int(np.add.reduce(t)) and np.maximum.reduce(gamma) + high < 30:
            return self._shared(gamma, z, low, high, k, x, t, y, slope)
        first = np.cumsum(t) - t
        at = np.arange(int(t.sum())) - np.repeat(first, t)
        eta = gamma[at] + np.repeat(z, t)
        if eta.max() < 3:  # products of 200 terms stay finite
            odds = np.exp(eta)
            more = 1 + odds
            loss, p = self._log_products(more, first, t), odds / more
        else:
            small = np.exp(-np.abs(eta))
            loss = np.add.reduceat(np.maximum(eta, 0) + np.log1p(small), first)
            p = np.where(eta >= 0, 1.0, small) / (1 + small)
        event, last = np.flatnonzero(y == 1), t - 1
        loss[event] -= gamma[last[event]] + z[event]
        w = slope(loss)
        p_w = p * np.repeat(w, t)
        per = np.bincount(at, weights=p_w, minlength=len(gamma)) - np.bincount(last[event], weights=w[event], minlength=len(gamma))
        each = np.add.reduceat(p_w, first)
        each[event] -= w[event]
        return loss, np.concatenate((per @ self.a, each @ x))

    def _shared(self, gamma: np.ndarray, z: np.ndarray, low: float, high: float, k: int, x: np.ndarray, t: np.ndarray, y: np.ndarray, slope: Callable[[np.ndarray], np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """``weighted`` from running sums of terms at k Chebyshev nodes between the lowest and highest effect; to rounding, the
        polynomials through them give each record's."""
        width, last, event = int(np.maximum.reduce(t)), t - 1, y == 1
        at, share = barycentric(z, 0.5 * (low + high), max(0.5 * (high - low), 1e-9), k)
        odds = np.exp(at)[:, None] * np.exp(gamma[:width])
        terms = np.empty((2, k, width))
        more = np.add(odds, 1.0, out=terms[0])
        p = np.divide(odds, more, out=terms[1])
        running = np.add.accumulate(np.log(more, out=odds), axis=1), np.add.accumulate(p, axis=1)
        loss, each = [np.add.reduce(own.take(last, axis=1) * share, axis=0) for own in running]
        loss -= event * (gamma.take(last) + z)
        w = slope(loss)
        failed = event * w
        ends = np.bincount((np.arange(0, k * width, width)[:, None] + last).ravel(), (share * w).ravel(), k * width).reshape(k, width)
        later = np.add.accumulate(ends[:, ::-1], axis=1)[:, ::-1]  # slopes of an interval: of all records that end there or later
        per = np.add.reduce(p * later, axis=0) - np.bincount(last, failed, width)
        return loss, np.concatenate((per @ self.a[:width], (w * each - failed) @ x))

    @staticmethod
    def _log_products(more: np.ndarray, first: np.ndarray, t: np.ndarray) -> np.ndarray:
        """Log of the product of each record's terms, all between one and e^3."""
        if t.max() <= 200:
            return np.log(np.multiply.reduceat(more, first))
        return np.add.reduceat(np.log(more), first)

    def _odds_sums(self, base: np.ndarray, own_odds: np.ndarray, f: np.ndarray, x: np.ndarray, t: np.ndarray, y: np.ndarray, w: np.ndarray, hessian: bool, rows: int = 256) -> np.ndarray:
        """``sums`` of the logit link where odds stay below e^25: they are products of an interval's and a record's, so no exponential is
        taken per term; logarithms are of products of eight terms, and pieces of ``rows`` records stay in the cache."""
        d, (q, e) = len(f), self.a.shape
        t = np.asarray(t, dtype=np.int64)
        order = np.argsort(t, kind="stable")
        value, at, slopes = 0.0, np.zeros(q), np.zeros(len(t))
        curve_at, curves, mixed = np.zeros(q), np.zeros(len(t)), np.zeros((e, d - e))
        for lo in range(0, len(order), rows):
            own = order[lo : lo + rows]
            first, k, ww = int(t[own[0]]), int(t[own[-1]]), w[own]
            p = np.zeros((len(own), -(-k // 8) * 8))
            np.multiply(own_odds[own][:, None], base[None, :k], out=p[:, :k])
            p[:, first:k] *= np.arange(first + 1, k + 1)[None, :] <= t[own][:, None]  # past its end a record has no odds
            more = p + 1
            value += float(ww @ np.log(more.reshape(len(own), -1, 8).prod(axis=2)).sum(axis=1))
            p = np.divide(p, more, out=p)[:, :k]
            at[:k] += ww @ p
            slopes[own] = p.sum(axis=1)
            if hessian:
                c = p - p * p
                curve_at[:k] += ww @ c
                curves[own] = c.sum(axis=1)
                mixed += (c @ self.a[:k]).T @ (x[own] * ww[:, None])
        event = y == 1
        value -= float(w[event] @ (np.log(base)[t[event] - 1] + np.log(own_odds[event])))
        at -= np.bincount(t[event] - 1, weights=w[event], minlength=q)
        grad = np.concatenate((at @ self.a, (w * (slopes - event)) @ x))
        if not hessian:
            return np.concatenate(([value], grad))
        hess = np.zeros((d, d))
        hess[:e, :e] = (self.a * curve_at[:, None]).T @ self.a
        hess[:e, e:] = mixed
        hess[e:, e:] = (x * (w * curves)[:, None]).T @ x
        return np.concatenate(([value], grad, hess[np.triu_indices(d)]))

    def sums(self, f: np.ndarray, x: np.ndarray, t: np.ndarray, y: np.ndarray, w: np.ndarray, hessian: bool = False) -> np.ndarray:
        """Weighted sums over records: loss, gradient, and upper triangle of the Hessian (logit only)."""
        d, e = len(f), self.a.shape[1]
        value, grad, hess = 0.0, np.zeros(d), np.zeros((d, d))
        gamma, z = self.a @ f[:e], x @ f[e:]
        if self.link == "logit" and len(z) and gamma.max() + z.max() < 25 and max(-gamma.min(), -z.min(), gamma.max(), z.max()) < 300:
            return self._odds_sums(np.exp(gamma), np.exp(z), f, x, t, y, w, hessian)
        for own, loss, r in self.parts(f, x, t, y):
            k, ww = r.shape[1], w[own][:, None]
            r = r * ww
            value += float(loss @ w[own])
            grad[:e] += r.sum(axis=0) @ self.a[:k]
            grad[e:] += r.sum(axis=1) @ x[own]
            if hessian:
                if self.link != "logit":
                    raise ValueError("the Hessian is for the logit link")
                p = 0.5 * (1 + np.tanh(0.5 * (gamma[None, :k] + z[own][:, None])))
                c = p * (1 - p) * (np.arange(1, k + 1)[None, :] <= t[own][:, None]) * ww
                hess[:e, :e] += (self.a[:k] * c.sum(axis=0)[:, None]).T @ self.a[:k]
                hess[:e, e:] += (c @ self.a[:k]).T @ x[own]
                hess[e:, e:] += (x[own] * c.sum(axis=1)[:, None]).T @ x[own]
        hess[e:, :e] = hess[:e, e:].T
        return np.concatenate(([value], grad, hess[np.triu_indices(d)] if hessian else []))
