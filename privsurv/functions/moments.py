"""Sums of bounded logit losses over all records from sums of products of their covariates, taken once.

A record's loss depends on its interval, its flag and its effect z alone, and is smooth in z.  Between Chebyshev nodes it is a polynomial
to rounding, so its sum over the records of an interval needs only the sums of T_k(z), and these are linear in sums of products of
Chebyshev polynomials of the covariates.  A value then costs the same for any number of records.  Where a polynomial of the highest
degree does not settle (long coefficient vectors, kinks) there is no value, and the caller sums record by record.
"""

from __future__ import annotations

import itertools
import math
from functools import cache

import numpy as np

DEGREE = 24  # highest total degree
SETTLED = 1e-12  # of the largest coefficient: what the last ones may have


@cache
def nodes(k: int) -> tuple[np.ndarray, np.ndarray]:
    """k Chebyshev nodes, and the matrix from values there to coefficients."""
    at = (np.arange(k) + 0.5) * math.pi / k
    to = 2.0 / k * np.cos(np.outer(np.arange(k), at))
    to[0] /= 2
    return np.cos(at), to


@cache
def _places(k: int) -> tuple[np.ndarray, np.ndarray]:
    angle = (np.arange(k) + 0.5) * math.pi / k
    return np.cos(angle), np.sin(angle) * (-1.0) ** np.arange(k)


def barycentric(z: np.ndarray, middle: float, half: float, k: int) -> tuple[np.ndarray, np.ndarray]:
    """k nodes around the middle, and (a row a node) the share of each in the value of their polynomial at each of ``z``."""
    at, weight = _places(k)
    at = middle + half * at
    away = z - at[:, None]
    if not away.all():
        away[away == 0] = 1e-300
    share = np.divide(weight[:, None], away, out=away)
    share /= np.add.reduce(share, axis=0)
    return at, share


def needed(half: float) -> int:
    """Nodes that settle log(1 + e^z) on an interval of this half width: its nearest singularities are pi away."""
    b = math.pi / max(half, 1e-9)
    return max(6, math.ceil(29.0 / math.log(b + math.sqrt(b * b + 1))) + 2)


def chebyshev(u: np.ndarray, k: int) -> np.ndarray:
    """Rows T_0(u)..T_{k-1}(u)."""
    out = np.ones((k, len(u)))
    out[1:2] = u
    for i in range(2, k):
        out[i] = 2 * u * out[i - 1] - out[i - 2]
    return out


class Moments:
    """Sums over records (with weights ``w``) for each interval and flag, of up to three covariates."""

    def __init__(self, a: np.ndarray, reach: np.ndarray, degree: int = DEGREE):
        """No records yet; ``reach`` bounds each covariate's absolute value."""
        self.a, self.degree, self.reach, p = a, degree, np.maximum(reach, 1e-300), len(reach)
        self.powers = sorted((c for c in itertools.product(range(degree + 1), repeat=p) if sum(c) <= degree), key=sum)
        size, place = len(self.powers), {c: i for i, c in enumerate(self.powers)}
        self.upto = np.searchsorted([sum(c) for c in self.powers], np.arange(degree + 1), side="right")
        # T_a times its own argument is half the sum of its neighbours; a missing neighbour points at a zero behind the last.
        self.near, self.share = np.full((2 * p, size), size), np.full((2 * p, size), 0.5)
        for c, i in place.items():
            for j, (side, step) in itertools.product(range(p), enumerate((-1, 1))):
                self.near[2 * j + side, i] = place.get((*c[:j], c[j] + step, *c[j + 1 :]), size)
                if (c[j], step) == (1, -1):
                    self.share[2 * j, i] = 1.0
        self.set(np.zeros(0, dtype=np.int64), np.zeros(0), np.zeros((0, size)))

    def set(self, keys: np.ndarray, mass: np.ndarray, sums: np.ndarray) -> Moments:
        """``keys`` are twice the interval, and one more for events; ``mass`` counts records, ``sums`` has a row for each key."""
        self.keys, self.mass, self.sums, self.t, self.event = keys, mass, sums, keys // 2, keys % 2 == 1
        return self

    def take(self, x: np.ndarray, t: np.ndarray, y: np.ndarray, w: np.ndarray | float = 1.0) -> Moments:
        """The sums of these records, each with its weight."""
        p, w = x.shape[1], np.broadcast_to(np.asarray(w, dtype=float), (len(t),))
        key = 2 * np.asarray(t, dtype=np.int64) + (np.asarray(y) == 1)
        order = np.argsort(key, kind="stable")
        keys, first = np.unique(key[order], return_index=True)
        sums = np.zeros((len(keys), len(self.powers)))
        flat = np.ravel_multi_index(tuple(np.array(self.powers).T), (self.degree + 1,) * p)
        for g, (lo, hi) in enumerate(zip(first, [*first[1:], len(order)], strict=True)):
            for at in range(lo, hi, 2048):
                own = order[at : min(hi, at + 2048)]
                each = [chebyshev(x[own, j] / self.reach[j], self.degree + 1) for j in range(p)]
                cube = each[0] * w[own]
                for more in each[1:-1]:
                    cube = (cube[:, None] * more[None]).reshape(-1, len(own))
                sums[g] += (cube @ each[-1].T).ravel()[flat] if p > 1 else cube.sum(axis=1)
        return self.set(keys, np.add.reduceat(w[order], first), sums)

    @staticmethod
    def pays(link: str, p: int, n: float, bound: str) -> bool:
        """Whether the sums are worth taking."""
        return link == "logit" and bound != "clip" and 1 <= p <= 3 and n >= 2000

    def _effects(self, c: np.ndarray, k: int) -> np.ndarray:
        """Sums of T_0..T_{k-1} of the scaled effect (whose terms ``c`` have absolute values that sum to one): groups by degrees."""
        size = self.upto[k - 1]
        near, share = np.where(self.near[:, :size] < size, self.near[:, :size], size), self.share[:, :size] * np.repeat(c, 2)[:, None]
        rows = np.zeros((k, size + 1))
        rows[0, 0] = 1
        for i in range(1, k):
            rows[i, :size] = (1 if i == 1 else 2) * (rows[i - 1][near] * share).sum(axis=0)
            if i > 1:
                rows[i] -= rows[i - 2]
        return self.sums[:, :size] @ rows[:, :size].T

    def total(self, f: np.ndarray, v: float, bound: str) -> float | None:
        """The sum of bounded losses, or None where a polynomial would not give it to rounding."""
        e = self.a.shape[1]
        width = int(self.t.max())
        gamma, c = self.a[:width] @ f[:e], f[e:] * self.reach
        half = float(np.abs(c).sum())
        if bound == "clip":
            return None
        k = needed(half)
        while k <= self.degree + 1:
            u, to = nodes(k)
            z = half * u
            eta = gamma[:, None] + z
            loss = np.cumsum(np.logaddexp(0, eta), axis=0)[self.t - 1]
            loss[self.event] -= eta[self.t[self.event] - 1]
            value = (v * np.tanh(loss / v) if bound == "tanh" else loss) @ to.T
            if np.abs(self.mass @ np.abs(value[:, -3:])).max() <= SETTLED * float(self.mass @ np.abs(value).max(axis=1)):
                return float((value * self._effects(c / half if half > 0 else c, k)).sum())
            k += 4
        return None
