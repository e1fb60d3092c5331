"""Minimisers that ask for one distributed pass per step."""

from __future__ import annotations

import numpy as np

from .objective import Objective, second_many

STEPS = (1.0, 0.5, 0.25, 0.1, 0.02)


def _search(o: Objective, f: np.ndarray, value: float, grad: np.ndarray, way: np.ndarray) -> tuple[np.ndarray, float, np.ndarray]:
    """Backtracking with all step lengths scored in one pass."""
    scale = 1.0
    for _ in range(8):
        tries = [f + scale * s * way for s in STEPS]
        for s, g, (v, gr) in zip(STEPS, tries, o.values(tries), strict=True):
            if np.isfinite(v) and v <= value + 1e-4 * scale * s * float(grad @ way):
                return g, v, gr
        scale *= STEPS[-1]
    return f, value, grad


def bfgs(o: Objective, f0: np.ndarray | None = None, tolerance: float = 1e-8, most: int = 200) -> np.ndarray:
    f = np.zeros(o.data.d) if f0 is None else np.asarray(f0, float)
    (value, grad), h = o.values([f])[0], np.eye(o.data.d)
    for k in range(most):
        if np.linalg.norm(grad) <= tolerance:
            break
        new, v, g = _search(o, f, value, grad, -h @ grad)
        s, y = new - f, g - grad
        if not s.any() or value - v <= 1e-13 * (1 + abs(value)):
            f = new
            break
        sy = float(s @ y)
        if sy > 1e-14:
            if k == 0:
                h *= sy / float(y @ y)
            u = np.eye(len(f)) - np.outer(s, y) / sy
            h = u @ h @ u.T + np.outer(s, s) / sy
        f, value, grad = new, v, g
    return f


def lbfgs(o: Objective, f0: np.ndarray | None = None, memory: int = 10, tolerance: float = 1e-8, most: int = 300) -> np.ndarray:
    """For many coefficients: keeps ``memory`` pairs in place of a matrix."""
    f = np.zeros(o.data.d) if f0 is None else np.asarray(f0, float)
    value, grad = o.values([f])[0]
    pairs: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(most):
        if np.linalg.norm(grad) <= tolerance:
            break
        way, kept = -grad, []
        for s, y in reversed(pairs):
            a = float(s @ way) / float(s @ y)
            kept.append(a)
            way = way - a * y
        if pairs:
            way = way * float(pairs[-1][0] @ pairs[-1][1]) / float(pairs[-1][1] @ pairs[-1][1])
        for (s, y), a in zip(pairs, reversed(kept), strict=True):
            way = way + s * (a - float(y @ way) / float(s @ y))
        new, v, g = _search(o, f, value, grad, way)
        if not (new - f).any() or value - v <= 1e-13 * (1 + abs(value)):
            f = new
            break
        if float((new - f) @ (g - grad)) > 1e-14:
            pairs = [*pairs[-memory + 1 :], (new - f, g - grad)]
        f, value, grad = new, v, g
    return f


def newton(o: Objective, f0: np.ndarray | None = None, tolerance: float = 1e-9, most: int = 50) -> np.ndarray:
    """Few passes, each with the Hessian; damped when a full step does not descend."""
    f = np.zeros(o.data.d) if f0 is None else np.asarray(f0, float)
    value, grad, h = o.second(f)
    for _ in range(most):
        if np.linalg.norm(grad) <= tolerance:
            break
        way = -np.linalg.solve(h + 1e-12 * np.eye(len(f)), grad)
        new = f + way
        v, g, h2 = o.second(new)
        if not np.isfinite(v) or v > value + 1e-12 + 1e-9 * abs(value):
            new, v, g = _search(o, f, value, grad, way)
            if not (new - f).any():
                break
            v, g, h2 = o.second(new)
        f, value, grad, h = new, v, g, h2
    return f


def newton_many(os: list[Objective], f0: np.ndarray | None = None, tolerance: float = 1e-9, most: int = 100, second=second_many) -> list[np.ndarray]:
    """Newton for several objectives on the same data (or, with another ``second``, each on its own): all that are not done share each
    pass.  Steps that do not descend are halved.  Raises if one of them does not reach the tolerance, since noise is calibrated to it."""
    if not os:
        return []
    data = os[0].data
    fs = [np.zeros(data.d) if f0 is None else np.asarray(f0, float) for _ in os]
    state, ways = second(os, fs), [np.zeros(data.d) for _ in os]
    scale, live = [1.0] * len(os), list(range(len(os)))
    for _ in range(most):
        live = [i for i in live if np.linalg.norm(state[i][1]) > tolerance and scale[i] > 1e-9]
        if not live:
            break
        for i in live:
            if scale[i] == 1.0:
                ways[i] = -np.linalg.solve(state[i][2] + 1e-12 * np.eye(data.d), state[i][1])
        tries = [fs[i] + scale[i] * ways[i] for i in live]
        for i, new, there in zip(live, tries, second([os[i] for i in live], tries), strict=True):
            if np.isfinite(there[0]) and there[0] <= state[i][0] + 1e-12 + 1e-9 * abs(state[i][0]):
                fs[i], state[i], scale[i] = new, there, 1.0
            else:
                scale[i] /= 2
    worst = max(float(np.linalg.norm(x[1])) for x in state)
    if not worst <= tolerance:
        raise ValueError(f"the solver stopped at a gradient norm of {worst:.3g}, above {tolerance:g}")
    return fs


def descend(o: Objective, step: float, iterations: int, f0: np.ndarray | None = None) -> list[np.ndarray]:
    """Plain gradient steps of fixed length; the whole trajectory."""
    f = np.zeros(o.data.d) if f0 is None else np.asarray(f0, float)
    out = [f]
    for _ in range(iterations):
        f = f - step * o.values([f])[0][1]
        out.append(f)
    return out


def gradient_norm(o: Objective, f: np.ndarray) -> float:
    return float(np.linalg.norm(o.values([f])[0][1]))


def certificate(o: Objective, f: np.ndarray) -> float:
    """Upper bound on the distance from the optimum, from strong convexity."""
    return gradient_norm(o, f) / (o.lam + o.extra)


SOLVERS = {"bfgs": bfgs, "lbfgs": lbfgs, "newton": newton}
