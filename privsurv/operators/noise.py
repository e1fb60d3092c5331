"""Noise with density proportional to exp(-|b| / scale): Gamma length, uniform direction.  Drawn on the driver, once."""

from __future__ import annotations

import numpy as np

from ..functions import rng


def gamma_sphere(d: int, scale: float, seed: object = None) -> np.ndarray:
    """From the system's entropy; with a seed, a replayable draw for tests (not private, since it can be replayed)."""
    if seed is not None:
        return rng.sphere(d, scale, seed)
    g = np.random.Generator(np.random.PCG64(np.random.SeedSequence()))
    way = g.standard_normal(d)
    return g.gamma(d, scale) * way / np.linalg.norm(way)


def laplace_vector(value: np.ndarray, sensitivity: float, epsilon: float, seed: object = None) -> np.ndarray:
    """Any vector with that l2 sensitivity, released under epsilon."""
    if epsilon <= 0 or sensitivity < 0:
        raise ValueError("epsilon is positive, sensitivity not negative")
    return np.asarray(value, float) + gamma_sphere(len(value), sensitivity / epsilon, seed)
