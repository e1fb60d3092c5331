"""Reproducible random columns from digests of their keys: the same under retries, repartitioning and in other engines.

For tests and data generation.  Production noise comes from the operating system's entropy, on the driver.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = float(1 << 52)


def uniform(*keys: Column | str | int) -> Column:
    """In (0, 1): 52 bits of the MD5 of the keys joined by bars."""
    text = F.concat_ws("|", *[k if isinstance(k, Column) else F.lit(str(k)) for k in keys])
    return (F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("double") + 0.5) / SCALE


def exponential(*keys: Column | str | int) -> Column:
    return -F.log(uniform(*keys))


def normal(*keys: Column | str | int) -> Column:
    return F.sqrt(-2 * F.log(uniform(*keys, "r"))) * F.cos(2 * math.pi * uniform(*keys, "a"))


def gamma(shape: int, *keys: Column | str | int) -> Column:
    """Gamma of whole shape and scale one: a sum of exponentials."""
    out = F.lit(0.0)
    for i in range(shape):
        out = out + exponential(*keys, str(i))
    return out


def value(*keys: object) -> float:
    """``uniform`` in Python."""
    return (int(hashlib.md5("|".join(map(str, keys)).encode()).hexdigest()[:13], 16) + 0.5) / SCALE


def normal_value(*keys: object) -> float:
    return math.sqrt(-2 * math.log(value(*keys, "r"))) * math.cos(2 * math.pi * value(*keys, "a"))


def sphere(d: int, scale: float, *keys: object) -> np.ndarray:
    """Replayed noise: length Gamma(d, scale), direction uniform on the sphere."""
    length = scale * sum(-math.log(value(*keys, "length", i)) for i in range(d))
    way = np.array([normal_value(*keys, "way", i) for i in range(d)])
    return length * way / np.linalg.norm(way)
