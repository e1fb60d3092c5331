"""Log gamma and its first two derivatives for positive numbers, by recurrence and asymptotic series.

The same code serves numpy arrays (``log=numpy.log``) and columns (``log=pyspark.sql.functions.log``).
"""

from __future__ import annotations

import math
from collections.abc import Callable

SHIFT = 12  # arguments are raised by this much; the series is then good to about 1e-11


def log_gamma(x, log: Callable):
    y, less = x + SHIFT, 0.0
    for i in range(SHIFT):
        less = less + log(x + i)
    r = 1 / y
    return (y - 0.5) * log(y) - y + 0.5 * math.log(2 * math.pi) + r * (1 / 12 - r * r * (1 / 360 - r * r / 1260)) - less


def digamma(x, log: Callable):
    y, less = x + SHIFT, 0.0
    for i in range(SHIFT):
        less = less + 1 / (x + i)
    r = 1 / y
    return log(y) - r / 2 - r * r * (1 / 12 - r * r * (1 / 120 - r * r / 252)) - less


def trigamma(x):
    y, more = x + SHIFT, 0.0
    for i in range(SHIFT):
        more = more + 1 / ((x + i) * (x + i))
    r = 1 / y
    return r + r * r / 2 + r * r * r * (1 / 6 - r * r * (1 / 30 - r * r / 42)) + more
