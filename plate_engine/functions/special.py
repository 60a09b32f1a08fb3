"""Digamma and log-gamma as native column expressions, numpy arrays and SQL text.

Both shift the argument by 8 and use the asymptotic series there.  Fixed values: the Bernoulli series' coefficients.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SHIFT = 8
DIGAMMA_SERIES = (1 / 12, -1 / 120, 1 / 252, -1 / 240, 1 / 132)
LGAMMA_SERIES = (1 / 12, -1 / 360, 1 / 1260, -1 / 1680)


def digamma(x: Column) -> Column:
    y = x + SHIFT
    z = 1.0 / (y * y)
    tail = F.lit(0.0)
    for c in reversed(DIGAMMA_SERIES):
        tail = z * (F.lit(c) + tail)
    shift = sum((1.0 / (x + k) for k in range(1, SHIFT)), 1.0 / x)
    return F.log(y) - 0.5 / y - tail - shift


def log_gamma(x: Column) -> Column:
    y = x + SHIFT
    z = 1.0 / (y * y)
    tail = F.lit(0.0)
    for c in reversed(LGAMMA_SERIES):
        tail = z * tail + c
    product = x
    for k in range(1, SHIFT):
        product = product * (x + k)
    return (y - 0.5) * F.log(y) - y + 0.5 * math.log(2 * math.pi) + tail / y - F.log(product)


def digamma_np(x: np.ndarray) -> np.ndarray:
    y = x + SHIFT
    z = 1.0 / (y * y)
    tail = np.zeros_like(y)
    for c in reversed(DIGAMMA_SERIES):
        tail = z * (c + tail)
    return np.log(y) - 0.5 / y - tail - sum(1.0 / (x + k) for k in range(SHIFT))


def log_gamma_np(x: np.ndarray) -> np.ndarray:
    y = x + SHIFT
    z = 1.0 / (y * y)
    tail = np.zeros_like(y)
    for c in reversed(LGAMMA_SERIES):
        tail = z * tail + c
    return (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + tail / y - sum(np.log(x + k) for k in range(SHIFT))


def digamma_sql(x: str) -> str:
    """The same value by direct sums, for the oracle."""
    shift = " + ".join(f"1e0/(({x}) + {k}e0)" for k in range(SHIFT))
    y = f"(({x}) + {SHIFT}e0)"
    series = " - ".join(f"({c!r}::DOUBLE) / pow({y}, {2 * k + 2})" for k, c in enumerate(DIGAMMA_SERIES))
    return f"(ln({y}) - 5e-1/{y} - {series} - ({shift}))"
