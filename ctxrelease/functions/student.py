"""Quantiles of Student's distribution and critical values of the studentised deviation.

Sizes up to SMALL are tabulated once per process by Newton's rule on the logarithm of the tail; beyond them the
quantile is a series in the inverse degrees of freedom around the normal one. `critical_column` gives Spark the same
values as built-in expressions: the table as one literal array, and a polynomial in log n beyond it.
"""

from __future__ import annotations

import math
from functools import lru_cache
from statistics import NormalDist

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SMALL = 1024
#: The polynomial of `critical_column` holds up to this many rows in a context.
LARGEST = 10**15
_DEGREE = 24


def _log_gamma(z: np.ndarray) -> np.ndarray:
    return np.array([math.lgamma(v) for v in z.ravel()]).reshape(z.shape)


def _beta_fraction(a: np.ndarray, b: np.ndarray, x: np.ndarray) -> np.ndarray:
    """The continued fraction of the incomplete beta function, by the modified Lentz rule, until it stands still."""
    c = np.ones_like(x)
    d = 1 / (1 - (a + b) * x / (a + 1))
    h = d.copy()
    for m in range(1, 2000):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 / (1 + num * d)
            c = 1 + num / c
            h = h * d * c
        if np.abs(d * c - 1).max(initial=0.0) < 1e-14:
            break
    return h


def log_tail(t: np.ndarray, df: np.ndarray) -> np.ndarray:
    """log P[T > t] for t > 0."""
    t, df = (np.array(v) for v in np.broadcast_arrays(np.asarray(t, np.float64), np.asarray(df, np.float64)))
    a, b = df / 2, np.full(df.shape, 0.5)
    x = df / (df + t * t)
    front = _log_gamma(a + b) - _log_gamma(a) - _log_gamma(b) + a * np.log(x) + b * np.log(t * t / (df + t * t))
    out = np.empty(t.shape)
    direct = x < (a + 1) / (a + b + 2)
    for side in (True, False):
        at = direct == side
        if not at.any():
            continue
        if side:
            out[at] = front[at] + np.log(_beta_fraction(a[at], b[at], x[at]) / a[at])
        else:
            out[at] = np.log1p(-np.exp(front[at]) * _beta_fraction(b[at], a[at], 1 - x[at]) / b[at])
    return out + math.log(0.5)


def _log_density(t: np.ndarray, df: np.ndarray) -> np.ndarray:
    return _log_gamma((df + 1) / 2) - _log_gamma(df / 2) - 0.5 * np.log(df * math.pi) - (df + 1) / 2 * np.log1p(t * t / df)


def _newton(p: np.ndarray, df: np.ndarray) -> np.ndarray:
    goal = np.log(p)
    t = np.sqrt(-2 * goal)
    for _ in range(60):
        tail = log_tail(t, df)
        step = (tail - goal) * np.exp(tail - _log_density(t, df)) / t
        t = t * np.exp(np.clip(step, -1.0, 3.0))
        if np.abs(step).max(initial=0.0) < 1e-14:
            break
    return t


def _series(p: np.ndarray, df: np.ndarray) -> np.ndarray:
    """Quantile for many degrees of freedom: the normal quantile and four corrections."""
    normal = NormalDist()
    z = np.array([-normal.inv_cdf(v) for v in p])
    z2 = z * z
    one = (z2 + 1) / 4
    two = ((5 * z2 + 16) * z2 + 3) / 96
    three = (((3 * z2 + 19) * z2 + 17) * z2 - 15) / 384
    four = ((((79 * z2 + 776) * z2 + 1482) * z2 - 1920) * z2 - 945) / 92160
    return z * (1 + (one + (two + (three + four / df) / df) / df) / df)


def upper_quantile(p: np.ndarray, df: np.ndarray) -> np.ndarray:
    """t with P[T > t] = p < 1/2."""
    p, df = (np.array(v) for v in np.broadcast_arrays(np.asarray(p, np.float64), np.asarray(df, np.float64)))
    out = np.empty(p.shape)
    few = df <= SMALL
    out[few], out[~few] = _newton(p[few], df[few]), _series(p[~few], df[~few])
    return out


def _critical(n: np.ndarray, alpha: float, sides: int) -> np.ndarray:
    n = n.astype(np.float64)
    t = upper_quantile(alpha / (sides * n), n - 2)
    return (n - 1) / np.sqrt(n) * np.sqrt(t * t / (n - 2 + t * t))


@lru_cache(maxsize=64)
def _small_table(alpha: float, sides: int) -> np.ndarray:
    """Critical values by size, infinite below three."""
    return np.concatenate([np.full(3, np.inf), _critical(np.arange(3, SMALL + 1), alpha, sides)])


def critical_values(n: np.ndarray, alpha: float = 0.05, sides: int = 2) -> np.ndarray:
    """Largest studentised deviation that a sample of each size shows by chance; infinite below three."""
    n = np.asarray(n, np.int64)
    out = _small_table(alpha, sides)[np.clip(n, 0, SMALL)]
    big = n > SMALL
    if big.any():
        sizes, at = np.unique(n[big], return_inverse=True)
        out[big] = _critical(sizes, alpha, sides)[at]
    return out


@lru_cache(maxsize=64)
def _polynomial(alpha: float, sides: int) -> tuple[float, ...]:
    """Coefficients of the critical value in v, log n scaled to [-1, 1]; the least-squares fit at Chebyshev points."""
    v = np.cos(np.pi * (np.arange(400) + 0.5) / 400)
    lo, hi = math.log(SMALL), math.log(LARGEST)
    n = np.exp(lo + (v + 1) / 2 * (hi - lo))
    t = upper_quantile(alpha / (sides * n), n - 2)
    crit = (n - 1) / np.sqrt(n) * np.sqrt(t * t / (n - 2 + t * t))
    return tuple(np.polynomial.chebyshev.cheb2poly(np.polynomial.chebyshev.chebfit(v, crit, _DEGREE)).tolist())


def critical_column(n: Column, alpha: float = 0.05, sides: int = 2) -> Column:
    """The critical value of a size as built-in expressions; within 1e-9 of critical_values, null below three."""
    lo, hi = math.log(SMALL), math.log(LARGEST)
    v = (F.log(n.cast("double")) - F.lit(lo)) * F.lit(2 / (hi - lo)) - F.lit(1.0)
    powers = _polynomial(alpha, sides)
    # Horner's rule as a fold over a literal array: the scaled logarithm is computed once
    folded = F.aggregate(F.lit(list(reversed(powers[:-1]))), F.lit(powers[-1]), lambda acc, c: acc * v + c)
    table = F.lit(_small_table(alpha, sides)[3:].tolist())
    return F.when(n < 3, F.lit(None).cast("double")).when(n <= SMALL, F.try_element_at(table, (n - 2).cast("int"))).otherwise(folded)
