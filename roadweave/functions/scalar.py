"""Column expressions and driver scalars of the measures."""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, functions as F


def log_factorial(n: Column) -> Column:
    """ln n!: exact up to 20, then Stirling's series, which is good to 1e-11 there."""
    x = n.cast("double")
    series = x * F.ln(x) - x + 0.5 * F.ln(2 * math.pi * x) + 1 / (12 * x) - 1 / (360 * x * x * x) + 1 / (1260 * x * x * x * x * x)
    return F.when(n < 2, F.lit(0.0)).when(n <= 20, F.ln(F.factorial(n.cast("int")))).otherwise(series)


def log_choose(n: Column, k: Column) -> Column:
    """ln of the binomial coefficient."""
    return log_factorial(n) - log_factorial(k) - log_factorial(n - k)


def idf(total: Column, having: Column) -> Column:
    """ln(total / having): 0 for what all have."""
    return F.ln(total / having)


#: Largest set whose numbers of partitions are computed by recurrence.
EXACT_PARTITIONS = 4096


@lru_cache(maxsize=256)
def log_partitions(n: int, k: int) -> float:
    """ln of the number of ways to part n things into at most k classes."""
    if n == 0 or k == 0:
        return 0.0
    k = min(k, n)
    if n > EXACT_PARTITIONS:
        # Leading terms i**n / i! of the classes' Stirling numbers.
        terms = np.array([n * math.log(i) - math.lgamma(i + 1) for i in range(max(1, k - 64), k + 1)])
        return float(np.logaddexp.reduce(terms))
    return float(np.logaddexp.reduce(_stirling_row(n)[1 : k + 1]))


@lru_cache(maxsize=64)
def _stirling_row(n: int) -> np.ndarray:
    """ln of the Stirling numbers of the second kind, for 0 to n classes."""
    row = np.full(n + 1, -np.inf)
    row[0] = 0.0
    with np.errstate(divide="ignore"):
        classes = np.log(np.arange(n + 1))
    for i in range(1, n + 1):
        new = np.full(n + 1, -np.inf)
        new[1 : i + 1] = np.logaddexp(row[:i], classes[1 : i + 1] + row[1 : i + 1])
        row = new
    return row


def haversine_km(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """Great-circle distance on a sphere of 6371 km."""
    half = lambda a, b: F.pow(F.sin(F.radians(b - a) / 2), F.lit(2))
    h = half(lat1, lat2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * half(lon1, lon2)
    return 2 * 6371.0 * F.asin(F.sqrt(h))
