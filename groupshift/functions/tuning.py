"""Tuning values, as Python numbers and as expressions for DataFrames and SQL."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Multipliers of the theoretical level in the sweep: seven, evenly spaced in logarithm from 0.1 to 3.
GRID = tuple(0.1 * 30 ** (i / 6) for i in range(7))


def lambda_theory(n: int, groups: int, least_size: int, sigma: float = 1.0) -> float:
    return sigma * (1 + math.sqrt(4 * math.log(groups * n) / least_size))


def lambda_practical(n: int, groups: int, least_size: int, sigma: float = 1.0) -> float:
    return lambda_theory(n, groups, least_size, sigma) / 2


def lambda_tail(delta: float, least_size: int, sigma: float = 1.0) -> float:
    return sigma * (1 + math.sqrt(2 * math.log(1 / delta) / least_size))


def lambda_univariate(n: int, sigma: float = 1.0) -> float:
    return sigma * (1 + math.sqrt(4 * math.log(n)))


def lambda_sparse(p: int, n: int) -> float:
    """The level of the competitor without groups."""
    return math.sqrt(math.log(p * math.log(n)) / 2)


def lambda_grid(n: int, groups: int, least_size: int, sigma: float = 1.0) -> list[float]:
    return [m * lambda_theory(n, groups, least_size, sigma) for m in GRID]


def theory_column(n: Column, groups: Column, least_size: Column, sigma: Column | None = None) -> Column:
    return (F.lit(1.0) if sigma is None else sigma) * (1 + F.sqrt(4 * F.log(groups * n) / least_size))
