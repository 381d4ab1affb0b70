"""Column expressions of the constraints and the weight, and the closed-form bounds."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from alignspark.params import AlignParams

#: Weights are compared as integers of this many parts of one.
SCALE = 1_000_000_000


def theta_spread(t: Column) -> Column:
    """Largest difference of the non-missing timestamps of an array; 0 where fewer than two are present."""
    return F.coalesce(F.array_max(t) - F.array_min(t), F.lit(0)).cast("long")


def phi_spread(x: Column) -> Column:
    """Largest difference of the row numbers of a tuple; missing cells keep theirs."""
    return (F.array_max(x) - F.array_min(x)).cast("long")


def conflicts(a: Column, b: Column) -> Column:
    """Whether two tuples share a cell."""
    return F.exists(F.zip_with(a, b, lambda p, q: p == q), lambda same: same)


def pairs_complete(lam: Column) -> Column:
    return (lam * (lam - 1) / 2).cast("long")


def pairwise_distance(x: Column, m: int) -> Column:
    """Sum of row differences over all pairs: with sorted rows each counts (2k - m - 1) times."""
    ranked = F.transform(F.array_sort(x), lambda v, k: v * (2 * k - (m - 1)))
    return F.aggregate(ranked, F.lit(0).cast("long"), lambda acc, v: acc + v)


def weight(lam: Column, d: Column, p: AlignParams) -> Column:
    return (F.lit(p.k1) * lam * (lam - 1) / 2 + F.lit(p.b)) / (F.lit(p.k2) * d + F.lit(p.c))


def fixed(w: Column) -> Column:
    return F.round(w * F.lit(float(SCALE))).cast("long")


def weight_bounds(m: int, p: AlignParams) -> tuple[float, float]:
    """Largest and smallest weight a tuple of m cells can have under the position constraint."""
    top = (p.k1 * m * (m - 1) / 2 + p.b) / p.c
    return top, p.b / (p.k2 * p.beta * (m // 2) * ((m + 1) // 2) + p.c)


def candidate_count_bound(n: int, m: int, beta: int) -> int:
    """Number of index vectors of spread <= beta over n rows: the candidates when theta doesn't bind."""
    if n <= 0:
        return 0
    if n <= beta:
        return n**m
    return (n - beta) * ((beta + 1) ** m - beta**m) + beta**m


def bound_packing(m: int) -> float:
    return 3 / (2 * (m + 1))


def bound_greedy(n: int, m: int, w_max: float, w_min: float) -> float:
    return math.ceil(n / m) * w_min / (n * w_max)


def bound_expectation(n: int, m: int, w_max: float, w_min: float) -> float:
    k = math.ceil(n / m)
    return min((k + 1) * w_min / (n * w_max), k * w_min / ((n - 1) * w_max + w_min))


def operation_bounds(n: int, m: int, beta: int) -> dict[str, float]:
    """The worst-case counts that the analysis gives, to set beside measured counters."""
    rc, g = n * (beta + 1) ** m, (4 * beta + 1) ** m
    log = math.log2(4 * beta + 1)
    return {
        "candidates": n * m * (beta + 1) ** m, "weights": rc * m * m, "greedy": rc * m * g + rc * m * log,
        "expectation": 2 * rc * m * g + rc * m * log,
    }
