"""Fractional edge covers and bounds of the join size."""

from __future__ import annotations

import math
from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Scopes = dict[str, tuple[str, ...]]


def _cover(scopes: Scopes, cost: dict[str, Fraction]) -> tuple[Fraction, dict[str, Fraction]]:
    """Cheapest cover, from the packing that is its dual: one row a table, one column a variable, pivots by least index."""
    names, variables = list(scopes), sorted({v for s in scopes.values() for v in s})
    m, n = len(names), len(variables)
    rows = [[Fraction(v in scopes[t]) for v in variables] + [Fraction(i == j) for j in range(m)] + [cost[t]] for i, t in enumerate(names)]
    gain = [Fraction(-1)] * n + [Fraction(0)] * (m + 1)
    basis = list(range(n, n + m))
    while (enter := next((j for j in range(n + m) if gain[j] < 0), None)) is not None:
        options = [(rows[i][-1] / rows[i][enter], basis[i], i) for i in range(m) if rows[i][enter] > 0]
        i = min(options)[2]
        rows[i] = [x / rows[i][enter] for x in rows[i]]
        for k in range(m):
            if k != i and rows[k][enter]:
                rows[k] = [x - rows[k][enter] * y for x, y in zip(rows[k], rows[i], strict=True)]
        gain = [x - gain[enter] * y for x, y in zip(gain, rows[i], strict=True)]
        basis[i] = enter
    return gain[-1], {t: gain[n + i] for i, t in enumerate(names)}


def fractional_edge_cover(scopes: Scopes) -> tuple[Fraction, dict[str, Fraction]]:
    """Least total weight of tables such that every variable is covered by 1 or more; exact."""
    return _cover(scopes, dict.fromkeys(scopes, Fraction(1)))


def weighted_cover(scopes: Scopes, sizes: dict[str, int]) -> dict[str, Fraction]:
    """The cover of least sum of weight times log size."""
    return _cover(scopes, {t: Fraction(math.log(max(2, sizes[t]))).limit_denominator(10**6) for t in scopes})[1]


def agm_bound(sizes: dict[str, int], weights: dict[str, Fraction]) -> float:
    """Product of size to the power of its weight: bounds the number of distinct result tuples."""
    return math.exp(sum(float(w) * math.log(sizes[t]) for t, w in weights.items() if sizes[t] > 0)) if all(sizes[t] for t in weights) else 0.0


def bag_bound(potentials: dict[str, DataFrame], weights: dict[str, Fraction]) -> float:
    """The bound for bags, by Hoelder's inequality: product of (sum of n^(1/w))^w; weight 0 takes the largest n."""
    bound = 1.0
    for t, w in weights.items():
        power = F.max("n").cast("double") if w == 0 else F.sum(F.pow("n", F.lit(float(1 / w))))
        total = potentials[t].agg(power).first()[0] or 0.0
        bound *= total if w == 0 else total ** float(w)
    return bound
