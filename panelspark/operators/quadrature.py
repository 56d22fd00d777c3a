"""Quadrature rules on pairs of reference triangles, one for each number of common vertices.

All rules map the unit four-cube. Without a common vertex each triangle is collapsed from a square. With common vertices the
domain is cut into pieces where the singular factor cancels against the Jacobian; the pieces are written with
variables (x, a, b, c). Points are (s, t) and (u, v) with 0 <= t <= s <= 1; every rule's weights sum to 1/4.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession

SCHEMA = "case int, q int, s double, t double, u double, v double, w double"


def gauss(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Gauss-Legendre points and weights on the unit interval."""
    x, w = np.polynomial.legendre.leggauss(n)
    return (x + 1) / 2, w / 2


def _swap(p):
    return (p[2], p[3], p[0], p[1])


def pieces(case: int, x, a, b, c):
    """The points and Jacobians of all pieces of a case; works on numbers, arrays and anything with arithmetic."""
    if case == 0:  # here the four variables are those of two squares
        return [((x, x * a, b, b * c), x * b)]
    if case == 1:
        p = (x, x * a, x * b, x * b * c)
        return [(p, x**3 * b), (_swap(p), x**3 * b)]
    if case == 2:
        j = x**3 * a**2
        return [
            ((x, x * a * c, x * (1 - a * b), x * a * (1 - b)), j),
            ((x, x * a, x * (1 - a * b * c), x * a * b * (1 - c)), j * b),
            ((x * (1 - a * b), x * a * (1 - b), x, x * a * b * c), j * b),
            ((x * (1 - a * b * c), x * a * b * (1 - c), x, x * a), j * b),
            ((x * (1 - a * b * c), x * a * (1 - b * c), x, x * a * b), j * b),
        ]
    j = x**3 * a**2 * b
    half = [
        (x, x * (1 - a + a * b), x * (1 - a * b * c), x * (1 - a)),
        (x, x * a * (1 - b + b * c), x * (1 - a * b), x * a * (1 - b)),
        (x * (1 - a * b * c), x * a * (1 - b * c), x, x * a * (1 - b)),
    ]
    return [(q, j) for p in half for q in (p, _swap(p))]


@lru_cache(maxsize=32)
def rule(case: int, n: int) -> np.ndarray:
    """Rows (s, t, u, v, w)."""
    g, w = gauss(n)
    x, a, b, c = (m.ravel() for m in np.meshgrid(g, g, g, g, indexing="ij"))
    weight = np.prod([m.ravel() for m in np.meshgrid(w, w, w, w, indexing="ij")], axis=0)
    rows = [np.stack([np.broadcast_to(q, x.shape) for q in p] + [weight * j], 1) for p, j in pieces(case, x, a, b, c)]
    return np.concatenate(rows)


def rule_frame(spark: SparkSession, quad, cases=(0, 1, 2, 3)) -> DataFrame:
    """The rules as a small table; its size is fixed by the orders (under 20 000 rows), so it may be broadcast."""
    rows = [(case, q, *map(float, r)) for case in cases for q, r in enumerate(rule(case, quad.points(case)))]
    return spark.createDataFrame(rows, SCHEMA)


def triangle_rule(n: int) -> np.ndarray:
    """Rows (s, t, w) on one reference triangle; the weights sum to 1/2."""
    g, w = gauss(n)
    return np.array([(x, x * y, p * q * x) for x, p in zip(g, w, strict=True) for y, q in zip(g, w, strict=True)])
