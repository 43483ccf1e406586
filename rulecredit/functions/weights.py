"""Coalition weights and low-discrepancy points."""

from __future__ import annotations

from math import comb

from pyspark.sql import Column
from pyspark.sql import functions as F


def shapley_weights(n: int, top: int) -> list[float]:
    """k!(n-k-1)!/n! for k = 0..top (at most n - 1), exact before the final division."""
    return [1.0 / (n * comb(n - 1, k)) for k in range(min(top, n - 1) + 1)] if n else []


def kernel_weights(n: int, top: int) -> list[float]:
    """(n-1)/(C(n,s) s (n-s)) for s = 0..top; the infinite ends are 0 here and handled apart."""
    return [(n - 1) / (comb(n, s) * s * (n - s)) if 0 < s < n else 0.0 for s in range(top + 1)]


def lookup(values: list[float], at: Column) -> Column:
    """values[at], 0 beyond the list."""
    if not values:
        return F.lit(0.0)
    return F.coalesce(F.get(F.array(*[F.lit(float(v)) for v in values]), at), F.lit(0.0))


def uniform(*parts: Column | int | str) -> Column:
    """A repeatable number in [0, 1) from a 53-bit hash of the parts."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.pmod(F.shiftrightunsigned(F.xxhash64(*cols), 11), F.lit(1 << 53)) / F.lit(float(1 << 53))


BITS = 24
#: Degree, inner coefficients and first direction numbers of the primitive polynomials
#: over GF(2) that the usual Sobol tables take for dimensions 2, 3, ...; dimension 1 needs none.
POLYNOMIALS = (
    (1, 0, (1,)),
    (2, 1, (1, 3)),
    (3, 1, (1, 3, 1)),
    (3, 2, (1, 1, 1)),
    (4, 1, (1, 1, 3, 3)),
    (4, 4, (1, 3, 5, 13)),
    (5, 2, (1, 1, 5, 5, 17)),
    (5, 4, (1, 1, 5, 5, 5)),
    (5, 7, (1, 1, 7, 11, 19)),
    (5, 11, (1, 1, 5, 1, 1)),
    (5, 13, (1, 1, 1, 3, 11)),
    (5, 14, (1, 3, 5, 5, 31)),
    (6, 1, (1, 3, 3, 9, 7, 49)),
    (6, 13, (1, 1, 1, 15, 21, 21)),
    (6, 16, (1, 3, 1, 13, 27, 49)),
)
DIMENSIONS = len(POLYNOMIALS) + 1


def directions(dimension: int) -> list[int]:
    """Direction numbers of one dimension, as BITS-bit integers."""
    if dimension == 0:
        return [1 << (BITS - 1 - b) for b in range(BITS)]
    degree, inner, m = POLYNOMIALS[dimension - 1]
    v = [x << (BITS - 1 - b) for b, x in enumerate(m)]
    for b in range(degree, BITS):
        x = v[b - degree] ^ (v[b - degree] >> degree)
        for j in range(1, degree):
            if inner >> (degree - 1 - j) & 1:
                x ^= v[b - j]
        v.append(x)
    return v


def sobol_point(i: Column, dimension: int, shift: Column) -> Column:
    """Coordinate (from 0, below DIMENSIONS) of the i-th Sobol point, shifted modulo 1; i up to 2 ** BITS."""
    picked = F.transform(F.array(*[F.lit(d) for d in directions(dimension)]), lambda d, b: F.when(F.getbit(i.cast("long"), b) == 1, d).otherwise(F.lit(0)))
    x = F.aggregate(picked, F.lit(0), lambda acc, d: acc.bitwiseXOR(d))
    moved = x / F.lit(float(1 << BITS)) + shift
    return moved - F.floor(moved)
