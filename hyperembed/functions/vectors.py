"""Column expressions on arrays and the repeatable hash of the package; no Python runs on rows."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, functions as F

#: Modulus of the hash; every product below stays under 2 ** 63, so SQL engines with 64-bit integers agree on it.
PRIME = 2147483647


def mix(a, b, seed: int) -> Column:
    """Hash of two integers: affine step, square, affine step with the next seed."""
    a, b = (F.pmod(x if isinstance(x, Column) else F.lit(x), F.lit(PRIME)).cast("long") for x in (a, b))

    def affine(t, k):
        return F.pmod(t * 48271 + b * 69621 + F.lit(k * 16807 + 12345), F.lit(PRIME))

    t = affine(a, seed)
    return affine(F.pmod(t * t + 12345, F.lit(PRIME)), seed + 1)


def mix_numbers(a: np.ndarray, b: int, seed: int) -> np.ndarray:
    """The same hash of arrays of 64-bit integers."""
    a, b = np.mod(np.asarray(a, np.int64), PRIME), b % PRIME
    affine = lambda t, k: (t * 48271 + b * 69621 + k * 16807 + 12345) % PRIME
    t = affine(a, seed)
    return affine((t * t + 12345) % PRIME, seed + 1)


def mix_sql(a: str, b: str, seed: int) -> str:
    """The same hash as SQL text."""
    t = f"(((({a}) % {PRIME}) * 48271 + (({b}) % {PRIME}) * 69621 + {seed * 16807 + 12345}) % {PRIME})"
    u = f"(({t} * {t} + 12345) % {PRIME})"
    return f"(({u} * 48271 + (({b}) % {PRIME}) * 69621 + {(seed + 1) * 16807 + 12345}) % {PRIME})"


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Cosine; 0 if a vector is zero."""
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n).otherwise(F.lit(0.0))


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def tlog(x: Column) -> Column:
    """Truncated logarithm: ln(max(x, 1))."""
    return F.log(F.greatest(x, F.lit(1.0)))


def register(spark) -> None:
    """SQL functions of the package."""
    for name, text in {
        "tlog": "(x DOUBLE) RETURNS DOUBLE RETURN ln(greatest(x, 1D))",
        "vec_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    }.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{text}")
