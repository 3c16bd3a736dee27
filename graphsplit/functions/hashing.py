"""A hash that Spark, NumPy and SQL engines compute alike, wherever a method asks for randomness."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 2147483647


def _steps(x, seed):
    a = (x % PRIME * 48271 + (seed * 69621 + 11)) % PRIME
    b = (a * a + a * 16807 + 12345) % PRIME
    return (b * b + b * 69621 + 7) % PRIME


def mix(x, seed: int = 0):
    """For a Column, an int or an int64 array of non-negative numbers; below 2 ** 31."""
    if isinstance(x, str):
        x = F.col(x)
    if isinstance(x, Column):
        return _steps(x.cast("long"), F.lit(seed).cast("long"))
    return _steps(np.asarray(x, dtype=np.int64) if isinstance(x, np.ndarray) else int(x), int(seed))


def mix_sql(x: str, seed: int = 0) -> str:
    """The same as a SQL expression; every product stays below 2 ** 63."""
    p = PRIME
    a = f"(((({x}) % {p}) * 48271 + {seed * 69621 + 11}) % {p})"
    b = f"(({a} * {a} + 16807 * {a} + 12345) % {p})"
    return f"(({b} * {b} + 69621 * {b} + 7) % {p})"
