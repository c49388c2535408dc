"""A portable hash order: the same integers in Spark, NumPy, Python and SQL, for every sampling choice."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: A prime below 2^31 and a multiplier of its full period.
PRIME, MULT = 2147483647, 48271
ROUNDS = 3


def mix(*parts: Column | int) -> Column:
    """Fold of the parts, smaller than PRIME; products stay below 2^62, so plain bigint arithmetic is exact."""
    h: Column = F.lit(1).cast("long")
    for p in parts:
        x = F.lit(p).cast("long") if isinstance(p, int) else p.cast("long")
        h = F.pmod(h * MULT + F.pmod(x, F.lit(PRIME)) + 1, F.lit(PRIME))
    for _ in range(ROUNDS):
        h = F.pmod(h * MULT + 1, F.lit(PRIME))
    return h


def mix_np(*parts) -> np.ndarray:
    h = np.int64(1)
    for p in parts:
        h = (h * MULT + np.asarray(p, np.int64) % PRIME + 1) % PRIME
    for _ in range(ROUNDS):
        h = (h * MULT + 1) % PRIME
    return h


def mix_sql(*parts: str) -> str:
    """The same as a DuckDB expression."""
    h = "cast(1 as bigint)"
    for p in parts:
        h = f"(({h} * {MULT} + (cast({p} as bigint) % {PRIME} + {PRIME}) % {PRIME} + 1) % {PRIME})"
    for _ in range(ROUNDS):
        h = f"(({h} * {MULT} + 1) % {PRIME})"
    return h
