"""A hash of ids in whole-number arithmetic that SQL engines share."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

PRIME = 2147483647


def hashed(i, seed: int):
    """A 31-bit hash of a column: a product modulo a prime, then two rounds in which the value multiplies its own upper bits."""
    p = F.lit(PRIME)
    x = F.pmod(F.pmod(i.cast("long"), p) * 48271 + F.lit(seed % 1_000_003) * 69621, p)
    x = F.pmod(x * (F.shiftright(x, 8) + 16807), p)
    return F.pmod(x * (F.shiftright(x, 11) + 39373) + 7, p)


def hashed_numpy(i: np.ndarray, seed: int) -> np.ndarray:
    x = (i % PRIME * 48271 + seed % 1_000_003 * 69621) % PRIME
    x = x * ((x >> 8) + 16807) % PRIME
    return (x * ((x >> 11) + 39373) + 7) % PRIME


def hashed_sql(i: str, seed: int) -> str:
    first = f"SELECT (({i}) % {PRIME} * 48271 + {seed % 1_000_003} * 69621) % {PRIME} AS x"
    return f"(SELECT (x * ((x >> 11) + 39373) + 7) % {PRIME} FROM (SELECT x * ((x >> 8) + 16807) % {PRIME} AS x FROM ({first})))"
