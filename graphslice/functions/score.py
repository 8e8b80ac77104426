"""Block scores: gain from placed neighbours against a penalty for size, and the bonus of the previous block."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class PowerPenalty:
    """gain - alpha * gamma * size ** (gamma - 1) with alpha = m * k ** (gamma - 1) / n ** gamma."""

    gamma: float = 1.5
    ties_by_load = False

    def alpha(self, n: float, m: float, k: int) -> float:
        if not n:
            return 0.0
        if self.gamma == 1.5:
            return m * math.sqrt(k) / (n * math.sqrt(n))
        if self.gamma == 2:
            return m * k / (n * n)
        return m * k ** (self.gamma - 1) / n**self.gamma

    def scorer(self, n: float, m: float, k: int):
        a = self.alpha(n, m, k)
        if self.gamma == 1.5:
            f, root = a * 1.5, math.sqrt
            return lambda gain, size: gain - f * root(size)
        if self.gamma == 2:
            f = a * 2
            return lambda gain, size: gain - f * size
        f, p = a * self.gamma, self.gamma - 1
        return lambda gain, size: gain - f * size**p

    def many(self, n: float, m: float, k: int):
        """`scorer` on arrays, bit for bit the same, where larger sizes always score lower; None where that is not sure."""
        a = self.alpha(n, m, k)
        if not a > 0 or self.gamma not in (1.5, 2):
            return None
        if self.gamma == 2:
            return self.scorer(n, m, k)
        f = a * 1.5
        return lambda gain, size: gain - f * np.sqrt(size)

    def column(self, gain: Column, size: Column, n: float, m: float, k: int) -> Column:
        a = self.alpha(n, m, k)
        if self.gamma == 1.5:
            return gain - F.lit(a * 1.5) * F.sqrt(size)
        return gain - F.lit(a * self.gamma) * (size if self.gamma == 2 else F.pow(size, F.lit(self.gamma - 1)))


@dataclass(frozen=True)
class LinearPenalty:
    """gain * (1 - size / (n / k)); equal scores go to the least loaded block."""

    ties_by_load = True

    def scorer(self, n: float, m: float, k: int):
        share = n / k if n else 1.0
        return lambda gain, size: gain * (1 - size / share)

    def many(self, n: float, m: float, k: int):
        return None

    def column(self, gain: Column, size: Column, n: float, m: float, k: int) -> Column:
        return gain * (F.lit(1) - size / F.lit(n / k if n else 1.0))


def sticky(score: Column, block: Column, previous: Column, kappa: float) -> Column:
    """The previous block's score times kappa if positive, divided by it if negative."""
    return F.when(block == previous, F.when(score > 0, score * F.lit(kappa)).when(score < 0, score / F.lit(kappa)).otherwise(score)).otherwise(score)


def limit(n: float, k: int, eps: float = 0.03) -> int:
    """Largest allowed block weight. Percent arithmetic in whole numbers where eps and n are whole."""
    percent = round(eps * 100)
    if abs(eps * 100 - percent) < 1e-12 and float(n).is_integer():
        return -(-(100 + percent) * int(n) // (100 * k))
    return math.ceil((1 + eps) * n / k)


__all__ = ["LinearPenalty", "PowerPenalty", "limit", "sticky"]
