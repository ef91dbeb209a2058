"""Relevance of a pattern from its counts: a positive and b negative rows of P positive and N negative ones.

Every measure rises in a and falls in b where the pattern is positively associated. Its bound is its
value with no negative row left, which no extension exceeds, as an extension covers a subset; the
floor of a score is the least positive support whose bound reaches it.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def _fscore(a, b, p, n, ln):
    return 2.0 * a / (p + a + b)


def _chi2(a, b, p, n, ln):
    """Phi squared: chi squared over the number of rows."""
    rows, covered = p + n, a + b
    spread = 1.0 * covered * (rows - covered) * p * n
    return (1.0 * a * n - 1.0 * b * p) * (1.0 * a * n - 1.0 * b * p) / ln.where(spread > 0, spread, 1.0) * ln.where(spread > 0, 1.0, 0.0)


def _plogp(x, ln):
    return ln.where(x > 0, x * ln.log2(ln.where(x > 0, x, 1.0)), 0.0)


def _infogain(a, b, p, n, ln):
    """Entropy of the class less its entropy given whether the pattern covers."""
    rows, covered = p + n, a + b
    rest = rows - covered

    def part(x, size):
        return _plogp(1.0 * x / ln.where(size > 0, size, 1), ln)

    whole = -part(p, rows) - part(n, rows)
    inside = -(part(a, covered) + part(b, covered)) * covered / rows
    outside = -(part(p - a, rest) + part(n - b, rest)) * rest / rows
    return whole - inside - outside


def _suppdiff(a, b, p, n, ln):
    return 1.0 * a / ln.where(p > 0, p, 1) - 1.0 * b / ln.where(n > 0, n, 1)


def _confidence(a, b, p, n, ln):
    covered = a + b
    return 1.0 * a / ln.where(covered > 0, covered, 1)


def _recall(a, b, p, n, ln):
    return 1.0 * a / p


class _Numbers:
    log2 = staticmethod(np.log2)

    @staticmethod
    def where(test, yes, no):
        return np.where(test, yes, no)


class _Columns:
    log2 = staticmethod(F.log2)

    @staticmethod
    def where(test, yes, no):
        lit = lambda x: x if isinstance(x, Column) else F.lit(x)
        if isinstance(test, (bool, np.bool_)):
            return lit(yes if test else no)
        return F.when(test, lit(yes)).otherwise(lit(no))


@dataclass(frozen=True)
class Measure:
    """strict: the bound rises strictly in a, so a pattern without negative rows can't be bettered by a smaller cover."""

    name: str
    formula: Callable
    strict: bool = True
    inverse: Callable | None = None

    def floor_column(self, score: Column) -> Column:
        """The floor as a column, where it has a closed form."""
        if self.inverse is None:
            raise ValueError(f"{self.name} has no closed form of its floor")
        return self.inverse(score)

    def column(self, a: Column, b: Column, p, n) -> Column:
        return self.formula(a, b, p, n, _Columns)

    def values(self, a, b, p: int, n: int) -> np.ndarray:
        return np.asarray(self.formula(np.asarray(a, np.float64), np.asarray(b, np.float64), float(p), float(n), _Numbers), np.float64)

    def bound(self, a: Column, p, n) -> Column:
        return self.formula(a, F.lit(0), p, n, _Columns)

    def bounds(self, a, p: int, n: int) -> np.ndarray:
        """The bound for positive supports."""
        return self.values(a, np.zeros(np.shape(a)), p, n)

    def floor(self, score: float, p: int, n: int) -> float:
        """Least share of positive rows whose bound reaches the score; by bisection where there is no closed form."""
        if score <= 0:
            return 0.0
        q = p / (p + n)
        if self.inverse is not None:
            return self.inverse(score)
        if self.name == "chi2":
            return score / (1 - q + q * score)
        if self.name in ("suppdiff", "recall"):
            return score
        if self.name == "confidence":
            return 0.0
        low, high = 0.0, 1.0
        for _ in range(100):
            middle = (low + high) / 2
            low, high = (low, middle) if float(self.values(middle * p, 0, p, n)) >= score else (middle, high)
        return high


def _fscore_floor(score: Column) -> Column:
    return score / (2 - score)


FSCORE = Measure("fscore", _fscore, inverse=_fscore_floor)
CHI2 = Measure("chi2", _chi2)
INFOGAIN = Measure("infogain", _infogain)
SUPPDIFF = Measure("suppdiff", _suppdiff)
CONFIDENCE = Measure("confidence", _confidence, strict=False)
RECALL = Measure("recall", _recall)
MEASURES: dict[str, Measure] = {m.name: m for m in (FSCORE, CHI2, INFOGAIN, SUPPDIFF, CONFIDENCE, RECALL)}
#: The Dice coefficient is the F-score.
MEASURES["dice"] = FSCORE


def register(measure: Measure) -> None:
    """Adds a measure of one's own, if it rises and falls as searches need."""
    if not dual_monotone(measure):
        raise ValueError(f"{measure.name} isn't dual monotone")
    MEASURES[measure.name] = measure


def dual_monotone(measure: Measure, p: int = 12, n: int = 17) -> bool:
    """Whether it rises in a and falls in b over the whole grid where a / p >= b / n."""
    tiny = 1e-12
    for a in range(p + 1):
        for b in range(n + 1):
            if a * n < b * p:
                continue
            here = float(measure.values(a, b, p, n))
            if a < p and float(measure.values(a + 1, b, p, n)) < here - tiny:
                return False
            if b < n and a * n >= (b + 1) * p and float(measure.values(a, b + 1, p, n)) > here + tiny:
                return False
    return True


def associated(a, b, p, n):
    """Positive support at least as large as negative support, in whole numbers."""
    return a * n >= b * p


def corner_bound(measure: Measure, a: int, b: int, p: int, n: int) -> float:
    """Bound for convex measures: the larger of the values with one of the two counts at zero."""
    return max(float(measure.values(a, 0, p, n)), float(measure.values(0, b, p, n)))


def harmonic(confidence: float, support: float) -> float:
    return 0.0 if not confidence + support else 2 * confidence * support / (confidence + support)


