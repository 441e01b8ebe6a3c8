"""Similarity rules with exact rational thresholds.

A rule depends on the overlap and the two sizes only; ``holds`` is an integer test, so no threshold is
ever rounded. The same test exists on ints and on Columns.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

KINDS = ("jaccard", "dice", "cosine", "overlap", "contain", "hamming")


@dataclass(frozen=True)
class SimilarityRule:
    kind: str
    num: int
    den: int

    @classmethod
    def of(cls, kind: str, theta: str | Fraction | int) -> SimilarityRule:
        if kind not in KINDS:
            raise ValueError(f"unknown rule {kind}")
        t = Fraction(theta)
        return cls(kind, t.numerator, t.denominator)

    @classmethod
    def jaccard(cls, theta: str | Fraction) -> SimilarityRule:
        return cls.of("jaccard", theta)

    @property
    def symmetric(self) -> bool:
        return self.kind != "contain"

    def _test(self, o, x, y, least):
        """>= 0 where similar; works on ints, arrays of ints and Columns. ``hamming``: theta is the greatest symmetric difference."""
        n, d = self.num, self.den
        return {
            "jaccard": lambda: o * (d + n) - (x + y) * n,
            "dice": lambda: o * 2 * d - (x + y) * n,
            "cosine": lambda: o * o * d * d - x * y * n * n,
            "overlap": lambda: o * d - least(x, y) * n,
            "contain": lambda: o * d - x * n,
            "hamming": lambda: o * 2 * d + n - (x + y) * d,
        }[self.kind]()

    def holds(self, overlap: int, x: int, y: int) -> bool:
        return self._test(overlap, x, y, min) >= 0

    def holds_each(self, overlap: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return self._test(overlap, x, y, np.minimum) >= 0

    def holds_col(self, overlap: Column, x: Column, y: Column) -> Column:
        o, x, y = (c.cast("bigint") for c in (overlap, x, y))
        return self._test(o, x, y, F.least) >= 0

    def score_col(self, overlap: Column, x: Column, y: Column) -> Column:
        o, x, y = (c.cast("double") for c in (overlap, x, y))
        return {
            "jaccard": lambda: o / (x + y - o),
            "dice": lambda: 2 * o / (x + y),
            "cosine": lambda: o / F.sqrt(x * y),
            "overlap": lambda: o / F.least(x, y),
            "contain": lambda: o / x,
            "hamming": lambda: x + y - 2 * o,
        }[self.kind]()

    def required_overlap(self, x: int, y: int) -> int | None:
        """Least overlap of at least one element at which sizes x and y are similar."""
        return next((i for i in range(1, min(x, y) + 1) if self.holds(i, x, y)), None)

    def is_monotone(self, sizes: tuple[int, ...]) -> bool:
        """Whether more overlap never ends similarity; keys are exact only then."""
        for x in sizes:
            for y in sizes:
                state = [self.holds(i, x, y) for i in range(1, min(x, y) + 1)]
                if state != sorted(state):
                    return False
        return True
