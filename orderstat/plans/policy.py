"""Parameters and the choice between sorting and partitioning."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from enum import Enum
from fractions import Fraction


class Branch(str, Enum):
    SORT = "sort"
    PARTITION = "partition"


@dataclass(frozen=True)
class TallCache:
    """Memory of M elements in blocks of B with M >= B^(1 + eps); d is the exponent that a k-way distribution needs."""

    eps: Fraction = Fraction(1)

    @staticmethod
    def of(eps: float | str | Fraction) -> TallCache:
        return TallCache(Fraction(str(eps)) if isinstance(eps, float) else Fraction(eps))

    @property
    def d(self) -> Fraction:
        return max(1 + 2 / self.eps, Fraction(2))

    def sorts_by_fanout(self, n: int, delta: int) -> bool:
        """Whether (2 n)^d >= delta^(d + 1), in whole numbers: both sides to the power of d's denominator."""
        d = self.d
        return _power_at_least(2 * n, d, delta, d + 1)

    def sorts_by_blocks(self, n: int, delta: int) -> bool:
        """Whether n^(1 + 1 / (1 + eps)) >= delta^2."""
        return _power_at_least(n, 1 + 1 / (1 + self.eps), delta, Fraction(2))

    def threshold(self, n: int) -> int:
        """Largest gap threshold at which n elements are sorted."""
        return int((2 * n) ** (self.d / (self.d + 1))) if n else 0


def _power_at_least(a: int, p: Fraction, b: int, q: Fraction) -> bool:
    if a <= 0 or b <= 0:
        return a > 0 or b <= 0
    left, right = float(p) * math.log2(a), float(q) * math.log2(b)
    if abs(left - right) > 1e-6 * max(1.0, abs(left)):
        return left > right
    common = math.lcm(p.denominator, q.denominator)
    return a ** int(p * common) >= b ** int(q * common)


def choose_branch(n: int, delta: int, tall: TallCache = TallCache()) -> Branch:
    return Branch.SORT if tall.sorts_by_fanout(n, delta) or tall.sorts_by_blocks(n, delta) else Branch.PARTITION


@dataclass(frozen=True)
class Settings:
    """How the engine works. None of it changes an answer.

    finish_rows: a subproblem of at most so many rows is ordered by one task. accuracy: rank error of a summary is at most
    n / accuracy. min_fanout: pivots asked for at least, where pivots="summary". max_pivots bounds what is broadcast for a subproblem,
max_total_pivots what is for all subproblems of a level. collapse: True selects on the histogram of distinct values, False never does,
"auto" does where a sketch counts at most collapse_values of them.
    listed_ranks: rank lists up to this length are held on the driver, longer ones stay DataFrames.
    """

    tall: TallCache = field(default_factory=TallCache)
    branch: str = "auto"
    pivots: str = "auto"
    trim: str = "auto"
    how: str = "auto"
    finish_rows: int = 5_000_000
    bucket_rows: int = 1_000_000
    accuracy: int = 10_000
    min_fanout: int = 256
    max_pivots: int = 4096
    max_total_pivots: int = 1 << 20
    max_sort_buckets: int = 20_000
    max_levels: int = 64
    listed_ranks: int = 50_000
    collapse: bool | str = False
    collapse_values: int = 10_000
