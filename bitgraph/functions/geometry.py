"""Matrix sides, subdivision schedules and cell codes.

A schedule lists the factor by which each level divides a side, all powers of two. A cell's code puts its row and column
digits of each level side by side, the top level first, so that sorted codes are the order of the tree.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Schedule:
    factors: tuple[int, ...]

    def __post_init__(self):
        if not self.factors or any(k < 2 or k & (k - 1) for k in self.factors):
            raise ValueError("factors are powers of two, one at least")

    @property
    def side(self) -> int:
        out = 1
        for k in self.factors:
            out *= k
        return out

    @property
    def bits(self) -> tuple[int, ...]:
        return tuple(k.bit_length() - 1 for k in self.factors)

    @classmethod
    def uniform(cls, k: int, dim: int) -> Schedule:
        """The fewest levels of k that reach dim."""
        factors = [k]
        while k ** len(factors) < dim:
            factors.append(k)
        return cls(tuple(factors))

    @classmethod
    def hybrid(cls, dim: int, top_k: int = 4, top_levels: int = 5, low_k: int = 2) -> Schedule:
        """top_k for the first levels, then low_k."""
        factors, side = [], 1
        while side < dim or not factors:
            factors.append(top_k if len(factors) < top_levels else low_k)
            side *= factors[-1]
        return cls(tuple(factors))

    @classmethod
    def named(cls, name: str, dim: int) -> Schedule:
        return {"k2": lambda: cls.uniform(2, dim), "k4": lambda: cls.uniform(4, dim), "hybrid": lambda: cls.hybrid(dim)}[name]()


def dimension(n_so: int, n_s: int, n_o: int) -> int:
    """Rows and columns that a square matrix of all IDs needs."""
    return max(1, n_so + max(n_s, n_o))


def cell_code(row: Column, col: Column, schedule: Schedule) -> Column:
    """The code of a 0-based cell as shifts and masks; 62 bits at most."""
    if sum(schedule.bits) > 31:
        raise ValueError("a code has 62 bits at most: use tiles")
    out, below = F.lit(0).cast("bigint"), sum(schedule.bits)
    for b in schedule.bits:
        below -= b
        digit = lambda c: F.shiftright(c, below).bitwiseAND((1 << b) - 1)  # noqa: B023, E731
        out = F.shiftleft(out, 2 * b).bitwiseOR(F.shiftleft(digit(row), b)).bitwiseOR(digit(col))
    return out


def decode_cell(code: Column, schedule: Schedule) -> tuple[Column, Column]:
    row = col = F.lit(0).cast("bigint")
    below = 2 * sum(schedule.bits)
    for b in schedule.bits:
        below -= 2 * b
        digits = F.shiftright(code, below)
        row = F.shiftleft(row, b).bitwiseOR(F.shiftright(digits, b).bitwiseAND((1 << b) - 1))
        col = F.shiftleft(col, b).bitwiseOR(digits.bitwiseAND((1 << b) - 1))
    return row, col
