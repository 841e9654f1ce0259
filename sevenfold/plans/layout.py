"""Block-cyclic layouts over q**k logical workers for schemes of n0 x n0 blocks and q products; 7 and 2 by default."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column
from pyspark.sql import functions as F


def digits_of(p: int, base: int = 7) -> int:
    """k with p = base**k; raises for another p."""
    k, x = 0, 1
    while x < p:
        x, k = x * base, k + 1
    if x != p:
        raise ValueError(f"{p} is not a power of {base}")
    return k


@dataclass(frozen=True)
class LayoutSpec:
    """An n x n matrix, dealt for ``levels`` recursion levels to ``workers`` = q**k.

    Cyclic grid of q**floor(k/2) x q**ceil(k/2). ``fine`` divides the coarsest
    block that still deals every submatrix of depth ``levels`` evenly.
    """

    n: int
    workers: int
    levels: int
    fine: int = 1
    q: int = 7
    n0: int = 2

    @property
    def k(self) -> int:
        return digits_of(self.workers, self.q)

    @property
    def grid(self) -> tuple[int, int]:
        return self.q ** (self.k // 2), self.q ** (self.k - self.k // 2)

    @property
    def block(self) -> tuple[int, int]:
        rows, cols = self.grid
        return self.n // (self.n0**self.levels * rows * self.fine), self.n // (self.n0**self.levels * cols * self.fine)

    @property
    def unit(self) -> int:
        """n must be a multiple of this."""
        return self.n0**self.levels * self.grid[1] * self.fine

    def check(self) -> LayoutSpec:
        if self.n % self.unit:
            low = self.n // self.unit * self.unit
            near = min((x for x in (low, low + self.unit) if x), key=lambda x: abs(x - self.n))
            raise ValueError(f"n={self.n} is not a multiple of {self.unit}; the nearest valid n is {near}")
        return self

    def owner(self, bi: Column, bj: Column) -> Column:
        """Worker of the block in block row ``bi`` and block column ``bj``."""
        rows, cols = self.grid
        return (F.pmod(bi, F.lit(rows)) * cols + F.pmod(bj, F.lit(cols))).cast("int")

    def after(self, letter: str) -> LayoutSpec:
        """The layout of the subproblems after a wide or a serial level."""
        if letter == "W":
            return replace(self, n=self.n // self.n0, workers=self.workers // self.q, levels=self.levels - 1)
        if letter == "S":
            return replace(self, n=self.n // self.n0, levels=self.levels - 1)
        raise ValueError(letter)


def with_digit(owner: Column, place: int, digit: Column, base: int = 7) -> Column:
    """``owner`` with its digit at ``place`` (0 = rightmost) replaced."""
    unit = base**place
    old = F.pmod(F.floor(owner / unit), F.lit(base))
    return (owner + (digit - old) * unit).cast("int")


def exchange_peers(owner: Column, place: int, base: int = 7) -> Column:
    """The workers that differ from ``owner`` in one digit at most."""
    return F.transform(F.sequence(F.lit(0), F.lit(base - 1)), lambda d: with_digit(owner, place, d, base))


def usable_workers(p: int, allow: tuple[int, ...] = (1, 2, 3, 6)) -> tuple[int, int, int]:
    """Largest c * 7**k up to ``p``: (workers, c, k)."""
    found = [(c * 7**k, c, k) for c in allow for k in range(40) if c * 7**k <= p]
    return max(found)
