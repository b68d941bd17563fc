"""Scales, smooth numbers and the lattice arithmetic of cells, in numpy and as Columns."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

PRIMES = (2, 3, 5)


def smooth(n: float) -> int:
    """The number >= 1 without prime factors other than 2, 3 and 5 that is nearest to ``n``; of two as near the smaller."""
    best, a = 1, 1
    while a <= 2 * max(n, 1):
        b = a
        while b <= 2 * max(n, 1):
            c = b
            while c <= 2 * max(n, 1):
                if (abs(c - n), c) < (abs(best - n), best):
                    best = c
                c *= 5
            b *= 3
        a *= 2
    return best


def chain(grid: int) -> list[int]:
    """Divisors of ``grid``, descending, each a multiple of the next: the cell widths that fit bins of that width."""
    out, rest = [grid], grid
    for p in (*PRIMES, *range(7, grid + 1, 2)):
        while rest % p == 0:
            rest //= p
            out.append(rest)
        if rest == 1:
            break
    return out


def cell_width(wish: float, grid: int | None) -> int:
    """The largest of ``chain(grid)`` not above ``wish``; without a grid the nearest whole number >= 1."""
    if grid is None:
        return max(1, int(wish + 0.5))
    return next((c for c in chain(grid) if c <= max(1, wish)), 1)


def slider_steps(width: int, pixels: int) -> list[int]:
    """Discrete places of a slider over ``width`` scales: a smooth step of about one pixel."""
    step = smooth(width / pixels)
    return list(range(0, width + 1, step))


def near(edges: np.ndarray, c: int) -> np.ndarray:
    """Number of the cell edge nearest to each edge; a tie goes to the lower one."""
    return (2 * edges + c - 1) // (2 * c)


def up(edges: np.ndarray, c: int) -> np.ndarray:
    return -(-edges // c)


def down(edges: np.ndarray, c: int) -> np.ndarray:
    return edges // c


def near_col(e: Column, c: Column) -> Column:
    return F.floor((2 * e + c - 1) / (2 * c)).cast("long")


def up_col(e: Column, c: Column) -> Column:
    return F.ceil(e / c).cast("long")


def down_col(e: Column, c: Column) -> Column:
    return F.floor(e / c).cast("long")


def morton(columns: Sequence[Column], bits: int) -> Column:
    """Interleaved bits of whole numbers below 2**bits, the first column's highest bit first."""
    out = F.lit(0).cast("long")
    k = len(columns)
    for b in range(bits):
        for i, c in enumerate(columns):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(c.cast("long"), b).bitwiseAND(F.lit(1).cast("long")), b * k + (k - 1 - i)))
    return out


def sampled(key: Column, rate: float) -> Column:
    """A repeatable share of rows by a multiplicative hash of a whole-number key."""
    return F.pmod(key * F.lit(2654435761), F.lit(1 << 20)) < int(rate * (1 << 20))


def sampled_sql(key: str, rate: float) -> str:
    return f"({key} * 2654435761) % {1 << 20} < {int(rate * (1 << 20))}"
