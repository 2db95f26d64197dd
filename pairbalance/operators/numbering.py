"""Numbers of pairs: inside a block, over all blocks, and the interval that a number falls into.

All functions take and give integer columns. Inside a block of n records with places 0..n-1 the pairs (x, y), x < y,
are numbered by x and then by y.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .matrix import half


def div(a: Column, b: Column | int) -> Column:
    """Whole division of longs."""
    return F.call_function("div", a, b if isinstance(b, Column) else F.lit(b))


def wide_div(a: Column, b: Column) -> Column:
    """Whole division of decimals without a remainder lost to rounding."""
    return ((a - a % b) / b).cast("decimal(38,0)")


def column_start(x: Column, n: Column, wide: bool = False) -> Column:
    """The number of pairs whose smaller place is before x."""
    return half(x * (n * 2 - x - 1), wide)


def cell(x: Column, y: Column, n: Column, wide: bool = False) -> Column:
    return column_start(x, n, wide) + y - x - 1


def cell_two_source(x: Column, y: Column, n_s: Column) -> Column:
    """The number of the pair of record x of R and record y of S."""
    return x * n_s + y


def uncell(p: Column, n: Column) -> tuple[Column, Column]:
    """The pair of a number. Counted from the last pair, columns grow by one each, so a root gives the column to within
    one however large the block; whole numbers settle it."""
    q = div(n * (n - 1), 2) - 1 - p
    guess = F.floor((F.sqrt(q.cast("double") * 8 + 1) - 1) / 2).cast("long")
    back = guess - (div(guess * (guess + 1), 2) > q).cast("long") + (div((guess + 1) * (guess + 2), 2) <= q).cast("long")
    x = n - 2 - back
    return x, p - column_start(x, n) + x + 1


def interval_of(p: Column, total: int, r: int, cut: str = "proportional") -> Column:
    """The interval of a pair number: r shares that differ by one at most, or shares of ceil(total / r) and a rest."""
    if cut == "proportional":
        return div(p * r, max(1, total)).cast("int")
    return div(p, width(total, r)).cast("int")


def width(total: int, r: int) -> int:
    return max(1, -(-total // r))


def interval_bounds(k: Column, total: int, r: int, cut: str = "proportional") -> tuple[Column, Column]:
    """The first and the last pair number of an interval; last < first for an empty one."""
    k = k.cast("long")
    if cut == "proportional":
        start = lambda i: div(i * total + (r - 1), r)
        return start(k), start(k + 1) - 1
    w = width(total, r)
    return F.least(k * w, F.lit(total).cast("long")), F.least((k + 1) * w, F.lit(total).cast("long")) - 1
