"""Keys of controlled skew."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PERMUTE = 7_919  # a prime: ids that follow one another land far apart


def shares(b: int, s: float, tail_share: float = 0.0) -> list[float]:
    """The share of each of b blocks, falling by e^-s from block to block; the rest is for the tail."""
    raw = [math.exp(-s * k) for k in range(b)]
    return [(1 - tail_share) * x / sum(raw) for x in raw]


def cut_points(n: int, b: int, s: float, tail_share: float = 0.0) -> list[int]:
    """The first place, of n, behind each block: whole numbers, the same for every engine."""
    out, total = [], 0.0
    for share in shares(b, s, tail_share):
        total += share
        out.append(round(total * n))
    return out


def _place(identity: Column, n: int) -> Column:
    step = PERMUTE
    while math.gcd(step, n) != 1:
        step += 2
    return F.pmod(identity * step, F.lit(n))


def exponential_key(df: DataFrame, identity: Column, n: int, b: int = 100, s: float = 0.0, tail_share: float = 0.0, tail_blocks: int = 1) -> DataFrame:
    """df with block_key: block k of b with a share falling as e^(-s k), and a tail spread over many small blocks.

    identity numbers the n records from 0 without gaps. Where a record falls follows from its number alone.
    """
    points = cut_points(n, b, s, tail_share)
    place = _place(identity.cast("long"), n)
    ends = F.array(*map(F.lit, points))
    k = F.size(F.filter(ends, lambda e: e <= place))
    tail = F.concat(F.lit("t"), F.lpad(F.pmod(place, F.lit(max(1, tail_blocks))).cast("string"), 8, "0"))
    return df.withColumn("block_key", F.when(k < b, F.concat(F.lit("k"), F.lpad(k.cast("string"), 4, "0"))).otherwise(tail))


def key_sql(identity: str, n: str, b: int, s: float) -> str:
    """The key without a tail as SQL, by the same whole numbers, for n that is no multiple of PERMUTE."""
    ends, total = [], 0.0
    for share in shares(b, s):
        total += share
        ends.append(f"{total!r}::DOUBLE")
    points = f"list_transform([{', '.join(ends)}], lambda x: CAST(round_even(x * {n}, 0) AS BIGINT))"
    return f"'k' || lpad(CAST(len(list_filter({points}, lambda e: e <= ((({identity}) * {PERMUTE}) % {n}))) AS VARCHAR), 4, '0')"
