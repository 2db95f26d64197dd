"""User functions: matchers, aggregates, table functions and SQL functions."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


def as_matcher(fn: Callable[[str, str], float], returns: str = "double"):
    """A Python comparison of two texts as a vectorised function over two columns."""

    @F.pandas_udf(returns)
    def matcher(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([fn(x, y) for x, y in zip(a, b, strict=True)], dtype="object" if returns == "string" else None)

    return matcher


def gini_of(values: list[float]) -> float:
    """0 where all values are equal, near 1 where one holds all."""
    ordered, n, total = sorted(values), len(values), sum(values)
    if not n or not total:
        return 0.0
    return sum((2 * i - n + 1) * v for i, v in enumerate(ordered)) / (n * total)


@F.pandas_udf(DoubleType())
def gini(loads: pd.Series) -> float:
    """Inequality of loads, as an aggregate."""
    return float(gini_of(loads.tolist()))


@F.udtf(returnType="hi: int, lo: int, pairs: long")
class PieceTasks:
    """The tasks of a heavy block from the sizes of its pieces (0 for an empty one)."""

    def eval(self, counts: list):
        for hi, a in enumerate(counts):
            for lo in range(hi + 1):
                pairs = a * (a - 1) // 2 if hi == lo else a * counts[lo]
                if pairs:
                    yield hi, lo, pairs


@F.udtf(returnType="reduce_ix: int")
class IntervalsOf:
    """The intervals that hold a pair of record e in a block of n records whose first pair has a number, of total pairs
    cut into r."""

    def eval(self, e: int, n: int, first_pair: int, total: int, r: int):
        if e is None or n is None or n < 2:
            return
        number = lambda x, y: x * (2 * n - x - 3) // 2 + y - 1 + first_pair
        seen = {r * number(min(e, k), max(e, k)) // total for k in range(n) if k != e}
        for k in sorted(seen):
            yield (k,)


def register(spark: SparkSession) -> None:
    """Table functions piece_tasks and intervals_of, and SQL functions pair_cell, pair_interval and edit_similarity."""
    spark.udtf.register("piece_tasks", PieceTasks)
    spark.udtf.register("intervals_of", IntervalsOf)
    for statement in (
        "pair_cell(x BIGINT, y BIGINT, n BIGINT) RETURNS BIGINT RETURN x * (2 * n - x - 3) div 2 + y - 1",
        "pair_interval(p BIGINT, total BIGINT, r BIGINT) RETURNS BIGINT RETURN r * p div total",
        "edit_similarity(a STRING, b STRING) RETURNS DOUBLE RETURN 1 - levenshtein(a, b) / greatest(length(a), length(b), 1)",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {statement}")
