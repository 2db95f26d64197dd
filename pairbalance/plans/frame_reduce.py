"""Reduce steps as pandas functions, for comparisons that need whole groups.

The ids of a group are held in memory as a whole, its pairs are not: a group of one source gives them out piece by piece.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from ..operators import layout

KEY = ["reduce_ix", "block_ix", "hi", "lo"]
OUT = "left_id long, right_id long, block_ix long, reduce_ix int"
#: Pairs that a group gives out at once, unless one record has more.
MOST = 1 << 18


def _frame(left: np.ndarray, right: np.ndarray, block_ix: int, reduce_ix: int) -> pd.DataFrame:
    return pd.DataFrame({"left_id": left, "right_id": right, "block_ix": np.full(len(left), block_ix), "reduce_ix": np.full(len(left), reduce_ix, np.int32)})


def within(ids: np.ndarray, most: int = MOST) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All pairs of one piece, ids rising, some records with all behind them at a time."""
    n, start = len(ids), 0
    behind = np.arange(n - 1, -1, -1)
    while start < n - 1:
        stop = start + max(1, most // int(behind[start]))
        yield np.repeat(ids[start:stop], behind[start:stop]), np.concatenate([ids[x + 1 :] for x in range(start, min(stop, n))])
        start = stop


def across(a: np.ndarray, b: np.ndarray, most: int = MOST) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All pairs of two pieces, some records of the first with all of the second at a time."""
    step = max(1, most // max(1, len(b)))
    for start in range(0, len(a) if len(b) else 0, step):
        x = np.repeat(a[start : start + step], len(b))
        y = np.tile(b, len(x) // len(b))
        yield np.minimum(x, y), np.maximum(x, y)


def pairs_by_group(routed: DataFrame, r: int, most: int = MOST) -> DataFrame:
    """Pairs of each sub-block task, one group at a time and of it at most so many pairs."""

    def reduce(key: tuple, batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        reduce_ix, block_ix, hi, lo = (int(k) for k in key)
        read = [(x["entity_id"].to_numpy(), x["part_ix"].to_numpy()) for x in batches]
        ids, parts = (np.concatenate(x) for x in zip(*read, strict=True))
        found = within(np.sort(ids), most) if hi == lo else across(ids[parts == hi], ids[parts == lo], most)
        for left, right in found:
            yield _frame(left, right, block_ix, reduce_ix)

    rows = layout.route(routed.select(*KEY, "part_ix", "entity_id"), r)
    return rows.groupBy(*KEY).applyInPandas(reduce, OUT)


def pairs_by_cogroup(routed: DataFrame, r: int) -> DataFrame:
    """Pairs of R and S of each two-source task."""

    def reduce(key: tuple, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        a, b = left["entity_id"].to_numpy(), right["entity_id"].to_numpy()
        return _frame(np.repeat(a, len(b)), np.tile(b, len(a)), key[1], key[0])

    rows = layout.route(routed.select(*KEY, "source", "entity_id"), r)
    one, other = rows.where("source = 'R'"), rows.where("source = 'S'")
    other = other.toDF(*other.columns)  # columns of its own: both sides come from one table
    return one.groupBy(*KEY).cogroup(other.groupBy(*KEY)).applyInPandas(reduce, OUT)
