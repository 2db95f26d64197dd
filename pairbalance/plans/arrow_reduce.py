"""The sub-block reduce step as a function over the sorted rows of a task."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import layout

IDS = "left_id long, right_id long, block_ix long, reduce_ix int"
SCHEMA = "left_id long, right_id long, left_attr string, right_attr string, block_ix long, reduce_ix int"


def _places(n: int, held: int, inside: bool, most: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places (x, y) of n new rows and the rows that each meets: all held ones or, inside a piece, also the new ones
    before it. At most so many at once."""
    start = 0
    while start < n:
        full = held + (start if inside else 0)
        stop = min(n, start + max(1, most // max(1, full + 1)))
        counts = np.arange(start, stop) * inside + held
        while stop - start > 1 and counts.sum() > most:
            stop = start + (stop - start) // 2
            counts = counts[: stop - start]
        if stop - start == 1:
            for low in range(0, int(counts[0]), most):
                y = np.arange(low, min(low + most, int(counts[0])))
                yield np.full(len(y), start), y
        else:
            yield np.repeat(np.arange(start, stop), counts), np.concatenate([np.arange(c) for c in counts])
        start = stop


def _runs(columns: list[np.ndarray]) -> Iterator[tuple[int, int]]:
    """The first place of each run of equal rows and the place behind it."""
    n = len(columns[0])
    changes = np.zeros(max(0, n - 1), bool)
    for c in columns:
        changes |= c[1:] != c[:-1]
    ends = [0, *(np.flatnonzero(changes) + 1).tolist(), n] if n else []
    yield from zip(ends, ends[1:], strict=False)


def pairs_by_stream(routed: DataFrame, r: int, most: int = 50_000, most_text: int = 1 << 25, attrs: bool = True) -> DataFrame:
    """Pairs of every task, holding one piece of one task at a time and giving out at most ``most`` pairs,
    or about ``most_text`` characters of them, at once. Without ``attrs`` no text is moved.

    Rows are sorted with the kept side first, so the other side streams past it; the order of arrival is by this
    sort and never assumed.
    """
    kept = F.when(F.col("hi") == F.col("lo"), F.lit(0)).otherwise((F.col("part_ix") != F.col("hi")).cast("int"))
    columns = ["reduce_ix", "block_ix", "hi", "lo", "side", "entity_id", *(["attr"] if attrs else [])]
    rows = layout.route(routed.withColumn("side", kept).select(*columns), r).sortWithinPartitions(*columns[:6])

    def reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, ids, texts = None, np.zeros(0, np.int64), pa.array([], pa.string())
        for batch in batches:
            numbers = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(6)]
            for start, stop in _runs(numbers[:5]):
                ix, block, hi, lo, side = (int(c[start]) for c in numbers[:5])
                if (ix, block, hi, lo) != task:
                    task, ids, texts = (ix, block, hi, lo), ids[:0], texts[:0]
                held, new = len(ids), numbers[5][start:stop]
                all_ids = np.concatenate([ids, new])
                all_texts = pa.concat_arrays([texts, batch.column(6)[start:stop]]) if attrs else texts
                if side == 1 or hi == lo:
                    for x, y in _places(len(new), held, hi == lo, most):
                        yield from give(x + held, y, all_ids, all_texts, block, ix)
                if side == 0:
                    ids, texts = all_ids, all_texts

    def give(x: np.ndarray, y: np.ndarray, ids: np.ndarray, texts: pa.Array, block: int, ix: int) -> Iterator[pa.RecordBatch]:
        first, second = np.where(ids[x] < ids[y], x, y), np.where(ids[x] < ids[y], y, x)
        ends = [len(x)]
        if attrs:
            sizes = pa.compute.fill_null(pa.compute.utf8_length(texts), 0).to_numpy(zero_copy_only=False)
            at = np.cumsum(sizes[first] + sizes[second]) // most_text
            ends = [*(np.flatnonzero(at[1:] != at[:-1]) + 1).tolist(), len(x)]
        for a, b in zip([0, *ends], ends, strict=False):
            i, j = first[a:b], second[a:b]
            moved = [texts.take(pa.array(i)), texts.take(pa.array(j))] if attrs else []
            yield pa.RecordBatch.from_arrays([pa.array(ids[i]), pa.array(ids[j]), *moved, pa.array(np.full(b - a, block)), pa.array(np.full(b - a, ix, np.int32))], names)

    schema = SCHEMA if attrs else IDS
    names = [c.split()[0] for c in schema.split(", ")]
    return rows.mapInArrow(reduce, schema)
