"""Placement of tasks on reduce tasks, and simulated run times."""

from __future__ import annotations

import heapq

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import TASKS
from ..operators.prefix import dense_index

#: Up to this many tasks the exact placement runs on the driver; beyond it tasks of equal size are placed together.
EXACT_TASKS = 200_000


def least_loaded(sizes: list[int], r: int) -> list[int]:
    """For tasks in the given order the reduce task with the least load so far, the first of equals."""
    loads = [(0, i) for i in range(r)]
    out = []
    for size in sizes:
        load, i = loads[0]
        heapq.heapreplace(loads, (load + size, i))
        out.append(i)
    return out


def greedy(tasks: DataFrame, r: int, mode: str = "auto") -> DataFrame:
    """tasks with reduce_ix: largest first, to the least loaded reduce task; ties by block and piece.

    ``exact`` brings the tasks to the driver and so has a limit on their number. ``classed`` brings only the distinct
    sizes and gives the same loads: which of two equal tasks goes where is all that may differ.
    """
    if mode == "classed":
        return _classed(tasks, r)
    rows = tasks.select(*TASKS.names).limit(EXACT_TASKS + 1).collect()
    if len(rows) <= EXACT_TASKS:
        return _exact(tasks, rows, r)
    if mode == "exact":
        raise ValueError("too many tasks for the exact placement; use classed")
    return _classed(tasks, r)


def _exact(tasks: DataFrame, rows: list, r: int) -> DataFrame:
    rows.sort(key=lambda t: (-t.pairs, t.block_ix, t.hi, t.lo))
    placed = [(*t, i) for t, i in zip(rows, least_loaded([t.pairs for t in rows], r), strict=True)]
    # at most EXACT_TASKS rows of 28 bytes, so records need no shuffle to meet them
    return F.broadcast(tasks.sparkSession.createDataFrame(placed, "block_ix long, hi int, lo int, pairs long, reduce_ix int"))


def filled_level(loads: np.ndarray, size: int, count: int) -> np.ndarray:
    """How many of ``count`` equal tasks each reduce task gets when each goes to the least loaded, the first of equals."""
    if size == 0:
        out = np.zeros(len(loads), np.int64)
        out[int(np.argmin(loads))] = count
        return out
    low, high = int(loads.min()), int(loads.min()) + size * count + 1  # a task is placed at a load below the level
    taken = lambda level: np.maximum(0, -(-(level - loads) // size))
    while low < high:
        middle = (low + high + 1) // 2
        if int(taken(middle).sum()) <= count:
            low = middle
        else:
            high = middle - 1
    out = taken(low)
    rest = count - int(out.sum())
    at = np.flatnonzero(loads + out * size == low)[:rest]  # the next tasks start exactly at the level
    out[at] += 1
    return out


def _classed(tasks: DataFrame, r: int) -> DataFrame:
    sizes = sorted(((t["pairs"], t["count"]) for t in tasks.groupBy("pairs").count().collect()), reverse=True)
    loads, start, ranges = np.zeros(r, np.int64), 0, []
    for size, count in sizes:
        got = filled_level(loads, size, count)
        loads += got * size
        for i in np.flatnonzero(got):
            ranges.append((int(size), start, start + int(got[i]), int(i)))
            start += int(got[i])
    spark = tasks.sparkSession
    ranked = dense_index(tasks.withColumn("__order", -F.col("pairs")), ["__order", "block_ix", "hi", "lo"], "__rank").drop("__order")
    table = spark.createDataFrame(ranges, "size long, first long, behind long, reduce_ix int")
    met = (F.col("pairs") == F.col("size")) & (F.col("__rank") >= F.col("first")) & (F.col("__rank") < F.col("behind"))
    return ranked.join(table, met).select(*TASKS.names, "reduce_ix")


def makespan(loads: list[float], slots: int) -> float:
    """The time at which all tasks have ended, started in queue order on the slot that is free first."""
    ends = [0.0] * max(1, slots)
    for load in loads:
        heapq.heapreplace(ends, ends[0] + load)
    return max(ends)
