"""Sub-block splitting: heavy blocks fall into the pieces of their input partitions, and every task of about equal
size goes to the reduce task with the least load.

A block is heavy when its pairs exceed the average over the reduce tasks, so fewer than r blocks are. A heavy block
of p non-empty pieces gives p tasks of a piece with itself and p * (p - 1) / 2 tasks of two pieces.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import WHOLE
from . import layout


def heavy_blocks(profile: DataFrame, r: int, total: int, max_entities: int | None = None) -> DataFrame:
    """Rows of the profile whose pairs exceed total / r, or whose records exceed a memory cap."""
    heavy = F.col("pairs") * r > F.lit(total)
    return profile.where(heavy | (F.col("n") > max_entities) if max_entities else heavy)


def _light_tasks(profile: DataFrame, heavy: DataFrame) -> DataFrame:
    light = profile.join(F.broadcast(heavy.select("block_ix")), "block_ix", "left_anti").where("pairs > 0")
    return light.select("block_ix", F.lit(WHOLE).alias("hi"), F.lit(WHOLE).alias("lo"), "pairs")


def match_tasks(matrix: DataFrame, profile: DataFrame, r: int, total: int, keep_zero_tasks: bool = False, max_entities: int | None = None) -> DataFrame:
    """(block_ix, hi, lo, pairs): light blocks whole, heavy blocks by piece pairs with hi >= lo.

    Only the cells of heavy blocks meet each other; there are at most (r - 1) * m of them.
    """
    heavy = heavy_blocks(profile, r, total, max_entities)
    cells = matrix.join(F.broadcast(heavy.select("block_ix")), "block_ix", "left_semi").select("block_ix", "part_ix", "n")
    a, b = cells.alias("a"), cells.alias("b")
    met = a.join(b, (F.col("a.block_ix") == F.col("b.block_ix")) & (F.col("a.part_ix") >= F.col("b.part_ix")))
    same = F.col("a.part_ix") == F.col("b.part_ix")
    size = F.when(same, F.expr("a.n * (a.n - 1) div 2")).otherwise(F.col("a.n") * F.col("b.n"))
    split = met.select(F.col("a.block_ix").alias("block_ix"), F.col("a.part_ix").alias("hi"), F.col("b.part_ix").alias("lo"), size.alias("pairs"))
    return _light_tasks(profile, heavy).unionByName(split if keep_zero_tasks else split.where("pairs > 0"))


def match_tasks_two_source(matrix: DataFrame, profile: DataFrame, r: int, total: int) -> DataFrame:
    """The same for R and S: heavy blocks by a piece of R (hi) and a piece of S (lo), never a piece with itself."""
    heavy = heavy_blocks(profile, r, total)
    cells = matrix.join(F.broadcast(heavy.select("block_ix")), "block_ix", "left_semi")
    a = cells.where("source = 'R'").select("block_ix", F.col("part_ix").alias("hi"), F.col("n").alias("n_r"))
    b = cells.where("source = 'S'").select("block_ix", F.col("part_ix").alias("lo"), F.col("n").alias("n_s"))
    split = a.join(b, "block_ix").select("block_ix", "hi", "lo", F.expr("n_r * n_s").alias("pairs"))
    return _light_tasks(profile, heavy).unionByName(split)


def destinations(matrix: DataFrame, placed: DataFrame) -> DataFrame:
    """(block_key, block_ix, part_ix, tasks): the tasks (hi, lo, reduce_ix) of the records of each cell. It is made of
    cells and tasks alone."""
    cell = ["block_key", "block_ix", "part_ix"]
    task = F.struct("hi", "lo", "reduce_ix").alias("task")
    whole = placed.where(F.col("hi") == WHOLE).select("block_ix", task)
    sides = placed.where(F.col("hi") != WHOLE).select("block_ix", task, F.explode(F.array_distinct(F.array("hi", "lo"))).alias("part_ix"))
    light = matrix.select(*cell).join(whole, "block_ix").select(*cell, F.array("task").alias("tasks"))
    heavy = matrix.select(*cell).join(sides, ["block_ix", "part_ix"]).groupBy(*cell).agg(F.collect_list("task").alias("tasks"))
    return light.unionByName(heavy)


def route(df: DataFrame, matrix: DataFrame, placed: DataFrame) -> DataFrame:
    """A copy of each record for every task that holds its block or piece. Records meet the tasks of their own cell, so
    no block is brought together ahead of its tasks."""
    rows = df.join(destinations(matrix, placed), ["block_key", "part_ix"]).withColumn("task", F.explode("tasks"))
    return rows.select("block_ix", "task.hi", "task.lo", "task.reduce_ix", *(c for c in df.columns if c != "block_key"))


KEY = ["reduce_ix", "block_ix", "hi", "lo"]


def _pairs(a: DataFrame, b: DataFrame, test: str, attrs: bool) -> DataFrame:
    more = [F.col("a.attr").alias("x"), F.col("b.attr").alias("y")] if attrs else []
    met = a.alias("a").hint("merge").join(b.alias("b"), KEY).where(test)
    return met.select(F.col("a.entity_id").alias("i"), F.col("b.entity_id").alias("j"), "block_ix", "reduce_ix", *more)


def pairs(routed: DataFrame, r: int, attrs: bool = False) -> DataFrame:
    """(left_id, right_id, block_ix, reduce_ix): the pairs of every task, each once.

    Of two pieces one goes to the left and the other to the right side; a piece with itself goes to both. Both sides are
    sent to their task by number, so the join below adds no shuffle, and no order of arrival matters.
    """
    a = layout.route(routed.where("hi = lo OR part_ix = hi"), r)
    b = layout.route(routed.where("hi = lo OR part_ix = lo"), r)
    met = _pairs(a, b, "a.hi <> a.lo OR a.entity_id < b.entity_id", attrs)
    swap = F.col("i") > F.col("j")
    more = [F.when(swap, F.col("y")).otherwise(F.col("x")).alias("left_attr"), F.when(swap, F.col("x")).otherwise(F.col("y")).alias("right_attr")] if attrs else []
    return met.select(F.least("i", "j").alias("left_id"), F.greatest("i", "j").alias("right_id"), "block_ix", "reduce_ix", *more)


def pairs_two_source(routed: DataFrame, r: int, attrs: bool = False) -> DataFrame:
    """(left_id of R, right_id of S, block_ix, reduce_ix)."""
    a, b = (layout.route(routed.where(F.col("source") == s), r) for s in "RS")
    met = _pairs(a, b, "true", attrs)
    names = {"i": "left_id", "j": "right_id", "x": "left_attr", "y": "right_attr"}
    return met.select(*(F.col(c).alias(names.get(c, c)) for c in met.columns))
