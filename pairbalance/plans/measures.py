"""Measures of load, copies and results."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import pair_interval
from . import engine, schedule


def imbalance(loads: DataFrame) -> DataFrame:
    """One row: tasks, total, largest, average and the largest load over the average, and as a share of all."""
    rows = loads.agg(F.count("*").alias("tasks"), F.sum("pairs").alias("total"), F.max("pairs").alias("largest"))
    return rows.select("tasks", "total", "largest", (F.col("total") / F.col("tasks")).alias("average"), F.expr("try_divide(largest * tasks, total)").alias("over_average"), F.expr("try_divide(largest, total)").alias("share"))


def dataset_profile(profile: DataFrame) -> DataFrame:
    """One row: records, blocks, pairs, and what the largest block holds of records and of pairs."""
    rows = profile.agg(F.sum("n").alias("entities"), F.count("*").alias("blocks"), F.sum("pairs").alias("pairs"), F.max("n").alias("largest"), F.max("pairs").alias("largest_pairs"))
    return rows.select("entities", "blocks", "pairs", "largest", "largest_pairs", (F.col("largest") / F.col("entities")).alias("largest_entity_share"), F.expr("try_divide(largest_pairs, pairs)").alias("largest_pair_share"))


def map_output(routed: DataFrame) -> int:
    """Rows that leave the map side."""
    return routed.count()


def peak_group(routed: DataFrame, keys: list[str]) -> int:
    """The most records of one reduce call."""
    return int(routed.groupBy(*keys).count().agg(F.coalesce(F.max("count"), F.lit(0))).first()[0])


def pair_checks(plan: engine.Plan, roles: bool, cut: str = "proportional") -> DataFrame:
    """One row: candidate pairs that tasks form before the test of the number, and all pairs; no pair is formed."""
    rows, key = engine.indexed(plan), ["reduce_ix", "block_ix"]
    if roles:
        sides = zip(pair_interval.route_roles(rows, plan.total, plan.r, cut), ("n_low", "n_high"), strict=True)
        low, high = (x.groupBy(*key).agg(F.count("*").alias(c)) for x, c in sides)
        formed = low.join(high, key).select((F.col("n_low") * F.col("n_high")).alias("formed"))
    else:
        sizes = pair_interval.route(rows, plan.total, plan.r, cut).groupBy(*key).count()
        formed = sizes.select(F.expr("count * (count - 1) div 2").alias("formed"))
    return formed.agg(F.coalesce(F.sum("formed"), F.lit(0)).alias("formed"), F.lit(plan.total).cast("long").alias("pairs"))


def agreement(a: DataFrame, b: DataFrame) -> tuple[int, int]:
    """Rows that only one of two results has, with repeats; (0, 0) where they are equal."""
    return a.exceptAll(b).count(), b.exceptAll(a).count()


def blocking_recall(matches: DataFrame, reference: DataFrame) -> DataFrame:
    """One row: reference matches, those found, and those lost to blocking."""
    hits = matches.select("left_id", "right_id").distinct().withColumn("hit", F.lit(1))
    n, found = reference.join(hits, ["left_id", "right_id"], "left").agg(F.count("*"), F.count("hit")).first()
    return matches.sparkSession.createDataFrame([(n, found, n - found)], "matches long, found long, lost long")


def time_per_10k(seconds: float, pairs: int) -> float:
    """Milliseconds for ten thousand pairs."""
    return seconds * 1000 * 10_000 / max(1, pairs)


def speedup(one: float, many: float) -> float:
    return one / many if many else float("inf")


def simulated_speedup(loads: list[int], nodes: int, slots_per_node: int = 2) -> float:
    """Total work over the makespan on nodes of two slots, tasks started in the order of the queue, against one node that is
    busy throughout."""
    span = schedule.makespan(loads, nodes * slots_per_node)
    return sum(loads) / slots_per_node / span if span else 0.0
