"""From a table of entities to matches, by any strategy."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.similarity import edit_distance_within
from ..operators import layout, matrix, pair_interval, sub_block, whole_block
from ..operators.numbering import interval_bounds
from ..storage import cut as cut_table
from . import schedule


@dataclass
class Plan:
    """What the first stage found: cells, profile, all pairs, and the annotated records."""

    records: DataFrame
    cells: DataFrame
    profile: DataFrame
    total: int
    r: int
    two_source: bool


def first_stage(df: DataFrame, r: int, two_source: bool = False, combine: bool = True, explicit_order: list[str] | None = None, pieces: str = "input", max_entities: int | None = None) -> Plan:
    """Count cells and pairs. df has entity_id, block_key, part_ix (and source). ``pieces="auto"`` replaces the input
    partitions by as many pieces as the balance needs."""
    if combine and explicit_order is None:
        cells, profile, total = matrix.cells_and_profile(df, two_source)
    else:
        cells = cut_table(matrix.block_matrix(df, two_source, combine, explicit_order), "cells")
        profile = cut_table(matrix.block_profile(cells, two_source), "profile")
        total = matrix.total_pairs(profile)
    if pieces == "auto" and not two_source:
        df = layout.with_pieces(df, profile, total, r, max_entities=max_entities)
        cells = matrix.cells_and_profile(df)[0]
    return Plan(df, cells, profile, total, r, two_source)


def tasks(plan: Plan, mode: str = "auto", keep_zero_tasks: bool = False, max_entities: int | None = None) -> DataFrame:
    """Match tasks with their reduce task."""
    if plan.two_source:
        found = sub_block.match_tasks_two_source(plan.cells, plan.profile, plan.r, plan.total)
    else:
        found = sub_block.match_tasks(plan.cells, plan.profile, plan.r, plan.total, keep_zero_tasks, max_entities)
    return schedule.greedy(found, plan.r, mode)


def routed(plan: Plan, strategy: str, cut: str = "proportional", relevance: str = "exact", mode: str = "auto") -> DataFrame:
    """The rows that leave the map side."""
    if strategy == "whole_block":
        return whole_block.route(plan.records, plan.r)
    if strategy == "sub_block":
        return sub_block.route(plan.records, plan.cells, tasks(plan, mode))
    if plan.two_source:
        return pair_interval.route_two_source(indexed(plan), plan.total, plan.r, cut)
    return pair_interval.route(indexed(plan), plan.total, plan.r, cut, relevance)


def indexed(plan: Plan) -> DataFrame:
    """Records of blocks with a pair, with their place in the block and the block's numbers."""
    return pair_interval.with_entity_index(plan.records, plan.cells, plan.two_source, plan.profile)


def pairs(plan: Plan, strategy: str, cut: str = "proportional", relevance: str = "exact", roles: bool = True, attrs: bool = False, mode: str = "auto") -> DataFrame:
    """(left_id, right_id, ..., reduce_ix): every pair inside a block once."""
    if strategy == "whole_block":
        return (whole_block.pairs_two_source if plan.two_source else whole_block.pairs)(plan.records, plan.r, attrs)
    if strategy == "sub_block":
        rows = routed(plan, strategy, mode=mode)
        return (sub_block.pairs_two_source if plan.two_source else sub_block.pairs)(rows, plan.r, attrs)
    if strategy != "pair_interval":
        raise ValueError(f"unknown strategy {strategy}")
    if plan.two_source:
        return pair_interval.pairs_two_source(routed(plan, strategy, cut), plan.r, attrs)
    if roles:
        return pair_interval.pairs(*pair_interval.route_roles(indexed(plan), plan.total, plan.r, cut), plan.r, attrs)
    rows = routed(plan, strategy, cut, relevance)
    return pair_interval.pairs(rows, rows, plan.r, attrs)


def task_loads(plan: Plan, strategy: str, cut: str = "proportional", mode: str = "auto") -> DataFrame:
    """(reduce_ix, pairs) of all r reduce tasks, from the first stage alone."""
    spark = plan.cells.sparkSession
    every = spark.range(plan.r).select(F.col("id").cast("int").alias("reduce_ix"))
    if strategy == "pair_interval":
        low, high = interval_bounds(F.col("reduce_ix"), plan.total, plan.r, cut)
        return every.select("reduce_ix", F.greatest(high - low + 1, F.lit(0)).cast("long").alias("pairs"))
    if strategy == "whole_block":
        placed = plan.profile.select(whole_block.home(F.col("block_key"), plan.r).alias("reduce_ix"), "pairs")
    else:
        placed = tasks(plan, mode).select("reduce_ix", "pairs")
    sums = placed.groupBy("reduce_ix").agg(F.sum("pairs").alias("pairs"))
    return every.join(sums, "reduce_ix", "left").select("reduce_ix", F.coalesce("pairs", F.lit(0)).cast("long").alias("pairs"))


def compared(found: DataFrame, tenths: int = 8, matcher: Callable[[Column, Column], Column] | None = None, threshold: float = 0.8) -> DataFrame:
    """(left_id, right_id, distance, similarity) of the pairs that match; distance is null for a matcher of one's own."""
    a, b = F.col("left_attr"), F.col("right_attr")
    if matcher is not None:
        rows = found.withColumn("similarity", matcher(a, b)).where(F.col("similarity") >= threshold)
        return rows.select("left_id", "right_id", F.lit(None).cast("int").alias("distance"), "similarity")
    rows = found.withColumn("distance", edit_distance_within(a, b, tenths)).where("distance IS NOT NULL")
    longest = F.greatest(F.length(a), F.length(b))
    return rows.select("left_id", "right_id", "distance", F.when(longest == 0, F.lit(1.0)).otherwise(1 - F.col("distance") / longest).alias("similarity"))


def match(df: DataFrame, strategy: str = "pair_interval", r: int = 8, m: int = 8, cut: str = "proportional", relevance: str = "exact", roles: bool = True, kind: str = "mod", missing_keys: str = "error", tenths: int = 8, matcher=None, threshold: float = 0.8, compare: bool = True, pieces: str = "input", reducer: str = "native", attrs: bool = True) -> DataFrame:
    """Matches of one source. df has entity_id, attr and block_key.

    Records without a key are an error, left out (``drop``), or compared with all others (``all_pairs``).
    ``compare=False`` gives the pairs, without texts if not ``attrs``. ``reducer="arrow"`` runs the sub-block reduce step as a Python function over
    the sorted rows of each task, for comparisons that no expression can state.
    """
    if missing_keys == "error" and not df.where("block_key IS NULL").isEmpty():
        raise ValueError("records without a key; say missing_keys='drop' or 'all_pairs'")
    attrs = attrs or compare
    if missing_keys == "all_pairs":
        from . import nullkeys

        found = nullkeys.pairs_one_source(df, strategy, r, m)
    else:
        plan = first_stage(layout.with_partition(df.where("block_key IS NOT NULL"), m, kind), r, pieces=pieces)
        if reducer == "arrow":
            from .arrow_reduce import pairs_by_stream

            found = pairs_by_stream(routed(plan, "sub_block"), r, attrs=attrs)
        else:
            found = pairs(plan, strategy, cut, relevance, roles, attrs)
    return compared(found, tenths, matcher, threshold) if compare else found


def match_two_source(df: DataFrame, strategy: str = "pair_interval", r: int = 8, m: int = 8, tenths: int = 8, cut: str = "proportional", compare: bool = True, missing_keys: str = "drop") -> DataFrame:
    """Matches of R with S. df has source besides; partitions of S are numbered behind those of R."""
    if missing_keys == "all_pairs":
        from . import nullkeys

        found = nullkeys.pairs_two_source(df, strategy, r, m)
    else:
        plan = first_stage(two_source_layout(df.where("block_key IS NOT NULL"), m, m), r, two_source=True)
        found = pairs(plan, strategy, cut, attrs=True)
    return compared(found, tenths) if compare else found


def two_source_layout(df: DataFrame, m_r: int, m_s: int) -> DataFrame:
    """df with part_ix: 0..m_r-1 for R, and m_r..m_r+m_s-1 for S."""
    of_r = F.col("source") == "R"
    return df.withColumn("part_ix", F.when(of_r, F.pmod("entity_id", F.lit(m_r))).otherwise(F.pmod("entity_id", F.lit(m_s)) + m_r).cast("int"))


def copies(plan: Plan, strategy: str, cut: str = "proportional") -> int:
    """Rows that will leave the map side, from cells and profile alone."""
    of = lambda df, c: int(df.agg(F.coalesce(F.sum(c), F.lit(0))).first()[0])
    if strategy == "whole_block":
        return of(plan.cells, "n")
    if strategy == "pair_interval":
        return pair_interval.copies(plan.profile, plan.total, plan.r, cut)
    heavy = F.broadcast(sub_block.heavy_blocks(plan.profile, plan.r, plan.total).select("block_ix"))
    cells = plan.cells.join(heavy, "block_ix", "left_semi")
    pieces = cells.groupBy("block_ix").agg(F.count("*").alias("pieces"))
    split = cells.join(F.broadcast(pieces), "block_ix").select((F.col("n") * (F.col("pieces") - 1 + (F.col("n") > 1).cast("int"))).alias("n"))
    return of(split, "n") + of(plan.profile.where("pairs > 0").join(heavy, "block_ix", "left_anti"), "n")


def advise(plan: Plan, most_pairs: int = 10**15) -> dict:
    """Which strategy to take, from the first stage alone: no record is read.

    Of the strategies whose largest load is within a tenth of the average, the one that moves the fewest rows. Sub-block
    splitting is among them when the input order does not follow the key; even intervals always are. ``finer_key`` says
    that there are more pairs than can be compared.
    """
    largest = lambda s: int(task_loads(plan, s).agg(F.max("pairs")).first()[0] or 0)
    strategies = ("whole_block", "sub_block", "pair_interval")
    mean = plan.total / plan.r if plan.r else 0
    loads, moved = {s: largest(s) for s in strategies}, {s: copies(plan, s) for s in strategies}
    good = [s for s in strategies if loads[s] <= 1.1 * mean + 1] or ["pair_interval"]
    return {"strategy": min(good, key=moved.__getitem__), "largest": loads, "copies": moved, "mean": math.ceil(mean), "finer_key": plan.total > most_pairs}
