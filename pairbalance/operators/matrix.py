"""Counts of records by block and input partition, and what follows from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..storage import cut as written
from .prefix import dense_index, running_sum, running_sums

WIDE = "decimal(38,0)"


def half(product: Column, wide: bool) -> Column:
    """Half of an even product, exactly; decimals are not divided with div, which wraps."""
    if not wide:
        return F.call_function("div", product, F.lit(2))
    return ((product - product % 2) / F.lit(2).cast("decimal(1,0)")).cast(WIDE)


def block_matrix(df: DataFrame, by_source: bool = False, combine: bool = True, explicit_order: list[str] | None = None) -> DataFrame:
    """(block_key, block_ix[, source], part_ix, n): the non-empty cells; records without a key are left out.

    Counting inside each task before the shuffle is what Spark does anyway; without ``combine`` the single rows are
    moved by their key first.
    """
    keyed = df.where(F.col("block_key").isNotNull())
    if not combine:
        keyed = keyed.repartition("block_key")
    cells = keyed.groupBy("block_key", *(["source"] if by_source else []), "part_ix").agg(F.count("*").alias("n"))
    return with_block_index(cells, explicit_order)


def with_block_index(cells: DataFrame, explicit_order: list[str] | None = None) -> DataFrame:
    """cells with block_ix, the place of the key in byte order or in a given short list."""
    keys = cells.select("block_key").distinct()
    if explicit_order is not None:
        places = F.create_map(*(F.lit(x) for i, k in enumerate(explicit_order) for x in (k, i)))
        index = keys.withColumn("block_ix", F.element_at(places, F.col("block_key")).cast("long"))
    else:
        index = dense_index(keys, ["block_key"], "block_ix")
    rest = [c for c in cells.columns if c != "block_key"]
    return cells.join(index, "block_key").select("block_key", "block_ix", *rest)


def block_profile(matrix: DataFrame, two_source: bool = False, wide: bool = False) -> DataFrame:
    """(block_key, block_ix, n[, n_r, n_s], pairs, first_pair): records, pairs, and pairs of all blocks before.

    With two sources only pairs across count, and blocks that one side lacks are dropped. ``wide`` counts pairs as
    decimals, for blocks of more than some billions of records.
    """
    kind = WIDE if wide else "long"
    n = F.sum("n").cast("long")
    if two_source:
        side = lambda s: F.sum(F.when(F.col("source") == s, F.col("n")).otherwise(0)).cast("long")
        rows = matrix.groupBy("block_key", "block_ix").agg(n.alias("n"), side("R").alias("n_r"), side("S").alias("n_s"))
        rows = rows.where("n_r > 0 AND n_s > 0").withColumn("pairs", (F.col("n_r").cast(kind) * F.col("n_s").cast(kind)).cast(kind))
    else:
        rows = matrix.groupBy("block_key", "block_ix").agg(n.alias("n"))
        size = F.col("n").cast("decimal(19,0)") if wide else F.col("n")
        rows = rows.withColumn("pairs", half(size * (size - 1), wide).cast(kind))
    return running_sum(rows, ["block_ix"], F.col("pairs"), "first_pair")


def cells_and_profile(df: DataFrame, by_source: bool = False) -> tuple[DataFrame, DataFrame, int]:
    """block_matrix() in byte order of the keys, block_profile() and all pairs, with one pass over the order for both the
    index and the pairs before. Blocks without a pair keep their index; with two sources the profile drops them."""
    side = ["source"] if by_source else []
    counted = written(df.where(F.col("block_key").isNotNull()).groupBy("block_key", *side, "part_ix").agg(F.count("*").alias("n")), "counts")
    if by_source:
        of = lambda s: F.sum(F.when(F.col("source") == s, F.col("n")).otherwise(0)).cast("long")
        sizes = counted.groupBy("block_key").agg(F.sum("n").cast("long").alias("n"), of("R").alias("n_r"), of("S").alias("n_s"))
        sizes = sizes.withColumn("pairs", F.col("n_r") * F.col("n_s"))
    else:
        sizes = counted.groupBy("block_key").agg(F.sum("n").cast("long").alias("n")).withColumn("pairs", half(F.col("n") * (F.col("n") - 1), False))
    indexed, totals = running_sums(sizes, ["block_key"], {"block_ix": F.lit(1).cast("long"), "first_pair": F.col("pairs")})
    sized = [c for c in sizes.columns if c not in ("block_key", "pairs")]
    every = written(indexed.select("block_key", "block_ix", *sized, "pairs", "first_pair"), "profile")
    cells = written(counted.join(every.select("block_key", "block_ix"), "block_key").select("block_key", "block_ix", *side, "part_ix", "n"), "cells")
    return cells, every.where("pairs > 0") if by_source else every, totals["first_pair"]


def total_pairs(profile: DataFrame) -> int:
    """All pairs: one number that comes to the driver."""
    return int(profile.agg(F.coalesce(F.sum("pairs"), F.lit(0))).first()[0])


def cell_prefix(matrix: DataFrame, by_source: bool = False) -> DataFrame:
    """Each cell with the records of its block (and source) in earlier partitions."""
    w = Window.partitionBy("block_ix", *(["source"] if by_source else [])).orderBy("part_ix").rowsBetween(Window.unboundedPreceding, -1)
    return matrix.withColumn("before", F.coalesce(F.sum("n").over(w), F.lit(0)).cast("long"))
