"""Records without a blocking key: they may match any record, so they are compared with all.

Each case is a union of disjoint parts, so no pair is found twice and nothing has to be made distinct. All-pairs parts
run under one constant key, as a single block that the strategies split like any other heavy block.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import keys, layout

OUT = ["left_id", "right_id", "left_attr", "right_attr"]


def _keyed(df: DataFrame) -> DataFrame:
    return df.where("block_key IS NOT NULL")


def _keyless(df: DataFrame) -> DataFrame:
    return df.where("block_key IS NULL")


def _across(r_rows: DataFrame, s_rows: DataFrame, strategy: str, r: int, m: int) -> DataFrame:
    """All pairs of two sides under the constant key."""
    from . import engine

    both = r_rows.withColumn("source", F.lit("R")).unionByName(s_rows.withColumn("source", F.lit("S"))).withColumn("block_key", keys.constant_key())
    plan = engine.first_stage(engine.two_source_layout(both, m, m), r, two_source=True)
    return engine.pairs(plan, strategy, attrs=True).select(*OUT)


def _within(df: DataFrame, strategy: str, r: int, m: int) -> DataFrame:
    from . import engine

    plan = engine.first_stage(layout.with_partition(df, m), r)
    return engine.pairs(plan, strategy, attrs=True).select(*OUT)


def pairs_one_source(df: DataFrame, strategy: str = "pair_interval", r: int = 8, m: int = 8) -> DataFrame:
    """Blocks, then keyed with keyless records, then keyless records with each other."""
    df = df.select("entity_id", "attr", "block_key")
    inside = _within(_keyed(df), strategy, r, m)
    mixed = _across(_keyed(df), _keyless(df), strategy, r, m)
    swap = F.col("left_id") > F.col("right_id")
    pick = lambda x, y: F.when(swap, F.col(y)).otherwise(F.col(x)).alias(x)
    mixed = mixed.select(pick("left_id", "right_id"), pick("right_id", "left_id"), pick("left_attr", "right_attr"), pick("right_attr", "left_attr"))
    among = _within(_keyless(df).withColumn("block_key", keys.constant_key()), strategy, r, m)
    return inside.unionByName(mixed).unionByName(among)


def pairs_two_source(df: DataFrame, strategy: str = "pair_interval", r: int = 8, m: int = 8) -> DataFrame:
    """Blocks of R and S, then all of R with keyless records of S, then keyless records of R with keyed ones of S."""
    from . import engine

    df = df.select("entity_id", "attr", "block_key", "source")
    plan = engine.first_stage(engine.two_source_layout(_keyed(df), m, m), r, two_source=True)
    inside = engine.pairs(plan, strategy, attrs=True).select(*OUT)
    of = lambda s: df.where(F.col("source") == s).drop("source")
    return inside.unionByName(_across(of("R"), _keyless(of("S")), strategy, r, m)).unionByName(_across(_keyless(of("R")), _keyed(of("S")), strategy, r, m))
