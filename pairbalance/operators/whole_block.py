"""Baselines: whole blocks by a hash of their key, all pairs, and salted keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import keys, layout

PAIR = ["left_id", "right_id", "block_key", "reduce_ix"]


def home(key: Column, r: int) -> Column:
    """The task of a block: the first 32 bits of the MD5 of its key, modulo r, which any engine can tell."""
    return (F.conv(F.left(F.md5(key), F.lit(8)), 16, 10).cast("long") % r).cast("int")


def route(df: DataFrame, r: int) -> DataFrame:
    """Records with the task of their block: one copy each."""
    return df.where(F.col("block_key").isNotNull()).withColumn("reduce_ix", home(F.col("block_key"), r))


def pairs(df: DataFrame, r: int, attrs: bool = False) -> DataFrame:
    """All pairs inside blocks; the largest block bounds the slowest task."""
    rows = layout.route(route(df, r), r)
    more = [F.col("a.attr").alias("left_attr"), F.col("b.attr").alias("right_attr")] if attrs else []
    joined = rows.alias("a").hint("merge").join(rows.alias("b"), ["reduce_ix", "block_key"]).where("a.entity_id < b.entity_id")
    return joined.select(F.col("a.entity_id").alias("left_id"), F.col("b.entity_id").alias("right_id"), "block_key", "reduce_ix", *more)


def pairs_two_source(df: DataFrame, r: int, attrs: bool = False) -> DataFrame:
    """All pairs of R and S inside blocks."""
    rows = layout.route(route(df, r), r)
    more = [F.col("a.attr").alias("left_attr"), F.col("b.attr").alias("right_attr")] if attrs else []
    joined = rows.where("source = 'R'").alias("a").hint("merge").join(rows.where("source = 'S'").alias("b"), ["reduce_ix", "block_key"])
    return joined.select(F.col("a.entity_id").alias("left_id"), F.col("b.entity_id").alias("right_id"), "block_key", "reduce_ix", *more)


def all_pairs(df: DataFrame, most: int = 5_000) -> DataFrame:
    """Every pair without blocking: quadratic, so only for tables of a few thousand rows."""
    if (n := df.limit(most + 1).count()) > most:
        raise ValueError(f"more than {n - 1} rows: all pairs are for tiny inputs")
    a, b = df.alias("a"), df.alias("b")
    return a.join(b, F.col("a.entity_id") < F.col("b.entity_id")).select(
        F.col("a.entity_id").alias("left_id"), F.col("b.entity_id").alias("right_id"), F.col("a.attr").alias("left_attr"), F.col("b.attr").alias("right_attr")
    )


def salted(df: DataFrame, q: int) -> DataFrame:
    """All pairs inside blocks over q salts of each key: the larger record is copied to every salt."""
    keyed = df.where(F.col("block_key").isNotNull())
    a = keyed.withColumn("salt", F.pmod(F.xxhash64("entity_id"), F.lit(q)).cast("int"))
    b = keyed.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(q - 1))))
    joined = a.alias("a").hint("merge").join(b.alias("b"), ["block_key", "salt"]).where("a.entity_id < b.entity_id")
    return joined.select(F.col("a.entity_id").alias("left_id"), F.col("b.entity_id").alias("right_id"), "block_key", "salt")


def pairs_adaptive(df: DataFrame) -> DataFrame:
    """All pairs inside blocks by a plain join on the key, so Spark may split a large partition of one side at run time
    (spark.sql.adaptive.skewJoin); it splits by bytes, and every part still meets the whole block."""
    keyed = df.where(F.col("block_key").isNotNull())
    met = keyed.alias("a").hint("merge").join(keyed.alias("b"), "block_key").where("a.entity_id < b.entity_id")
    return met.select(F.col("a.entity_id").alias("left_id"), F.col("b.entity_id").alias("right_id"), "block_key")


def finer_key(df: DataFrame, text_column: str, length: int = 5) -> DataFrame:
    """df with a longer prefix as key: blocks shrink by hand, and matches across the new blocks are lost."""
    return df.withColumn("block_key", keys.prefix_key(text_column, length))
