"""Joins in which one key may hold any share of the rows."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Tables of ids or pairs up to this many rows (a few tens of bytes each) are broadcast, larger ones are shuffled.
BROADCAST_ROWS = 1_000_000
#: Rows of one key that a task gets, about.
KEY_ROWS = 256
#: Keys that are dealt out, at most; with more rows the share of a task grows instead.
MOST_HOT = 100_000


def small(df: DataFrame) -> DataFrame:
    """df marked for broadcast where its rows have been counted and are few."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def salts_of(size: Column, rows: int = KEY_ROWS) -> Column:
    """Over how many salts the rows of a key are dealt."""
    return F.ceil(size / rows).cast("int")


def join_salted(left: DataFrame, right: DataFrame, key: str, deal_by: str, left_salts: Column, right_salts: Column, how: str = "inner") -> DataFrame:
    """left with the row of right of its key. Both know the number of salts of a key: rows of left are dealt over them,
    and the row of right is copied to each."""
    dealt = left.withColumn("__salt", F.pmod(F.xxhash64(deal_by), F.greatest(left_salts, F.lit(1))).cast("int"))
    copied = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.greatest(right_salts, F.lit(1)) - 1)))
    return dealt.join(copied, [key, "__salt"], how).drop("__salt")


def join_dealt(left: DataFrame, right: DataFrame, key: str, deal_by: str, sizes: DataFrame, total: int, how: str = "inner") -> DataFrame:
    """The same where sizes (key, size) are of the keys of left, which has ``total`` rows: the keys of many rows, at most
    MOST_HOT, are fetched and broadcast; where there is none this is a plain join."""
    rows = max(KEY_ROWS, math.ceil(total / MOST_HOT))
    hot = sizes.select(key, "size").where(F.col("size") > rows).collect()
    if not hot:
        return left.join(right, key, how)
    table = left.sparkSession.createDataFrame([(k, -(-n // rows)) for k, n in hot], f"{key} long, __salts int")
    salts = F.coalesce("__salts", F.lit(1))
    dealt, copied = (x.join(F.broadcast(table), key, "left") for x in (left, right))
    return join_salted(dealt, copied.withColumnRenamed("__salts", "__copies"), key, deal_by, salts, F.coalesce("__copies", F.lit(1)), how).drop("__salts", "__copies")


def sizes_of(df: DataFrame, key: str) -> DataFrame:
    return df.groupBy(key).agg(F.count("*").alias("size"))


def beside(left: DataFrame, right: DataFrame, key: str, deal_by: str, how: str = "inner") -> DataFrame:
    """left with the row of right of its key: by broadcast where right is small, else dealt out."""
    if right.count() <= BROADCAST_ROWS:
        return left.join(F.broadcast(right), key, how)
    return join_dealt(left, right, key, deal_by, sizes_of(left, key), left.count(), how)
