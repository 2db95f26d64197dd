"""Blocking keys and the entity table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def prefix_key(column: str | Column, length: int = 3) -> Column:
    """The first characters of a trimmed text in lower case; a longer prefix gives smaller blocks and loses matches."""
    c = F.col(column) if isinstance(column, str) else column
    return F.lower(F.left(F.trim(c), F.lit(length)))


def strict(key: Column, length: int = 3) -> Column:
    """The key where it consists of ASCII letters alone, else null."""
    return F.when(key.rlike(f"^[a-z]{{{length}}}$"), key)


def constant_key() -> Column:
    """One key for all records: a single block of all pairs."""
    return F.lit("*")


def with_block_key(df: DataFrame, key: Column, policy: str = "as_is", length: int = 3) -> DataFrame:
    """df with block_key; the strict policy leaves records of odd keys without one."""
    if policy not in ("as_is", "strict"):
        raise ValueError(f"unknown policy {policy}")
    return df.withColumn("block_key", key if policy == "as_is" else strict(key, length))


def entities(df: DataFrame, entity_id: Column, attr: Column, key: Column, policy: str = "as_is", source: Column | None = None) -> DataFrame:
    """(entity_id, attr, block_key[, source]) of a table: the narrow rows that the methods move; join the rest back later."""
    columns = [entity_id.cast("long").alias("entity_id"), attr.alias("attr"), (key if policy == "as_is" else strict(key)).alias("block_key")]
    return df.select(*columns, *([] if source is None else [source.alias("source")]))
