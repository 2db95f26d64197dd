"""Column names and types that the methods share."""

from __future__ import annotations

from pyspark.sql.types import IntegerType, LongType, StringType, StructField, StructType

#: What every method reads. block_key is null for a record without a key; source is R or S when two sources are matched.
ENTITIES = StructType([
    StructField("entity_id", LongType()),
    StructField("attr", StringType()),
    StructField("block_key", StringType()),
    StructField("source", StringType()),
    StructField("part_ix", IntegerType()),
])
#: A match task: a whole block (hi = lo = WHOLE), a piece with itself (hi = lo), or two pieces (hi > lo).
TASKS = StructType([
    StructField("block_ix", LongType()),
    StructField("hi", IntegerType()),
    StructField("lo", IntegerType()),
    StructField("pairs", LongType()),
])
WHOLE = -1
CUTS = ("proportional", "ceiling")
RELEVANCE = ("exact", "span")
STRATEGIES = ("whole_block", "sub_block", "pair_interval")
