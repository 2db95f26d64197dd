"""Which input partition a record belongs to, and which task a row is sent to."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..storage import cut
from .prefix import running_sums

#: Rows of a table of blocks that is broadcast, at most.
MOST_BROADCAST = 1_000_000

def with_partition(df: DataFrame, m: int, kind: str = "mod", order_by: list[str] | None = None) -> DataFrame:
    """df with part_ix in 0..m-1: by id, by a hash of it, by order (equal shares of the sorted records), or as read.

    The first three depend on the data alone. ``input`` takes the number of the task that read a row, which a
    later run may change, so its result is written at once.
    """
    if kind == "mod":
        return df.withColumn("part_ix", F.pmod("entity_id", F.lit(m)).cast("int"))
    if kind == "hash":
        return df.withColumn("part_ix", F.pmod(F.xxhash64("entity_id"), F.lit(m)).cast("int"))
    if kind == "ordered":
        ranked, sums = running_sums(df, [*(order_by or ["block_key"]), "entity_id"], {"__rank": F.lit(1).cast("long")})
        n = max(1, sums["__rank"])
        return ranked.withColumn("part_ix", F.expr(f"cast(__rank * {m} div {n} as int)")).drop("__rank")
    if kind == "input":
        return materialise(df.withColumn("part_ix", F.pmod(F.spark_partition_id(), F.lit(m)).cast("int")))
    raise ValueError(f"unknown layout {kind}")


def with_pieces(df: DataFrame, profile: DataFrame, total: int, r: int, grain: int = 4, max_entities: int | None = None) -> DataFrame:
    """df with part_ix as pieces whose number follows the block's pairs and not the input.

    A heavy block gets about sqrt(2 * grain * pairs * r / total) pieces, so each piece pair holds about
    total / (grain * r) pairs and all blocks together give O(grain * r) tasks however many input partitions there are.
    """
    q = F.ceil(F.sqrt(2.0 * grain * r * F.col("pairs").cast("double") / max(1, total)))
    if max_entities:
        q = F.greatest(q, F.ceil(F.col("n") / max_entities))
    pieces = profile.select("block_key", q.cast("int").alias("__q")).where("__q > 1")
    # without a cap on records these are fewer than 2 * grain * r blocks
    pieces = F.broadcast(pieces) if not max_entities or pieces.count() <= MOST_BROADCAST else pieces
    joined = df.drop("part_ix").join(pieces, "block_key", "left")
    return joined.withColumn("part_ix", F.pmod(F.xxhash64("entity_id"), F.coalesce("__q", F.lit(1))).cast("int")).drop("__q")


def materialise(df: DataFrame) -> DataFrame:
    """df as written to the shared folder: the annotated records that the second stage reads."""
    return cut(df, "annotated")


def route(df: DataFrame, r: int, column: str | Column = "reduce_ix") -> DataFrame:
    """Rows to the task that the column numbers, 0..r-1: part of a composite key decides, the rest may group or sort."""
    return df.repartitionById(r, F.col(column) if isinstance(column, str) else column)


def grouped(df: DataFrame, keys: list[str]):
    """Groups within the tasks of a routed table, by keys that contain the routing column."""
    return df.groupBy(*keys)


def spread(df: DataFrame, n: int, how: str = "hash", columns: tuple[str, ...] = ()) -> DataFrame:
    """df over n partitions: merged (coalesce), by hash, or by range of the columns."""
    if how == "coalesce":
        return df.coalesce(n)
    return df.repartitionByRange(n, *columns) if how == "range" else df.repartition(n, *columns)
