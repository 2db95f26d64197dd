"""Running sums and dense indexes over a total order, in two phases.

A window without partitions would send all rows to one task. Here rows are split by range, each part is summed, the
sums of the parts before are added to a sum inside the part. One number for each part visits the driver.
"""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..storage import cut


def running_sums(df: DataFrame, order: list[str], values: dict[str, Column], parts: int | None = None) -> tuple[DataFrame, dict[str, int]]:
    """df with, for each named value, its sum over all rows before in the given order, which must be total; and the sums
    over all rows. Nulls count as zero."""
    if taken := set(values) & set(df.columns):
        raise ValueError(f"{taken} exist")
    held = {name: f"__{name}" for name in values}
    valued = df.withColumns({held[n]: c for n, c in values.items()})
    # without a number Spark merges small neighbouring ranges at run time, and their order stays
    ranged = valued.repartitionByRange(parts, *order) if parts else valued.repartitionByRange(*order)
    ranged = ranged.withColumn("__range", F.spark_partition_id())
    ranged = cut(ranged, "ranges")  # which part a row is in must not change when it is computed again
    sums = sorted(tuple(r) for r in ranged.groupBy("__range").agg(*(F.coalesce(F.sum(h), F.lit(0)) for h in held.values())).collect())
    inside = Window.partitionBy("__range").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    totals, out = {}, ranged
    for i, (name, h) in enumerate(held.items(), 1):
        before = dict(zip((r[0] for r in sums), accumulate([0, *(r[i] for r in sums)]), strict=False))
        totals[name] = int(sum(r[i] for r in sums))
        kind = ranged.schema[h].dataType
        offset = F.element_at(F.create_map(*(F.lit(x) for k, v in before.items() for x in (k, v))), F.col("__range")) if before else F.lit(0)
        total = F.coalesce(F.sum(h).over(inside), F.lit(0)) + offset
        out = out.withColumn(name, total.cast(kind if kind.typeName() == "decimal" else "long"))
    return out.drop("__range", *held.values()), totals


def running_sum(df: DataFrame, order: list[str], value: Column, name: str, parts: int | None = None) -> DataFrame:
    """df with the sum of value over all rows before, in the given order, which must be total."""
    return running_sums(df, order, {name: value}, parts)[0]


def dense_index(df: DataFrame, order: list[str], name: str, parts: int | None = None) -> DataFrame:
    """df with the number of rows before each row."""
    return running_sum(df, order, F.lit(1).cast("long"), name, parts)
