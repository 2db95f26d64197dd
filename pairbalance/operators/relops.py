"""Relational operators that users of the methods need around them: thin and named."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def project(df: DataFrame, **columns: Column) -> DataFrame:
    return df.select(*(c.alias(name) for name, c in columns.items()))


def where(df: DataFrame, *tests: Column | str) -> DataFrame:
    """Rows that pass all tests; simple ones reach the Parquet scan."""
    for test in tests:
        df = df.where(test)
    return df


def join_hash(a: DataFrame, b: DataFrame, on: list[str], how: str = "inner") -> DataFrame:
    return a.join(b.hint("shuffle_hash"), on, how)


def join_merge(a: DataFrame, b: DataFrame, on: list[str], how: str = "inner") -> DataFrame:
    return a.join(b.hint("merge"), on, how)


def join_broadcast(a: DataFrame, b: DataFrame, on: list[str], most: int = 100_000, how: str = "inner") -> DataFrame:
    """b is broadcast if it has at most ``most`` rows, else joined as usual."""
    small = b.limit(most + 1).count() <= most
    return a.join(F.broadcast(b) if small else b, on, how)


def join_theta(a: DataFrame, b: DataFrame, test: Column) -> DataFrame:
    """Any condition: every row with every row, so for small sides."""
    return a.crossJoin(b).where(test)


def join_between(points: DataFrame, point: str, spans: DataFrame, low: str, high: str, bucket: int) -> DataFrame:
    """Points inside spans [low, high]: both meet in buckets of a fixed width."""
    a = points.withColumn("__b", F.floor(F.col(point) / bucket))
    b = spans.withColumn("__b", F.explode(F.sequence(F.floor(F.col(low) / bucket), F.floor(F.col(high) / bucket))))
    return a.join(b, "__b").where(F.col(point).between(F.col(low), F.col(high))).drop("__b")


def join_overlap(a: DataFrame, b: DataFrame, bucket: int) -> DataFrame:
    """Spans (a_low, a_high) with spans (b_low, b_high) that share a number; each pair once, in its first common bucket."""
    cover = lambda df, p: df.withColumn("__b", F.explode(F.sequence(F.floor(F.col(f"{p}_low") / bucket), F.floor(F.col(f"{p}_high") / bucket))))
    met = cover(a, "a").join(cover(b, "b"), "__b").where("a_low <= b_high AND b_low <= a_high")
    return met.where(F.col("__b") == F.floor(F.greatest("a_low", "b_low") / bucket)).drop("__b")


def join_asof(left: DataFrame, right: DataFrame, on: str, time: str, value: str, out: str) -> DataFrame:
    """Each row of left with the latest value of right at or before its time: one shuffle and one sort, no join."""
    marked = left.withColumns({out: F.lit(None).cast(right.schema[value].dataType), "__left": F.lit(1)})
    other = right.select(*(F.col(c) if c in (on, time) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns), F.col(value).alias(out), F.lit(0).alias("__left"))
    w = Window.partitionBy(on).orderBy(time, "__left").rowsBetween(Window.unboundedPreceding, 0)
    return marked.unionByName(other).withColumn(out, F.last(out, ignorenulls=True).over(w)).where("__left = 1").drop("__left")


def join_outer(a: DataFrame, b: DataFrame, on: list[str], how: str = "full") -> DataFrame:
    return a.join(b, on, how)


def join_semi(a: DataFrame, b: DataFrame, on: list[str]) -> DataFrame:
    return a.join(b, on, "left_semi")


def join_anti(a: DataFrame, b: DataFrame, on: list[str]) -> DataFrame:
    return a.join(b, on, "left_anti")


def agg_hash(df: DataFrame, keys: list[str], **aggregates: Column) -> DataFrame:
    return df.groupBy(*keys).agg(*(c.alias(name) for name, c in aggregates.items()))


def agg_sort(df: DataFrame, keys: list[str], column: str) -> DataFrame:
    """Least and greatest text of each group: such buffers are sorted and not hashed."""
    return df.groupBy(*keys).agg(F.min(column).alias("least"), F.max(column).alias("greatest"))


def distinct_counts(df: DataFrame, column: str, approximate: bool = False) -> DataFrame:
    return df.agg((F.approx_count_distinct(column) if approximate else F.count_distinct(column)).alias("n"))


def agg_cube(df: DataFrame, keys: list[str], total: Column, how: str = "cube") -> DataFrame:
    """Totals by every subset (cube) or every prefix (rollup) of the keys, with the number of the grouping."""
    return getattr(df, how)(*keys).agg(total.alias("total"), F.grouping_id().cast("long").alias("level"))


def matrix_dense(cells: DataFrame, m: int) -> DataFrame:
    """A small matrix with a column for each of m partitions."""
    wide = cells.groupBy("block_ix").pivot("part_ix", list(range(m))).sum("n").na.fill(0)
    return wide.toDF("block_ix", *(f"p{i}" for i in range(m)))


def matrix_long(wide: DataFrame) -> DataFrame:
    """Back to non-empty cells."""
    columns = [c for c in wide.columns if c != "block_ix"]
    return wide.unpivot("block_ix", columns, "part", "n").where("n > 0").select("block_ix", F.substring("part", 2, 9).cast("int").alias("part_ix"), "n")


def agg_collect(df: DataFrame, keys: list[str], value: str, by: str) -> DataFrame:
    """Of each group the value at the greatest by, the sorted distinct values, and the exact median of by."""
    return df.groupBy(*keys).agg(F.max_by(value, by).alias("top"), F.array_join(F.array_sort(F.collect_set(F.col(value).cast("string"))), ",").alias("all_values"), F.percentile(by, 0.5).alias("median"))


def win_rank(df: DataFrame, by: list[str], order: list[Column]) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumns({"place": F.row_number().over(w), "rank": F.rank().over(w), "dense": F.dense_rank().over(w), "quarter": F.ntile(4).over(w), "share": F.percent_rank().over(w)})


def win_analytic(df: DataFrame, by: list[str], order: list[str], value: str) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return df.withColumns({"before": F.lag(value).over(w), "behind": F.lead(value).over(w), "first_value": F.first(value).over(whole), "last_value": F.last(value).over(whole), "second_value": F.nth_value(value, 2).over(whole)})


def win_frames(df: DataFrame, by: list[str], rows_order: str, seconds: Column, span: int) -> DataFrame:
    """Rows before within the group, and rows of the last span seconds."""
    rows = Window.partitionBy(*by).orderBy(rows_order).rowsBetween(Window.unboundedPreceding, -1)
    ranged = Window.partitionBy(*by).orderBy("__s").rangeBetween(-span, 0)
    return df.withColumn("__s", seconds).withColumns({"rows_before": F.count("*").over(rows), "recent": F.count("*").over(ranged)}).drop("__s")


def sort_global(df: DataFrame, *order: Column | str) -> DataFrame:
    return df.orderBy(*order)


def sort_local(df: DataFrame, *order: Column | str) -> DataFrame:
    return df.sortWithinPartitions(*order)


def top_k(df: DataFrame, k: int, *order: Column) -> DataFrame:
    """The first k rows: each task keeps k, so no full sort."""
    return df.orderBy(*order).limit(k)


def top_k_per(df: DataFrame, by: list[str], k: int, *order: Column) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)


def union_all(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b, allowMissingColumns=True)


def set_ops(a: DataFrame, b: DataFrame, how: str) -> DataFrame:
    """intersect, intersectAll, subtract or exceptAll."""
    return getattr(a, how)(b)


def sample(df: DataFrame, fraction: float, seed: int = 0) -> DataFrame:
    return df.sample(False, fraction, seed)
