"""Streams (an extension: the methods are stated for static tables)."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..storage import shared_folder


def instants(df: DataFrame, column: str = "ts") -> DataFrame:
    """Watermarks need instants: a time without a zone is read in the session's."""
    return df.withColumn(column, F.col(column).cast("timestamp"))


def matrix(stream: DataFrame, key: Column, part: Column) -> DataFrame:
    """Running counts by block and partition; use it with the update or complete mode."""
    return stream.select(key.alias("block_key"), part.cast("int").alias("part_ix")).where("block_key IS NOT NULL").groupBy("block_key", "part_ix").agg(F.count("*").alias("n"))


def with_lateness(stream: DataFrame, delay: str, column: str = "ts") -> DataFrame:
    """Rows older than the newest by more than the delay may be dropped, and are counted in the query's progress."""
    return stream.withWatermark(column, delay)


def windowed(stream: DataFrame, keys: list[str], kind: str = "tumbling", size: str = "1 day", slide: str | None = None, gap: str = "1 hour", column: str = "ts") -> DataFrame:
    """Counts by keys and window: tumbling, sliding or session."""
    w = F.session_window(column, gap) if kind == "session" else F.window(column, size, slide if kind == "sliding" else None)
    counted = stream.groupBy(w.alias("w"), *keys).agg(F.count("*").alias("n"))
    return counted.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n")


def dedup(stream: DataFrame, keys: list[str]) -> DataFrame:
    """The first of exact repeats within the watermark."""
    return stream.dropDuplicatesWithinWatermark(keys)


def join_static(stream: DataFrame, table: DataFrame, on: list[str]) -> DataFrame:
    return stream.join(table, on)


def join_interval(left: DataFrame, right: DataFrame, on: str, span: str, left_time: str = "ts", right_time: str = "ts") -> DataFrame:
    """Rows of two streams of equal key where right follows left within a span; both need a watermark."""
    a, b = left.alias("a"), right.alias("b")
    test = (F.col(f"a.{on}") == F.col(f"b.{on}")) & (F.col(f"b.{right_time}") >= F.col(f"a.{left_time}")) & (F.col(f"b.{right_time}") <= F.col(f"a.{left_time}") + F.expr(f"INTERVAL {span}"))
    return a.join(b, test)


def block_state(stream: DataFrame, schema: str = "block_key string, records long, pairs long") -> DataFrame:
    """Records and pairs of each block so far, kept as state. stream has block_key."""

    def update(key: tuple, frames, state):
        n = state.get[0] if state.exists else 0
        n += sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"block_key": [key[0]], "records": [n], "pairs": [n * (n - 1) // 2]})

    return stream.select("block_key").groupBy("block_key").applyInPandasWithState(update, schema, "records long", "update", "NoTimeout")


def match_increment(stored: DataFrame, batch: DataFrame, r: int, m: int = 4, tenths: int = 8) -> DataFrame:
    """Matches that a batch of new records adds: stored with new ones across, and new ones among themselves."""
    from ..plans import engine

    columns = ["entity_id", "attr", "block_key"]
    both = stored.select(*columns, F.lit("R").alias("source")).unionByName(batch.select(*columns, F.lit("S").alias("source")))
    across = engine.match_two_source(both, "sub_block", r, m, tenths)
    return across.unionByName(engine.match(batch.select(*columns), "sub_block", r, m, missing_keys="drop", tenths=tenths))


def match_stream(stream: DataFrame, stored_path: str, out_path: str, r: int) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function: match each batch with those stored before it, then store it. Both are written under the
    batch's number, so a batch that is replayed gives the same tables."""

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch = batch.persist()
        try:
            earlier = [f"{stored_path}/batch={k}" for k in range(number)]
            stored = spark.read.schema(batch.schema).parquet(*earlier) if earlier else batch.limit(0)
            match_increment(stored, batch, r).write.mode("overwrite").parquet(f"{out_path}/batch={number}")
            batch.write.mode("overwrite").parquet(f"{stored_path}/batch={number}")
        finally:
            batch.unpersist()

    return step


def finish(stream: DataFrame, name: str, mode: str = "complete"):
    """Run a stream over all that is there and give the table of its result and its progress reports: the last table of
    complete results, or all that was appended or updated. It is kept as Parquet in the shared folder."""
    spark = stream.sparkSession
    place = f"{shared_folder(spark)}/streams/{name}"
    done: set[int] = set()

    def store(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{place}/out/batch={number}")
        done.add(number)

    query = stream.writeStream.foreachBatch(store).outputMode(mode).option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    if not done:
        return spark.createDataFrame([], stream.schema), query.recentProgress
    last = [max(done)] if mode == "complete" else sorted(done)
    return spark.read.schema(stream.schema).parquet(*(f"{place}/out/batch={k}" for k in last)), query.recentProgress
