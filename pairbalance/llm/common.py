"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator
from sys import getsizeof

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType
from pyspark.sql.pandas.types import to_arrow_schema

from ..storage import cut, discard  # noqa: F401  the operators take them from here

#: Rows of an Arrow batch that become Python objects at a time.
SLICE = 512


def filled(column: str | Column) -> Column:
    """A text column with null as the empty text."""
    return F.coalesce(F.col(column) if isinstance(column, str) else column, F.lit(""))


def fold_of(id_column: str, folds: int) -> Column:
    """crc32 of the id as text, modulo folds; null ids go to no fold (-1)."""
    return F.coalesce(F.crc32(F.col(id_column).cast("string")) % folds, F.lit(-1))


def give_back() -> None:
    """Hand memory that Python no longer uses back to the system: workers live on from task to task, and the driver too."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def over_batches(df: DataFrame, schema: StructType | str, fn: Callable[[pa.RecordBatch], pa.RecordBatch]) -> DataFrame:
    """fn over the Arrow batches of df, a bounded number of rows at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE):
                out = fn(batch.slice(at, SLICE))
                if out.num_rows:
                    yield out
        give_back()

    return df.mapInArrow(run, schema)


def map_columns(df: DataFrame, schema: StructType, fn: Callable[[list[pa.Array]], list]) -> DataFrame:
    """Apply fn to the columns of each Arrow batch; it returns the output columns in the order of schema."""
    arrow = to_arrow_schema(schema)

    def apply(batch: pa.RecordBatch) -> pa.RecordBatch:
        out = zip(fn(batch.columns), arrow, strict=True)
        return pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x, f.type) for x, f in out], schema=arrow)

    return over_batches(df, schema, apply)


def filter_rows(df: DataFrame, keep: Callable[[pa.RecordBatch], list[bool]]) -> DataFrame:
    """Keep the rows for which keep(batch) is true; every column passes unchanged."""
    return over_batches(df, df.schema, lambda batch: batch.filter(pa.array(keep(batch), pa.bool_())))


def sample_rows(docs: DataFrame, picked: DataFrame, id_column: str, text_column: str) -> list:
    """(id, text, label) of a bounded set of picked (id, label) rows; picked must have been limited by the caller."""
    chosen = F.broadcast(picked.toDF("__id", "__label"))
    joined = docs.select(F.col(id_column).alias("__doc"), filled(text_column).alias("__text"))
    return joined.join(chosen, F.col("__doc") == F.col("__id")).select("__doc", "__text", "__label").collect()


class Bounded(dict):
    """A cache that computes what it lacks and holds at most twice ``most`` bytes, by the sizes of keys and values. When
    one half is full it becomes the old half, which is still asked, and the old half goes; so frequent entries stay. An
    entry that would take an eighth of a half by itself is not kept."""

    ENTRY = 110  # of a dictionary, for each entry

    def __init__(self, make: Callable, most: int):
        super().__init__()
        self.make, self.most, self.held, self.old = make, most, 0, {}

    def size(self, key, value) -> int:
        return getsizeof(key) + getsizeof(value) + self.ENTRY

    def __missing__(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        took = self.size(key, value)
        if took * 8 <= self.most:
            if self.held + took > self.most:
                self.old, self.held = dict(self), 0
                self.clear()
            self[key] = value
            self.held += took
        return value


_kept: dict[str, object] = {}


def once_per_worker(key: str, make: Callable[[], object]):
    """make() of this key, kept in the Python worker from task to task. Only the last key stays: the caches and models of
    an operator are gone when a worker turns to another."""
    if key not in _kept:
        _kept.clear()
        give_back()
        _kept[key] = make()
    return _kept[key]
