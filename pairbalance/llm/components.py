"""Connected components of links between ids."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, discard
from .dealt import beside

LINKS = "a long, b long"


class UnionFind:
    """Sets of ids, each under its smallest one."""

    def __init__(self):
        self.above: dict[int, int] = {}

    def root(self, x: int) -> int:
        above = self.above
        top = x
        while above.setdefault(top, top) != top:
            top = above[top]
        while above[x] != top:
            above[x], x = top, above[x]
        return top

    def join(self, x: int, y: int) -> None:
        x, y = self.root(x), self.root(y)
        if x < y:
            self.above[y] = x
        elif y < x:
            self.above[x] = y


def _forests(links: DataFrame) -> DataFrame:
    """The links of each task as stars under their smallest ids: fewer links with the same components."""

    def contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets = UnionFind()
        for batch in batches:
            for x, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                sets.join(x, y)
            if len(sets.above) > 1_000_000:
                yield star(sets)
                sets = UnionFind()
        yield star(sets)

    def star(sets: UnionFind) -> pa.RecordBatch:
        found = [(x, sets.root(x)) for x in list(sets.above) if sets.root(x) != x]
        return pa.RecordBatch.from_arrays([pa.array([p[i] for p in found], pa.int64()) for i in (0, 1)], ["a", "b"])

    return links.select("a", "b").mapInArrow(contract, LINKS)


def components(links: DataFrame) -> DataFrame:
    """(id, component) of every linked id: the smallest id of its component.

    Union-find shortens the links of each task; then, round by round, every set hooks to the smallest set it
    is linked with, chains of hooks are halved until they end, and the links are renamed. The number of sets
    that are left at least halves in a round. Nothing is collected, and a set of any size is dealt out over tasks.
    """
    links = cut(_forests(links).where("a <> b").distinct(), "links")
    labels = cut(links.select(F.col("a").alias("id")).union(links.select("b")).distinct().withColumn("component", F.col("id")), "labels")
    while not links.isEmpty():
        both = links.union(links.select("b", "a"))
        hooks = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("b")).toDF("set", "into")
        hooks = cut(hooks.withColumn("moved", F.lit(True)), "hooks")
        while not hooks.where("moved").isEmpty():
            further = hooks.select(F.col("set").alias("into"), F.col("into").alias("next"))
            jumped = beside(hooks.select("set", "into"), further, "into", "set")
            jumped = cut(jumped.select("set", F.col("next").alias("into"), (F.col("next") != F.col("into")).alias("moved")), "hooks")
            discard(hooks)
            hooks = jumped
        into = hooks.select("set", "into")
        named = beside(labels, into.toDF("component", "into"), "component", "id", "left")
        named = cut(named.select("id", F.coalesce("into", "component").alias("component")), "labels")
        renamed = beside(beside(links, into.toDF("a", "to_a"), "a", "b"), into.toDF("b", "to_b"), "b", "a")
        renamed = cut(renamed.select(F.col("to_a").alias("a"), F.col("to_b").alias("b")).where("a <> b").distinct(), "links")
        for table in (labels, links, hooks):
            discard(table)
        labels, links = named, renamed
    discard(links)
    return labels
