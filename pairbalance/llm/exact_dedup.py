"""Exact deduplication with a heavy-hitter split.

Each text is reduced to a digest of itself without white space. Misra-Gries summaries of the digests,
one of a fixed number of counters per task, name the digests that may be frequent. Their groups are
counted exactly, and the winners (at most ``counters`` rows) are broadcast, so that rows of hot groups
are settled where they are read. The other digests, none of which is frequent, are shuffled as usual.

Defined results: a null text is the empty text; of rows that tie in length the smallest id stays;
repeated rows of the winning id all count as kept; an id may have several texts, each of which belongs to its own
group; null ids lose against any other id; texts of any length are read whole; an empty table gives an empty result;
other columns of the input are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, filled

COUNTERS = 512


class FrequentItems:
    """A Misra-Gries summary: any item seen more than total / (counters + 1) times keeps a counter."""

    def __init__(self, counters: int):
        self.counters, self.held = counters, {}

    def add(self, items: list, counts: list[int]) -> None:
        held = self.held
        for item, count in zip(items, counts, strict=True):
            held[item] = held.get(item, 0) + count
        if len(held) > self.counters:
            cutoff = sorted(held.values(), reverse=True)[self.counters]
            self.held = {k: v - cutoff for k, v in held.items() if v > cutoff}


def digest_of(text: Column) -> Column:
    """SHA-256 of the text without ASCII white space."""
    return F.unhex(F.sha2(F.regexp_replace(text, r"[ \t-\r]+", ""), 256))


def digests(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(id, digest, points): SHA-256 of the text without ASCII white space, and the text's code points."""
    text = filled(text_column)
    return docs.select(
        F.col(id_column).alias("id"),
        digest_of(text).alias("digest"),
        F.length(text).alias("points"),
    )


def frequent_digests(table: DataFrame, counters: int = COUNTERS) -> DataFrame:
    """At most ``counters`` digests, among them every one with more than a 1/counters share of the rows of some task."""

    def summarise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        summary = FrequentItems(counters)
        for batch in batches:
            seen = pc.value_counts(batch.column(0))
            summary.add(seen.field(0).to_pylist(), seen.field(1).to_pylist())
        if summary.held:
            yield pa.RecordBatch.from_arrays(
                [pa.array(list(summary.held), pa.binary()), pa.array(list(summary.held.values()), pa.int64())], ["digest", "seen"]
            )

    merged = table.select("digest").mapInArrow(summarise, "digest binary, seen long").groupBy("digest").agg(F.sum("seen").alias("seen"))
    return merged.where("seen > 1").orderBy(F.desc("seen"), "digest").limit(counters).select("digest")


def _winner():
    return F.max(F.struct(F.col("points"), F.col("id").isNotNull().alias("has"), (-F.col("id")).alias("neg")))


def groups(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", counters: int = COUNTERS) -> DataFrame:
    """One row per input row: id, digest, keep_id, group_size."""
    table = cut(digests(docs, id_column, text_column), "digests")
    hot = F.broadcast(frequent_digests(table, counters))
    settled = table.join(hot, "digest").groupBy("digest").agg(_winner().alias("w"), F.count("*").alias("group_size"))
    settled = cut(settled.select(F.col("digest").alias("hot_digest"), (-F.col("w.neg")).alias("keep_id"), "group_size"), "winners")
    split = table.join(F.broadcast(settled), F.col("digest") == F.col("hot_digest"), "left")
    heavy = split.where(F.col("hot_digest").isNotNull()).select("id", "digest", "keep_id", "group_size")
    same = Window.partitionBy("digest")
    rest = split.where(F.col("hot_digest").isNull()).select("id", "digest", "points")
    rest = rest.withColumns({"w": _winner().over(same), "group_size": F.count("*").over(same)})
    return heavy.unionByName(rest.select("id", "digest", (-F.col("w.neg")).alias("keep_id"), "group_size"))


def exact_groups(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", counters: int = COUNTERS) -> DataFrame:
    """groups() with the kept flag and the digest as lower-case hex."""
    return groups(docs, id_column, text_column, counters).select(
        F.col("id").alias("doc_id"),
        "keep_id",
        "group_size",
        F.col("id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def deduplicate(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", counters: int = COUNTERS) -> DataFrame:
    """The rows of docs whose id wins the group of their text, with all their columns. Rows are told apart by id and
    digest: of two texts under one id, one may go and the other stay."""
    lost = groups(docs, id_column, text_column, counters).where(~F.col("id").eqNullSafe(F.col("keep_id")))
    lost = lost.select(F.col("id").alias("__lost"), F.col("digest").alias("__digest")).distinct()
    same = docs[id_column].eqNullSafe(F.col("__lost")) & (digest_of(filled(docs[text_column])) == F.col("__digest"))
    return docs.join(lost, same, "left_anti")
