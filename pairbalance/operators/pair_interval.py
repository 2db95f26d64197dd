"""Pair-interval balancing: all pairs are numbered, and the numbers are cut into r intervals of equal size.

A record goes to the intervals that hold a pair of it. Which these are follows from the record's place in its block and
from the block's size and first pair number alone. Those come with the record's cell (block and input partition), so no
step ahead of the routing brings a whole block together.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import layout
from .matrix import cell_prefix
from .numbering import cell, cell_two_source, column_start, interval_bounds, interval_of, uncell


def with_entity_index(df: DataFrame, matrix: DataFrame, by_source: bool = False, profile: DataFrame | None = None) -> DataFrame:
    """Keyed records with block_ix and entity_ix, the place inside the block (and source): partitions one after another,
    by id inside a partition. The window works on one cell at a time. With a profile, its sizes come along, and blocks
    without a pair, which are most blocks of a large table, are left out before any record is moved."""
    side = ["source"] if by_source else []
    before = cell_prefix(matrix, by_source).select("block_key", "block_ix", *side, "part_ix", "before")
    if profile is not None:
        before = before.join(profile.where("pairs > 0").drop("block_key"), "block_ix")
    w = Window.partitionBy("block_key", *side, "part_ix").orderBy("entity_id")
    return df.join(before, ["block_key", *side, "part_ix"]).withColumn("entity_ix", (F.row_number().over(w) - 1 + F.col("before")).cast("long")).drop("before")


def segments(profile: DataFrame, total: int, r: int, cut: str = "proportional") -> DataFrame:
    """One row for each block and interval that meet, at most blocks + r: the first and last pair number inside the
    block, pa and pb, and the pairs (xa, ya) and (xb, yb) of these numbers."""
    span = F.sequence(interval_of(F.col("first_pair"), total, r, cut), interval_of(F.col("first_pair") + F.col("pairs") - 1, total, r, cut))
    rows = _bounded(profile.where("pairs > 0").withColumn("reduce_ix", F.explode(span)), total, r, cut).where("pa <= pb")
    (xa, ya), (xb, yb) = uncell(F.col("pa"), F.col("n")), uncell(F.col("pb"), F.col("n"))
    return rows.withColumns({"xa": xa, "ya": ya, "xb": xb, "yb": yb})


#: Copies of records as the smaller and as the larger of a segment's pairs.
COPIES = (
    "xb - xa + 1 + CASE WHEN xa = xb THEN yb - ya + 1 WHEN xb - xa = 1 THEN n - ya + greatest(0, least(yb, ya - 1) - xb)"
    " ELSE n - xa - 2 + CAST(ya = xa + 1 AS INT) END"
)


def copies(profile: DataFrame, total: int, r: int, cut: str = "proportional") -> int:
    """How many copies of records route_roles() makes, from the profile alone."""
    rows = segments(profile, total, r, cut).agg(F.coalesce(F.sum(F.expr(COPIES)), F.lit(0)))
    return int(rows.first()[0])


def _bounded(rows: DataFrame, total: int, r: int, cut: str) -> DataFrame:
    """rows with pa and pb, the first and the last pair number of the block in the interval."""
    low, high = interval_bounds(F.col("reduce_ix"), total, r, cut)
    return rows.withColumns({"pa": F.greatest(low - F.col("first_pair"), F.lit(0)), "pb": F.least(high - F.col("first_pair"), F.col("pairs") - 1)})


class _Place:
    """Expressions of a record at place e of a block of n records of one source."""

    def __init__(self, total: int, r: int, cut: str):
        self.total, self.r, self.cut = total, r, cut
        self.width = total // r  # no interval but the last is narrower
        self.e, self.n = F.col("entity_ix"), F.col("n")

    def of(self, p: Column) -> Column:
        """The interval of a pair number of the block."""
        return interval_of(F.col("first_pair") + p, self.total, self.r, self.cut)

    def through(self, first: Column, last: Column) -> Column:
        return F.sequence(self.of(first), self.of(last))

    def each(self, number, count: Column) -> Column:
        """The intervals of the pairs number(i), i below count."""
        return F.array_distinct(F.transform(F.sequence(F.lit(0).cast("long"), count - 1), lambda i: self.of(number(i))))

    def run(self, first: Column, count: Column) -> Column:
        """The intervals of neighbouring pair numbers; with fewer pairs than intervals, some between them are empty."""
        return F.when(count > 0, self.through(first, first + count - 1) if self.width else self.each(lambda i: first + i, count))

    def apart(self, number, count: Column, gap: Column) -> Column:
        """The intervals of rising pair numbers at most so far apart: all from first to last where an interval is at least
        as wide, else those of the numbers one by one, which only blocks of fewer records than about 2 r need."""
        wide = self.through(number(F.lit(0).cast("long")), number(count - 1))
        return F.when(count > 0, F.when(gap <= self.width, wide).otherwise(self.each(number, count)))

    def as_smaller(self) -> Column:
        return self.run(column_start(self.e, self.n), self.n - 1 - self.e)

    def as_larger(self) -> Column:
        return self.apart(lambda i: cell(i, self.e, self.n), self.e, self.n - 2)

    def span(self) -> Column:
        """All intervals from that of the record's first pair to that of its last."""
        first = F.when(self.e > 0, self.e - 1).otherwise(0)
        last = F.when(self.e < self.n - 1, cell(self.e, self.n - 1, self.n)).otherwise(F.col("pairs") - 1)
        return self.through(first, last)


ROUTED = ["reduce_ix", "block_ix", "entity_ix", "entity_id", "n", "pa", "pb"]


def _copied(indexed: DataFrame, wanted: Column, at: _Place) -> DataFrame:
    """A copy of each record for each wanted interval, with the pair numbers of the block in it."""
    rows = _bounded(indexed.withColumn("reduce_ix", F.explode(wanted)), at.total, at.r, at.cut)
    return rows.select(*(["source", "n_s"] if "n_s" in rows.columns else []), *ROUTED, *(["attr"] if "attr" in rows.columns else []))


def route(indexed: DataFrame, total: int, r: int, cut: str = "proportional", relevance: str = "exact") -> DataFrame:
    """A copy of each record for every interval that it takes part in (exact), or for all from that of its first pair to
    that of its last (span)."""
    at = _Place(total, r, cut)
    if relevance == "span":
        return _copied(indexed, at.span(), at)
    none = F.array().cast("array<int>")
    return _copied(indexed, F.array_union(F.coalesce(at.as_smaller(), none), F.coalesce(at.as_larger(), none)), at)


def route_roles(indexed: DataFrame, total: int, r: int, cut: str = "proportional") -> tuple[DataFrame, DataFrame]:
    """Copies of records as the smaller, and as the larger, record of the interval's pairs."""
    at = _Place(total, r, cut)
    return _copied(indexed, at.as_smaller(), at), _copied(indexed, at.as_larger(), at)


def candidates(smaller: DataFrame, larger: DataFrame, r: int) -> DataFrame:
    """Smaller with larger records of the same interval and block, with the number of the pair inside the block."""
    a = layout.route(smaller, r).alias("a").hint("merge")
    b = layout.route(larger, r).alias("b")
    met = a.join(b, ["reduce_ix", "block_ix"]).where("a.entity_ix < b.entity_ix")
    return met.withColumn("p", cell(F.col("a.entity_ix"), F.col("b.entity_ix"), F.col("a.n")))


def pairs(smaller: DataFrame, larger: DataFrame, r: int, attrs: bool = False) -> DataFrame:
    """(left_id, right_id, block_ix, reduce_ix): the pairs whose number lies in the task's own interval, each once.

    A pair is judged by its number alone; numbers do not rise in the order in which records arrive.
    """
    own = candidates(smaller, larger, r).where("p BETWEEN a.pa AND a.pb")
    swap = F.col("a.entity_id") > F.col("b.entity_id")
    pick = lambda x, y, name: F.when(swap, F.col(y)).otherwise(F.col(x)).alias(name)
    more = [pick("a.attr", "b.attr", "left_attr"), pick("b.attr", "a.attr", "right_attr")] if attrs else []
    return own.select(F.least("a.entity_id", "b.entity_id").alias("left_id"), F.greatest("a.entity_id", "b.entity_id").alias("right_id"), "block_ix", "reduce_ix", *more)


def route_two_source(indexed: DataFrame, total: int, r: int, cut: str = "proportional") -> DataFrame:
    """A copy of each record of R and S for every interval that it takes part in.

    The pairs of a record of R are neighbours in number; those of a record of S lie n_s apart.
    """
    at, n_r, n_s = _Place(total, r, cut), F.col("n_r"), F.col("n_s")
    of_s = at.apart(lambda i: cell_two_source(i, at.e, n_s), n_r, n_s)
    return _copied(indexed, F.when(F.col("source") == "R", at.run(at.e * n_s, n_s)).otherwise(of_s), at)


def pairs_two_source(routed: DataFrame, r: int, attrs: bool = False) -> DataFrame:
    """(left_id of R, right_id of S, block_ix, reduce_ix)."""
    a, b = (layout.route(routed.where(F.col("source") == s), r) for s in "RS")
    met = a.alias("a").hint("merge").join(b.alias("b"), ["reduce_ix", "block_ix"])
    p = cell_two_source(F.col("a.entity_ix"), F.col("b.entity_ix"), F.col("a.n_s"))
    more = [F.col("a.attr").alias("left_attr"), F.col("b.attr").alias("right_attr")] if attrs else []
    return met.where(p.between(F.col("a.pa"), F.col("a.pb"))).select(F.col("a.entity_id").alias("left_id"), F.col("b.entity_id").alias("right_id"), "block_ix", "reduce_ix", *more)
