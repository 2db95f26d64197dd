"""Comparison of two attributes, as native expressions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

Measure = Callable[[Column, Column], Column]


def _longest(a: Column, b: Column) -> Column:
    return F.greatest(F.length(a), F.length(b))


def edit_distance_within(a: Column, b: Column, tenths: int = 8) -> Column:
    """The edit distance where 1 - distance / longer length is at least tenths / 10, else null.

    All in whole numbers: the bound keeps the distance to a band, and equal texts and lengths that differ by more skip it.
    """
    bound = F.call_function("div", _longest(a, b) * (10 - tenths), F.lit(10)).cast("int")
    near = F.abs(F.length(a) - F.length(b)) <= bound
    d = F.when(a == b, F.lit(0)).when(near, F.call_function("levenshtein", a, b, bound))
    return F.when(d >= 0, d)


def edit_match(a: Column, b: Column, tenths: int = 8) -> Column:
    """Whether the normalised edit similarity reaches the threshold."""
    return edit_distance_within(a, b, tenths).isNotNull()


def edit_similarity(a: Column, b: Column) -> Column:
    return F.when(_longest(a, b) == 0, F.lit(1.0)).otherwise(1.0 - F.levenshtein(a, b) / _longest(a, b))


def edit_similarity_within(tenths: int) -> Measure:
    """The edit similarity where it is at least tenths / 10, else 0: within the bound of edit_distance_within."""

    def bounded(a: Column, b: Column) -> Column:
        d = edit_distance_within(a, b, tenths)
        return F.when(_longest(a, b) == 0, F.lit(1.0)).otherwise(F.coalesce(1.0 - d / _longest(a, b), F.lit(0.0)))

    return bounded


def tokens(a: Column) -> Column:
    return F.array_distinct(F.filter(F.split(F.lower(a), "[^a-z0-9]+"), lambda t: t != ""))


def token_jaccard(a: Column, b: Column) -> Column:
    x, y = tokens(a), tokens(b)
    union = F.size(F.array_union(x, y))
    return F.when(union == 0, F.lit(0.0)).otherwise(F.size(F.array_intersect(x, y)) / union)


def same_sound(a: Column, b: Column) -> Column:
    return (F.soundex(a) == F.soundex(b)).cast("double")


def cosine(a: Column, b: Column) -> Column:
    """Of two arrays of numbers."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda u, v: u.cast("double") * v.cast("double")), F.lit(0.0), lambda s, v: s + v)
    norm = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(norm == 0, F.lit(0.0)).otherwise(dot(a, b) / norm)


def combined(measures: list[Measure], weights: list[float]) -> Measure:
    """The weighted mean of several measures."""
    if len(measures) != len(weights) or not measures:
        raise ValueError("one weight for each measure")

    def mean(a: Column, b: Column) -> Column:
        total = F.lit(0.0)
        for measure, weight in zip(measures, weights, strict=True):
            total = total + measure(a, b) * weight
        return total / sum(weights)

    return mean
