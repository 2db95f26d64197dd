"""Places of regular expressions in texts, as native expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SPANS = "array<struct<start: int, end: int, hit: string>>"


def found(text: Column, pattern: str | Column, gate: Column | None = None) -> Column:
    """All matches from the left as structs (start, end, hit), in code points, end exclusive.

    The texts between the matches, from split(), give the distances between them. The gate must hold wherever
    there is a match; rows that fail it are not searched.
    """
    pattern = F.lit(pattern) if isinstance(pattern, str) else pattern
    hits = F.regexp_extract_all(text, pattern, F.lit(0))
    gaps = F.split(text, pattern, -1)
    pairs = F.zip_with(hits, F.slice(gaps, 1, F.size(hits)), lambda h, g: F.struct(h.alias("hit"), F.length(g).alias("gap")))
    nothing = F.from_json(F.lit('{"at": 0, "spans": []}'), f"struct<at: int, spans: {SPANS}>")

    def step(state: Column, x: Column) -> Column:
        start = state.at + x.gap
        end = start + F.length(x.hit)
        span = F.struct(start.alias("start"), end.alias("end"), x.hit.alias("hit"))
        return F.struct(end.alias("at"), F.concat(state.spans, F.array(span)).alias("spans"))

    placed = F.aggregate(pairs, nothing, step, lambda s: s.spans)
    present = F.regexp_like(text, pattern) if gate is None else gate & F.regexp_like(text, pattern)
    return F.when(present, placed).otherwise(F.from_json(F.lit("[]"), SPANS))
