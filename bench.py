"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from pairbalance.operators import layout, skewgen
from pairbalance.plans import engine, measures
from pairbalance.queries import QUERIES, pages, part

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
HEADLINE = (
    "block_profile", "whole_block_pairs", "sub_block_pairs", "pair_interval_pairs", "matches_whole_block", "matches_sub_block", "matches_pair_interval",
    "two_source_matches", "map_output_sweep", "imbalance_sweep_r", "skew_imbalance", "large_set_load",
)
STRATEGIES = ("whole_block", "sub_block", "pair_interval")


def force(df) -> None:
    """Run a plan in full without keeping its rows."""
    df.write.format("noop").mode("overwrite").save()


def timed(fn) -> float:
    start = time.perf_counter()
    force(fn())
    return round(time.perf_counter() - start, 3)


def matched(rows, strategy: str, r: int, kind: str = "hash", m: int = 20) -> tuple[float, int]:
    """Seconds of both stages of a match, and the pairs compared."""
    total = 0

    def run():
        nonlocal total
        plan = engine.first_stage(layout.with_partition(rows, m, kind), r)
        total = plan.total
        return engine.compared(engine.pairs(plan, strategy, attrs=True))

    def plain():
        return engine.compared(engine.pairs(engine.Plan(layout.with_partition(rows, m, kind), None, None, 0, r, False), strategy, attrs=True))

    if strategy != "whole_block":
        return timed(run), total
    return timed(plain), engine.first_stage(layout.with_partition(rows, m, kind), r).total  # whole blocks need no first stage


def reported_skew(spark):
    """Names of parts under a key whose largest block has 18 % of records and 71 % of pairs, as the first published set has."""
    rows = part(spark, SF)
    return skewgen.exponential_key(rows, F.col("entity_id"), rows.count(), b=1, tail_share=0.82, tail_blocks=51)


def by_tasks(spark) -> dict[str, float]:
    """That set by r, as read and sorted by key: seconds, and milliseconds for ten thousand pairs."""
    rows, out = reported_skew(spark), {}
    out["first_stage_s"] = timed(lambda: engine.first_stage(layout.with_partition(rows, 20, "hash"), 100).profile)
    for r in (20, 100, 160):
        for s in STRATEGIES:
            seconds, total = matched(rows, s, r)
            out |= {f"{s}_r{r}_s": seconds, f"{s}_r{r}_ms_per_10k_pairs": round(measures.time_per_10k(seconds, total), 2)}
    for s in STRATEGIES[1:]:
        out[f"{s}_r100_sorted_s"] = matched(rows, s, 100, "ordered")[0]
    return out | {"reported_skew_pairs": total}


def by_skew(spark) -> dict[str, float]:
    """Titles of pages in 100 blocks that fall by e^-s: milliseconds for ten thousand pairs at m = 20 and r = 100."""
    rows, out = pages(spark, SF).drop("source"), {}
    n = rows.count()
    for s in (0.0, 0.4, 1.0):
        keyed = skewgen.exponential_key(rows, F.col("entity_id"), n, s=s)
        for strategy in STRATEGIES:
            seconds, total = matched(keyed, strategy, 100)
            out[f"skew_{s}_{strategy}_ms_per_10k_pairs"] = round(measures.time_per_10k(seconds, total), 1)
    return out


def large(spark) -> dict[str, float]:
    """About 25 million comparisons of product names in a few large blocks."""
    seconds, total = matched(part(spark, SF), "pair_interval", 100, "mod")
    return {"part_pairs": total, "part_pair_interval_s": seconds, "part_ms_per_10k_pairs": round(measures.time_per_10k(seconds, total), 2)}


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "16g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    force(QUERIES["block_profile"](spark, SF))  # start-up and compilation are not measured
    took = {name: timed(lambda name=name: QUERIES[name](spark, SF)) for name in HEADLINE}
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "measures": by_tasks(spark) | by_skew(spark) | large(spark), "sf": os.path.basename(SF.rstrip("/"))}))


if __name__ == "__main__":
    main()
