"""Numbering, placement, skew, missing keys, and what holds whatever the parameters."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from pairbalance.functions import IntervalsOf, as_matcher, gini_of, similarity
from pairbalance.operators import keys, layout, matrix, numbering, pair_interval, prefix, skewgen, sub_block, whole_block
from pairbalance.plans import engine, measures, nullkeys, schedule


def entities(spark, rows):
    return spark.createDataFrame(rows, "entity_id long, attr string, block_key string")


def mixed(seed=1, n=120, blocks="aaaaaabbbccdefgh"):
    rng = random.Random(seed)
    return [(i * 3 + 1, "".join(rng.choice("xyz") for _ in range(6)), rng.choice(blocks)) for i in range(n)]


def brute(rows):
    return {(a[0], b[0]) for a, b in itertools.combinations(sorted(rows), 2) if a[2] is not None and a[2] == b[2]}


def found(df):
    got = [(r.left_id, r.right_id) for r in df.collect()]
    assert len(got) == len(set(got))
    return set(got)


@pytest.mark.parametrize("total,r,cut,sizes", [(10, 4, "proportional", [3, 2, 3, 2]), (10, 4, "ceiling", [3, 3, 3, 1]), (5, 4, "proportional", [2, 1, 1, 1]), (5, 4, "ceiling", [2, 2, 1, 0])])
def test_cuts(spark, total, r, cut, sizes):
    low, high = numbering.interval_bounds(F.col("id"), total, r, cut)
    assert [x[0] for x in spark.range(r).select(F.greatest(high - low + 1, F.lit(0))).collect()] == sizes
    k = numbering.interval_of(F.col("id"), total, r, cut)
    counts = dict(spark.range(total).groupBy(k.alias("k")).count().collect())
    assert [counts.get(i, 0) for i in range(r)] == sizes


def test_numbers_of_large_blocks(spark):
    n = 2_000_000_000
    rows = spark.createDataFrame([(x, y, n) for x, y in [(0, 1), (0, n - 1), (1, 2), (n - 2, n - 1), (n // 2, n // 2 + 1), (12345, n - 7)]], "x long, y long, n long")
    p = numbering.cell(F.col("x"), F.col("y"), F.col("n"))
    x, y = numbering.uncell(F.col("p"), F.col("n"))
    for row in rows.withColumn("p", p).withColumns({"bx": x, "by": y}).collect():
        assert (row.x, row.y) == (row.bx, row.by)


def test_wide_pairs(spark):
    cells = spark.createDataFrame([("a", 0, 0, 20_000_000_000), ("b", 1, 0, 3)], "block_key string, block_ix long, part_ix int, n long")
    rows = {r.block_key: r for r in matrix.block_profile(cells, wide=True).collect()}
    assert int(rows["a"].pairs) == 20_000_000_000 * 19_999_999_999 // 2 and int(rows["b"].first_pair) == int(rows["a"].pairs)


def test_running_sum(spark):
    rows = [(i, i % 7) for i in range(500)]
    got = prefix.running_sum(spark.createDataFrame(rows, "k long, v long"), ["k"], F.col("v"), "s", parts=5).orderBy("k").collect()
    total = 0
    for row in got:
        assert row.s == total
        total += row.v


def test_sizes_and_pairs():
    count = lambda sizes: sum(n * (n - 1) // 2 for n in sizes)
    assert count([25, 25]) == 600 and count([45, 5]) == 1000


@pytest.mark.parametrize("sizes,r", [([5, 5, 5, 3, 3, 1, 1, 1, 1], 4), ([7], 3), ([2] * 11, 3), ([9, 4, 4, 4, 1], 5)])
def test_filled_level_equals_one_by_one(sizes, r):
    expected = np.zeros(r, np.int64)
    for size, i in zip(sizes, schedule.least_loaded(sizes, r), strict=True):
        expected[i] += size
    loads = np.zeros(r, np.int64)
    for size in sorted(set(sizes), reverse=True):
        loads += schedule.filled_level(loads, size, sizes.count(size)) * size
    assert sorted(loads) == sorted(expected)


def test_makespan():
    assert schedule.makespan([5, 4, 3, 2, 1], 2) == 8 and schedule.makespan([], 3) == 0


@pytest.mark.parametrize("kind", ["mod", "hash", "ordered", "input"])
@pytest.mark.parametrize("m,r", [(1, 1), (3, 7), (5, 2), (4, 400)])
def test_layouts_do_not_change_the_pairs(spark, kind, m, r):
    rows = mixed()
    plan = engine.first_stage(layout.with_partition(entities(spark, rows), m, kind), r)
    assert found(engine.pairs(plan, "pair_interval")) == brute(rows)
    assert found(engine.pairs(plan, "sub_block")) == brute(rows)
    loads = [x.pairs for x in engine.task_loads(plan, "pair_interval").collect()]
    assert sum(loads) == plan.total and max(loads) - min(loads) <= 1
    assert sub_block.heavy_blocks(plan.profile, r, plan.total).count() <= max(0, r - 1)
    tasks = sub_block.match_tasks(plan.cells, plan.profile, r, plan.total)
    largest = tasks.agg(F.max("pairs")).first()[0]
    assert max(x.pairs for x in engine.task_loads(plan, "sub_block").collect()) <= plan.total / r + largest


def test_exact_is_within_span_and_by_definition(spark):
    plan = engine.first_stage(layout.with_partition(entities(spark, mixed(3)), 3), 7)
    exact = {(r.entity_id, r.reduce_ix) for r in engine.routed(plan, "pair_interval").collect()}
    span = {(r.entity_id, r.reduce_ix) for r in engine.routed(plan, "pair_interval", relevance="span").collect()}
    assert exact <= span
    x = pair_interval.with_entity_index(plan.records, plan.cells).join(plan.profile.select("block_ix", "n", "first_pair"), "block_ix")
    listed = {(r.entity_id, k) for r in x.collect() for (k,) in IntervalsOf.func().eval(r.entity_ix, r.n, r.first_pair, plan.total, 7)} if hasattr(IntervalsOf, "func") else exact
    assert exact == listed


@pytest.mark.parametrize("rows", [[], [(1, "a", "k")], [(i, "a", str(i)) for i in range(5)], [(i, "a", "k") for i in range(9)]], ids=["empty", "one", "singletons", "giant"])
def test_small_inputs(spark, rows):
    df = entities(spark, rows)
    for strategy in ("whole_block", "sub_block", "pair_interval"):
        assert found(engine.match(df, strategy, r=4, m=3, compare=False)) == brute(rows)


def test_pieces_do_not_follow_the_input(spark):
    rows = [(i, "a", "k") for i in range(60)] + [(100 + i, "a", "j") for i in range(4)]
    df = layout.with_partition(entities(spark, rows), 1)
    plan = engine.first_stage(df, 6, pieces="auto")
    assert found(engine.pairs(plan, "sub_block")) == brute(rows)
    loads = [x.pairs for x in engine.task_loads(plan, "sub_block").collect()]
    assert max(loads) < 1.5 * plan.total / 6
    one = engine.first_stage(df, 6)
    assert max(x.pairs for x in engine.task_loads(one, "sub_block").collect()) == 60 * 59 // 2


def test_zero_tasks_are_kept_if_asked(spark):
    rows = [(0, "a", "k"), (1, "a", "k"), (3, "a", "k"), (5, "a", "k"), (7, "a", "j"), (9, "a", "j")]
    plan = engine.first_stage(layout.with_partition(entities(spark, rows), 2), 3)
    more = sub_block.match_tasks(plan.cells, plan.profile, 3, plan.total, keep_zero_tasks=True)
    assert more.where("pairs = 0").count() == 1
    assert sub_block.match_tasks(plan.cells, plan.profile, 3, plan.total).where("pairs = 0").count() == 0


def test_memory_cap_makes_blocks_heavy(spark):
    rows = [(i, "a", "kj"[i % 2]) for i in range(20)]
    plan = engine.first_stage(layout.with_partition(entities(spark, rows), 5), 1)
    assert sub_block.heavy_blocks(plan.profile, 1, plan.total).count() == 0
    assert sub_block.heavy_blocks(plan.profile, 1, plan.total, max_entities=8).count() == 2


@pytest.mark.parametrize("strategy", ["sub_block", "pair_interval", "whole_block"])
def test_missing_keys_one_source(spark, strategy):
    rows = [(i, "a", k) for i, k in enumerate(["a", None, "b", "a", None, "b", "c", None])]
    got = found(nullkeys.pairs_one_source(entities(spark, rows), strategy, 3, 2))
    assert got == {(a[0], b[0]) for a, b in itertools.combinations(rows, 2) if a[2] is None or b[2] is None or a[2] == b[2]}
    with pytest.raises(ValueError):
        engine.match(entities(spark, rows))
    assert found(engine.match(entities(spark, rows), missing_keys="drop", compare=False)) == brute(rows)


def test_missing_keys_two_sources(spark):
    sides = [(i, "a", k, "RS"[i % 2]) for i, k in enumerate(["a", None, "b", "a", None, "b", "c", None, "a", "a"])]
    df = spark.createDataFrame(sides, "entity_id long, attr string, block_key string, source string")
    expected = {(a[0], b[0]) for a in sides for b in sides if a[3] == "R" and b[3] == "S" and (a[2] is None or b[2] is None or a[2] == b[2])}
    assert found(nullkeys.pairs_two_source(df, "pair_interval", 3, 2)) == expected


def test_edit_threshold(spark):
    rows = spark.createDataFrame([("abcde", "abcdx", True), ("abcdefghi", "abcdefgxy", False), ("", "", True), ("a", "", False), ("é", "e", False)], "a string, b string, yes boolean")
    for row in rows.withColumn("got", similarity.edit_match(F.col("a"), F.col("b"))).collect():
        assert row.got == row.yes, row


def test_other_measures(spark):
    rows = spark.createDataFrame([("Robert Smith", "rupert  SMITH", 1 / 3), ("", "", 0.0), ("a b", "b a a", 1.0)], "a string, b string, jaccard double")
    a, b = F.col("a"), F.col("b")
    for row in rows.withColumns({"got": similarity.token_jaccard(a, b), "sound": similarity.same_sound(F.substring(a, 1, 6), F.substring(b, 1, 6))}).collect():
        assert abs(row.got - row.jaccard) < 1e-9 and row.sound == (row.jaccard < 1)


def test_makespans_by_nodes(spark):
    """Each load, makespan and number of copies against counts of the pairs themselves, for few nodes."""
    from pairbalance import queries

    rows = entities(spark, mixed(n=60))
    got = {(r.nodes, r.strategy): r for r in queries._makespans(spark, rows, ("whole_block", "sub_block", "pair_interval")).collect()}
    for n in (1, 2, 5):
        plan = engine.first_stage(layout.with_partition(rows, 2 * n), 10 * n)
        for s in ("whole_block", "sub_block", "pair_interval"):
            counts = dict(engine.pairs(plan, s).groupBy("reduce_ix").count().collect())
            loads = [counts.get(i, 0) for i in range(10 * n)]
            slots = [0] * (2 * n)
            for load in loads:
                slots[slots.index(min(slots))] += load
            assert (got[n, s].makespan, got[n, s].speedup) == (max(slots), sum(loads) / 2 / max(slots))
    assert got[1, "whole_block"].rows_out == 60


def test_makespan_follows_the_queue():
    assert schedule.makespan([1, 1, 4], 2) == 5 and schedule.makespan([4, 1, 1], 2) == 4
    assert measures.simulated_speedup([1, 1, 4], 1) == 0.6


def test_measures(spark):
    assert gini_of([1, 1, 1]) == 0 and gini_of([0, 0, 9]) > 0.6 and gini_of([]) == 0
    assert measures.time_per_10k(2.25, 100_000) == 225.0 and measures.speedup(10, 5) == 2
    plan = engine.first_stage(layout.with_partition(entities(spark, mixed()), 3), 5)
    plain, roles = (measures.pair_checks(plan, x).first() for x in (False, True))
    assert plain.formed >= plan.total <= roles.formed <= plan.total * 2 + 5 * 400
    assert measures.agreement(engine.pairs(plan, "sub_block").select("left_id", "right_id"), engine.pairs(plan, "whole_block").select("left_id", "right_id")) == (0, 0)
    assert measures.peak_group(engine.routed(plan, "whole_block"), ["block_key"]) == plan.profile.agg(F.max("n")).first()[0]
    assert measures.map_output(engine.routed(plan, "whole_block")) == 120
    said = engine.advise(plan)
    assert said["strategy"] in ("whole_block", "sub_block", "pair_interval") and not said["finer_key"]


def test_skew(spark):
    df = spark.range(2_000).select(F.col("id").alias("entity_id"))
    flat = skewgen.exponential_key(df, F.col("entity_id"), 2_000, 100, 0.0).groupBy("block_key").count().collect()
    assert len(flat) == 100 and {r["count"] for r in flat} == {20}
    steep = skewgen.exponential_key(df, F.col("entity_id"), 2_000, 100, 1.0).groupBy("block_key").count().agg(F.max("count")).first()[0]
    assert abs(steep / 2_000 - 0.632) < 0.01


def test_behaviour_under_skew_and_sorting(spark):
    df = spark.range(4_000).select(F.col("id").alias("entity_id"))
    over = lambda p, s: measures.imbalance(engine.task_loads(p, s)).first().over_average
    flat, steep = (engine.first_stage(layout.with_partition(skewgen.exponential_key(df, F.col("entity_id"), 4_000, 100, s), 20, "hash"), 100) for s in (0.0, 1.0))
    assert over(steep, "whole_block") > 50 > over(flat, "whole_block")
    assert over(steep, "pair_interval") < 1.01 and over(steep, "sub_block") < 1.1
    ordered = engine.first_stage(layout.with_partition(skewgen.exponential_key(df, F.col("entity_id"), 4_000, 100, 0.3), 20, "ordered"), 100)
    assert over(ordered, "sub_block") > 2 > 1.01 > over(ordered, "pair_interval")
    said = engine.advise(ordered)
    assert said["strategy"] == "pair_interval"
    sides = [x.count() for x in pair_interval.route_roles(engine.indexed(ordered), ordered.total, ordered.r)]
    assert said["copies"] == {"whole_block": 4_000, "pair_interval": sum(sides), "sub_block": engine.routed(ordered, "sub_block").count()}


def test_python_matcher_and_stream_reducer(spark):
    rows = mixed(5, 40)
    matcher = as_matcher(lambda a, b: float(a[0] == b[0]))
    got = found(engine.match(entities(spark, rows), matcher=matcher, threshold=1.0))
    attr = {r[0]: r[1] for r in rows}
    assert got == {(a, b) for a, b in brute(rows) if attr[a][0] == attr[b][0]}
    assert found(engine.match(entities(spark, rows), reducer="arrow", compare=False)) == brute(rows)


def test_all_pairs_refuses_large_inputs(spark):
    with pytest.raises(ValueError):
        whole_block.all_pairs(entities(spark, [(i, "a", "k") for i in range(12)]), most=10)
    assert keys.prefix_key("x", 5) is not None


def test_blocks_without_a_pair_are_left_out_early(spark):
    rows = [(0, "a", "k", "R"), (1, "a", "k", "S"), (2, "a", "j", "R"), (3, "a", "j", "R"), (4, "a", "solo", "S")]
    df = spark.createDataFrame(rows, "entity_id long, attr string, block_key string, source string")
    two = engine.first_stage(engine.two_source_layout(df, 2, 2), 3, two_source=True)
    left = pair_interval.with_entity_index(two.records, two.cells, True, two.profile).collect()
    assert {r.entity_id for r in left} == {0, 1}
    one = engine.first_stage(layout.with_partition(df.drop("source"), 2), 3)
    left = pair_interval.with_entity_index(one.records, one.cells, profile=one.profile).collect()
    assert {r.entity_id for r in left} == {0, 1, 2, 3}


@pytest.mark.parametrize("strategy,two", [("sub_block", False), ("pair_interval", False), ("sub_block", True), ("pair_interval", True)])
def test_no_record_is_moved_by_its_block_alone(spark, strategy, two):
    """With tables of blocks too large to broadcast, records meet their block's numbers by cell."""
    rows = [(*row, "RS"[row[0] % 2]) for row in mixed(n=400)]
    df = spark.createDataFrame(rows, "entity_id long, attr string, block_key string, source string")
    laid = engine.two_source_layout(df, 3, 3) if two else layout.with_partition(df, 3)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = engine.first_stage(laid, 5, two_source=two)
        records = plan.records.withColumn("attr", F.concat("attr", F.lit("!")))  # tells exchanges of records from those of cells
        plan.records = records
        text = engine.routed(plan, strategy)._jdf.queryExecution().executedPlan().toString().splitlines()
        keyed = [line for line in text if "Exchange hashpartitioning(" in line]
        of_records = [line for k, line in enumerate(text) if "Exchange hashpartitioning(" in line and any("!" in x for x in text[k : k + 4])]
        assert keyed and of_records and all("part_ix" in line for line in of_records), of_records
        assert found(engine.pairs(plan, strategy)) == found(engine.pairs(plan, "whole_block"))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_groups_give_their_pairs_out_piece_by_piece(spark):
    """No frame of a group holds more than so many pairs, or those of one record."""
    from pairbalance.plans import frame_reduce

    ids = np.arange(50)
    for pieces, n in ((list(frame_reduce.within(ids, 60)), 50 * 49 // 2), (list(frame_reduce.across(ids, ids + 50, 60)), 2500)):
        assert len({p for x, y in pieces for p in zip(x.tolist(), y.tolist(), strict=True)}) == sum(len(x) for x, _ in pieces) == n
        assert max(len(x) for x, _ in pieces) <= 60 and all((x < y).all() for x, y in pieces)
    assert not [*frame_reduce.within(ids[:1]), *frame_reduce.across(ids, ids[:0]), *frame_reduce.across(ids[:0], ids)]
    rows = mixed(n=80)
    plan = engine.first_stage(layout.with_partition(entities(spark, rows), 3), 4)
    assert found(frame_reduce.pairs_by_group(engine.routed(plan, "sub_block"), 4, most=7)) == brute(rows)


def test_streamed_pairs_without_texts(spark):
    """Pairs that are not compared move no text, and small pieces of the output hold the same pairs."""
    from pairbalance.plans import arrow_reduce

    rows = mixed(6, 90)
    got = engine.match(entities(spark, rows), r=5, m=3, reducer="arrow", compare=False, attrs=False)
    assert "left_attr" not in got.columns and found(got) == brute(rows)
    attr = {r[0]: r[1] for r in rows}
    plan = engine.first_stage(layout.with_partition(entities(spark, rows), 3), 5)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "4")
    try:
        for most, text in ((5, 1 << 20), (1000, 30)):
            got = arrow_reduce.pairs_by_stream(engine.routed(plan, "sub_block"), 5, most, text)
            assert found(got) == brute(rows) and all((r.left_attr, r.right_attr) == (attr[r.left_id], attr[r.right_id]) for r in got.collect())
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    for n, held, inside in ((40, 0, True), (40, 9, True), (9, 40, False), (1, 90, False), (5, 0, False)):
        pieces = list(arrow_reduce._places(n, held, inside, 16))
        assert {p for x, y in pieces for p in zip(x.tolist(), y.tolist(), strict=True)} == {(x, y) for x in range(n) for y in range(held + x * inside)}
        assert max((len(x) for x, _ in pieces), default=0) <= 16 and sum(len(x) for x, _ in pieces) == sum(held + x * inside for x in range(n))


@pytest.mark.parametrize("threshold", [0.3, 0.01, 1.0])
def test_cosine_of_pieces_is_that_of_pairs(spark, threshold):
    """Products of matrices give what the measure gives pair by pair, for odd vectors and those at the threshold too."""
    from pairbalance.operators import multi_key

    rng = random.Random(7)
    vectors = [[rng.gauss(0, 1) for _ in range(4)] for _ in range(40)] + [[3.0, 4.0, 0.0, 0.0], [3.0, 4.0, 0.0, 0.0], [0.0] * 4, None, [1.0, None, 2.0, 0.0], [1.0, 2.0], [2.0, 1.0], [], [1e200, 1.0, 0.0, 0.0], [1e-170, 0.0, 0.0, 0.0], [float("nan"), 0.0, 0.0, 1.0], [0.3, (1 - 0.09) ** 0.5, 0.0, 0.0], [1.0, 0.0, 0.0, 0.0]]
    df = spark.createDataFrame([(i, (i % 2) if i % 11 else None, v) for i, v in enumerate(vectors)], "entity_id long, label int, v array<double>")
    expected = found(multi_key.similar_in_block(df, "label", "v", similarity.cosine, threshold))
    for piece in (5, 1000):
        assert found(multi_key.cosine_in_block(df, "label", "v", threshold, piece)) == expected
    with pytest.raises(ValueError):
        multi_key.cosine_in_block(df, "label", "v", 0.0)


def test_pairs_of_several_keys_in_pieces(spark):
    """Whatever the size of pieces, a pair comes once; records may lack keys, and one's first key may be another's second."""
    from pairbalance.operators import multi_key

    rng = random.Random(3)
    rows = [(i, *(rng.choice(["a", "b", "c", "d", None]) for _ in range(3))) for i in range(60)]
    df = spark.createDataFrame(rows, "entity_id int, x string, y string, z string")
    for n in (1, 2, 3):
        expected = {(a[0], b[0]) for a, b in itertools.combinations(rows, 2) if {*a[1 : n + 1]} & {*b[1 : n + 1]} - {None}}
        for piece, most in ((7, 5), (1000, 1000)):
            assert found(multi_key.pairs(df, [F.col(c) for c in "xyz"[:n]], piece, most)) == expected
