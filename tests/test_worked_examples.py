"""The two worked examples: every figure that the examples state."""

import pytest
from pyspark.sql import functions as F

from pairbalance.operators import layout, pair_interval, sub_block
from pairbalance.plans import engine, measures

ONE = [(i, name, key, part) for i, (name, key, part) in enumerate([*zip("ABCDEFG", "wwxxxzz", [0] * 7), *zip("HIKLMNO", "wwyyzzz", [1] * 7)])]
TWO = [(i, n, k, s, p) for i, (n, k, s, p) in enumerate([*zip("ABCDEF", "wwzzxy", "RRRRRR", [0] * 6), *zip("GHIK", "wwzz", "SSSS", [1] * 4), *zip("LMN", "xxz", "SSS", [2] * 3)])]
ORDER = list("wyxz")
ID = {row[1]: row[0] for row in ONE}


@pytest.fixture(scope="module")
def one(spark):
    rows = spark.createDataFrame(ONE, "entity_id long, attr string, block_key string, part_ix int")
    return engine.first_stage(rows, 3, explicit_order=ORDER)


@pytest.fixture(scope="module")
def two(spark):
    rows = spark.createDataFrame(TWO, "entity_id long, attr string, block_key string, source string, part_ix int")
    return engine.first_stage(rows, 3, two_source=True, explicit_order=ORDER)


def loads(plan, strategy):
    return [x.pairs for x in engine.task_loads(plan, strategy).orderBy("reduce_ix").collect()]


def test_matrix_and_profile(one):
    cells = {(c.block_key, c.part_ix): c.n for c in one.cells.collect()}
    assert cells == {("w", 0): 2, ("w", 1): 2, ("y", 1): 2, ("x", 0): 3, ("z", 0): 2, ("z", 1): 3}
    profile = one.profile.orderBy("block_ix").collect()
    assert [(p.block_key, p.n, p.pairs, p.first_pair) for p in profile] == [("w", 4, 6, 0), ("y", 2, 1, 6), ("x", 3, 3, 7), ("z", 5, 10, 10)]
    assert one.total == 20
    row = measures.dataset_profile(one.profile).first()
    assert row.largest_pair_share == 0.5 and round(row.largest_entity_share, 2) == 0.36


def test_only_z_is_heavy(one):
    assert [h.block_key for h in sub_block.heavy_blocks(one.profile, 3, one.total).collect()] == ["z"]


@pytest.mark.parametrize("mode", ["exact", "classed"])
def test_sub_block_placement(one, mode):
    placed = {(t.block_ix, t.hi, t.lo): (t.pairs, t.reduce_ix) for t in engine.tasks(one, mode).collect()}
    assert placed[0, -1, -1] == (6, 0) and placed[3, 1, 0] == (6, 1)
    assert {k: v[0] for k, v in placed.items()} == {(0, -1, -1): 6, (3, 1, 0): 6, (2, -1, -1): 3, (3, 1, 1): 3, (1, -1, -1): 1, (3, 0, 0): 1}
    if mode == "exact":
        assert [placed[k][1] for k in ((2, -1, -1), (3, 1, 1), (1, -1, -1), (3, 0, 0))] == [2, 2, 0, 1]
    assert loads(one, "sub_block") == [7, 7, 6]


def test_map_output(one):
    assert engine.routed(one, "sub_block").count() == 19
    assert engine.routed(one, "pair_interval").count() == 18
    assert engine.routed(one, "whole_block").count() == 14


@pytest.mark.parametrize("cut", ["proportional", "ceiling"])
def test_intervals(one, cut):
    assert [x.pairs for x in engine.task_loads(one, "pair_interval", cut).orderBy("reduce_ix").collect()] == [7, 7, 6]


def test_records_go_where_they_have_pairs(one):
    to = {}
    for row in engine.routed(one, "pair_interval").collect():
        to.setdefault(row.entity_id, set()).add(row.reduce_ix)
    assert to[ID["M"]] == {1, 2} and to[ID["F"]] == {1}
    in_z = {ID[x] for x in "FGMNO"}
    assert {i for i, t in to.items() if 1 in t} >= in_z
    assert {i for i, t in to.items() if 2 in t} == in_z - {ID["F"]}
    indexed = pair_interval.with_entity_index(one.records, one.cells).where(F.col("entity_id") == ID["M"]).first()
    assert indexed.entity_ix == 2


@pytest.mark.parametrize("roles", [True, False])
def test_no_pair_is_lost_after_the_interval_ends(one, roles):
    """Pairs arrive by record, and their numbers do not rise in that order: 10 to 13 are all found by task 1."""
    found = engine.pairs(one, "pair_interval", roles=roles).where("reduce_ix = 1 AND block_ix = 3").collect()
    assert {(r.left_id, r.right_id) for r in found} == {(ID["F"], ID[x]) for x in "GMNO"}


@pytest.mark.parametrize("strategy", ["whole_block", "sub_block", "pair_interval"])
def test_every_pair_once(one, strategy):
    found = [(r.left_id, r.right_id) for r in engine.pairs(one, strategy).collect()]
    assert len(found) == len(set(found)) == 20
    assert set(found) == {(a[0], b[0]) for a in ONE for b in ONE if a[0] < b[0] and a[2] == b[2]}


def test_two_sources(two):
    profile = {p.block_key: (p.pairs, p.first_pair) for p in two.profile.collect()}
    assert profile == {"w": (4, 0), "x": (2, 4), "z": (6, 6)} and two.total == 12
    placed = {(t.block_ix, t.hi, t.lo): (t.pairs, t.reduce_ix) for t in engine.tasks(two, "exact").collect()}
    assert placed == {(0, -1, -1): (4, 0), (3, 0, 1): (4, 1), (2, -1, -1): (2, 2), (3, 0, 2): (2, 2)}
    assert loads(two, "pair_interval") == [4, 4, 4]
    rows = engine.routed(two, "pair_interval").collect()
    assert {r.reduce_ix for r in rows if r.entity_id == 2} == {1, 2}
    assert len(rows) == 15 and engine.routed(two, "sub_block").count() == 14
    expected = {(a[0], b[0]) for a in TWO for b in TWO if a[3] == "R" and b[3] == "S" and a[2] == b[2]}
    for strategy in ("whole_block", "sub_block", "pair_interval"):
        found = [(r.left_id, r.right_id) for r in engine.pairs(two, strategy).collect()]
        assert len(found) == 12 and set(found) == expected


def test_routing_on_part_of_a_key(spark):
    rows = [(s, c) for s, c, k in [("circle", 0, 2), ("circle", 1, 2), ("triangle", 0, 2), ("triangle", 2, 3), ("circle", 2, 1)] for _ in range(k)]
    df = layout.route(spark.createDataFrame(rows, "shape string, colour int"), 3, "colour")
    assert df.where(F.spark_partition_id() != F.col("colour")).count() == 0
    assert len(layout.grouped(df, ["colour", "shape"]).count().collect()) == 5
