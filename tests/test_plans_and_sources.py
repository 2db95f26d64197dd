"""Physical plans, readers and writers, and streams."""

import json

import pytest
from pyspark.sql import functions as F

from pairbalance import queries, queries_relational, sources, streaming  # noqa: F401
from pairbalance.functions import gini, register
from pairbalance.operators import layout, relops
from pairbalance.plans import engine, schedule

SF = "/root/testdata/sf0.001"


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_filters_and_columns_reach_the_scan(spark):
    text = plan_of(queries.QUERIES["scan_filter"](spark, SF))
    assert "PushedFilters: [" in text and "GreaterThanOrEqual(l_quantity" in text
    schema = text.split("ReadSchema: struct<")[1].split(">")[0]
    assert {c.split(":")[0] for c in schema.split(",")} == {"l_orderkey", "l_linenumber", "l_quantity", "l_returnflag", "l_shipdate"}


@pytest.mark.parametrize("strategy", ["sub_block", "pair_interval"])
def test_the_join_after_routing_adds_no_shuffle(spark, strategy):
    plan = queries.planned(spark, SF, r=5)
    text = plan_of(engine.pairs(plan, strategy))
    top = text[: text.index("Exchange")]
    assert "SortMergeJoin" in top
    assert text.count("shufflepartitionidpassthrough") >= 1 and "BroadcastNestedLoopJoin" not in text and "CartesianProduct" not in text
    rows = layout.route(engine.routed(plan, strategy).select("reduce_ix"), 5)
    assert rows.where(F.spark_partition_id() != F.col("reduce_ix")).count() == 0


def test_methods_use_no_python(spark):
    plan = queries.planned(spark, SF)
    for strategy in ("whole_block", "sub_block", "pair_interval"):
        text = plan_of(engine.compared(engine.pairs(plan, strategy, attrs=True)))
        assert not any(x in text for x in ("Python", "Pandas", "MapInArrow"))


def test_formats_round_trip(spark, tmp_path):
    nation = sources.read(spark, SF, "nation")
    for fmt in ("csv", "json", "orc", "parquet"):
        sources.write(nation, str(tmp_path / fmt), fmt=fmt)
        back = sources.read_as(spark, str(tmp_path / fmt), fmt, nation.schema)
        assert sorted(map(tuple, back.collect())) == sorted(map(tuple, nation.collect()))
    sources.write(nation.select("n_name"), str(tmp_path / "text"), fmt="text")
    assert sources.read_as(spark, str(tmp_path / "text"), "text", "value string").count() == nation.count()
    sources.write(nation, str(tmp_path / "parts"), partition_by=["n_regionkey"])
    assert sources.read_as(spark, str(tmp_path / "parts"), "parquet", nation.schema).where("n_regionkey = 1").count() == nation.where("n_regionkey = 1").count()
    sources.write(nation, str(tmp_path / "buckets"), table="nation_buckets", bucket_by=(4, ["n_nationkey"]), mode="overwrite")
    assert "Exchange" not in plan_of(spark.table("nation_buckets").groupBy("n_nationkey").count()).replace("BroadcastExchange", "")
    spark.sql("DROP TABLE nation_buckets")
    assert sources.inline(spark, [(1,)], "a int").count() == 1


def test_user_functions(spark):
    register(spark)
    assert spark.sql("SELECT count(*), sum(pairs) FROM piece_tasks(array(2, 0, 3))").first() == (3, 10)
    assert spark.sql("SELECT pair_cell(2L, 3L, 4L), pair_interval(7L, 20L, 3L), edit_similarity('abcd', 'abcx')").first() == (5, 1, 0.75)
    loads = spark.createDataFrame([("a", 1), ("a", 1), ("b", 0), ("b", 9)], "k string, load int")
    got = dict(loads.groupBy("k").agg(gini("load").alias("g")).collect())
    assert got == {"a": 0.0, "b": 0.5}


def test_broadcast_is_checked(spark):
    a = spark.range(10).toDF("k")
    assert "BroadcastHashJoin" in plan_of(relops.join_broadcast(a, a, ["k"]))
    assert relops.join_broadcast(a, a, ["k"], most=3).count() == 10


def test_exact_placement_has_a_limit(spark, monkeypatch):
    monkeypatch.setattr(schedule, "EXACT_TASKS", 3)
    plan = queries.planned(spark, SF)
    with pytest.raises(ValueError):
        engine.tasks(plan, "exact")
    placed = engine.tasks(plan)  # goes over to classes
    assert placed.agg(F.sum("pairs")).first()[0] == plan.total


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    events = sources.read(spark, SF, "events").where("event_id < 300")
    folder = str(tmp_path / "in")
    for k in range(3):
        events.where(f"event_id >= {k * 100} AND event_id < {k * 100 + 100}").coalesce(1).write.mode("append").parquet(folder)
    late = events.limit(7).withColumn("ts", F.expr("ts - INTERVAL 90 DAYS"))
    late.coalesce(1).write.mode("append").parquet(folder)
    stream = sources.read_stream(spark, folder, events.schema, 1)
    counts = streaming.windowed(streaming.with_lateness(streaming.instants(stream), "1 hour"), ["event_type"])
    table, progress = streaming.finish(counts, "late_counts", "update")
    dropped = sum(json.loads(p.json)["stateOperators"][0]["numRowsDroppedByWatermark"] for p in progress if json.loads(p.json)["stateOperators"])
    newest = {(r.start, r.event_type): r.n for r in table.groupBy("start", "event_type").agg(F.max("n").alias("n")).collect()}
    assert sum(newest.values()) in (300, 307) and (dropped > 0) == (sum(newest.values()) == 300)


def test_increments_add_up(spark, tmp_path):
    rows = queries.documents(spark, SF).drop("source")
    whole = {(min(r.left_id, r.right_id), max(r.left_id, r.right_id)) for r in engine.match(rows, "sub_block", 4, 3).collect()}
    first, second = rows.where("entity_id % 2 = 0"), rows.where("entity_id % 2 = 1")
    got = {(r.left_id, r.right_id) for r in engine.match(first, "sub_block", 4, 3).collect()}
    got |= {(min(r.left_id, r.right_id), max(r.left_id, r.right_id)) for r in streaming.match_increment(first, second, 4, 3).collect()}
    assert got == whole
    folder, stored, out = (str(tmp_path / x) for x in ("in", "stored", "out"))
    for k in range(2):
        rows.where(f"entity_id % 2 = {k}").coalesce(1).write.mode("append").parquet(folder)
    step = streaming.match_stream(None, stored, out, 4)
    stream = sources.read_stream(spark, folder, rows.schema, 1)
    stream.writeStream.foreachBatch(step).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    streamed = {(min(r.left_id, r.right_id), max(r.left_id, r.right_id)) for r in spark.read.parquet(out).collect()}
    assert streamed == whole
