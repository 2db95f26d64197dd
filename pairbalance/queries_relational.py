"""Queries for the relational operators and function classes around the methods."""

from __future__ import annotations

from pyspark.sql import functions as F

from . import oracle
from .operators import keys, layout, matrix, relops
from .queries import M, documents, planned, query
from .sources import read

_CELLS = f"WITH {oracle.base()} "


@query("scan_filter", "SELECT l_orderkey, l_linenumber, l_shipdate FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_shipdate < TIMESTAMP '1997-01-01'")
def scan_filter(spark, sf_dir):
    rows = relops.where(read(spark, sf_dir, "lineitem"), F.col("l_quantity").between(10, 20), F.col("l_returnflag").isin("A", "R"), "l_shipdate < TIMESTAMP_NTZ '1997-01-01'")
    return rows.select("l_orderkey", "l_linenumber", "l_shipdate")


@query("text_filters", "SELECT doc_id FROM documents WHERE text LIKE '%the%' AND regexp_matches(text, '[0-9]{3}') AND lang IS NOT NULL")
def text_filters(spark, sf_dir):
    return relops.where(read(spark, sf_dir, "documents"), F.col("text").like("%the%"), F.col("text").rlike("[0-9]{3}"), F.col("lang").isNotNull()).select("doc_id")


@query("project_case", "SELECT p_partkey, upper(p_brand) AS brand, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS size_class FROM part")
def project_case(spark, sf_dir):
    size = F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "middle").otherwise("large")
    return relops.project(read(spark, sf_dir, "part"), p_partkey=F.col("p_partkey"), brand=F.upper("p_brand"), size_class=size)


_JOINED = "SELECT o_orderkey, o_custkey, l_linenumber FROM orders JOIN lineitem ON o_orderkey = l_orderkey"


def _join(name: str) -> None:
    @query(name, _JOINED)
    def joined(spark, sf_dir):
        lines = read(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_linenumber")
        orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
        return getattr(relops, name)(lines, orders, ["o_orderkey"]).select("o_orderkey", "o_custkey", "l_linenumber")


for _name in ("join_hash", "join_merge"):
    _join(_name)


@query("join_broadcast", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def join_broadcast(spark, sf_dir):
    nation = read(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_name")
    return relops.join_broadcast(read(spark, sf_dir, "customer"), nation, ["c_nationkey"]).select("c_custkey", "n_name")


@query("join_theta", "SELECT item_id, s_suppkey FROM benchmark, supplier WHERE (item_id * 7 + s_suppkey) % 11 < 2")
def join_theta(spark, sf_dir):
    return relops.join_theta(read(spark, sf_dir, "benchmark").select("item_id"), read(spark, sf_dir, "supplier").select("s_suppkey"), F.expr("(item_id * 7 + s_suppkey) % 11 < 2"))


_BANDS = "(SELECT range AS band, range * 7000 AS low, range * 7000 + 9000 AS high FROM range(15))"


@query("join_between", f"SELECT l_orderkey, l_linenumber, band FROM lineitem JOIN {_BANDS} ON l_extendedprice BETWEEN low AND high")
def join_between(spark, sf_dir):
    bands = spark.range(15).select(F.col("id").alias("band"), (F.col("id") * 7000).alias("low"), (F.col("id") * 7000 + 9000).alias("high"))
    rows = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_extendedprice")
    return relops.join_between(rows, "l_extendedprice", bands, "low", "high", 8000).select("l_orderkey", "l_linenumber", "band")


@query("join_overlap", f"WITH {oracle.base()}, s AS (SELECT block_ix, first_pair AS a_low, first_pair + pairs - 1 AS a_high FROM profile WHERE pairs > 0), t AS (SELECT range AS k, range * 500 AS b_low, range * 500 + 599 AS b_high FROM range(40)) SELECT block_ix, k FROM s JOIN t ON a_low <= b_high AND b_low <= a_high")
def join_overlap(spark, sf_dir):
    spans = planned(spark, sf_dir).profile.where("pairs > 0").selectExpr("block_ix", "first_pair AS a_low", "first_pair + pairs - 1 AS a_high")
    marks = spark.range(40).selectExpr("id AS k", "id * 500 AS b_low", "id * 500 + 599 AS b_high")
    return relops.join_overlap(spans, marks, 400).select("block_ix", "k")


@query("join_asof", "WITH a AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'error'), b AS (SELECT user_id, ts, event_id AS click_id FROM events WHERE event_type = 'click') SELECT a.event_id, a.user_id, b.click_id FROM a ASOF LEFT JOIN b ON a.user_id = b.user_id AND a.ts >= b.ts")
def join_asof(spark, sf_dir):
    events = read(spark, sf_dir, "events")
    errors = events.where("event_type = 'error'").select("event_id", "user_id", "ts")
    clicks = events.where("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("click"))
    return relops.join_asof(errors, clicks, "user_id", "ts", "click", "click_id").select("event_id", "user_id", "click_id")


@query("join_full_outer", "WITH a AS (SELECT lang, count(*) AS r FROM documents WHERE lang <> 'es' GROUP BY 1), b AS (SELECT lang, count(*) AS s FROM documents WHERE lang <> 'de' GROUP BY 1) SELECT coalesce(a.lang, b.lang) AS lang, r, s FROM a FULL JOIN b ON a.lang = b.lang")
def join_full_outer(spark, sf_dir):
    rows = read(spark, sf_dir, "documents")
    a = rows.where("lang <> 'es'").groupBy("lang").agg(F.count("*").alias("r"))
    b = rows.where("lang <> 'de'").groupBy("lang").agg(F.count("*").alias("s"))
    return relops.join_outer(a, b, ["lang"])


@query("join_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(spark, sf_dir):
    return relops.join_semi(read(spark, sf_dir, "documents").select("doc_id", "lang"), read(spark, sf_dir, "labels"), ["doc_id"])


@query("join_anti", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, sf_dir):
    return relops.join_anti(read(spark, sf_dir, "documents").select("doc_id", "lang"), read(spark, sf_dir, "labels"), ["doc_id"])


@query("agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS DECIMAL(28, 2)) AS price FROM lineitem GROUP BY 1, 2")
def agg_hash(spark, sf_dir):
    price = F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("decimal(28,2)")
    return relops.agg_hash(read(spark, sf_dir, "lineitem"), ["l_returnflag", "l_linestatus"], n=F.count("*"), price=price)


@query("agg_sort", "SELECT p_brand, min(p_name) AS least, max(p_name) AS greatest FROM part GROUP BY 1")
def agg_sort(spark, sf_dir):
    return relops.agg_sort(read(spark, sf_dir, "part"), ["p_brand"], "p_name")


@query("distinct_blocks", f"SELECT count(DISTINCT block_key) AS n FROM ({oracle.DOCUMENTS})")
def distinct_blocks(spark, sf_dir):
    return relops.distinct_counts(documents(spark, sf_dir), "block_key")


@query("distinct_blocks_approximate")
def distinct_blocks_approximate(spark, sf_dir):
    return relops.distinct_counts(documents(spark, sf_dir), "block_key", approximate=True)


def _cube(how: str) -> None:
    @query(f"agg_{how}", _CELLS + f"SELECT block_ix, part_ix, CAST(sum(n) AS BIGINT) AS total, grouping(block_ix, part_ix) AS level FROM cells GROUP BY {how.upper()}(block_ix, part_ix)")
    def totals(spark, sf_dir):
        return relops.agg_cube(planned(spark, sf_dir).cells, ["block_ix", "part_ix"], F.sum("n"), how)


_cube("cube")
_cube("rollup")


@query("agg_grouping_sets", _CELLS + "SELECT block_ix, part_ix, CAST(sum(n) AS BIGINT) AS total FROM cells GROUP BY GROUPING SETS ((block_ix), (part_ix))")
def agg_grouping_sets(spark, sf_dir):
    cells = planned(spark, sf_dir).cells
    return spark.sql("SELECT block_ix, part_ix, sum(n) AS total FROM {cells} GROUP BY GROUPING SETS ((block_ix), (part_ix))", cells=cells)


@query("matrix_dense", _CELLS + "SELECT block_ix, " + ", ".join(f"CAST(coalesce(sum(n) FILTER (part_ix = {i}), 0) AS BIGINT) AS p{i}" for i in range(M)) + " FROM cells GROUP BY 1")
def matrix_dense(spark, sf_dir):
    return relops.matrix_dense(planned(spark, sf_dir).cells, M)


@query("matrix_unpivot", _CELLS + "SELECT block_ix, part_ix, n FROM cells")
def matrix_unpivot(spark, sf_dir):
    return relops.matrix_long(relops.matrix_dense(planned(spark, sf_dir).cells, M))


@query("agg_collect", "SELECT p_brand, arg_max(p_name, p_partkey) AS top, array_to_string(list_sort(list_distinct(list(CAST(p_name AS VARCHAR)))), ',') AS all_values, quantile_cont(p_partkey, 0.5) AS median FROM part GROUP BY 1")
def agg_collect(spark, sf_dir):
    return relops.agg_collect(read(spark, sf_dir, "part"), ["p_brand"], "p_name", "p_partkey")


@query("win_rank", "SELECT doc_id, row_number() OVER w AS place, rank() OVER v AS rank, dense_rank() OVER v AS dense, ntile(4) OVER w AS quarter, percent_rank() OVER v AS share FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id), v AS (PARTITION BY lang ORDER BY n_chars, doc_id)")
def win_rank(spark, sf_dir):
    rows = relops.win_rank(read(spark, sf_dir, "documents"), ["lang"], [F.col("n_chars"), F.col("doc_id")])
    return rows.select("doc_id", *(F.col(c).cast("long").alias(c) for c in ("place", "rank", "dense", "quarter")), "share")


@query("win_analytic", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS behind, first_value(event_id) OVER f AS first_value, last_value(event_id) OVER f AS last_value, nth_value(event_id, 2) OVER f AS second_value FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id), f AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_analytic(spark, sf_dir):
    rows = relops.win_analytic(read(spark, sf_dir, "events"), ["user_id"], ["ts", "event_id"], "event_id")
    return rows.select("event_id", "before", "behind", "first_value", "last_value", "second_value")


@query("win_frames", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS rows_before, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS recent FROM events")
def win_frames(spark, sf_dir):
    seconds = F.expr("datediff(to_date(ts), DATE '1970-01-01') * 86400L + hour(ts) * 3600 + minute(ts) * 60 + second(ts)")
    return relops.win_frames(read(spark, sf_dir, "events"), ["user_id"], "event_id", seconds, 3600).select("event_id", "rows_before", "recent")


@query("sort_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice, o_orderkey")
def sort_global(spark, sf_dir):
    return relops.sort_global(read(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice"), "o_totalprice", "o_orderkey")


@query("sort_local", "SELECT o_orderkey, o_custkey FROM orders")
def sort_local(spark, sf_dir):
    return relops.sort_local(read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), "o_custkey")


@query("top_blocks", f"WITH {oracle.base()} SELECT block_key, n, pairs FROM profile ORDER BY pairs DESC, block_key LIMIT 10")
def top_blocks(spark, sf_dir):
    return relops.top_k(planned(spark, sf_dir).profile.select("block_key", "n", "pairs"), 10, F.desc("pairs"), F.col("block_key"))


@query("top_per_group", "SELECT p_brand, p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_size DESC, p_partkey) <= 3")
def top_per_group(spark, sf_dir):
    return relops.top_k_per(read(spark, sf_dir, "part"), ["p_brand"], 3, F.desc("p_size"), F.col("p_partkey")).select("p_brand", "p_partkey")


@query("union_all", "SELECT doc_id AS id, text FROM documents UNION ALL SELECT item_id, text FROM benchmark")
def union_all(spark, sf_dir):
    a = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    return relops.union_all(a, read(spark, sf_dir, "benchmark").select("text", F.col("item_id").alias("id")))


def _sets(name: str, how: str, sql: str) -> None:
    @query(name, f"SELECT lang, source FROM documents {sql} SELECT lang, source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
    def found(spark, sf_dir):
        rows = read(spark, sf_dir, "documents")
        return relops.set_ops(rows.select("lang", "source"), relops.join_semi(rows, read(spark, sf_dir, "labels"), ["doc_id"]).select("lang", "source"), how)


_sets("set_intersect", "intersect", "INTERSECT")
_sets("set_intersect_all", "intersectAll", "INTERSECT ALL")
_sets("set_except", "subtract", "EXCEPT")
_sets("set_except_all", "exceptAll", "EXCEPT ALL")


@query("routed_groups", "SELECT l_suppkey, l_returnflag, count(*) AS n FROM lineitem GROUP BY 1, 2")
def routed_groups(spark, sf_dir):
    """Rows sent by one part of a key and grouped by the whole of it, without another shuffle."""
    rows = read(spark, sf_dir, "lineitem").withColumn("task", F.pmod("l_suppkey", F.lit(M)).cast("int"))
    return layout.grouped(layout.route(rows, M, "task"), ["task", "l_suppkey", "l_returnflag"]).agg(F.count("*").alias("n")).drop("task")


@query("spread_rows", "SELECT o_orderkey FROM orders")
def spread_rows(spark, sf_dir):
    rows = read(spark, sf_dir, "orders").select("o_orderkey")
    return layout.spread(layout.spread(rows, 6, "range", ("o_orderkey",)), 3, "coalesce")


@query("sampled_rows")
def sampled_rows(spark, sf_dir):
    return relops.sample(read(spark, sf_dir, "documents").select("doc_id"), 0.2, 7)


@query("string_functions", "SELECT p_partkey, upper(p_name) AS u, substr(p_name, 2, 3) AS s, length(p_name) AS n, strlen(p_name) AS bytes, concat_ws('-', p_brand, p_type) AS c, split_part(p_name, ' ', 1) AS w, replace(p_type, 'E', 'e') AS r, regexp_extract(p_brand, '[0-9]+', 0) AS d, translate(p_name, 'aeiou', 'AEIOU') AS t, strpos(p_name, 'e') AS i, lpad(p_brand, 12, '*') AS l, levenshtein(p_name, p_type) AS v FROM part")
def string_functions(spark, sf_dir):
    return read(spark, sf_dir, "part").select(
        "p_partkey", F.upper("p_name").alias("u"), F.substring("p_name", 2, 3).alias("s"), F.length("p_name").cast("long").alias("n"), F.octet_length("p_name").cast("long").alias("bytes"),
        F.concat_ws("-", "p_brand", "p_type").alias("c"), F.split("p_name", " ")[0].alias("w"), F.regexp_replace("p_type", "E", "e").alias("r"), F.regexp_extract("p_brand", "[0-9]+", 0).alias("d"),
        F.translate("p_name", "aeiou", "AEIOU").alias("t"), F.instr("p_name", "e").cast("long").alias("i"), F.lpad("p_brand", 12, "*").alias("l"), F.levenshtein("p_name", "p_type").cast("long").alias("v"),
    )


@query("math_functions", "SELECT o_orderkey, o_custkey // 7 AS d, o_custkey % 7 AS m, CAST(ceil(o_totalprice) AS BIGINT) AS c, CAST(floor(o_totalprice) AS BIGINT) AS f, sqrt(o_custkey) AS s, greatest(o_orderkey, o_custkey) AS g, least(o_orderkey, o_custkey) AS l, o_custkey << 3 AS x FROM orders")
def math_functions(spark, sf_dir):
    return read(spark, sf_dir, "orders").select(
        "o_orderkey", F.expr("o_custkey div 7").alias("d"), F.pmod("o_custkey", F.lit(7)).alias("m"), F.ceil("o_totalprice").alias("c"), F.floor("o_totalprice").alias("f"), F.sqrt("o_custkey").alias("s"),
        F.greatest("o_orderkey", "o_custkey").alias("g"), F.least("o_orderkey", "o_custkey").alias("l"), F.shiftleft("o_custkey", 3).alias("x"),
    )


@query("date_functions", "SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS m, year(o_orderdate) AS y, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS d, (o_orderdate::DATE + 30)::DATE AS later, (o_orderdate + INTERVAL 2 HOUR)::TIMESTAMP AS h FROM orders")
def date_functions(spark, sf_dir):
    return read(spark, sf_dir, "orders").select(
        "o_orderkey", F.expr("date_trunc('month', o_orderdate)").cast("timestamp_ntz").alias("m"), F.year("o_orderdate").cast("long").alias("y"), F.expr("datediff(to_date(o_orderdate), DATE '1995-01-01')").cast("long").alias("d"),
        F.expr("date_add(to_date(o_orderdate), 30)").alias("later"), F.expr("o_orderdate + INTERVAL 2 HOURS").alias("h"),
    )


@query("array_functions", "SELECT doc_id, len(list_distinct(string_split(lower(text), ' '))) AS n, array_to_string(list_sort(list_distinct(list_filter(string_split(text, ' '), lambda x: length(x) > 6))), ',') AS long_words, CAST(list_sum(list_transform(string_split(text, ' '), lambda x: length(x))) AS BIGINT) AS letters FROM documents")
def array_functions(spark, sf_dir):
    words = F.split("text", " ")
    return read(spark, sf_dir, "documents").select(
        "doc_id", F.size(F.array_distinct(F.split(F.lower("text"), " "))).cast("long").alias("n"),
        F.array_join(F.sort_array(F.array_distinct(F.filter(words, lambda x: F.length(x) > 6))), ",").alias("long_words"), F.aggregate(words, F.lit(0).cast("long"), lambda s, x: s + F.length(x)).alias("letters"),
    )


@query("map_functions", _CELLS + "SELECT block_ix, array_to_string(list_sort(list(part_ix)), ',') AS parts, CAST(sum(n * 2) AS BIGINT) AS doubled, CAST(coalesce(sum(n) FILTER (part_ix = 0), 0) AS BIGINT) AS at_zero FROM cells GROUP BY 1")
def map_functions(spark, sf_dir):
    maps = planned(spark, sf_dir).cells.groupBy("block_ix").agg(F.map_from_entries(F.collect_list(F.struct("part_ix", "n"))).alias("loads"))
    twice = F.map_values(F.transform_values("loads", lambda k, v: v * 2))
    return maps.select("block_ix", F.array_join(F.sort_array(F.map_keys("loads")).cast("array<string>"), ",").alias("parts"), F.aggregate(twice, F.lit(0).cast("long"), lambda s, x: s + x).alias("doubled"), F.coalesce(F.try_element_at("loads", F.lit(0)), F.lit(0)).cast("long").alias("at_zero"))


@query("json_functions", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, json_extract_string(props, '$.missing') AS missing FROM events")
def json_functions(spark, sf_dir):
    return read(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"), F.get_json_object("props", "$.missing").alias("missing"))


@query("html_titles", "SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title FROM pages")
def html_titles(spark, sf_dir):
    return read(spark, sf_dir, "pages").select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"))


@query("sql_functions", f"WITH {oracle.base()}, {oracle.PLACES} SELECT least(i, j) AS left_id, greatest(i, j) AS right_id, p AS number FROM numbered")
def sql_functions(spark, sf_dir):
    """Pair numbers by the registered SQL functions."""
    from .functions import register
    from .operators import pair_interval

    register(spark)
    p = planned(spark, sf_dir)
    x = pair_interval.with_entity_index(p.records, p.cells).join(p.profile.select("block_ix", "n", "first_pair"), "block_ix")
    return spark.sql("SELECT least(a.entity_id, b.entity_id) AS left_id, greatest(a.entity_id, b.entity_id) AS right_id, pair_cell(a.entity_ix, b.entity_ix, a.n) + a.first_pair AS number FROM {x} a JOIN {x} b ON a.block_ix = b.block_ix AND a.entity_ix < b.entity_ix", x=x)


@query("table_functions", f"WITH {oracle.base()}, {oracle.PLACES} SELECT i AS entity_id, {oracle.interval('p', 12)} AS reduce_ix FROM numbered UNION SELECT j, {oracle.interval('p', 12)} FROM numbered")
def table_functions(spark, sf_dir):
    """Intervals of each record by the Python table function: a check of the closed form, record by record."""
    from .functions import register
    from .operators import pair_interval

    register(spark)
    p = planned(spark, sf_dir)
    x = pair_interval.with_entity_index(p.records, p.cells).join(p.profile.where("pairs > 0").select("block_ix", "n", "first_pair"), "block_ix")
    return spark.sql(f"SELECT entity_id, t.reduce_ix FROM {{x}}, LATERAL intervals_of(entity_ix, n, first_pair, {p.total}L, 12L) t", x=x)


@query("wide_profile", f"WITH {oracle.base()} SELECT block_ix, CAST(pairs AS DECIMAL(38, 0)) AS pairs, CAST(first_pair AS DECIMAL(38, 0)) AS first_pair FROM profile")
def wide_profile(spark, sf_dir):
    cells = planned(spark, sf_dir).cells
    return matrix.block_profile(cells, wide=True).select("block_ix", "pairs", "first_pair")


@query("strict_keys", f"SELECT entity_id, block_key FROM ({oracle.strict(oracle.DOCUMENTS)})")
def strict_keys(spark, sf_dir):
    return keys.with_block_key(documents(spark, sf_dir), F.col("block_key"), "strict").select("entity_id", "block_key")
