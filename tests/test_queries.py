"""Queries against their SQL in DuckDB on the smallest tables."""

import duckdb
import pytest

import __spark_entry__
from pairbalance import queries

SF = "/root/testdata/sf0.001"

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHOSEN = [
    "block_matrix", "block_profile", "sub_block_placement", "sub_block_load_classed", "pair_interval_pairs", "pair_interval_pairs_span", "sub_block_pairs_auto_pieces", "relevant_intervals_exact",
    "relevant_intervals_span", "pair_numbers", "interval_sizes_ceiling", "uncell_roundtrip", "matches_pair_interval", "matches_sub_block", "two_source_matches", "two_source_pair_interval_load", "missing_keys_one_source",
    "sorted_input_load", "blocking_loss", "matches_combined", "matches_tokens", "pair_checks_roles", "skew_imbalance", "strategy_advice", "stream_sessions", "array_functions", "set_except_all", "multi_key_pairs", "embedding_pairs", "join_asof", "join_overlap", "agg_cube", "win_frames", "table_functions", "sql_functions", "stream_matrix", "stream_interval_join", "stream_block_state",
]


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", CHOSEN)
def test_query(spark, con, name):
    df = queries.QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted(repr(tuple(r)) for r in df.select(*columns).collect())
    cur = con.execute(queries.ORACLE[name])
    names = [d[0] for d in cur.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    assert got == sorted(repr(tuple(r[i] for i in at)) for r in cur.fetchall())


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() == 13


def test_every_oracle_has_a_query():
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
