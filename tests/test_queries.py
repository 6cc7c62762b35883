"""Registered queries against their SQL on the smallest given tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
NAMES = ["w01_running_example_shares", "w02_trade_nonlinear_extension", "w03_cyclic_hybrid", "w04_linear_chain_reduced", "w07_triangle", "w08_hub_triangle", "w10_condition_extension", "w18_dialog", "w20_events_binary", "w29_sql_running", "o_j8_range", "o_j9_asof", "o_a3_cube", "o_st4_dedup", "g_count_terms", "c_visited", "w30_cycle_with_ears_hybrid", "b4_shared_applications", "g_represented", "g_insert_terms", "c_candidates", "w21_incremental_orders", "o_st9_maintained_restart"]
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="given tables are absent")


@pytest.fixture(scope="module")
def tables():
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{SF}/{f}'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(spark, tables, name):
    got = entry.queries()[name](spark, SF)
    rel = tables.execute(entry.oracle_sql()[name])
    names = [d[0] for d in rel.description]
    assert sorted(got.columns) == sorted(names)
    expected = sorted(map(str, rel.fetchall()))
    assert sorted(str(tuple(r)) for r in got.select(*names).collect()) == expected


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    assert entry.entry(spark).count() == 235
