"""Registered queries against their SQL on the smallest tables."""

import glob
import os

import duckdb
import pytest

import __spark_entry__ as driver
from walkengine.operators import registry

SF = "/root/testdata/sf0.001"
QUICK = ["graph_basket_edges", "graph_trade_edges", "graph_links_edges", "in_positions_basket", "label_histogram_cube", "basket_walks_p2", "walks_to_target_list",
         "session_accepts_p7", "events_session_windows", "asof_next_event", "stream_hourly_labels", "stream_user_automaton", "cheapest_walks_ties",
         "chosen_plans", "sql_nfa_accepts", "sql_pattern_transitions", "graph_files_round_trip", "measure_emission", "geo_region_mates", "basket_walks_p4"]
NAMES = sorted(registry.oracle_sql()) if os.environ.get("WALKENGINE_ALL") else QUICK


@pytest.fixture(scope="module")
def tables():
    con = duckdb.connect()
    for path in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, tables, name):
    got, want = registry.queries()[name](spark, SF).toPandas(), tables.execute(registry.oracle_sql()[name]).fetch_df()
    columns = sorted(want.columns)
    assert sorted(got.columns) == columns
    rows = lambda x: sorted(map(tuple, x[columns].astype(str).replace({"None": "-", "nan": "-", "<NA>": "-"}).values.tolist()))
    assert rows(got) == rows(want)


def test_every_oracle_has_a_query():
    assert set(driver.oracle_sql()) <= set(driver.queries())


def test_entry_has_rows(spark):
    assert driver.entry(spark).count() == 20
