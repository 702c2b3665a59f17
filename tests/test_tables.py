"""Queries that once made their data up: they read a given table and equal their SQL."""

import pytest

from test_entry import tables, test_query_equals_sql as equals_sql  # noqa: F401  the fixture and the comparison

from walkengine.operators import registry

NAMES = ["sql_pattern_transitions", "reduced_automata", "measure_pattern_sizes", "eps_parallel", "baseline_brute_force_demo", "graph_demo_edges"]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table_and_equals_its_sql(spark, tables, tmp_path, name):  # noqa: F811
    equals_sql(spark, tables, name)
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        registry.queries()[name](spark, str(tmp_path)).collect()
