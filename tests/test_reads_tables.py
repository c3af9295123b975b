"""Queries that once made their data up: they follow their table, and fail without one."""

import pytest
from pyspark.errors import AnalysisException

from tests_support import SMALL
from tourspark.operators import catalog

MOVED = ["graph_complete_odd", "graph_grid_doubled", "level_stats_worked", "merge_tree_worked", "op_datasource_rmat", "op_datasource_torus", "sequential_one_task_audit_worked", "single_token_audit", "supersteps"]


@pytest.mark.parametrize("name", MOVED)
def test_reads_its_table(spark, duck, rows_of, name):
    made = catalog.queries()[name]
    assert rows_of(made(spark, SMALL)) == duck(catalog.oracle_sql()[name])
    with pytest.raises(AnalysisException):
        made(spark, "/nowhere").collect()
