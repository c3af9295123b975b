"""Streams over tables of many files: batches go by the query's own parts, not by files."""

import pytest

from tests_support import SMALL
from tourspark.operators import catalog


@pytest.fixture(scope="module")
def many_files(spark, tmp_path_factory):
    """The small events in eight files, each over the whole time."""
    folder = tmp_path_factory.mktemp("many")
    spark.read.parquet(f"{SMALL}/events.parquet").repartition(8, "event_id").write.parquet(f"{folder}/events.parquet")
    return str(folder)


@pytest.mark.parametrize("name", ["st_late", "st_circuit_of_windows"])
def test_batches_do_not_go_by_files(spark, duck, rows_of, many_files, name):
    assert rows_of(catalog.queries()[name](spark, many_files)) == duck(catalog.oracle_sql()[name])
