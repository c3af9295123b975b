"""Registered queries against their SQL at the smallest scale."""

import pytest

from tests_support import SMALL
from tourspark.operators import catalog

ORACLES = catalog.oracle_sql()
#: Those that run whole circuits have tests of their own.
SLOW = ("audit", "circuit_edge", "circuit_vertex", "phase1_", "memory_", "pairing", "sequential_", "st_", "level_stats", "exceptall", "cover")
QUICK = sorted(n for n in ORACLES if not any(s in n for s in SLOW))


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_sql(spark, duck, rows_of, name):
    assert rows_of(catalog.queries()[name](spark, SMALL)) == duck(ORACLES[name])


@pytest.mark.parametrize("name", ["st_tumbling", "st_session", "st_dedup", "st_parity_state", "st_join"])
def test_stream_equals_batch(spark, duck, rows_of, name):
    assert rows_of(catalog.queries()[name](spark, SMALL)) == duck(ORACLES[name])


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(catalog.queries())
