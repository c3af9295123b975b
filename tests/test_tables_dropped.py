"""Tables that nobody reads any more leave the disk."""

from pathlib import Path

from tests_support import SMALL
from tourspark import session
from tourspark.operators import catalog
from tourspark.plans.components import min_label_components
from tourspark.session import scratch, stage, stage_alone


def tables(spark):
    root = Path(session.stages_dir(spark).removeprefix("file:"))
    return {p.parent for p in root.rglob("_SUCCESS")} if root.exists() else set()


def test_runs_that_are_timed_leave_no_tables(spark):
    before = tables(spark)
    rows = catalog.queries()["workload_strong_scaling"](spark, SMALL).collect()
    # the graph alone, and what numbered its edges
    assert [r["n"] for r in rows] == [1, 2, 4, 8] and len(tables(spark) - before) <= 3


def test_rounds_keep_the_tables_of_one(spark):
    before = tables(spark)
    ring = [(i, (i + 1) % 5000) for i in range(5000)]
    found = min_label_components(spark.createDataFrame(ring, "u long, v long"))
    assert len(tables(spark) - before) == 1  # names
    assert [tuple(r) for r in found.groupBy("comp").count().collect()] == [(0, 5000)]


def test_scratch_is_deleted_and_results_stay(spark):
    before = tables(spark)
    with scratch(spark):
        out = stage_alone(spark, lambda: stage(spark.range(7).toDF("x"), "way").where("x > 2"), "out")
        assert out.count() == 4 and len(tables(spark) - before) == 1
    assert tables(spark) == before
