"""Plans: what reaches the scan, and what is not exchanged."""

from tests_support import SMALL
from tourspark import graphs
from tourspark.functions import graph as fg
from tourspark.functions.graph import Graph
from tourspark.operators import relational
from tourspark.session import stage


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_filters_and_columns_reach_the_scan(spark):
    made = relational.op_scan_project_filter(spark, SMALL)._jdf.queryExecution()
    text = spark.sparkContext._jvm.PythonSQLUtils.explainString(made, "formatted")
    assert "GreaterThanOrEqual(l_shipdate" in text and "In(l_returnflag" in text
    assert "l_extendedprice" in text.split("ReadSchema")[1] and "l_tax" not in text


def test_degrees_are_summed_before_the_exchange(spark):
    text = plan(fg.degrees(Graph.from_edges(graphs.supply_multi(spark, SMALL))))
    assert "partial_count" in text and text.count("Exchange hashpartitioning(v") == 1


def test_parts_by_expression_need_no_join(spark):
    g = Graph.from_edges(graphs.supplier_loops(spark, SMALL)).with_partition("hash", 8)
    g = g.map_edges(stage(g.edges, "plan"))
    assert "Join" not in plan(fg.split_edges(g)) and "Exchange" not in plan(fg.split_edges(g))


def test_small_sides_are_broadcast(spark):
    assert plan(relational.op_nation_region_broadcast(spark, SMALL)).count("BroadcastHashJoin") == 2
    assert "ShuffledHashJoin" in plan(relational.op_shuffle_hash_hint(spark, SMALL))
    assert "SortMergeJoin" in plan(relational.op_order_line_sortmerge(spark, SMALL))


def test_no_plan_brings_all_rows_to_one_task(spark):
    for build in (graphs.supplier_loops, graphs.event_trail, graphs.order_part):
        assert "SinglePartition" not in plan(Graph.from_edges(build(spark, SMALL)).edges)


def test_tables_of_vertices_stay_out_of_the_driver(spark):
    g = Graph.from_edges(graphs.supplier_loops(spark, SMALL))
    parts = stage(fg.vertex_parts(g.with_partition("hash", 4)), "plan")
    text = plan(fg.split_edges(Graph(stage(g.edges, "plan"), parts, 4)))
    assert "BroadcastHashJoin" not in text and text.count("SortMergeJoin") == 2
