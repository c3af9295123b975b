"""Circuits of every method against their graphs; policies, restart, rejections, plans."""

import random

import pytest
from pyspark.sql import functions as F

from tests_support import SMALL
from tourspark import graphs
from tourspark.functions.graph import Graph, double_edges, repair_parity, validate_partitioning
from tourspark.plans import baselines, extensions, phase2, phase3, verify
from tourspark.plans.circuit import circuit
from tourspark.plans.metagraph import join_levels, merge_tree, meta_graph
from tourspark.session import stage


def sound(g, made, comps=None):
    made = stage(made, "t")
    rows = verify.audit(g, made).collect()
    assert rows and all(r["chained"] and r["closed"] and r["complete"] and r["n_edges"] == r["distinct_eids"] for r in rows), rows
    assert verify.uncovered(g, made).count() == 0
    assert verify.parity_holds(g, verify.vertex_visits(made)).count() == 0
    assert comps is None or len(rows) == comps
    return made


@pytest.fixture(scope="module")
def worked(spark):
    g = graphs.worked_example(spark)
    return g.map_edges(stage(g.edges, "w"))


METHODS = {
    "merge": circuit, "no splice": lambda g: circuit(g, merge_internal=False), "rounds": lambda g: circuit(g, forest="boruvka", rank="doubling"),
    "sequential": baselines.sequential_circuit, "one task": lambda g: baselines.sequential_circuit(g, False), "pairing": baselines.pairing_circuit,
    "hybrid": lambda g: baselines.hybrid_circuit(g, 0), "hybrid option": lambda g: circuit(g, last_levels="pairing"),
    "token": lambda g: baselines.single_token_circuit(g)[0],
}


@pytest.mark.parametrize("name", METHODS)
def test_worked_example(worked, name):
    made = sound(worked, METHODS[name](worked), 1)
    visits = {r["v"]: r["visits"] for r in verify.vertex_visits(made).collect()}
    assert visits == {v: 2 if v in (3, 12) else 1 for v in range(1, 15)}


def test_token_needs_a_superstep_an_edge_at_least(worked):
    assert baselines.single_token_circuit(worked)[1] >= 16


@pytest.mark.parametrize("seed", range(2))
def test_random_graphs_of_many_components(spark, seed):
    rng = random.Random(seed)
    edges = []
    for base in (0, 100, 200):
        for _ in range(rng.randint(1, 4)):
            ring = [base + rng.randrange(9) for _ in range(rng.randint(1, 9))]
            edges += list(zip(ring, ring[1:] + ring[:1], strict=True))
    edges += [(300, 300), (400, 401), (400, 401)]
    g = Graph.from_edges(spark.createDataFrame(edges, "u long, v long"))
    g = g.map_edges(stage(g.edges, "r")).with_partition("hash", 5)
    comps = baselines.components(g).select("comp").distinct().count()
    for name in ("merge", "rounds", "hybrid"):
        sound(g, METHODS[name](g), comps)


def test_policies_give_the_same_fragments(spark):
    g = graphs.even_graph(spark, SMALL, "event_trail", 4)
    g = g.map_edges(stage(g.edges, "p"))
    tree = merge_tree(meta_graph(g), phase2.parts_of(g))
    seen = []
    for policy in phase2.POLICIES:
        ledger = phase2.run_levels(g, tree, remote_policy=policy).ledger
        seen.append((sorted(map(tuple, ledger.all_frags().drop("seconds").collect())), sorted(map(tuple, ledger.all_items().collect()))))
    assert all(s == seen[0] for s in seen)


def test_restart_after_the_last_level_is_lost(spark):
    g = graphs.even_graph(spark, SMALL, "event_trail", 4)
    g = g.map_edges(stage(g.edges, "p"))
    tree = merge_tree(meta_graph(g), phase2.parts_of(g))
    run = phase2.run_levels(g, tree)
    before = sorted(map(tuple, run.ledger.all_items().collect()))
    run.ledger.drop(2)
    assert run.ledger.levels() == [0, 1]
    again = phase2.run_levels(g, tree, ledger_path=run.ledger.path)
    assert sorted(map(tuple, again.ledger.all_items().collect())) == before
    sound(g, phase3.close_walks(phase3.unroll(again.ledger)), 1)
    assert sound(g, spark.createDataFrame(phase3.unroll_sequential(again.ledger), phase3.CIRCUIT), 1)


def test_forest_and_pairing_of_idle_parts(spark):
    g = graphs.even_graph(spark, SMALL, "geo_doubled")
    g = g.map_edges(stage(g.edges, "geo"))
    sound(g, circuit(g), 5)
    run = phase2.build(g, zero_weight="stop")
    assert run.tree.height == 0
    sound(g, phase3.close_walks(phase3.unroll(run.ledger)), 5)


def test_an_odd_graph_is_rejected_and_names_its_vertices(spark):
    g = Graph.from_edges(spark.createDataFrame([(1, 2), (2, 3), (3, 4)], "u long, v long"))
    with pytest.raises(ValueError, match=r"\[1, 4\]"):
        circuit(g)
    trail = extensions.trail_summary(extensions.open_trail(g)).collect()
    assert [tuple(r) for r in trail] == [(3, True, 1, 4)]


def test_covering_walk(spark):
    g = Graph.from_edges(spark.createDataFrame([(1, 2), (2, 3), (3, 4), (3, 5)], "u long, v long"))
    walk, extra = extensions.covering_walk(g)
    assert extra == 4
    assert [tuple(r) for r in extensions.cover_summary(g, walk, extra).collect()] == [(True, True, 4)]


def test_covering_walk_at_a_hub_stays_linear(spark, monkeypatch):
    """600 odd leaves of one hub: no table of balls or pairs grows with their square."""
    g = Graph.from_edges(spark.range(1, 601).selectExpr("0L AS u", "id AS v"))
    g = g.map_edges(stage(g.edges, "star"))
    sizes: list[int] = []

    def counted(df, label, *more):
        out = stage(df, label, *more)
        sizes.append(out.count())
        return out

    monkeypatch.setattr(extensions, "stage", counted)
    walk, extra = extensions.covering_walk(g)
    assert extra == 600 and max(sizes) <= 4 * 600
    assert [tuple(r) for r in extensions.cover_summary(g, walk, extra).collect()] == [(True, True, 600)]


def test_null_ends_are_left_out_and_an_empty_graph_has_no_circuit(spark):
    rows = spark.createDataFrame([(1, None), (None, 2)], "u long, v long")
    g = Graph.from_edges(rows)
    assert g.edges.count() == 0
    assert circuit(g, n=2).count() == 0


def test_a_vertex_in_two_parts_is_a_violation(spark):
    g = Graph.from_edges(spark.createDataFrame([(1, 2), (1, 2)], "u long, v long"))
    bad = spark.createDataFrame([(1, 0), (1, 1)], "v long, part int")
    assert {r["rule"] for r in validate_partitioning(g, bad).collect()} >= {"cover", "disjoint"}


def test_repair_makes_even(spark):
    g = Graph.from_edges(graphs.order_part(spark, SMALL))
    for pairing in ("by_id", "by_degree", "within_component"):
        fixed = repair_parity(g, pairing)
        assert fixed.edges.where("added").count() == 422
    sound(fixed, circuit(fixed, n=4))


def test_forms(worked, spark, tmp_path):
    rows = circuit(worked, form="vertices", start_vertex=3).orderBy("pos").collect()
    assert len(rows) == 17 and rows[0]["v"] == rows[-1]["v"] == 3
    assert len(circuit(worked, form="array").first()["circuit"]) == 16
    sound(worked, circuit(worked, sink=str(tmp_path / "c")), 1)


def test_tree_tour(spark):
    tree = Graph.from_edges(spark.createDataFrame([(1, 2), (1, 3), (3, 4), (10, 11)], "u long, v long"))
    made = stage(baselines.tree_tour(tree), "t")
    sound(Graph(double_edges(tree).edges), made, 2)


def test_partitioners_keep_their_limits(spark):
    g = Graph.from_edges(graphs.torus(spark, 16, 16))
    for how in ("bfs", "lpa", "hash", "range", "modulo"):
        own = g.with_partition(how, 4)
        assert validate_partitioning(own).count() == 0
    sound(g, circuit(g.with_partition("bfs", 4)), 1)


def test_plan_of_a_level_prunes_and_exchanges_once(spark):
    g = graphs.even_graph(spark, SMALL, "event_trail", 4)
    g = g.map_edges(stage(g.edges, "p"))
    tree = merge_tree(meta_graph(g), phase2.parts_of(g))
    levelled = phase2.prepare(g, tree)
    items = phase2.edge_items(levelled.where("join_level = 1"), tree.maps()[1])
    plan = phase2.phase1(items, 1, [0, 1])._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(join_level" in plan
    # one exchange, by the part's own number, and none by a hash that two parts might share
    assert plan.count("Exchange") - plan.count("BroadcastExchange") == 1 and "hashpartitioning" not in plan and "SinglePartition" not in plan
    assert "BroadcastHashJoin" in plan and "MapInArrow" in plan
    assert "Exchange hashpartitioning" not in join_levels(g, tree)._jdf.queryExecution().executedPlan().toString()


def test_dense_numbers(spark):
    from tourspark.functions.numbering import dense_number

    rows = dense_number(spark.range(1000).select((F.col("id") * 7919 % 1000).alias("x")), ["x"], "n", 5)
    assert rows.where("n <> x + 5").count() == 0
    assert dense_number(spark.range(0), ["id"]).count() == 0


def test_pairs_of_a_hub_use_every_candidate(spark):
    """All 600 leaves of a hub are two apart; the first 100,000 of 179,700 pairs begin at
    some 200 of them."""
    from pyspark.sql import functions as F

    a, b = spark.range(600).withColumnRenamed("id", "from"), spark.range(600).withColumnRenamed("id", "at")
    meets = a.join(b, F.col("from") < F.col("at")).withColumn("way", F.array("from", "at"))
    rows = extensions._disjoint(meets).collect()
    assert len(rows) == 300 and len({v for r in rows for v in (r["x"], r["y"])}) == 600
