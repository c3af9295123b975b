"""What must hold beyond one machine: parts in tasks of their own, no hot key in one task,
rounds on the cluster that give what a driver gives."""

import random

import pytest
from pyspark.sql import functions as F

from tests_support import SMALL
from tourspark import graphs
from tourspark.functions.graph import Graph
from tourspark.functions.numbering import dense_number
from tourspark.functions.rings import with_next
from tourspark.plans import baselines, measures, phase2, phase3, verify
from tourspark.plans.circuit import circuit, switch_level
from tourspark.plans.metagraph import greedy_matching, greedy_matching_distributed, join_levels, merge_tree, merge_tree_distributed, meta_graph, tree_for, with_holders
from tourspark.plans.phase1 import dealt
from tourspark.session import stage

ITEM = "part int, kind string, item_id long, a long, b long, len long, ra int, rb int"


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def plain(df):
    return sorted(map(tuple, df.collect()))


@pytest.fixture(scope="module")
def trail(spark):
    g = graphs.even_graph(spark, SMALL, "event_trail", 4)
    return g.map_edges(stage(g.edges, "trail"))


@pytest.mark.parametrize("parts", [[0, 1], [0, 1, 2, 3], list(range(8)), list(range(64)), [1, 3, 5, 7], [2, 9, 40, 41, 77]])
def test_every_part_has_a_task_of_its_own(spark, parts):
    rows = [(p, "edge", 100 * p + i, i, i + 1, 1, 0, 0) for p in parts for i in range(5)]
    placed = dealt(spark.createDataFrame(rows, ITEM), parts).withColumn("task", F.spark_partition_id())
    found = {(r["task"], r["part"]) for r in placed.collect()}
    assert len(found) == len({t for t, _ in found}) == len({p for _, p in found}) == len(parts)


def test_next_rows_of_rings(spark):
    rows = [(k, (i * 7919) % 1000 + k, f"r{i}") for k, n in ((1, 300), (2, 1), (3, 17)) for i in range(n)]
    df = spark.createDataFrame(rows, "k int, pos int, name string")
    for block in (F.shiftright("pos", 5), F.lit(0)):
        found = {(r["k"], r["pos"], r["name"]): (r["p2"], r["n2"]) for r in with_next(df, ["k"], ["pos"], block, {"pos": "p2", "name": "n2"}).collect()}
        for k in (1, 2, 3):
            own = sorted((p, n) for x, p, n in rows if x == k)
            assert all(found[k, *a] == b for a, b in zip(own, own[1:] + own[:1], strict=True))


def test_a_hub_is_paired_in_cells(spark):
    ends = [(1, s) for s in range(1000)] + [(2, s) for s in range(1000, 1004)] + [(3, 2000), (3, 2001)]
    df = spark.createDataFrame(ends, "v long, spot long")
    at = {s: v for v, s in ends}
    for hub in (10**6, 50):
        mate = dict(plain(baselines._paired(df, hub)))
        assert set(mate) == set(at) and all(mate[mate[s]] == s != mate[s] and at[s] == at[mate[s]] for s in mate)


def test_repeated_rows_are_dealt_over_ranges(spark):
    df = spark.range(20_000).select((F.col("id") * 0).alias("u"), (F.col("id") * 0 + 1).alias("v")).repartition(8)
    out = dense_number(df, ["u", "v"], "n")
    assert out.agg(F.min("n"), F.max("n"), F.countDistinct("n")).first() == (1, 20_000, 20_000)
    sizes = [r["count"] for r in df.withColumn("t", F.monotonically_increasing_id()).repartitionByRange(8, "u", "v", "t").groupBy(F.spark_partition_id()).count().collect()]
    assert max(sizes) < 8000


def test_rounds_give_the_drivers_circuit(spark, trail):
    """Either side of the row bound: the same forest, the same ranks, the same circuit."""
    run = phase2.run_levels(trail, tree_for(trail, phase2.parts_of(trail)), merge_internal=False)
    walks = stage(phase3.unroll(run.ledger), "walks")
    a = plain(phase3.close_walks(walks, "driver", "driver"))
    assert a == plain(phase3.close_walks(walks, "boruvka", "doubling")) and len(a) == trail.edges.count()


def test_items_meet_nodes_by_block(spark, trail, monkeypatch):
    """With blocks of four positions the walks are the same, and the join has the block."""
    run = phase2.run_levels(trail, tree_for(trail, phase2.parts_of(trail)))
    whole = plain(phase3.unroll(run.ledger))
    monkeypatch.setattr(phase3, "BLOCK_SHIFT", 2)
    made = phase3.unroll(run.ledger)
    assert "block" in plan(made) and plain(made) == whole
    audited = verify.audit(trail, stage(phase3.close_walks(made), "c")).first()
    assert audited["chained"] and audited["closed"] and audited["complete"]


def test_edges_only_ledgers_unroll_to_the_same(spark, trail):
    tree = tree_for(trail, phase2.parts_of(trail))
    bare = phase2.run_levels(trail, tree, emit_vertices=False)
    assert bare.ledger.all_items().where("a is not null or b is not null").isEmpty()
    assert plain(phase3.unroll(bare.ledger, trail.edges)) == plain(phase3.unroll(phase2.run_levels(trail, tree).ledger))


def test_the_budget_forces_the_switch(spark, trail):
    """From the level table alone; with no budget for level 0 all is paired."""
    tree = tree_for(trail, phase2.parts_of(trail))
    joined = stage(join_levels(trail, tree), "j")
    largest = {r["level"]: r["m"] for r in measures.level_stats(joined, tree).groupBy("level").agg(F.max("local").alias("m")).collect()}
    assert switch_level(joined, tree, max(largest.values())) is None
    assert switch_level(joined, tree, largest[0] - 1) == -1
    assert switch_level(joined, tree, max(largest[0], largest[1])) == 1
    for budget in (max(largest[0], largest[1]), 1):
        rows = stage(circuit(trail, budget=budget, check=False), "c")
        found = verify.audit(trail, rows).first()
        assert found["complete"] and found["closed"] and found["chained"]


def test_the_heavier_side_drops_its_copy(spark, trail):
    tree = tree_for(trail, phase2.parts_of(trail))
    rows = [r.asDict() for r in with_holders(stage(join_levels(trail, tree), "j"), tree).collect()]
    maps = tree.maps()

    def weight(level, part):
        return sum((maps[level][r["pu"]] == part) + (maps[level][r["pv"]] == part) for r in rows if r["join_level"] > level)

    known = {}
    for r in rows:
        if not r["join_level"]:
            assert r["holder"] == r["pu"]
            continue
        level = r["join_level"] - 1
        sides = [(known.setdefault((level, maps[level][p]), weight(level, maps[level][p])), -maps[level][p], p) for p in (r["pu"], r["pv"])]
        assert r["holder"] == min(sides)[2]  # the lighter keeps it; of equals the larger id
    assert len({r["holder"] == r["pu"] for r in rows if r["join_level"]}) == 2


def test_fragments_are_those_of_any_policy(spark, trail):
    tree = tree_for(trail, phase2.parts_of(trail))
    made = [plain(phase2.run_levels(trail, tree, remote_policy=p).ledger.all_items()) for p in phase2.POLICIES]
    assert all(m == made[0] for m in made)


def test_an_unfinished_tree_is_named(spark, trail):
    forest = merge_tree([(0, 1, 1)], [0, 1, 2, 3], zero_weight="stop")
    with pytest.raises(ValueError, match="more than one root"):
        phase2.run_levels(trail, forest)


@pytest.mark.parametrize("ties", ["id", "digest"])
def test_matchings_on_a_ring_of_equal_weights(spark, ties):
    ring = [(min(i, (i + 1) % 20), max(i, (i + 1) % 20), 5) for i in range(20)]
    found = greedy_matching_distributed(spark.createDataFrame(ring, "a int, b int, weight long"), ties)
    assert plain(found) == sorted(greedy_matching(ring, ties))


def test_a_meta_graph_too_large_for_a_driver_stays_in_the_cluster(spark, trail, monkeypatch):
    from tourspark.plans import metagraph

    monkeypatch.setattr(metagraph, "DRIVER_META", 1)
    assert tree_for(trail, [0, 1, 2, 3]).merges == merge_tree(meta_graph(trail), [0, 1, 2, 3], ties="digest").merges
    assert merge_tree_distributed(meta_graph(trail), [0, 1, 2, 3]).merges == merge_tree(meta_graph(trail), [0, 1, 2, 3]).merges
    with pytest.raises(ValueError, match="greedy tree"):
        tree_for(trail, [0, 1, 2, 3], "random")


def test_parts_keep_their_places(spark):
    """Growth goes on to the end; what no seed reaches is dealt out, and no part is overfull."""
    rng = random.Random(2)
    edges = [(i, rng.randrange(i)) for i in range(1, 150)] + [(1000 + i, 1000 + (i + 1) % 60) for i in range(60)] + [(5000 + 2 * i, 5001 + 2 * i) for i in range(20)]
    g = Graph.from_edges(spark.createDataFrame(edges, "u long, v long"))
    for how in ("bfs", "lpa"):
        sizes = {r["part"]: r["count"] for r in g.with_partition(how, 4, slack=0.05).vertices.groupBy("part").count().collect()}
        assert sum(sizes.values()) == 250 and max(sizes.values()) <= -(-250 * 1.05 // 4)


def test_clocks_are_within_the_tasks_time(spark, trail):
    import time

    began = time.perf_counter()
    run = phase2.run_levels(trail, tree_for(trail, phase2.parts_of(trail)))
    wall = time.perf_counter() - began
    rows = measures.time_split(run.ledger).collect()
    assert rows and all(r["seconds"] == pytest.approx(r["build"] + r["walk"] + r["emit"]) for r in rows)
    for level in {r["level"] for r in rows}:
        assert max(r["receive"] + r["seconds"] for r in rows if r["level"] == level) < wall
    shares = measures.time_shares(run.ledger).first()
    assert shares["receive"] + shares["build"] + shares["walk"] + shares["emit"] == pytest.approx(1.0)
    clock = measures.timed(lambda: spark.range(100).repartition(3))[1]
    assert clock["seconds"] > 0 and clock["tasks"] >= 3 and clock["stages"] >= 2 and clock["jobs"] >= 1


def test_days_are_built_once_from_all_their_batches(spark):
    """A day cut at noon is one circuit; a row of a day that is closed is counted as late."""
    from tourspark.operators.streams import day_circuits
    from tourspark.streaming import events as ev

    base = 1_700_006_400  # a midnight
    rows = [(k, base + s, k % 5) for k, s in enumerate([0, 10, 30_000, 43_000, 44_000, 80_000, 90_000, 100_000, 180_000, 190_000])]
    df = spark.createDataFrame(rows, "event_id long, t long, user_id long").select("event_id", F.timestamp_seconds("t").alias("ts"), "user_id", F.lit("x").alias("event_type"), F.lit(1.0).alias("value")).coalesce(1)
    late = df.where("event_id = 1").withColumn("event_id", F.lit(99).cast("long"))
    path = ev.staged_copies([df.where("event_id < 4"), df.where("event_id >= 4 AND event_id < 9"), late, df.where("event_id = 9")], gap=1.1)
    made, seen = ev.circuits_of_days(ev.stream_of(spark, path), day_circuits)
    days = {r["day"] - base // 86_400: (r["n_edges"], r["chained"], r["closed"]) for r in made.collect()}
    assert days == {0: (6, True, True), 1: (2, True, True), 2: (2, True, True)}
    assert sum(r["late"] for r in seen.collect()) == 1
