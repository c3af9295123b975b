"""Level tables and memory curves against golden values."""

import pytest

from tests_support import MIDDLE
from tourspark import graphs
from tourspark.plans import measures, phase2
from tourspark.plans.metagraph import join_levels, merge_tree, meta_graph
from tourspark.session import stage

# Level -> internal, odd, even, local, remote.
GOLDEN = {
    "worked": {0: (5, 8, 1, 11, 5), 1: (5, 4, 0, 7, 2), 2: (4, 0, 0, 4, 0)},
    "event_trail": {0: (0, 84, 66, 1271, 8729), 1: (0, 70, 80, 1395, 7376), 2: (0, 72, 78, 2501, 4910), 3: (150, 0, 0, 4946, 0)},
    "supplier_loops": {0: (0, 972, 1028, 7535, 52465), 1: (0, 962, 1038, 8081, 44870), 2: (0, 1004, 996, 15451, 29900), 3: (2000, 0, 0, 30402, 0)},
    "order_part_repaired": {0: (40, 5776, 10927, 7654, 56614), 1: (192, 7788, 8723, 11439, 48063), 2: (1141, 8344, 7026, 20197, 31760), 3: (15370, 0, 0, 35932, 0)},
    "torus": {0: (3072, 1024, 0, 7680, 512), 1: (512, 512, 0, 768, 256), 2: (256, 256, 0, 384, 128), 3: (256, 0, 0, 256, 0)},
}
# Cumulative state at start and end of each level, by policy.
STATE = {
    ("carry_both", "start"): [122_000, 107_902, 92_702, 62_804], ("carry_one", "start"): [69_535, 63_032, 62_802, 62_804],
    ("carry_one+deferred", "start"): [17_070, 18_162, 32_902, 62_804], ("carry_both", "end"): [107_902, 92_702, 62_804, 0],
    ("carry_one", "end"): [55_437, 47_832, 32_904, 0], ("carry_one+deferred", "end"): [2_972, 2_962, 3_004, 0],
}


def stats_of(spark, name):
    g = graphs.even_graph(spark, MIDDLE, name)
    g = g.map_edges(stage(g.edges.select("eid", "u", "v"), "m"))
    tree = merge_tree(meta_graph(g), phase2.parts_of(g))
    return g, tree, stage(measures.level_stats(join_levels(g, tree), tree), "s")


@pytest.mark.parametrize("name", GOLDEN)
def test_level_tables(spark, name):
    _, _, stats = stats_of(spark, name)
    found = {r["level"]: (r["i"], r["ob"], r["eb"], r["local"], r["remote"]) for r in measures.level_totals(stats).collect()}
    assert found == GOLDEN[name]


def test_memory_curves(spark):
    _, _, stats = stats_of(spark, "supplier_loops")
    got = {k: [r["cumulative"] for r in measures.memory_state(stats, *k).orderBy("level").collect()] for k in STATE}
    assert got == STATE
    # carrying both copies, merging alone changes nothing
    assert got["carry_both", "end"][:-1] == got["carry_both", "start"][1:]
    for lv in range(4):
        assert got["carry_one+deferred", "start"][lv] <= got["carry_one", "start"][lv] <= got["carry_both", "start"][lv]
    cut = {r["level"]: r["percent"] for r in measures.memory_reduction(measures.memory_state(stats, "carry_both", "end"), measures.memory_state(stats, "carry_one", "end")).collect()}
    assert 40 < cut[0] < 55 and cut[3] == 0
    held = {r["level"]: r["leaf_held"] for r in measures.memory_state(stats, "carry_one+deferred").collect()}
    assert held == {0: 52_465, 1: 44_870, 2: 29_900, 3: 0}


def test_the_kernel_finds_what_the_closed_forms_say(spark):
    g, tree, stats = stats_of(spark, "torus")
    ledger = phase2.run_levels(g, tree).ledger
    paths = {(r["level"], r["part"]): r["count"] for r in ledger.all_frags().where("ftype = 'path'").groupBy("level", "part").count().collect()}
    assert paths == {(r["level"], r["part"]): r["ob"] // 2 for r in stats.collect() if r["ob"]}
    items = {r["level"]: r["count"] for r in ledger.all_items().groupBy("level").count().collect()}
    assert items == {k: v[3] for k, v in GOLDEN["torus"].items()}


def test_supersteps_and_points(spark):
    assert [r["supersteps"] for r in measures.supersteps(spark, [2, 3, 4, 8]).collect()] == [2, 3, 3, 4]
    _, tree, stats = stats_of(spark, "event_trail")
    assert measures.phase1_work(stats).count() == 15
    sent = {r["level"]: (r["total"], r["largest"]) for r in measures.communication_totals(measures.communication(stats, tree)).collect()}
    assert set(sent) == {0, 1, 2} and all(a >= b for a, b in sent.values())


def test_fit_formula(spark):
    row = measures.complexity_fit(spark.createDataFrame([(float(i), 2.0 * i + 1) for i in range(15)], "expected double, observed double")).first()
    assert (row["slope"], row["intercept"], row["r2"], row["n"]) == (2.0, 1.0, 1.0, 15)
