"""Queries that measure levels keep fragments and figures, and no items, which they never read."""

import pytest

from tourspark import graphs
from tourspark.functions.graph import Graph
from tourspark.operators import workloads
from tourspark.plans import measures, partitioners, phase2
from tourspark.plans.ledger import Ledger
from tourspark.session import stage

SMALL = "/root/testdata/sf0.001"


@pytest.fixture
def ledgers(monkeypatch):
    made = []

    def create(spark, path=None, create=Ledger.create):
        made.append(create(spark, path))
        return made[-1]

    monkeypatch.setattr(Ledger, "create", staticmethod(create))
    return made


def _nothing_but_heads(ledgers, n):
    assert len(ledgers) == n
    for x in ledgers:
        assert x.levels() == [0, 1, 2, 3] and x.all_items().isEmpty() and not x.all_frags().isEmpty()


def test_detail(spark, ledgers):
    rows = workloads.workload_detail(spark, SMALL).collect()
    assert len(rows) == 30 and all(r["items"] == r["local"] and r["seconds"] > 0 for r in rows)
    _nothing_but_heads(ledgers, 2)


def test_complexity_fit(spark, ledgers):
    rows = {r["graph"]: r for r in workloads.workload_complexity_fit(spark, SMALL).collect()}
    assert {k: r["n"] for k, r in rows.items()} == {"supplier_loops": 15, "order_part_repaired": 15}
    _nothing_but_heads(ledgers, 2)


def test_partitioned_detail(spark, ledgers):
    assert sorted(map(tuple, workloads.workload_partitioned_detail(spark, SMALL).collect())) == [(level, True) for level in range(4)]
    _nothing_but_heads(ledgers, 1)


def test_levels_are_the_same_without_items(spark):
    g = graphs.even_graph(spark, SMALL, "supplier_loops", 4)
    g = g.map_edges(stage(g.edges, "p"))
    runs = [phase2.build(g, keep_items=keep).ledger for keep in (True, False)]
    heads = [sorted(map(tuple, x.all_frags().collect())) for x in runs]
    figures = [sorted(map(tuple, measures.time_split(x).select("level", "part", "items").collect())) for x in runs]
    assert heads[0] == heads[1] and figures[0] == figures[1] and heads[0]
    with pytest.raises(ValueError):
        phase2.build(g, keep_items=False, ledger_path="/tmp/none")


def test_growth_leaves_what_is_done(spark, monkeypatch):
    """No round keeps what is next to a full part, and edges between vertices that have parts
    are dropped on the way."""
    seen = []

    def kept(df, label, *rest, stage=partitioners.stage):
        made = stage(df, label, *rest)
        seen.append((label, made))
        return made

    monkeypatch.setattr(partitioners, "stage", kept)
    g = Graph.from_edges(graphs.torus(spark, 12, 12))
    at = g.with_partition("bfs", 4, slack=0.0)
    assert sorted(r["count"] for r in at.vertices.groupBy("part").count().collect()) == [36] * 4
    full, held = set(), []
    for label, made in seen:
        if label == "growth":
            full = {r["part"] for r in made.groupBy("part").count().where("count = 36").collect()}
        elif label == "border" and full:
            held.append({r["part"] for r in made.select("part").distinct().collect()} & full)
    assert held and not any(held)
    near = [made.count() for label, made in seen if label == "neighbours"]
    assert len(near) > 1 and near[-1] < near[0] / 2


def test_parts_of_several_numbers_share_what_they_grow_on(spark, monkeypatch):
    """The neighbours are worked out once for all eight rows, and the parts joined once a row."""
    from tourspark.operators import catalog
    from tourspark.plans import measures, partitioners

    asked, split = [], []
    neighbours, edges = partitioners._neighbours, measures.split_edges
    monkeypatch.setattr(partitioners, "_neighbours", lambda g: asked.append(1) or neighbours(g))
    monkeypatch.setattr(measures, "split_edges", lambda g: split.append(1) or edges(g))
    rows = catalog.queries()["workload_partitioned"](spark, "/root/testdata/sf0.001").collect()
    assert len(asked) == 1 and len(split) == 8
    assert sorted((r["how"], r["parts"]) for r in rows) == [(h, n) for h in ("bfs", "lpa") for n in (2, 3, 4, 8)]
    assert len({(r["vertices"], r["edges"]) for r in rows}) == 1
