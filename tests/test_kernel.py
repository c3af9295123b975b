"""The local kernel on hand fixtures and random multigraphs."""

import random

import numpy as np
import pytest

from tourspark.graphs import WORKED_EDGES, WORKED_PARTS
from tourspark.plans.baselines import closed_tour
from tourspark.plans.phase1 import fragments


def made(edges, boundary=(), **options):
    a, b = (np.array([e[i] for e in edges], np.int64) for i in (0, 1))
    frags, names, idle = fragments(a, b, set(boundary), **options)
    return frags, names, idle, a, b


def check(edges, boundary=(), **options):
    """Every edge in one fragment, every fragment a chain with the ends it says."""
    frags, names, idle, a, b = made(edges, boundary, **options)
    used = [s[0] for f in frags for s in f.steps]
    assert sorted(used) == list(range(len(edges)))
    for f in frags:
        at = names[f.src]
        for e, forward in f.steps:
            x, y = (a[e], b[e]) if forward else (b[e], a[e])
            assert x == at
            at = y
        assert at == names[f.dst]
        assert (f.src == f.dst) == (f.ftype != "path")
    return frags, names, idle


def odd(edges):
    degree = {}
    for u, v in edges:
        degree[u] = degree.get(u, 0) + 1
        degree[v] = degree.get(v, 0) + 1
    return {v for v, d in degree.items() if d % 2}


@pytest.mark.parametrize("edges", [
    [], [(1, 1)], [(1, 1), (1, 1)], [(1, 2), (1, 2)], [(0, 1), (1, 2), (2, 0), (0, 3), (3, 4), (4, 0)],
    [(i, j) for i in range(5) for j in range(i)], [(i, j) for i in range(7) for j in range(i)],
    [(0, 1), (1, 2), (2, 0), (5, 6), (6, 7), (7, 5)],
])
def test_even_fixtures_become_one_closed_walk_a_component(edges):
    frags, _, _ = check(edges)
    assert all(f.ftype == "free" for f in frags)
    assert len(frags) == {0: 0}.get(len(edges), 2 if len(edges) == 6 and (5, 6) in edges else 1)


def test_worked_example_level_0():
    parts = {}
    for u, v in WORKED_EDGES:
        if WORKED_PARTS[u] == WORKED_PARTS[v]:
            parts.setdefault(WORKED_PARTS[u], []).append((u, v))
    remote = {x for u, v in WORKED_EDGES if WORKED_PARTS[u] != WORKED_PARTS[v] for x in (u, v)}
    found = {}
    for p, edges in parts.items():
        frags, names, _ = check(edges, remote)
        found[p] = sorted((f.ftype, *sorted((int(names[f.src]), int(names[f.dst]))), len(f.steps)) for f in frags)
    assert found[1] == [("path", 1, 2, 1)]
    assert found[2] == [("cycle", 3, 3, 3)]
    assert found[3] == [("path", 6, 9, 3)]
    assert [f[0] for f in found[4]] == ["path", "path"] and sorted(x for f in found[4] for x in f[1:3]) == [10, 11, 13, 14]


def test_a_vertex_passed_before_still_starts_its_path():
    # paths cross at 2, itself odd: a flag for "touched" would lose the path that it owes
    edges = [(1, 2), (2, 3), (2, 4)]
    frags, _, _ = check(edges, {1, 2, 3, 4})
    assert sum(f.ftype == "path" for f in frags) == len(odd(edges)) // 2 == 2


def test_a_cycle_that_touches_only_a_later_cycle_is_not_lost():
    # path 0-1, cycle D through 1 and 2, cycle C through 2 and 5; C's edges come first
    edges = [(2, 5), (5, 6), (2, 6), (1, 2), (2, 3), (1, 3), (0, 1), (1, 9)]
    frags, _, _ = check(edges, {0, 9})
    assert [f.ftype for f in frags] == ["path"] and len(frags[0].steps) == len(edges)


def test_a_loop_at_an_odd_vertex_is_kept():
    frags, _, _ = check([(1, 2), (1, 1), (2, 2)], {1, 2})
    assert [f.ftype for f in frags] == ["path"] and len(frags[0].steps) == 3
    frags, _, _ = check([(1, 2), (7, 7)], {1, 2, 7}, merge_internal=False)
    assert sorted(f.ftype for f in frags) == ["cycle", "path"]


def test_boundary_vertices_without_cycles_are_counted():
    _, _, idle = check([(1, 2), (2, 3), (1, 3)], {1, 2, 3})
    assert idle == 2


def test_input_order_does_not_matter_after_the_sort():
    edges = [(random.Random(4).randrange(6), i % 6) for i in range(20)]
    first = made(edges, {0})[0]
    assert [f.steps for f in made(edges, {0})[0]] == [f.steps for f in first]


@pytest.mark.parametrize("seed", range(60))
def test_random_multigraphs(seed):
    rng = random.Random(seed)
    n = rng.randint(1, 12)
    edges = [(rng.randrange(n), rng.randrange(n)) for _ in range(rng.randint(0, 40))]
    boundary = odd(edges) | {v for v in range(n) if rng.random() < 0.3}
    for merge in (True, False):
        frags, names, idle = check(edges, boundary, merge_internal=merge)
        paths = [f for f in frags if f.ftype == "path"]
        ends = [int(names[x]) for f in paths for x in (f.src, f.dst)]
        assert sorted(ends) == sorted(odd(edges))
        touched = {v for e in edges for v in e}
        even = len((boundary & touched) - odd(edges))
        assert sum(f.ftype == "cycle" for f in frags) + idle == even


@pytest.mark.parametrize("seed", range(20))
def test_sequential_tour_on_random_even_graphs(seed):
    rng = random.Random(seed)
    edges = []
    for _ in range(rng.randint(1, 6)):
        ring = [rng.randrange(9) for _ in range(rng.randint(1, 8))]
        edges += list(zip(ring, ring[1:] + ring[:1], strict=True))
    u, v = (np.array([e[i] for e in edges], np.int64) for i in (0, 1))
    tour = closed_tour(np.arange(len(edges)), u, v)
    assert sorted(t[1] for t in tour) == list(range(len(edges)))
    by = {}
    for t in tour:
        by.setdefault(t[0], []).append(t)
    for rows in by.values():
        assert all(a[3] == b[2] for a, b in zip(rows, rows[1:] + rows[:1], strict=True))


def test_a_tour_takes_some_hundred_bytes_an_edge():
    """A task holds a whole component, so an edge must not cost several Python objects."""
    import tracemalloc

    import pandas as pd

    from tourspark.plans.baselines import _toured

    n = 20_000
    walk = np.random.default_rng(5).integers(0, 700, n)
    rows = pd.DataFrame({"comp": 0, "eid": np.arange(n), "u": walk, "v": np.roll(walk, -1)})
    tracemalloc.start()
    made = _toured(rows)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 250 * n
    assert sorted(made["eid"]) == list(range(n)) and made["pos"].tolist() == list(range(n))
    assert (made["dst"].to_numpy()[:-1] == made["src"].to_numpy()[1:]).all()


def test_tours_are_made_in_pieces_of_a_component_at_a_time():
    """Rows come in batches of any size; neither they nor the tour are held as a whole table."""
    import pyarrow as pa

    from tourspark.plans.baselines import PIECE, toured

    n, rng, rows = 200_000, np.random.default_rng(6), []
    for comp, size in ((0, 5), (10_000, n), (30_000, 1), (40_000, 7)):
        walk = comp + rng.integers(0, max(1, size // 20), size)
        rows += list(zip([comp] * size, range(len(rows), len(rows) + size), walk.tolist(), np.roll(walk, -1).tolist(), strict=True))
    whole = pa.table({c: np.array(x, np.int64) for c, x in zip(("comp", "eid", "u", "v"), zip(*rows, strict=True), strict=True)})
    ends = {e: {a, b} for _, e, a, b in rows}
    of = {e: c for c, e, _, _ in rows}
    del rows
    seen, last = 0, {}
    for batch in toured(iter(whole.to_batches(max_chunksize=10_007))):
        assert batch.num_rows <= PIECE
        for tour, pos, e, a, b in zip(*(batch.column(c).to_pylist() for c in ("comp", "pos", "eid", "src", "dst")), strict=True):
            assert {a, b} == ends.pop(e)
            at = last.get((of[e], tour))
            assert pos == (0 if at is None else at[0] + 1) and (at is None or at[1] == a)
            last[of[e], tour] = (pos, b)
        seen += batch.num_rows
    assert not ends and seen == n + 13


def test_a_tour_of_pieces_takes_some_fifty_bytes_an_edge():
    import tracemalloc

    import pyarrow as pa

    from tourspark.plans.baselines import toured

    n = 100_000
    walk = np.random.default_rng(5).integers(0, 3000, n)
    whole = pa.table({"comp": np.zeros(n, np.int64), "eid": np.arange(n), "u": walk, "v": np.roll(walk, -1)})
    tracemalloc.start()
    made = sum(b.num_rows for b in toured(iter(whole.to_batches(max_chunksize=5_000))))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert made == n and peak < 80 * n
