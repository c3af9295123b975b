"""Fragments by whole-array steps: every item once, paths between odd vertices, and no closed
trail that touches another one."""

import numpy as np
import pytest

from tourspark.plans import phase1
from tourspark.plans.flat import numbered, rings, trails


def _walks(a, b, merge=True):
    names, vertex = numbered(a, b)
    t = trails(vertex, merge)
    item, ahead = t.coded >> 1, (t.coded & 1).astype(bool)
    assert sorted(item.tolist()) == list(range(len(a)))
    src, dst = np.where(ahead, a[item], b[item]), np.where(ahead, b[item], a[item])
    out = []
    for i, path in enumerate(t.path.tolist()):
        s, d = (x[t.start[i] : t.start[i + 1]].tolist() for x in (src, dst))
        assert s[1:] == d[:-1] and (s[0], d[-1]) == (names[t.src[i]], names[t.dst[i]]) and path == (s[0] != d[-1])
        out.append((path, s, d))
    deg = np.bincount(vertex)
    odd = sorted(v for path, s, d in out if path for v in (s[0], d[-1]))
    assert odd == names[deg % 2 == 1].tolist()
    return out


@pytest.mark.parametrize("seed", range(40))
def test_random_multigraphs(seed):
    rng = np.random.default_rng(seed)
    n, far = int(rng.integers(1, 80)), 10**12 if seed % 4 == 0 else 1
    a, b = rng.integers(0, int(rng.integers(1, 30)), n), rng.integers(0, int(rng.integers(1, 30)), n) * far
    _walks(a, b, merge=False)
    at = {}
    for i, (path, s, d) in enumerate(_walks(a, b)):
        for v in s + d:
            at.setdefault(v, set()).add((i, path))
    assert all(len(x) == 1 or all(path for _, path in x) for x in at.values())


def test_long_and_short_rings():
    order = np.random.default_rng(1).permutation(50_000)
    after = np.empty(50_010, np.int64)
    after[order], after[50_000:] = np.roll(order, -1), np.r_[50_001, 50_000, range(50_002, 50_010)]
    ring, place = rings(after)
    assert len(set(ring.tolist())) == 10 and sorted(place[:50_000].tolist()) == list(range(50_000))
    assert all((place[order][1:] - place[order][:-1]) % 50_000 == 1)


def test_a_hub_of_doubled_edges_is_one_walk():
    leaf = np.repeat(np.arange(1, 30_001), 2)
    assert len(_walks(np.zeros_like(leaf), leaf)) == 1


@pytest.mark.parametrize("n", [300, phase1.FLAT + 1])
def test_a_part_says_the_same_of_itself_either_way(n):
    """Small parts walk item by item; as many paths, and the same sums, come of either way."""
    rng = np.random.default_rng(n)
    a, b = rng.integers(0, n // 5, n), rng.integers(0, n // 5, n)
    zero = np.zeros(n, np.int32)
    rows = [r for t in phase1.run_part(1, 2, np.zeros(n, bool), np.arange(n) + 7, a, b, np.full(n, 3), zero + 1, zero + 1, True) for r in t.to_pylist()]
    heads, items = ([r for r in rows if r["tag"] == tag] for tag in ("frag", "item"))
    assert sorted(r["item_id"] for r in items) == list(range(7, n + 7)) and sum(r["n_edges"] for r in heads) == 3 * n
    assert 2 * sum(r["ftype"] == "path" for r in heads) == sum(np.bincount(np.r_[a, b]) % 2)
    by = {}
    for r in items:
        assert (r["seq"], r["off"]) == (len(by.setdefault(r["fid"], [])), 3 * len(by[r["fid"]])) and (not by[r["fid"]] or by[r["fid"]][-1] == r["a"])
        by[r["fid"]].append(r["b"])
    assert all(by[r["fid"]][-1] == r["dst"] for r in heads)


def test_items_that_nobody_reads_stay_in_the_task():
    """Fragments and figures are the same; the items are walked, but not handed out."""
    rng = np.random.default_rng(5)
    n = phase1.FLAT + 1
    a, b = rng.integers(0, n // 5, n), rng.integers(0, n // 5, n)
    zero = np.zeros(n, np.int32)
    told = []
    for keep in (True, False):
        rows = [r for t in phase1.run_part(1, 2, np.zeros(n, bool), np.arange(n), a, b, np.ones(n, np.int64), zero, zero, True, keep_items=keep) for r in t.to_pylist()]
        assert any(r["tag"] == "item" for r in rows) == keep
        told.append([(r["tag"], r["fid"], r["ftype"], r["src"], r["dst"], r["n_edges"], r["len"]) for r in rows if r["tag"] != "item"])
    assert told[0] == told[1] and len(told[0]) > 1


def test_items_lie_in_order_of_kind_and_id():
    rng = np.random.default_rng(6)
    item, coarse = rng.permutation(5000), rng.random(5000) < 0.3
    assert phase1._in_order(coarse, item).tolist() == np.lexsort([item, coarse]).tolist()
