"""Fragments of a large part by whole-array steps: the job of ``phase1.walked`` without a
Python step for each item.

Item ends at a vertex are paired, which falls into trails: open ones between odd vertices, and
closed ones. Where a closed trail shares a vertex with another trail, the two exchange the
partners of an end, which makes them one; a union-find over trails tells which are still apart.
At last trails are put in order. Ends are numbered 2 item for ``a`` and 2 item + 1 for ``b``; an
end also stands for the step that leaves by it.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Of so many steps one is a mark, from which all marks' runs are followed side by side.
MARK = 64


@dataclass(frozen=True)
class Trails:
    """``coded`` as in ``phase1.Fragment``, of all trails in turn; trail i has those from
    ``start[i]`` to ``start[i + 1]`` and begins and ends at vertices ``src`` and ``dst``."""

    coded: np.ndarray
    start: np.ndarray
    path: np.ndarray
    src: np.ndarray
    dst: np.ndarray


def _width(n: int) -> type:
    """Whole numbers that hold n: half the memory as long as four bytes do."""
    return np.int32 if n < 1 << 31 else np.int64


def numbered(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The sorted names of all vertices, and the number of each end's vertex."""
    ends = np.empty(2 * len(a), np.int64)
    ends[0::2], ends[1::2] = a, b
    if not len(ends):
        return ends, ends
    low, high = int(ends.min()), int(ends.max())
    if high - low > 4 * len(ends):
        names, vertex = np.unique(ends, return_inverse=True)
        return names, vertex.astype(_width(len(ends)))
    ends -= low
    seen = np.zeros(high - low + 1, bool)
    seen[ends] = True
    return np.flatnonzero(seen) + low, (np.cumsum(seen, dtype=_width(len(ends))) - 1)[ends]


def _follow(after: np.ndarray, marks: np.ndarray, owner: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The mark that comes after each mark, and how far on; on the way every step gets the
    number of its mark and its place behind it."""
    is_mark = np.zeros(len(after), bool)
    is_mark[marks] = True
    onward, far = np.empty(len(marks), after.dtype), np.empty(len(marks), after.dtype)
    base = owner.max(initial=-1) + 1
    own, at, n = np.arange(len(marks), dtype=after.dtype), marks, 0
    owner[marks], place[marks] = own + base, 0
    while len(at):
        n, at = n + 1, after[at]
        hit = is_mark[at]
        onward[own[hit]], far[own[hit]] = at[hit], n
        at, own = at[~hit], own[~hit]
        owner[at], place[at] = own + base, n
    return owner[onward], far


def _least(after: np.ndarray) -> np.ndarray:
    """The least element of every ring of a permutation."""
    low, far = np.arange(len(after), dtype=after.dtype), after
    while True:
        new = np.minimum(low, low[far])
        if np.array_equal(new, low):
            return np.unique(low)
        low, far = new, far[far]


def rings(after: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The ring of every element of a permutation, numbered from 0, and its place there."""
    owner, place = np.full(len(after), -1, after.dtype), np.zeros(len(after), after.dtype)
    marks = np.flatnonzero(np.random.default_rng(0).random(len(after), np.float32) < 1 / MARK)
    onward, far = _follow(after, marks, owner, place)
    rest = np.flatnonzero(owner < 0)  # short rings, which no mark fell on
    if len(rest):
        index = np.empty(len(after), after.dtype)
        index[rest] = np.arange(len(rest))
        more, size = _follow(after, rest[_least(index[after[rest]])], owner, place)
        onward, far = np.concatenate([onward, more]), np.concatenate([far, size])
    ring, first = np.full(len(onward), -1, np.int64), np.zeros(len(onward), np.int64)
    alone = onward == np.arange(len(onward))
    n = int(alone.sum())
    ring[alone] = np.arange(n)
    # one step for each mark
    named, begins, follow, sizes = ring.tolist(), first.tolist(), onward.tolist(), far.tolist()
    for s in np.flatnonzero(~alone).tolist():
        if named[s] < 0:
            at, x = 0, s
            while named[x] < 0:
                named[x], begins[x] = n, at
                at += sizes[x]
                x = follow[x]
            n += 1
    place += np.array(begins, after.dtype)[owner]
    return np.array(named, after.dtype)[owner], place


def _joined(mate: np.ndarray, ring: np.ndarray, order: np.ndarray, head: np.ndarray) -> bool:
    """Exchange partners until no closed trail shares a vertex with another trail."""
    trail = np.minimum(ring[0::2], ring[1::2])
    is_open = np.zeros(int(ring.max()) + 1, bool)
    is_open[trail[ring[0::2] == ring[1::2]]] = True
    # of each pair of ends, and of an end that is left, the first; and the first of its vertex
    one = (np.arange(len(order)) - head) % 2 == 0
    x, y = order[head[one]], order[one]
    s, t = trail[x >> 1], trail[y >> 1]
    apart = (s != t) & ~(is_open[s] & is_open[t])
    x, y, s, t = (c[apart] for c in (x, y, s, t))
    _, once = np.unique(s.astype(np.int64) * len(is_open) + t, return_index=True)
    up, closed = list(range(len(is_open))), (~is_open).tolist()

    def root(c: int) -> int:
        while up[c] != c:
            up[c] = up[up[c]]
            c = up[c]
        return c

    for p, q, c, d in zip(*(v[once].tolist() for v in (x, y, s, t)), strict=True):
        c, d = root(c), root(d)
        if c == d or not (closed[c] or closed[d]):
            continue
        up[d], closed[c] = c, closed[c] and closed[d]
        p2, q2 = int(mate[p]), int(mate[q])
        mate[p], mate[q2] = q2, p
        if p2 == p:
            mate[q] = q
        elif q2 == q:
            mate[p2] = p2
        else:
            mate[p2], mate[q] = q, p2
    return len(once) > 0


def trails(vertex: np.ndarray, merge_internal: bool = True) -> Trails:
    """Trails over items whose ends lie at ``vertex``: paths between odd vertices, and closed
    ones, which touch no other trail unless ``merge_internal`` is off."""
    m = len(vertex)
    if not m:
        none = np.zeros(0, np.int64)
        return Trails(none, np.zeros(1, np.int64), none.astype(bool), none, none)
    # sorted by vertex, then by end; a plain sort of one number each is the fastest
    bits = m.bit_length()
    width = _width(m)
    order = vertex.astype(np.int64) << bits
    order |= np.arange(m)
    order.sort()
    order = (order & ((1 << bits) - 1)).astype(width)
    at = vertex[order]
    new = np.r_[True, at[1:] != at[:-1]]
    mate = np.arange(m, dtype=width)
    head = np.maximum.accumulate(np.where(new, mate, 0))
    i = np.flatnonzero(((mate - head) % 2 == 0) & ~np.r_[new[1:], True])
    del at, new
    mate[order[i]], mate[order[i + 1]] = order[i + 1], order[i]
    flip = np.arange(m, dtype=width) ^ 1
    ring, place = rings(mate[flip])
    if merge_internal and _joined(mate, ring, order, head):
        ring, place = rings(mate[flip])
    del order, head
    size = np.bincount(ring).astype(width)
    # an open trail is one ring there and back, a closed one two rings, of which one stays
    there = ring < ring[flip]
    both = ring == ring[flip]
    is_open = np.zeros(len(size), bool)
    is_open[ring[both]] = True
    turn = np.flatnonzero((mate == np.arange(m)) & both)
    begin = np.zeros(len(size), width)
    begin[ring[turn[::-1]]] = place[turn[::-1]]  # the smaller of the two ends
    size = np.where(is_open, size // 2, size)
    place -= begin[ring]
    place += np.where(place < 0, np.where(is_open, 2 * size, size)[ring], 0)
    kept = np.flatnonzero(there | both & (place < size[ring]))
    used = np.unique(ring[kept])
    start = np.r_[0, np.cumsum(size[used], dtype=np.int64)]
    index = np.zeros(len(size), np.int64)
    index[used] = start[:-1]
    steps = np.empty(len(kept), width)
    steps[index[ring[kept]] + place[kept]] = kept
    return Trails(steps ^ 1, start, is_open[used], vertex[steps[start[:-1]]], vertex[steps[start[1:] - 1] ^ 1])
