"""Local paths and cycles of every part, found by an Arrow kernel inside one task a part.

Input rows are items: original edges, or paths of the level below standing as one coarse
edge. Output rows are fragments (headers), their items, and one row of figures a part, in one
pass, told apart by a tag.
"""

from __future__ import annotations

import resource
import time
from array import array
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark.plans.flat import Trails, numbered, trails
from tourspark.session import lookup, ship

ITEM_IN = "part int, kind string, item_id long, a long, b long, len long, ra int, rb int"
OUT = (
    "tag string, fid long, part int, ftype string, src long, dst long, n_edges long, rs int, rd int, "
    "seq int, off long, item_kind string, item_id long, fwd boolean, a long, b long, len long, "
    "receive double, build double, walk double, emit double, peak long"
)
#: A fragment's id holds its level, its part and its number in the part.
LEVEL_SHIFT, PART_SHIFT = 58, 36
#: Parts of so many items are done by whole-array steps, and items of one output table.
FLAT, PIECE = 20_000, 1 << 20
_ARROW = {"string": pa.string(), "long": pa.int64(), "int": pa.int32(), "boolean": pa.bool_(), "double": pa.float64()}


def fragment_id(level: int, part: int, n: int) -> int:
    return level << LEVEL_SHIFT | part << PART_SHIFT | n


@dataclass
class Fragment:
    """``coded``: 2 item + 1 for a step along an item, 2 item for one against it."""

    ftype: str
    src: int
    dst: int
    coded: array

    @property
    def steps(self) -> list[tuple[int, bool]]:
        return [(c >> 1, bool(c & 1)) for c in self.coded]


def _flat(x: np.ndarray) -> array:
    return array("q", x.astype(np.int64, copy=False).tobytes())


class Walker:
    """Adjacency in flat arrays of 8 bytes an entry, a cursor for each vertex, and a used flag
    for each item."""

    def __init__(self, a: np.ndarray, b: np.ndarray):
        self.names, both = np.unique(np.concatenate([a, b]), return_inverse=True)
        n = len(a)
        self.a, self.b = _flat(both[:n]), _flat(both[n:])
        order = np.argsort(both, kind="stable")
        self.edge = _flat(order % n) if n else array("q")
        at = np.zeros(len(self.names) + 1, np.int64)
        np.cumsum(np.bincount(both, minlength=len(self.names)), out=at[1:])
        self.degree = _flat(np.diff(at))
        self.cursor, self.stop = _flat(at[:-1]), _flat(at[1:])
        self.used = bytearray(n)

    def walk(self, at: int) -> tuple[array, int]:
        """Go on along unused items until no more leave: each list place is read once."""
        steps = array("q")
        edge, used, cursor, stop, a, b = self.edge, self.used, self.cursor, self.stop, self.a, self.b
        while True:
            c, end = cursor[at], stop[at]
            while c < end and used[edge[c]]:
                c += 1
            if c == end:
                cursor[at] = c
                return steps, at
            e = edge[c]
            cursor[at] = c + 1
            used[e] = 1
            if a[e] == at:
                steps.append(2 * e + 1)
                at = b[e]
            else:
                steps.append(2 * e)
                at = a[e]

    def left(self, at: int) -> bool:
        c, end = self.cursor[at], self.stop[at]
        while c < end and self.used[self.edge[c]]:
            c += 1
        self.cursor[at] = c
        return c < end

    def spliced(self, start: int, steps: array) -> array:
        """``steps`` with every cycle that hangs on one of its vertices put in, and theirs."""
        out = array("q")
        stack, at = [iter(steps)], start
        while stack:
            if self.left(at):
                more, _ = self.walk(at)  # all residual degrees are even: it comes back here
                stack.append(iter(more))
                continue
            step = next(stack[-1], None)
            if step is None:
                stack.pop()
                continue
            out.append(step)
            at = self.b[step >> 1] if step & 1 else self.a[step >> 1]
        return out


def fragments(a: np.ndarray, b: np.ndarray, boundary: set[int], merge_internal: bool = True) -> tuple[list[Fragment], np.ndarray, int]:
    """Fragments over items a-b; names of vertices; how many even boundary vertices stay
    without a cycle."""
    w = Walker(a, b)
    made, idle = walked(w, boundary, merge_internal)
    return made, w.names, idle


def walked(w: Walker, boundary: set[int], merge_internal: bool = True) -> tuple[list[Fragment], int]:
    """First paths between odd vertices, each start chosen by its residual degree; then one
    cycle for each even boundary vertex; then cycles that are left, put into a fragment they
    touch or kept as free closed walks."""
    names = w.names.tolist()
    odd = [d % 2 == 1 for d in w.degree]
    made: list[Fragment] = []
    for v in range(len(names)):
        if odd[v]:
            steps, end = w.walk(v)
            odd[v] = odd[end] = False
            made.append(Fragment("path", v, end, steps))
    idle = 0
    for v in range(len(names)):
        if names[v] in boundary and w.degree[v] % 2 == 0:
            steps, end = w.walk(v)
            if steps:
                made.append(Fragment("cycle", v, end, steps))
            else:
                idle += 1
    if merge_internal:
        for f in made:
            f.coded = w.spliced(f.src, f.coded)
    for e in range(len(w.used)):
        if not w.used[e]:
            v = w.a[e]
            steps, end = w.walk(v)
            made.append(Fragment("free", v, end, w.spliced(v, steps) if merge_internal else steps))
    return made, idle


def _laid(made: list[Fragment]) -> Trails:
    """Fragments one after another."""
    start = np.r_[0, np.cumsum([len(f.coded) for f in made], dtype=np.int64)]
    coded = np.concatenate([np.frombuffer(f.coded, np.int64) for f in made]) if made else np.zeros(0, np.int64)
    path = np.array([f.ftype == "path" for f in made], bool)
    return Trails(coded, start, path, np.array([f.src for f in made], np.int64), np.array([f.dst for f in made], np.int64))


def run_part(level: int, part: int, coarse: np.ndarray, item: np.ndarray, a: np.ndarray, b: np.ndarray, length: np.ndarray, ra: np.ndarray, rb: np.ndarray, merge_internal: bool, receive: float = 0.0, emit_vertices: bool = True, keep_items: bool = True) -> Iterator[pa.Table]:
    """A part's fragments, its items by pieces, then its figures: seconds to receive its rows
    (moving and merging), to build the arrays, to walk, and to make the output, and the most
    memory that this process has held. ``coarse``: which items are paths of the level below.
    Without ``keep_items`` the items are walked and made like ever, but not handed out."""
    clock = [time.perf_counter()]
    names, vertex = numbered(a, b)
    retire = np.zeros(len(names), np.int64)
    retire[vertex[0::2]], retire[vertex[1::2]] = ra, rb
    large = len(a) >= FLAT
    w = None if large else Walker(a, b)
    clock.append(time.perf_counter())
    if large:
        t = trails(vertex, merge_internal)
        ftype = np.where(t.path, "path", np.where(retire[t.src] > level, "cycle", "free"))
    else:
        made, _ = walked(w, set(names[retire > level].tolist()), merge_internal)
        t, ftype = _laid(made), [f.ftype for f in made]
    del vertex, w
    clock.append(time.perf_counter())
    schema = pa.schema([(n, _ARROW[k]) for n, k in (c.split() for c in OUT.split(", "))])

    def table(**columns) -> pa.Table:
        n = len(next(iter(columns.values())))
        return pa.table([pa.array(columns[f.name], f.type) if f.name in columns else pa.nulls(n, f.type) for f in schema], schema=schema)

    pick = t.coded >> 1
    size = length[pick]
    before = np.cumsum(size) - size
    n_edges = np.diff(np.r_[before[t.start[:-1]], size.sum()]) if len(t.path) else before
    fid = fragment_id(level, part, 0) + np.arange(len(t.path))
    ends = {"src": names[t.src], "dst": names[t.dst], "rs": retire[t.src], "rd": retire[t.dst]}
    yield table(tag=["frag"] * len(fid), fid=fid, part=np.full(len(fid), part), ftype=ftype, n_edges=n_edges, **ends)
    of = np.repeat(np.arange(len(fid)), np.diff(t.start))
    kinds = pa.array(["edge", "frag"])
    for at in range(0, len(pick), PIECE):
        cut = slice(at, at + PIECE)
        own, i, fwd = of[cut], pick[cut], (t.coded[cut] & 1).astype(bool)
        sides = {"a": np.where(fwd, a[i], b[i]), "b": np.where(fwd, b[i], a[i])} if emit_vertices else {}
        rows = table(
            tag=["item"] * len(i), fid=fid[own], part=np.full(len(i), part), seq=np.arange(at, at + len(i)) - t.start[own], off=before[cut] - before[t.start[own]],
            item_kind=kinds.take(pa.array(coarse[i].astype(np.int8))), item_id=item[i], fwd=fwd, len=size[cut], **sides,
        )
        if keep_items:
            yield rows
    clock.append(time.perf_counter())
    build, walk, emit = np.diff(clock).tolist()
    yield table(tag=["part"], part=[part], n_edges=[int(length.sum())], len=[len(a)], receive=[receive], build=[build], walk=[walk], emit=[emit], peak=[resource.getrusage(resource.RUSAGE_SELF).ru_maxrss * 1024])


def dealt(items: DataFrame, parts: Sequence[int]) -> DataFrame:
    """``items`` with each part in a task of its own: part number i of the sorted parts goes to
    task i, so a level's time is that of its largest part."""
    parts = sorted(parts)
    if parts == list(range(len(parts))):
        placed = items.withColumn("slot", F.col("part"))
    else:
        placed = items.join(lookup(items.sparkSession, [(p, i) for i, p in enumerate(parts)], "part int, slot int"), "part")
    return placed.repartitionById(max(1, len(parts)), "slot").drop("slot")


def _in_order(coarse: np.ndarray, item: np.ndarray) -> np.ndarray:
    """Places of the items: paths after edges, each by their ids."""
    edges, paths = np.flatnonzero(~coarse), np.flatnonzero(coarse)
    return np.concatenate([edges[np.argsort(item[edges])], paths[np.argsort(item[paths])]])


def _by_degree(a: np.ndarray, b: np.ndarray, item: np.ndarray) -> np.ndarray:
    """Places of the items: those with an end of small degree first, then by their ids."""
    _, at = numbered(a, b)
    deg = np.bincount(at)[at]
    return np.lexsort([item, np.minimum(deg[0::2], deg[1::2])])


def phase1(items: DataFrame, level: int, parts: Sequence[int], merge_internal: bool = True, order: str = "eid", emit_vertices: bool = True, keep_items: bool = True) -> DataFrame:
    """Fragments and their items of every part of a level.

    ``items`` has the columns of ITEM_IN; ``ra`` and ``rb`` are the levels at which the ends
    have no edge left to other parts, so an end is a boundary vertex where that is above
    ``level``. One exchange brings a part together, and its task sorts and holds it. ``order='degree'`` walks small-degree ends first. Without ``emit_vertices``
    items say which edge and which way only, and unrolling looks the ends up. Without
    ``keep_items`` there are fragments and figures only, for callers that unroll nothing.
    """
    if order not in ("eid", "degree"):
        raise ValueError(f"unknown order {order}")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        since = time.perf_counter()
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        rows = pa.Table.from_batches(held)
        held.clear()
        columns = {c: rows[c].to_numpy() for c in ("part", "a", "b", "coarse", "item_id", "len", "ra", "rb")}
        del rows
        own = columns.pop("part")
        parts = np.unique(own).tolist()  # one, as parts are dealt
        for part in parts:
            mine = columns if len(parts) == 1 else {c: x[own == part] for c, x in columns.items()}
            sort = _in_order(mine["coarse"], mine["item_id"]) if order == "eid" else _by_degree(mine["a"], mine["b"], mine["item_id"])
            a, b, coarse, item, length, ra, rb = (mine.pop(c)[sort] for c in ("a", "b", "coarse", "item_id", "len", "ra", "rb"))
            del sort
            receive = time.perf_counter() - since
            for table in run_part(level, part, coarse, item, a, b, length, ra, rb, merge_internal, receive, emit_vertices, keep_items):
                yield from table.to_batches(max_chunksize=65_536)
            since = time.perf_counter()

    ship(items.sparkSession)
    # a flag is moved, not a word
    items = items.withColumn("coarse", F.col("kind") == "frag").drop("kind")
    return dealt(items, parts).mapInArrow(kernel, OUT)


def as_pandas(made: list[Fragment], names: np.ndarray) -> pd.DataFrame:
    """Small results as rows, for tests."""
    return pd.DataFrame([(f.ftype, int(names[f.src]), int(names[f.dst]), len(f.coded)) for f in made], columns=["ftype", "src", "dst", "n"])
