"""The methods to compare with: sequential, pairing, single token, trees, and the hybrid."""

from __future__ import annotations

from array import array
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tourspark import schemas
from tourspark.functions.graph import Graph, bidirect
from tourspark.functions.numbering import dense_number
from tourspark.functions.rings import with_next
from tourspark.plans import phase2, phase3
from tourspark.plans.components import components, min_label_components
from tourspark.plans.ledger import Ledger
from tourspark.plans.metagraph import MergeTree, tree_for
from tourspark.plans.phase1 import LEVEL_SHIFT, OUT
from tourspark.session import drop, ship, stage, stage_alone


#: Rows of a tour that are made into output at once.
PIECE = 1 << 16


def _coded(names: np.ndarray, ends: np.ndarray, kind: str) -> np.ndarray:
    """Places of the ends among the names, a piece at a time."""
    out = np.empty(len(ends), kind)
    for at in range(0, len(ends), PIECE):
        out[at : at + PIECE] = np.searchsorted(names, ends[at : at + PIECE])
    return out


def _incidences(a: np.ndarray, b: np.ndarray, n_names: int) -> tuple[np.ndarray, np.ndarray]:
    """Where each vertex's list starts, and the lists: the edges that it is first in, then
    those that it is second in, both in turn."""
    many = np.bincount(a, minlength=n_names)
    at = np.concatenate([[0], np.cumsum(many + np.bincount(b, minlength=n_names))])
    place, ahead = np.empty(2 * len(a), a.dtype), at[:-1]
    for side in (a, b):
        order = np.argsort(side, kind="stable")
        # sorted by vertex, a place differs by a constant for each vertex from its place in the list
        shift = ahead - (np.cumsum(np.bincount(side, minlength=n_names)) - np.bincount(side, minlength=n_names))
        for k in range(0, len(order), PIECE):
            own = order[k : k + PIECE]
            place[shift[side[own]] + np.arange(k, k + len(own))] = own
        del order
        ahead = ahead + many
    return at, place


def _whole(x: np.ndarray, kind: str) -> array:
    out = array(kind)
    out.frombytes(np.ascontiguousarray(x, kind).view(np.uint8))
    return out


def tour_pieces(columns: list[np.ndarray]) -> Iterator[dict[str, np.ndarray]]:
    """comp, pos, eid, src, dst in order, by one stack of edges for each component, some rows
    at a time. ``columns``: eid, u and v, taken out of the list, so that they can be freed.

    Vertices, edges, the stack and the trail are flat arrays of whole numbers of four bytes
    as long as those do, some 40 bytes an edge in all with the edges' ids.
    """
    v, u, eid = columns.pop(), columns.pop(), columns.pop()
    n, names = len(eid), np.union1d(np.unique(u), np.unique(v))
    kind = "i" if 2 * n < 1 << 31 else "q"
    a = _coded(names, u, kind)
    del u
    b = _coded(names, v, kind)
    del v
    at, place = (_whole(x, kind) for x in _incidences(a, b, len(names)))
    # of an edge's ends both come from the one that the stack is at
    across, used = _whole(a ^ b, kind), bytearray(n)
    del a, b
    cursor = at[:-1]
    trail, source, size = array(kind), array(kind), array("q")
    for first in range(len(names)):
        began = len(trail)
        vertex, taken = array(kind, [first]), array(kind, [-1])
        while vertex:
            x = vertex[-1]
            c, end = cursor[x], at[x + 1]
            while c < end and used[place[c]]:
                c += 1
            cursor[x] = c
            if c < end:
                e = place[c]
                used[e] = 1
                vertex.append(across[e] ^ x)
                taken.append(e)
            else:
                vertex.pop()
                e = taken.pop()
                if e >= 0:
                    trail.append(e)  # backwards: from x to where it came from
                    source.append(x)
        if len(trail) > began:
            size.append(len(trail) - began)
    del at, place, cursor, used
    trail, source, across = (np.frombuffer(x, kind) for x in (trail, source, across))
    stops = np.cumsum(np.frombuffer(size, np.int64))
    starts = np.r_[0, stops[:-1]].astype(np.int64)
    for k in range(0, len(trail), PIECE):
        edges, src = trail[k : k + PIECE], source[k : k + PIECE]
        row = np.arange(k, k + len(edges))
        tour = np.searchsorted(stops, row, side="right")
        yield {"comp": names[source[starts[tour]]], "pos": row - starts[tour], "eid": eid[edges], "src": names[src], "dst": names[src ^ across[edges]]}


def tour_columns(eid: np.ndarray, u: np.ndarray, v: np.ndarray) -> dict[str, np.ndarray]:
    """The same in one piece."""
    pieces = list(tour_pieces([eid, u, v]))
    none = [np.zeros(0, np.int64)]
    return {c: np.concatenate([p[c] for p in pieces] or none) for c in ("comp", "pos", "eid", "src", "dst")}


def closed_tour(eid: np.ndarray, u: np.ndarray, v: np.ndarray) -> list[tuple[int, int, int, int]]:
    """(tour, edge, src, dst) in order, for a caller that takes rows."""
    made = tour_columns(eid, u, v)
    return list(zip(*(made[c].tolist() for c in ("comp", "eid", "src", "dst")), strict=True))


def _toured(rows: pd.DataFrame) -> pd.DataFrame:
    rows = rows.sort_values("eid")
    return pd.DataFrame(tour_columns(*(rows[c].to_numpy(np.int64) for c in ("eid", "u", "v"))))


def _joined(held: list[tuple[np.ndarray, ...]]) -> list[np.ndarray]:
    """The columns of the parts in ``held``, one after the other; ``held`` is emptied."""
    columns = [list(c) for c in zip(*held, strict=True)]
    held.clear()
    out = []
    while columns:
        out.append(np.concatenate(columns.pop(0)))
    return out


def toured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The tours of rows (comp, eid, u, v) in order of comp and eid. A component is held at a
    time, neither its input nor its output as a whole table."""
    held: list[tuple[np.ndarray, ...]] = []
    now = None

    def tours() -> Iterator[pa.RecordBatch]:
        for piece in tour_pieces(_joined(held)):
            yield pa.RecordBatch.from_pydict({c: pa.array(x, pa.int64()) for c, x in piece.items()})

    for rows in batches:
        if not rows.num_rows:
            continue
        comp, *rest = (rows.column(c).to_numpy() for c in ("comp", "eid", "u", "v"))
        edge = np.flatnonzero(np.r_[True, comp[1:] != comp[:-1], True])
        for x, y in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
            if held and comp[x] != now:
                yield from tours()
            now = comp[x]
            held.append(tuple(c[x:y].copy() for c in rest))
    if held:
        yield from tours()


def sequential_circuit(g: Graph, per_component: bool = True) -> DataFrame:
    """The linear-time algorithm in one task, or one task a component.

    A baseline: a whole component is in one task's memory, by definition of the method.
    """
    ship(g.edges.sparkSession)
    if per_component:
        rows = g.edges.join(components(g).withColumnRenamed("v", "u"), "u").select("comp", "eid", "u", "v")
        rows = rows.repartition("comp").sortWithinPartitions("comp", "eid")
    else:
        rows = g.edges.select(F.lit(0).cast("long").alias("comp"), "eid", "u", "v").coalesce(1).sortWithinPartitions("eid")
    return rows.mapInArrow(toured, schemas.CIRCUIT)


def _ring_ranks(links: DataFrame, max_rounds: int = 64) -> DataFrame:
    """id, head, at: for a permutation (id, next_id, size, head), the place of each element
    after its ring's head, by doubling pointers."""
    back = links.select(F.col("next_id").alias("id"), F.col("id").alias("ptr"), F.col("size").alias("gap"), "head")
    own = F.col("id") == F.col("head")
    back = stage(back.select("id", "head", F.when(own, F.col("id")).otherwise(F.col("ptr")).alias("ptr"), F.when(own, F.lit(0)).otherwise(F.col("gap")).alias("gap")), "ranks")
    for _ in range(max_rounds):
        if back.where("ptr <> head").isEmpty():
            return back.select("id", "head", F.col("gap").alias("at"))
        far = back.select(F.col("id").alias("ptr"), F.col("ptr").alias("far"), F.col("gap").alias("more"))
        before, back = back, stage(back.join(far, "ptr").select("id", "head", F.col("far").alias("ptr"), (F.col("gap") + F.col("more")).alias("gap")), "ranks")
        drop(before)
    raise RuntimeError(f"the ranks did not settle within {max_rounds} rounds")


def _ring_heads(darts: DataFrame, cycle_method: str, max_rounds: int = 64) -> DataFrame:
    """(id, head): the least dart of every ring."""
    if cycle_method == "components":
        return min_label_components(darts, "id", "next_id").select(F.col("v").alias("id"), F.col("comp").alias("head"))
    if cycle_method != "doubling":
        raise ValueError(f"unknown method {cycle_method}")
    far = stage(darts.select("id", "next_id", F.least("id", "next_id").alias("head")), "heads")
    for _ in range(max_rounds):
        onward = far.select(F.col("id").alias("next_id"), F.col("next_id").alias("beyond"), F.col("head").alias("low"))
        new = stage(far.join(onward, "next_id").select("id", F.col("beyond").alias("next_id"), F.least("head", "low").alias("head"), (F.col("low") < F.col("head")).alias("moved")), "heads")
        drop(far)
        if new.where("moved").isEmpty():
            return new.select("id", "head")
        far = new
    raise RuntimeError(f"the heads did not settle within {max_rounds} rounds")


#: Edge ends of a vertex that one task sorts.
HUB = 1 << 16


def _couples(ends: DataFrame, key: list[str]) -> tuple[DataFrame, DataFrame]:
    """Ends of each key paired in order as (p, q), and the ends that are left over."""
    rows = ends.withColumn("rn", F.row_number().over(Window.partitionBy(*key).orderBy("spot")))
    pairs = rows.groupBy(*key, F.expr("(rn - 1) div 2").alias("pair")).agg(F.min("spot").alias("p"), F.max("spot").alias("q"), F.count("*").alias("n"), F.first("v").alias("at"))
    return pairs.where("n = 2").select("p", "q"), pairs.where("n = 1").select(F.col("at").alias("v"), F.col("p").alias("spot"))


def _paired(ends: DataFrame, hub: int = HUB) -> DataFrame:
    """(x, y), both ways: a partner for every edge end (v, spot), whose number at v is even.

    The ends of a hub are dealt over cells and paired there; each cell leaves one end at the
    most, and those are paired last.
    """
    hubs = stage(ends.groupBy("v").count().where(F.col("count") > hub).select("v", F.ceil(F.col("count") / hub).cast("int").alias("cells")), "hubs")
    dealt = ends.join(hubs, "v", "left").withColumn("cell", F.coalesce(F.pmod(F.xxhash64("spot"), F.col("cells")), F.lit(0)).cast("int"))
    found, _ = _couples(dealt.where("cells is null"), ["v"])
    if not hubs.isEmpty():
        first, rest = _couples(dealt.where("cells is not null"), ["v", "cell"])
        found = found.unionByName(first).unionByName(_couples(rest, ["v"])[0])
    both = F.explode(F.array(F.struct(F.col("p").alias("x"), F.col("q").alias("y")), F.struct(F.col("q").alias("x"), F.col("p").alias("y"))))
    return found.select(both.alias("m")).select("m.x", "m.y")


def pair_cycles(items: DataFrame, cycle_method: str = "components") -> DataFrame:
    """walk, off, key, ahead, a, b, len: cycles over items (key, a, b, len) whose degrees are even.

    Item ends at a vertex are paired in order of their numbers. Every item gives a dart for
    each direction; a dart goes on with the dart that leaves by its end's partner. That is a
    permutation whose rings come twice, once for each direction; the ring with the smaller
    head stays.
    """
    ids = stage(dense_number(items, ["kind", "item_id"], "key", 0), "darts")
    side = F.explode(F.array(F.struct(F.col("a").alias("v"), F.lit(0).alias("end")), F.struct(F.col("b").alias("v"), F.lit(1).alias("end"))))
    ends = ids.select("key", side.alias("s")).select(F.col("s.v").alias("v"), (F.col("key") * 2 + F.col("s.end")).alias("spot"))
    mate = _paired(stage(ends, "ends"))
    # dart 2k leaves by end 0 and arrives at end 1; dart 2k+1 the other way round
    darts = stage(mate.select(F.col("x").bitwiseXOR(F.lit(1)).alias("id"), F.col("y").alias("next_id")), "mates")
    heads = stage_alone(darts.sparkSession, lambda: _ring_heads(darts, cycle_method), "ring-heads")
    twin = heads.select(F.col("id").bitwiseXOR(F.lit(1)).alias("id"), F.col("head").alias("other"))
    kept = stage(heads.join(twin, "id").where("head < other").select("id", "head"), "rings")
    sized = kept.join(darts, "id").join(ids.select((F.col("key") * 2).alias("even"), "len"), F.expr("id - id % 2 = even"))
    at = _ring_ranks(sized.select("id", "next_id", F.col("len").alias("size"), "head"))
    way = F.col("id") % 2 == 0
    rows = at.withColumn("key", F.expr("id div 2")).join(ids, "key")
    return rows.select(
        F.col("head").alias("walk"), F.col("at").alias("off"), "kind", "item_id", way.alias("ahead"),
        F.when(way, F.col("a")).otherwise(F.col("b")).alias("a"), F.when(way, F.col("b")).otherwise(F.col("a")).alias("b"), "len",
    )


def pairing_circuit(g: Graph, cycle_method: str = "components", forest: str = "auto", rank: str = "auto") -> DataFrame:
    """Pair edge ends at every vertex, find the cycles, join them along a forest, rank."""
    items = g.edges.select(F.lit("edge").alias("kind"), F.col("eid").alias("item_id"), F.col("u").alias("a"), F.col("v").alias("b"), F.lit(1).cast("long").alias("len"))
    place = [F.col(c).alias(name) for c, name in {"walk": "walk", "off": "pos", "item_id": "eid", "a": "src", "b": "dst"}.items()]
    walks = stage_alone(g.edges.sparkSession, lambda: pair_cycles(items, cycle_method).select(*place), "walks")
    return phase3.close_staged(walks, forest, rank)


def hybrid_circuit(
    g: Graph, switch_level: int = 0, strategy: str = "greedy", cycle_method: str = "components", tree: MergeTree | None = None,
    levelled: DataFrame | None = None, forest: str = "auto", rank: str = "auto", emit_vertices: bool = True, **options,
) -> DataFrame:
    """Levels up to ``switch_level`` part by part, then the coarse graph by pairing.

    No task then holds the last levels' coarse graph, which keeps every edge cut late. The
    cycles that pairing finds go to the ledger as one more level, and unrolling is as ever.
    """
    tree = tree or tree_for(g, phase2.parts_of(g), strategy)

    def unrolled() -> DataFrame:
        run = phase2.run_levels(g, tree, stop_after=switch_level, levelled=levelled, emit_vertices=emit_vertices, **options)
        level = switch_level + 1
        late = run.levelled.where(F.col("join_level") >= level).select(F.lit("edge").alias("kind"), F.col("eid").alias("item_id"), F.col("u").alias("a"), F.col("v").alias("b"), F.lit(1).cast("long").alias("len"))
        if run.ledger.has(switch_level):
            paths = run.ledger.frags(switch_level).where("ftype = 'path'").select(F.lit("frag").alias("kind"), F.col("fid").alias("item_id"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("n_edges").alias("len"))
            late = late.unionByName(paths)
        rows = stage_alone(late.sparkSession, lambda: pair_cycles(late, cycle_method).withColumn("fid", F.col("walk") + F.lit(level << LEVEL_SHIFT)), "paired")
        _write_level(run.ledger, level, rows)
        return phase3.unroll(run.ledger, None if emit_vertices else g.edges)

    walks = stage_alone(g.edges.sparkSession, unrolled, "walks")
    return phase3.close_staged(walks, forest, rank)


def _write_level(ledger: Ledger, level: int, rows: DataFrame) -> None:
    """Pairing's cycles in the ledger's form."""
    heads = rows.groupBy("fid").agg(F.sum("len").alias("n_edges"), F.min_by("a", "off").alias("src")).withColumns({"tag": F.lit("frag"), "ftype": F.lit("free"), "dst": F.col("src"), "part": F.lit(0)})
    items = rows.withColumns({"tag": F.lit("item"), "part": F.lit(0), "item_kind": F.col("kind"), "fwd": F.col("ahead")})
    names = [c.split()[0] for c in OUT.split(", ")]
    kinds = dict(c.split() for c in OUT.split(", "))
    full = lambda d: d.select(*[(F.col(c) if c in d.columns else F.lit(None)).cast(kinds[c]).alias(c) for c in names])
    ledger.write(level, full(heads).unionByName(full(items)))


def single_token_circuit(g: Graph, max_steps: int = 10_000) -> tuple[DataFrame, int]:
    """(circuit, supersteps) with one active vertex: each superstep asks the graph for an
    unused edge at the token's vertex, or steps back. For tiny graphs: it needs at least a
    superstep for each edge."""
    spark = g.edges.sparkSession
    edges = g.edges.select("eid", "u", "v").persist()
    used: list[int] = []
    out, steps = [], 0
    try:
        while True:
            first = edges.where(~F.col("eid").isin(used)).orderBy("u", "eid").limit(1).collect()
            if not first:
                break
            start = first[0]["u"]
            stack, trail = [(start, -1, -1)], []
            while stack:
                steps += 1
                if steps > max_steps:
                    raise RuntimeError(f"more than {max_steps} supersteps")
                at = stack[-1][0]
                found = edges.where(((F.col("u") == at) | (F.col("v") == at)) & ~F.col("eid").isin(used)).orderBy("eid").limit(1).collect()
                if found:
                    e = found[0]
                    used.append(e["eid"])
                    stack.append((e["v"] if e["u"] == at else e["u"], e["eid"], at))
                else:
                    x, e, came = stack.pop()
                    if e >= 0:
                        trail.append((e, x, came))
            comp = min(x for _, x, _ in trail)
            out += [(comp, p, e, x, y) for p, (e, x, y) in enumerate(trail)]
    finally:
        edges.unpersist()
    return spark.createDataFrame(out, schemas.CIRCUIT), steps


def tree_tour(tree: Graph) -> DataFrame:
    """A closed tour of every tree of a forest, each edge once in each direction.

    The rule is local: who comes to v from x goes on to the neighbour after x in v's order,
    and after the last to the first. Edges of the tour are numbered 2 eid and 2 eid + 1.
    """
    darts = bidirect(tree.edges).withColumn("id", F.col("eid") * 2 + (F.col("src") > F.col("dst")).cast("long"))
    # any order of a vertex's neighbours will do: by cells, so that no task sorts a hub
    cell = F.pmod(F.xxhash64("dst"), F.lit(phase3.SPREAD))
    turn = with_next(darts.select("src", "dst", "id"), ["src"], ["dst", "id"], cell, {"id": "next_id"})
    turn = stage(turn.select(F.col("id").bitwiseXOR(F.lit(1)).alias("id"), "next_id"), "turns")
    heads = min_label_components(turn, "id", "next_id").select(F.col("v").alias("id"), F.col("comp").alias("head"))
    at = _ring_ranks(turn.join(heads, "id").withColumn("size", F.lit(1).cast("long")))
    rows = stage(at.join(darts.select("id", "src", "dst"), "id"), "toured")
    comp = rows.groupBy("head").agg(F.min("src").alias("comp"))
    return rows.join(comp, "head").select("comp", F.col("at").alias("pos"), F.col("id").alias("eid"), "src", "dst")
