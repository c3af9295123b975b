"""Unrolling the fragments, joining closed walks at shared vertices, and ranking the edges."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark import schemas
from tourspark.functions.numbering import dense_number
from tourspark.functions.rings import with_next
from tourspark.plans.components import min_label_components
from tourspark.plans.ledger import Ledger
from tourspark.session import drop, stage, stage_alone

#: Up to so many rows of links or runs, some 50 MB as Python rows, a driver works out the
#: order; beyond, rounds do. Both give the same forest and the same ranks.
DRIVER_ROWS = 100_000
#: Positions of a walk in one block of the joins of edges with runs and of items with nodes.
BLOCK_SHIFT = 16
#: Blocks over which the walks of one vertex are dealt.
SPREAD = 64


def top_walks(ledger: Ledger) -> DataFrame:
    """fid, level, n_edges of the fragments that are closed walks of their own."""
    return ledger.all_frags().where("ftype <> 'path'").select("fid", "level", "n_edges")


def unroll(ledger: Ledger, edges: DataFrame | None = None) -> DataFrame:
    """walk, pos, eid, src, dst of every edge, by one join a level from the top down.

    A node is a fragment that a walk uses, with its first position and direction. Its items
    that are edges are done; its items that are paths become nodes one level below. Nodes and
    items meet by fragment and block of its positions, so a fragment that is nearly the whole
    circuit is dealt over many tasks. ``edges`` gives the ends where items don't have them.
    """
    nodes, done = None, None
    for level in reversed(ledger.levels()):
        tops = ledger.frags(level).where("ftype <> 'path'").select("fid", F.col("fid").alias("walk"), F.lit(0).cast("long").alias("base"), F.lit(True).alias("ahead"), F.col("n_edges").alias("size"))
        nodes = tops if nodes is None else nodes.unionByName(tops)
        blocks = nodes.withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.shiftright(F.greatest(F.col("size") - 1, F.lit(0)), BLOCK_SHIFT))))
        items = ledger.items(level).withColumn("block", F.shiftright("off", BLOCK_SHIFT))
        at = F.when(F.col("ahead"), F.col("base") + F.col("off")).otherwise(F.col("base") + F.col("size") - F.col("off") - F.col("len"))
        rows = items.join(blocks, ["fid", "block"]).select("walk", at.alias("pos"), "item_kind", "item_id", (F.col("ahead") == F.col("fwd")).alias("same"), F.when(F.col("ahead"), F.col("a")).otherwise(F.col("b")).alias("src"), F.when(F.col("ahead"), F.col("b")).otherwise(F.col("a")).alias("dst"), "len")
        if level:
            rows = stage(rows, "unrolled")
        found = rows.where("item_kind = 'edge'").select("walk", "pos", F.col("item_id").alias("eid"), "same", "src", "dst")
        done = found if done is None else done.unionByName(found)
        nodes = rows.where("item_kind = 'frag'").select(F.col("item_id").alias("fid"), "walk", F.col("pos").alias("base"), F.col("same").alias("ahead"), F.col("len").alias("size"))
    if done is None:
        return ledger.spark.createDataFrame([], "walk long, pos long, eid long, src long, dst long")
    if edges is None:
        return done.drop("same")
    ends = done.drop("src", "dst").join(edges.select("eid", "u", "v"), "eid")
    return ends.select("walk", "pos", "eid", F.when(F.col("same"), F.col("u")).otherwise(F.col("v")).alias("src"), F.when(F.col("same"), F.col("v")).otherwise(F.col("u")).alias("dst"))


def incidence(walks: DataFrame) -> DataFrame:
    """(v, walk, pos): the first place at which a walk leaves a vertex."""
    return walks.groupBy(F.col("src").alias("v"), "walk").agg(F.min("pos").alias("pos"))


def pivots(walks: DataFrame) -> DataFrame:
    """(v, n_walks): vertices on two closed walks or more."""
    return incidence(walks).groupBy("v").agg(F.count("*").alias("n_walks")).where("n_walks > 1")


def _links(inc: DataFrame) -> DataFrame:
    """(walk, least, v): every walk with the least walk at a vertex they share, one vertex for
    each such pair. They connect just what sharing vertices connects."""
    least = inc.groupBy("v").agg(F.min("walk").alias("least"))
    return inc.join(least, "v").where("walk <> least").groupBy("walk", "least").agg(F.min("v").alias("v"))


def forest_driver(links: DataFrame) -> DataFrame:
    """A spanning forest of the links, by union-find on the driver."""
    up: dict[int, int] = {}

    def root(a: int) -> int:
        while (b := up.get(a, a)) != a:
            up[a] = up.get(b, b)
            a = b
        return a

    kept = []
    for r in links.orderBy("walk", "least").collect():
        a, b = root(r["walk"]), root(r["least"])
        if a != b:
            up[max(a, b)] = min(a, b)
            kept.append(tuple(r))
    return links.sparkSession.createDataFrame(kept, links.schema)


def forest_boruvka(links: DataFrame, max_rounds: int = 64) -> DataFrame:
    """A spanning forest in rounds: every component takes its least link to another one."""
    spark = links.sparkSession
    live = stage(dense_number(links, ["walk", "least"], "id", 0).withColumns({"x": F.col("walk"), "y": F.col("least")}), "links")
    kept = spark.createDataFrame([], links.schema)
    for _ in range(max_rounds):
        if live.isEmpty():
            return kept
        before = live
        sides = live.select(F.explode(F.array("x", "y")).alias("c"), "id")
        picked = stage(live.join(sides.groupBy("c").agg(F.min("id").alias("id")).select("id").distinct(), "id"), "picked")
        kept = kept.unionByName(picked.select(links.columns))
        names = min_label_components(picked, "x", "y")
        left, right = names.withColumnsRenamed({"v": "x", "comp": "cx"}), names.withColumnsRenamed({"v": "y", "comp": "cy"})
        live = live.join(left, "x", "left").join(right, "y", "left").select("id", *links.columns, F.coalesce("cx", "x").alias("x"), F.coalesce("cy", "y").alias("y")).where("x <> y")
        live = stage(live, "links")
        drop(before)
    raise RuntimeError(f"the forest did not end within {max_rounds} rounds")


def stitch(inc: DataFrame, forest: str = "auto") -> DataFrame:
    """(walk, pos, to_walk, to_pos): what leads to a place goes on at another one.

    At each chosen vertex the walks of the forest's links exchange their next edges in a
    circle. Along a forest every exchange joins walks that are still apart, so one circuit
    is left in each component.
    """
    links = stage(_links(inc), "links")
    if forest == "auto":
        forest = "driver" if links.count() <= DRIVER_ROWS else "boruvka"
    tree = forest_driver(links) if forest == "driver" else forest_boruvka(links)
    chosen = tree.select("v", F.explode(F.array("walk", "least")).alias("walk")).distinct()
    at = stage(inc.join(chosen, ["v", "walk"]), "exchanged")
    block = F.pmod(F.xxhash64("walk"), F.lit(SPREAD))
    return with_next(at, ["v"], ["walk"], block, {"walk": "to_walk", "pos": "to_pos"}).select("walk", "pos", "to_walk", "to_pos")


def runs_of(lengths: DataFrame, cuts: DataFrame) -> DataFrame:
    """walk, start, size, low, next_walk, next_start: walks cut at the exchanged places.

    ``lengths``: walk, n, low (its least vertex). A run may wrap past the walk's end. A walk
    without cuts is one run that follows itself.
    """
    ahead = {"pos": "stop", "to_walk": "next_walk", "to_pos": "next_start"}
    cut = with_next(cuts, ["walk"], ["pos"], F.shiftright("pos", BLOCK_SHIFT), ahead).select("walk", F.col("pos").alias("start"), *ahead.values())
    rows = lengths.join(cut, "walk", "left")
    size = F.when(F.col("start").isNull() | (F.col("stop") == F.col("start")), F.col("n")).otherwise(F.pmod(F.col("stop") - F.col("start"), F.col("n")))
    return rows.select("walk", F.coalesce("start", F.lit(0)).alias("start"), size.alias("size"), "n", "low", F.coalesce("next_walk", "walk").alias("next_walk"), F.coalesce("next_start", F.lit(0)).alias("next_start"))


RANKED = "walk long, start long, comp long, at long"


def rank_driver(runs: DataFrame) -> DataFrame:
    """(walk, start, comp, at): each run's component and first position, on the driver."""
    follow, size, low = {}, {}, {}
    for r in runs.collect():
        k = (r["walk"], r["start"])
        follow[k], size[k], low[k] = (r["next_walk"], r["next_start"]), r["size"], r["low"]
    out, seen = [], set()
    for k in sorted(follow):
        if k in seen:
            continue
        ring, at, x = [], 0, k
        while x not in seen:
            seen.add(x)
            ring.append((x, at))
            at += size[x]
            x = follow[x]
        comp = min(low[x] for x, _ in ring)
        out += [(w, s, comp, p) for (w, s), p in ring]
    return runs.sparkSession.createDataFrame(out, RANKED)


def rank_doubling(runs: DataFrame, max_rounds: int = 64) -> DataFrame:
    """As ``rank_driver``, by rounds in which every run's pointer back doubles its reach."""
    ids = stage(dense_number(runs, ["walk", "start"], "id", 0), "run-ids")
    key = ids.select(F.col("walk").alias("next_walk"), F.col("start").alias("next_start"), F.col("id").alias("next_id"))
    linked = stage(ids.join(key, ["next_walk", "next_start"]).select("id", "next_id", "walk", "start", "size", "low"), "run-links")
    comps = min_label_components(linked, "id", "next_id").withColumnRenamed("v", "id").withColumnRenamed("comp", "head")
    # the head of a ring is its run of least id; others point back and add up sizes
    back = linked.select(F.col("next_id").alias("id"), F.col("id").alias("ptr"), F.col("size").alias("gap"))
    back = back.join(comps, "id").select("id", "head", F.when(F.col("id") == F.col("head"), F.col("id")).otherwise(F.col("ptr")).alias("ptr"), F.when(F.col("id") == F.col("head"), F.lit(0)).otherwise(F.col("gap")).alias("gap"))
    back = stage(back, "ranks")
    for _ in range(max_rounds):
        if back.where("ptr <> head").isEmpty():
            low = linked.join(comps, "id").groupBy("head").agg(F.min("low").alias("comp"))
            return back.join(low, "head").join(linked, "id").select("walk", "start", "comp", F.col("gap").alias("at"))
        far = back.select(F.col("id").alias("ptr"), F.col("ptr").alias("far"), F.col("gap").alias("more"))
        before, back = back, stage(back.join(far, "ptr").select("id", "head", F.col("far").alias("ptr"), (F.col("gap") + F.col("more")).alias("gap")), "ranks")
        drop(before)
    raise RuntimeError(f"the ranks did not settle within {max_rounds} rounds")


def placed(walks: DataFrame, runs: DataFrame, ranks: DataFrame) -> DataFrame:
    """comp, pos, eid, src, dst: every edge at its run's position.

    A run covers blocks of positions of its walk; edges meet runs by walk and block, so even
    a walk with most of the edges is dealt over many tasks.
    """
    known = runs.join(ranks, ["walk", "start"]).withColumn("stop", F.col("start") + F.col("size"))
    spans = F.array(
        F.struct(F.col("start").alias("lo"), F.least("stop", "n").alias("hi"), F.col("at").alias("to")),
        F.struct(F.lit(0).cast("long").alias("lo"), F.greatest(F.col("stop") - F.col("n"), F.lit(0)).alias("hi"), (F.col("at") + F.col("n") - F.col("start")).alias("to")),
    )
    parts = known.select("walk", "comp", F.explode(spans).alias("s")).select("walk", "comp", "s.*").where("hi > lo")
    blocks = parts.withColumn("block", F.explode(F.sequence(F.shiftright("lo", BLOCK_SHIFT), F.shiftright(F.col("hi") - 1, BLOCK_SHIFT))))
    edges = walks.withColumn("block", F.shiftright("pos", BLOCK_SHIFT))
    return edges.join(blocks, ["walk", "block"]).where("pos >= lo AND pos < hi").select("comp", (F.col("to") + F.col("pos") - F.col("lo")).alias("pos"), "eid", "src", "dst")


def close_walks(walks: DataFrame, forest: str = "auto", rank: str = "auto") -> DataFrame:
    """One circuit a component from closed walks (walk, pos, eid, src, dst)."""
    return close_staged(stage(walks, "walks"), forest, rank)


def close_staged(walks: DataFrame, forest: str = "auto", rank: str = "auto") -> DataFrame:
    """As ``close_walks``, for walks that have been staged."""
    inc = stage(incidence(walks), "incidence")
    lengths = walks.groupBy("walk").agg(F.count("*").alias("n"), F.min("src").alias("low"))
    runs = stage_alone(walks.sparkSession, lambda: runs_of(lengths, stitch(inc, forest)), "runs")
    drop(inc)
    if rank == "auto":
        rank = "driver" if runs.count() <= DRIVER_ROWS else "doubling"
    ranks = rank_driver(runs) if rank == "driver" else rank_doubling(runs)
    return placed(walks, runs, ranks)


def rotate(circuit: DataFrame, start_vertex: int) -> DataFrame:
    """The circuit through ``start_vertex`` begins there; others stay as they are."""
    at = circuit.where(F.col("src") == start_vertex).groupBy("comp").agg(F.min("pos").alias("shift"))
    size = circuit.groupBy("comp").agg(F.count("*").alias("n"))
    known = size.join(at, "comp", "left")
    return circuit.join(known, "comp").select("comp", F.pmod(F.col("pos") - F.coalesce("shift", F.lit(0)), F.col("n")).alias("pos"), "eid", "src", "dst")


def as_vertices(circuit: DataFrame) -> DataFrame:
    """(comp, pos, v): the vertices in turn, the first once more at the end."""
    last = circuit.groupBy("comp").agg(F.max(F.struct("pos", "dst")).alias("e")).select("comp", (F.col("e.pos") + 1).alias("pos"), F.col("e.dst").alias("v"))
    return circuit.select("comp", "pos", F.col("src").alias("v")).unionByName(last)


def as_array(circuit: DataFrame) -> DataFrame:
    """(comp, circuit): all edges of a component in one row, for small results."""
    return circuit.groupBy("comp").agg(F.array_sort(F.collect_list(F.struct("pos", "eid", "src", "dst"))).alias("circuit"))


def unroll_sequential(ledger: Ledger, start: int | None = None) -> list[tuple[int, int, int, int, int]]:
    """(comp, pos, eid, src, dst) for a ledger that a driver can hold, in a single pass.

    A walk is unrolled until it comes to a vertex that a walk not yet begun passes; that walk
    goes first, from there, and the old one goes on when it has come back.
    """
    heads = {r["fid"]: r for r in ledger.all_frags().collect()}
    bodies: dict[int, list] = {}
    for r in ledger.all_items().orderBy("fid", "seq").collect():
        bodies.setdefault(r["fid"], []).append(r)

    def expand(fid: int, ahead: bool) -> Iterator[tuple[int, int, int]]:
        stack = [iter(bodies[fid] if ahead else reversed(bodies[fid]))]
        way = [ahead]
        while stack:
            r = next(stack[-1], None)
            if r is None:
                stack.pop()
                way.pop()
            elif r["item_kind"] == "edge":
                yield (r["item_id"], r["a"], r["b"]) if way[-1] else (r["item_id"], r["b"], r["a"])
            else:
                same = r["fwd"] == way[-1]
                stack.append(iter(bodies[r["item_id"]] if same else reversed(bodies[r["item_id"]])))
                way.append(same)

    walks = {f: list(expand(f, True)) for f, h in heads.items() if h["ftype"] != "path"}
    through: dict[int, list[tuple[int, int]]] = {}
    for f, steps in walks.items():
        for i, (_, a, _) in enumerate(steps):
            through.setdefault(a, []).append((f, i))
    begun: set[int] = set()
    out = []
    order = sorted(walks, key=lambda f: (0 if start is not None and any(a == start for _, a, _ in walks[f]) else 1, f))
    for first in order:
        if first in begun:
            continue
        begun.add(first)
        steps = walks[first]
        if start is not None and (turn := next((i for i, s in enumerate(steps) if s[1] == start), 0)):
            steps = steps[turn:] + steps[:turn]
        rows, stack = [], [iter(steps)]
        pending = steps[0][1]
        while stack:
            waiting, other = through.get(pending, []), None
            while waiting and other is None:
                x = waiting.pop()
                other = x if x[0] not in begun else None
            if other:
                f, i = other
                begun.add(f)
                stack.append(iter(walks[f][i:] + walks[f][:i]))
                continue
            step = next(stack[-1], None)
            if step is None:
                stack.pop()
                pending = None
                continue
            rows.append(step)
            pending = step[2]
        comp = min(r[1] for r in rows)
        out += [(comp, p, *r) for p, r in enumerate(rows)]
    return out


CIRCUIT = schemas.CIRCUIT
