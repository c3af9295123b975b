"""Merging parts level by level along the tree, phase 1 at each level."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark.functions.graph import Graph
from tourspark.plans.ledger import Ledger
from tourspark.plans.metagraph import MergeTree, join_levels, retire_levels, tree_for, with_holders
from tourspark.plans.phase1 import phase1
from tourspark.session import lookup, stage

#: What a part holds of its remote edges: both directions of each; one of them, which the
#: lighter of the two sides that merge keeps; or nothing, the edges staying where they were
#: read until the level at which they join.
POLICIES = ("carry_both", "carry_one", "deferred", "carry_one+deferred")


@dataclass(frozen=True)
class Run:
    """``levelled``: eid, u, v, pu, pv, ru, rv, join_level, a folder for each join level, and
    holder if one copy is carried."""

    ledger: Ledger
    tree: MergeTree
    levelled: DataFrame


def prepare(g: Graph, tree: MergeTree, edges: DataFrame | None = None, holders: bool = False) -> DataFrame:
    """Edges with the level at which they join and the levels at which their ends retire; with
    ``holders`` also the part that holds the one copy of a remote edge, which only a policy
    that carries one copy asks for. ``edges``: the join levels, if known."""
    edges = join_levels(g, tree) if edges is None else edges  # looked up anew where it is read
    retire = retire_levels(edges)
    both = edges.join(retire.withColumnsRenamed({"v": "u", "retire_level": "ru"}), "u").join(retire.withColumnRenamed("retire_level", "rv"), "v")
    if holders:
        both = with_holders(both, tree)
    kept = ["eid", "u", "v", "pu", "pv", "ru", "rv", *(["holder"] if holders else []), "join_level"]
    return stage(both.select(*kept), "levelled", ("join_level",))


def _relabelled(rows: DataFrame, column: str, step: dict[int, int]) -> DataFrame:
    """``column`` by the map of parts, which has a row a part."""
    moves = [(a, b) for a, b in step.items() if a != b]
    if not moves:
        return rows
    small = lookup(rows.sparkSession, moves, "old int, new int")
    return rows.join(small, rows[column] == small["old"], "left").withColumn(column, F.coalesce("new", column).cast("int")).drop("old", "new")


def edge_items(rows: DataFrame, part_map: dict[int, int]) -> DataFrame:
    own = rows.select(F.col("pu").alias("part"), F.lit("edge").alias("kind"), F.col("eid").alias("item_id"), F.col("u").alias("a"), F.col("v").alias("b"), F.lit(1).cast("long").alias("len"), F.col("ru").alias("ra"), F.col("rv").alias("rb"))
    return _relabelled(own, "part", part_map)


def path_items(frags: DataFrame, step: dict[int, int]) -> DataFrame:
    own = frags.where("ftype = 'path'").select("part", F.lit("frag").alias("kind"), F.col("fid").alias("item_id"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("n_edges").alias("len"), F.col("rs").alias("ra"), F.col("rd").alias("rb"))
    return _relabelled(own, "part", step)


def run_levels(
    g: Graph, tree: MergeTree, ledger_path: str | None = None, remote_policy: str = "carry_one+deferred", resume: bool = True,
    merge_internal: bool = True, order: str = "eid", stop_after: int | None = None, levelled: DataFrame | None = None, emit_vertices: bool = True,
    keep_items: bool = True,
) -> Run:
    """Phase 1 at every level of the tree; all fragments go to the ledger.

    A level that the ledger has is not run again. Under the deferred policies a level reads
    only the folder of its own join level; the carrying ones move the remote edges that are
    left along with the parts at every level. Fragments are the same under all of them.
    Levels with neither edges nor paths are left out. Without ``keep_items`` every level is
    walked as ever, but its items, which unrolling alone reads, don't go to the ledger.
    """
    if ledger_path is not None and not keep_items:
        raise ValueError("a ledger that is kept needs its items")
    if remote_policy not in POLICIES:
        raise ValueError(f"unknown policy {remote_policy}")
    spark = g.edges.sparkSession
    ledger, maps = Ledger.create(spark, ledger_path), tree.maps()
    levelled = levelled if levelled is not None else prepare(g, tree, holders=remote_policy == "carry_one")
    joins = {r["join_level"]: r["count"] for r in levelled.groupBy("join_level").count().collect()}  # a row a level
    if None in joins:
        raise ValueError(f"{joins[None]} edges never join: the merge tree has more than one root")
    state = None
    if "deferred" not in remote_policy:
        one = [F.struct(F.lit(0).alias("side"), F.col("holder").alias("at"))]
        two = [F.struct(F.lit(i).alias("side"), F.col(p).alias("at")) for i, p in enumerate(("pu", "pv"))]
        state = levelled.withColumn("s", F.explode(F.array(*(two if remote_policy == "carry_both" else one)))).select("*", "s.side", "s.at").drop("s")
        state = stage(state.where((F.col("side") == 0) | (F.col("join_level") > 0)), "state")
    last, paths = max(joins, default=-1), 0
    for level in range(last + 1):
        if stop_after is not None and level > stop_after:
            break
        if state is None:
            local = levelled.where(F.col("join_level") == level)
        else:
            local = state.where((F.col("join_level") == level) & (F.col("side") == 0)).select(levelled.columns)
        if not ledger.has(level) or not resume:
            items = edge_items(local, maps[level])
            if level and paths:
                step = {maps[level - 1][p]: maps[level][p] for p in tree.parts}
                items = items.unionByName(path_items(ledger.frags(level - 1), step))
            ledger.write(level, phase1(items, level, sorted(set(maps[level].values())), merge_internal, order, emit_vertices, keep_items))
        paths = ledger.frags(level).where("ftype = 'path'").count()
        if state is not None and level < last:
            left = state.where(F.col("join_level") > level)
            state = stage(_relabelled(left, "at", {maps[level][p]: maps[level + 1][p] for p in tree.parts}), "state")
    return Run(ledger, tree, levelled)


def parts_of(g: Graph) -> list[int]:
    """The parts, where a partitioner numbers them from 0, or those in the vertex table."""
    if g.part_of is not None:
        return list(range(g.n_parts or 1))
    return sorted(r["part"] for r in g.vertices.select("part").distinct().collect())


def build(g: Graph, strategy: str = "greedy", zero_weight: str = "pair", **options) -> Run:
    return run_levels(g, tree_for(g, parts_of(g), strategy, zero_weight), **options)
