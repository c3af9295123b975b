"""The whole method: parts, merge tree, levels, unrolling and stitching."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark.functions.graph import Graph, require_even
from tourspark.plans import phase2, phase3
from tourspark.plans.metagraph import MergeTree, join_levels, tree_for
from tourspark.session import drop, stage, stage_alone

#: Items, edges or coarse edges, that one task should walk at most.
PART_ITEMS = 20_000_000


def switch_level(levelled: DataFrame, tree: MergeTree, budget: int) -> int | None:
    """The last level before a part would get more than ``budget`` items; None if none does,
    -1 if parts of the first level do. From the closed forms of the level table, no run."""
    from tourspark.plans.measures import level_stats

    over = level_stats(levelled, tree).where(F.col("local") > budget).agg(F.min("level")).first()[0]
    return None if over is None else over - 1


def circuit(
    g: Graph, n: int = 8, how: str = "hash", form: str = "edges", start_vertex: int | None = None, sink: str | None = None,
    remote_policy: str = "carry_one+deferred", strategy: str = "greedy", last_levels: str = "auto", switch: int = 1, budget: int = PART_ITEMS,
    merge_internal: bool = True, order: str = "eid", emit_vertices: bool = True, forest: str = "auto", rank: str = "auto", check: bool = True,
) -> DataFrame:
    """A closed walk over all edges of every component, each edge once.

    ``form``: ``edges`` (comp, pos, eid, src, dst), ``vertices`` or ``array``. A graph without
    parts is partitioned by ``how`` into ``n``. ``last_levels``: ``merge`` merges parts to the
    root; ``pairing`` hands the coarse graph above level ``switch`` to the pairing scheme;
    ``auto`` merges as long as no part gets more than ``budget`` items, and pairs from there
    on, so that no task outgrows it. All are exact. With a ``sink`` the edges are written
    there, range-partitioned by component and position. A graph with an odd vertex is
    rejected.
    """
    from tourspark.plans.baselines import hybrid_circuit, pairing_circuit

    if last_levels not in ("auto", "merge", "pairing"):
        raise ValueError(f"unknown way with the last levels {last_levels}")
    if check:
        require_even(g)
    if g.part_of is None and g.vertices is None:
        g = g.with_partition(how, n)
    tree, joined = tree_for(g, phase2.parts_of(g), strategy), None
    level = switch if last_levels == "pairing" else None
    # no part can have more items than the graph has edges
    if last_levels == "auto" and g.edges.count() > budget:
        joined = stage(join_levels(g, tree), "joined")
        level = switch_level(joined, tree, budget)
        if level is not None and level < 0:
            drop(joined)
    options = {"remote_policy": remote_policy, "merge_internal": merge_internal, "order": order, "emit_vertices": emit_vertices}
    if level is not None and level < 0:
        out = pairing_circuit(g, forest=forest, rank=rank)
    else:
        levelled = phase2.prepare(g, tree, joined, holders=remote_policy == "carry_one")
        if joined is not None:
            drop(joined)
        if level is not None and level < tree.height:
            out = hybrid_circuit(g, level, tree=tree, levelled=levelled, forest=forest, rank=rank, **options)
        else:
            unrolled = lambda: phase3.unroll(phase2.run_levels(g, tree, levelled=levelled, **options).ledger, None if emit_vertices else g.edges)
            walks = stage_alone(g.edges.sparkSession, unrolled, "walks")
            out = phase3.close_staged(walks, forest, rank)
        drop(levelled)
    if start_vertex is not None:
        out = phase3.rotate(out, start_vertex)
    if sink:
        out.repartitionByRange("comp", "pos").sortWithinPartitions("comp", "pos").write.mode("overwrite").parquet(sink)
        out = g.edges.sparkSession.read.schema(phase3.CIRCUIT).parquet(sink)
    return {"edges": lambda x: x, "vertices": phase3.as_vertices, "array": phase3.as_array}[form](out)
