"""Connected components by relational rounds; the lineage is cut in the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark.session import drop, stage


def _rounds_error(n: int) -> RuntimeError:
    return RuntimeError(f"components did not settle within {n} rounds")


def min_label_components(edges: DataFrame, u: str = "u", v: str = "v", max_rounds: int = 64) -> DataFrame:
    """(v, comp): every vertex of ``edges`` with the smallest vertex of its component.

    Each round contracts: every vertex hooks to the neighbour of smallest digest or to itself,
    pointers are doubled twice, and edges inside a tree are dropped, so the edges shrink by
    rounds and isolated trees leave early. Digests are others in each round: by the numbers
    themselves a ring numbered in turn would be one chain of hooks, of which a round takes
    four. Minima are summed before they are shuffled, and the joins are plain inner joins on
    the vertex, which the engine can split where a hub is hot. At last a component is named
    after its smallest vertex.
    """
    live = stage(
        edges.select(F.col(u).cast("long").alias("a"), F.col(v).cast("long").alias("b")).where("a is not null and b is not null"),
        "cc-edges",
    )
    ends = live.select(F.explode(F.array("a", "b")).alias("v")).distinct()
    names = stage(ends.select("v", F.col("v").alias("comp")), "cc-names")
    for turn in range(max_rounds):
        crossing = live.where("a <> b")
        both = crossing.select(F.explode(F.array(F.struct(F.col("a").alias("x"), F.col("b").alias("y")), F.struct(F.col("b").alias("x"), F.col("a").alias("y")))).alias("e")).select("e.x", "e.y")
        at = lambda c: F.struct(F.xxhash64(c, F.lit(turn)).alias("h"), F.col(c).alias("p"))  # noqa: B023, E731
        hook = both.groupBy("x").agg(F.min(at("y")).alias("n")).select("x", F.least("n", at("x"))["p"].alias("p"))
        first = hook = stage(hook, "cc-hook")
        if hook.isEmpty():
            drop(live, hook)
            least = names.groupBy("comp").agg(F.min("v").alias("least"))
            return names.join(least, "comp").select("v", F.col("least").alias("comp"))
        for _ in range(2):
            far = hook.select(F.col("x").alias("p"), F.col("p").alias("q"))
            hook = hook.join(far, "p").select("x", F.col("q").alias("p"))
        tree, before, named = stage(hook, "cc-tree"), live, names
        hook = tree
        names = stage(
            names.join(hook.withColumnRenamed("x", "comp"), "comp", "left").select("v", F.coalesce("p", "comp").alias("comp")),
            "cc-names",
        )
        left = hook.select(F.col("x").alias("a"), F.col("p").alias("pa"))
        right = hook.select(F.col("x").alias("b"), F.col("p").alias("pb"))
        live = crossing.join(left, "a").join(right, "b").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).where("a <> b").distinct()
        live = stage(live, "cc-edges")
        drop(first, tree, before, named)  # a round reads the tables of the one before only
    raise _rounds_error(max_rounds)


def components(g, method: str = "label_min", max_rounds: int = 64) -> DataFrame:
    """(v, comp): every vertex with the smallest vertex of its component.

    ``label_min`` contracts trees of smallest neighbours; ``star`` alternates large-star and
    small-star rewriting of the edges until they are stars.
    """
    if method == "label_min":
        return min_label_components(g.edges, max_rounds=max_rounds)
    if method != "star":
        raise ValueError(f"unknown method {method}")
    rows = stage(g.edges.select(F.greatest("u", "v").alias("a"), F.least("u", "v").alias("b")).distinct(), "star")
    every = stage(rows.select(F.explode(F.array("a", "b")).alias("v")).distinct(), "star-v")
    live = rows.where("a <> b")
    for _ in range(max_rounds):
        # large star: larger neighbours of a vertex go to the least of its neighbourhood
        both = live.select("a", "b").unionByName(live.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        large = stage(large.where("a <> b"), "star-large")
        # small star: smaller neighbours and the vertex itself go to the least of them
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e")).select("e.a", "e.b").where("a <> b").distinct()
        small = stage(small, "star-small")
        if small.exceptAll(live.select("a", "b")).isEmpty() and live.select("a", "b").exceptAll(small).isEmpty():
            return every.join(small.groupBy("a").agg(F.min("b").alias("comp")).withColumnRenamed("a", "v"), "v", "left").select("v", F.coalesce("comp", "v").alias("comp"))
        live = small
    raise _rounds_error(max_rounds)
