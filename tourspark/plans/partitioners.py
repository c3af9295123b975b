"""Partitioners: expressions where the part follows from the id, iterations where it doesn't."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tourspark.functions.graph import Graph, bidirect, ends
from tourspark.functions.numbering import dense_number
from tourspark.session import lookup, stage


#: New vertices of a round that are broadcast, so that the edges need not be moved.
FRESH = 100_000


def beside(vertices: DataFrame) -> DataFrame:
    """A table of vertices for a join. Its file is a few bytes a row, so the engine would take
    it for small and hold it whole in the driver, once a round; it goes by the key instead."""
    return vertices.hint("merge")


def _digest(v: Column) -> Column:
    return F.conv(F.substring(F.md5(v.cast("string")), 1, 8), 16, 10).cast("long")


def partition(g: Graph, how: str, n: int, step: int = 1, mapping: DataFrame | None = None, rounds: int = 8, slack: float = 0.1, ground: Ground | None = None) -> Graph:
    """``g`` with parts.

    ``hash``: digest of the id; ``modulo``: (v div step) % n; ``range``: equal id ranges;
    ``external`` and ``column``: ``mapping`` (v, part) as given; ``bfs``: growth from n seeds
    until nothing grows; ``lpa``: ``rounds`` of label propagation. The last two keep every
    part within (1 + slack) of equal size; for several partitions of one graph, ``ground`` is
    what they share (``ground_of``).
    """
    if n < 1:
        raise ValueError("at least one part")
    if how == "hash":
        return Graph(g.edges, None, n, lambda v: F.pmod(_digest(v), F.lit(n)).cast("int"))
    if how == "modulo":
        # ids are not negative; the shift keeps two sides of a bipartite graph together
        return Graph(g.edges, None, n, lambda v: F.pmod(F.floor(v / step), F.lit(n)).cast("int"))
    if how == "range":
        low, high = g.edges.agg(F.min("u"), F.max("v")).first()
        low, width = low or 0, (high or 0) - (low or 0) + 1
        return Graph(g.edges, None, n, lambda v: F.least(F.floor((v - low) * n / width), F.lit(n - 1)).cast("int"))
    if how in ("external", "column"):
        if mapping is None:
            raise ValueError("a mapping (v, part) is needed")
        return Graph(g.edges, mapping.select(F.col("v").cast("long").alias("v"), F.col("part").cast("int").alias("part")), n)
    if how == "bfs":
        return Graph(g.edges, _grow(ground or ground_of(g), n, slack), n)
    if how == "lpa":
        return Graph(g.edges, _propagate(ground or ground_of(g), n, rounds, slack), n)
    raise ValueError(f"unknown partitioner {how}")


def _capacity(n_vertices: int, n: int, slack: float) -> int:
    return max(1, math.ceil(n_vertices / n * (1 + slack)))


def _neighbours(g: Graph) -> DataFrame:
    return stage(bidirect(g.edges).where("src <> dst").groupBy("src", "dst").count().withColumnRenamed("count", "w"), "neighbours")


@dataclass(frozen=True)
class Ground:
    """``near``: src, dst, w of neighbours; ``every``: v, each vertex; ``size``: how many."""

    near: DataFrame
    every: DataFrame
    size: int


def ground_of(g: Graph) -> Ground:
    near, every = _neighbours(g), stage(ends(g.edges).distinct(), "vertices")
    return Ground(near, every, every.count())


def _settle(wishes: DataFrame, room: DataFrame) -> DataFrame:
    """The strongest wishes of each part that it has room for. ``room``: one row a part."""
    ranked = wishes.withColumn("__rk", F.row_number().over(Window.partitionBy("part").orderBy(F.desc("w"), "v")))
    return ranked.join(room, "part").where("__rk <= room").select("v", "part")


def _rooms(at: DataFrame, n: int, capacity: int) -> list[int]:
    """How many more vertices each part takes."""
    sizes = {r["part"]: r["count"] for r in at.groupBy("part").count().collect()}  # a row a part
    return [max(0, capacity - sizes.get(p, 0)) for p in range(n)]


def _room_rows(spark, rooms: list[int]) -> DataFrame:
    return lookup(spark, list(enumerate(rooms)), "part int, room int")


def _fill(every: DataFrame, done: DataFrame, n: int, capacity: int) -> DataFrame:
    """Vertices without a part, numbered by their digests and dealt to the parts' places."""
    left = every.join(beside(done), "v", "left_anti").withColumn("__d", _digest(F.col("v")))
    if left.isEmpty():
        return done
    first, spans = 0, []
    for p, room in enumerate(_rooms(done, n, capacity)):
        spans += [(p, first, first + room)] if room else []
        first += room
    places = lookup(every.sparkSession, spans, "part int, lo long, hi long")
    numbered = dense_number(left, ["__d", "v"], "__place", 0)
    return done.unionByName(numbered.join(places, F.expr("__place >= lo AND __place < hi")).select("v", "part"))


def _grow(ground: Ground, n: int, slack: float) -> DataFrame:
    """Every round the vertices next to a part join the one with most edges to them, as far as
    it has room. It goes on until no part grows; what no seed reaches is dealt out.

    A part that is full stays full, so what is next to it and what it took last is looked at no
    more. Of the edges those between two vertices without a part stay, and those of the newest
    ones; they are written anew whenever half of the vertices that were left have got one.
    """
    near, every = ground.near, ground.every
    left = n_vertices = ground.size
    capacity = _capacity(n_vertices, n, slack)
    seeds = every.orderBy(_digest(F.col("v")), "v").limit(n).select("v").collect()  # one row a part
    spark = every.sparkSession
    done = stage(spark.createDataFrame([(r["v"], p) for p, r in enumerate(seeds)], "v long, part int"), "growth")
    # what is next to the parts, with its edges to each: a round adds the new vertices' edges only
    border, fresh = spark.createDataFrame([], "v long, part int, w long"), F.broadcast(done)
    while True:
        rooms = _rooms(done, n, capacity)
        room = _room_rows(spark, rooms)
        # only parts with room are asked, or full ones would hold up their neighbours' growth
        open_parts = F.col("part").isin([p for p, x in enumerate(rooms) if x])
        new = near.join(fresh.where(open_parts), near["src"] == fresh["v"]).select(F.col("dst").alias("v"), "part", "w")
        border = border.where(open_parts).unionByName(new).join(beside(done.select("v")), "v", "left_anti").groupBy("v", "part").agg(F.sum("w").alias("w"))
        border = stage(border, "border")
        wish = border.groupBy("v").agg(F.max(F.struct("w", -F.col("part"))).alias("b")).select("v", (-F.col("b.col2")).cast("int").alias("part"), "b.w")
        more = stage(_settle(wish, room), "grown")
        grown = more.count()
        if not grown:
            return stage(_fill(every, done, n, capacity), "bfs")
        free = n_vertices - sum(capacity - x for x in rooms)
        if 2 * free < left:
            left, took = free, beside(done.select("v"))
            near = near.join(took, near["src"] == took["v"], "left_anti").join(took, near["dst"] == took["v"], "left_anti")
            near = stage(near, "neighbours")
        done = stage(done.unionByName(more), "growth")
        fresh = F.broadcast(more) if grown <= FRESH else beside(more)


def _propagate(ground: Ground, n: int, rounds: int, slack: float) -> DataFrame:
    """From equal parts, every round the vertices whose neighbours are mostly elsewhere go
    there, those with most such edges first, as far as there is room."""
    near, every = ground.near, ground.every
    capacity = _capacity(ground.size, n, slack)
    dealt = dense_number(every.withColumn("__d", _digest(F.col("v"))), ["__d", "v"], "__place", 0)
    at = stage(dealt.select("v", F.pmod("__place", F.lit(n)).cast("int").alias("part")), "labels")
    for _ in range(rounds):
        seen = near.join(beside(at), near["dst"] == at["v"]).groupBy("src", "part").agg(F.sum("w").alias("w"))
        best = seen.groupBy("src").agg(F.max(F.struct("w", -F.col("part"))).alias("b")).select(F.col("src").alias("v"), (-F.col("b.col2")).cast("int").alias("to"), "b.w")
        moves = best.join(beside(at), "v").where("`to` <> part").select("v", F.col("to").alias("part"), "w")
        chosen = _settle(moves, _room_rows(at.sparkSession, _rooms(at, n, capacity))).select("v", F.col("part").alias("to"))
        at = stage(at.join(beside(chosen), "v", "left").select("v", F.coalesce("to", "part").alias("part")), "labels")
    return at
