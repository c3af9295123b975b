"""Open trails, and closed walks over graphs that aren't even."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tourspark.functions.graph import Graph, bidirect, odd_vertices
from tourspark.plans.circuit import circuit
from tourspark.plans.components import components
from tourspark.plans.verify import chain_breaks
from tourspark.session import stage


def open_trail(g: Graph) -> DataFrame:
    """A trail over all edges, each once, of components with two odd vertices at most.

    An edge between the two makes a component even; its circuit, turned to begin after that
    edge and without it, is the trail. A component with more odd vertices is an error.
    """
    names = stage(components(g), "oc")
    odd = odd_vertices(g).join(names, "v").groupBy("comp").agg(F.min("v").alias("u"), F.max("v").alias("v"), F.count("*").alias("n"))
    odd = stage(odd, "odd")
    if not odd.where("n > 2").isEmpty():
        raise ValueError("a component has more than two odd vertices")
    top = (g.edges.agg(F.max("eid")).first()[0] or 0) + 1
    # ids above all others: one added edge a component, numbered by its component's vertex
    added = odd.select((F.col("u") + F.lit(top)).alias("eid"), "u", "v")
    even = Graph(stage(g.edges.select("eid", "u", "v").unionByName(added), "even"), g.vertices, g.n_parts, g.part_of)
    rows = stage(circuit(even, check=False), "oc")
    cut = rows.where(F.col("eid") >= top).select("comp", (F.col("pos") + 1).alias("shift"))
    size = rows.groupBy("comp").agg(F.count("*").alias("m"))
    turned = rows.join(size.join(cut, "comp", "left"), "comp").select("comp", F.pmod(F.col("pos") - F.coalesce("shift", F.lit(0)), F.col("m")).alias("pos"), "eid", "src", "dst")
    return turned.where(F.col("eid") < top)


def trail_summary(trail: DataFrame) -> DataFrame:
    """n_edges, chained, and the two ends of a trail in one component."""
    ends = trail.groupBy("comp").agg(F.count("*").alias("n_edges"), F.min_by("src", "pos").alias("a"), F.max_by("dst", "pos").alias("b"))
    return ends.join(chain_breaks(trail), "comp").select("n_edges", (F.col("n") == 0).alias("chained"), F.least("a", "b").alias("low"), F.greatest("a", "b").alias("high"))


def covering_walk(g: Graph) -> tuple[DataFrame, int]:
    """A closed walk over all edges of every component, some of them again, and how many
    more edges it takes.

    Odd vertices are paired greedily: balls around them grow by one a round, and where balls
    meet in a vertex their centres are paired, the nearest first, until no vertex is in two
    balls; so the balls of all that are left have no more rows than the graph has vertices,
    whatever hubs it has. The edges of the pair's ways to where they meet are doubled. It isn't
    always the least number of edges. A component has an even number of odd vertices, so all
    find a partner.
    """
    left = stage(odd_vertices(g).select("v"), "odd")
    steps = stage(bidirect(g.edges).where("src <> dst").groupBy("src", "dst").agg(F.min("eid").alias("eid")), "steps")
    extra = None
    reach = left.select(F.col("v").alias("from"), F.col("v").alias("at"), F.array().cast("array<long>").alias("way"))
    while not left.isEmpty():
        # one shortest way to each vertex reached, from every odd vertex that is left
        grown = reach.join(steps, reach["at"] == steps["src"]).select("from", F.col("dst").alias("at"), F.concat("way", F.array("eid")).alias("way"))
        both = reach.unionByName(grown).groupBy("from", "at").agg(F.min(F.struct(F.size("way").alias("n"), "way")).alias("b")).select("from", "at", "b.way")
        reach = stage(both, "reach")
        while True:
            meets = stage(_neighbours(reach), "meets")
            if meets.isEmpty():
                break
            found = _disjoint(meets)
            edges = found.select(F.explode("way").alias("eid"))
            extra = edges if extra is None else extra.unionByName(edges)
            gone = stage(found.select(F.explode(F.array("x", "y")).alias("v")), "gone")
            left = stage(left.join(gone, "v", "left_anti"), "odd")
            reach = stage(reach.join(gone.withColumnRenamed("v", "from"), "from", "left_anti"), "reach")
    if extra is None:
        return circuit(g), 0
    # an edge that two paths double twice needs only its parity
    again = stage(extra.groupBy("eid").count().where("count % 2 = 1").select("eid"), "again")
    top = (g.edges.agg(F.max("eid")).first()[0] or 0) + 1
    more = g.edges.join(again, "eid").select((F.col("eid") + F.lit(top)).alias("eid"), "u", "v")
    even = Graph(stage(g.edges.select("eid", "u", "v").unionByName(more), "even"), g.vertices, g.n_parts, g.part_of)
    return circuit(even), again.count()


def _neighbours(reach: DataFrame) -> DataFrame:
    """(from, at, way): centres whose balls meet, two by two in order of distance at each
    vertex, so there are half as many pairs as rows at most; of a pair its shortest way."""
    own = Window.partitionBy("at").orderBy(F.size("way"), "from")
    ranked = reach.withColumn("k", F.floor((F.row_number().over(own) - 1) / 2))
    met = ranked.groupBy("at", "k").agg(F.min("from").alias("x"), F.max("from").alias("y"), F.flatten(F.collect_list("way")).alias("way")).where("x < y")
    return met.groupBy("x", "y").agg(F.min(F.struct(F.size("way").alias("n"), "way")).alias("b")).select(F.col("x").alias("from"), F.col("y").alias("at"), "b.way")


def _disjoint(meets: DataFrame) -> DataFrame:
    """(x, y, way): pairs that share no vertex, the nearest first, from all candidates.

    In rounds on the cluster: a pair that is best for both of its ends is taken. Ties go by a
    digest of the pair, so that a round takes many; every round takes the best that is left.
    """
    rank = F.struct(F.size("way").alias("n"), F.xxhash64("x", "y").alias("h"), "x", "y")
    live = stage(meets.select(F.col("from").alias("x"), F.col("at").alias("y"), "way"), "meets")
    found = live.where("false")
    while not live.isEmpty():
        best = live.select(F.explode(F.array("x", "y")).alias("p"), rank.alias("r")).groupBy("p").agg(F.min("r").alias("r"))
        votes = best.groupBy("r").count().where("count = 2").select("r.x", "r.y")
        taken = stage(live.join(votes, ["x", "y"]), "pairs")
        found = found.unionByName(taken)
        gone = taken.select(F.explode(F.array("x", "y")).alias("p"))
        live = stage(live.join(gone, live["x"] == gone["p"], "left_anti").join(gone, live["y"] == gone["p"], "left_anti"), "meets")
    return found


def cover_summary(g: Graph, walk: DataFrame, extra: int) -> DataFrame:
    """closed, covers (every pair of the graph's edges is walked), extra edges."""
    pairs = g.edges.select("u", "v").exceptAll(walk.select(F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v"))).count()
    ends = walk.groupBy("comp").agg((F.min_by("src", "pos") == F.max_by("dst", "pos")).alias("c")).join(chain_breaks(walk), "comp")
    return ends.agg(F.bool_and(F.col("c") & (F.col("n") == 0)).alias("closed")).select("closed", F.lit(pairs == 0).alias("covers"), F.lit(extra).cast("int").alias("extra"))
