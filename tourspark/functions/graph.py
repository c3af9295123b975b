"""The graph: edges with ids of their own, optional parts, degrees, parity and its repair."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tourspark.functions.numbering import dense_number
from tourspark.session import stage


@dataclass(frozen=True)
class Graph:
    """``edges``: eid, u, v with u <= v, one row an undirected edge. ``part_of`` gives the part
    of a vertex as an expression where there is one; else ``vertices`` (v, part) holds it."""

    edges: DataFrame
    vertices: DataFrame | None = None
    n_parts: int | None = None
    part_of: Callable[[Column], Column] | None = None

    @staticmethod
    def from_edges(df: DataFrame, u: str = "u", v: str = "v", keep_parallel: bool = True, keep_loops: bool = True) -> Graph:
        """Edges from the pairs of ``df``; pairs with a null end are left out."""
        a, b = F.col(u).cast("long"), F.col(v).cast("long")
        pairs = df.where(a.isNotNull() & b.isNotNull()).select(F.least(a, b).alias("u"), F.greatest(a, b).alias("v"))
        if not keep_loops:
            pairs = pairs.where("u <> v")
        if not keep_parallel:
            pairs = pairs.dropDuplicates(["u", "v"])
        return Graph(dense_number(pairs, ["u", "v"], "eid", 0).select("eid", "u", "v"))

    def with_partition(self, how: str, n: int, **options) -> Graph:
        from tourspark.plans.partitioners import partition

        return partition(self, how, n, **options)

    def map_edges(self, edges: DataFrame) -> Graph:
        return replace(self, edges=edges)


def bidirect(edges: DataFrame) -> DataFrame:
    """Both directions of every edge, from one scan: eid, src, dst. A loop gives two rows."""
    both = F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst")))
    return edges.select("eid", F.explode(both).alias("d")).select("eid", "d.src", "d.dst")


def ends(edges: DataFrame, *keep: str) -> DataFrame:
    """One row an edge end: v and the kept columns."""
    return edges.select(F.explode(F.array("u", "v")).alias("v"), *keep)


def degrees(g: Graph) -> DataFrame:
    """(v, deg): edge ends at each vertex, so a loop counts 2."""
    return ends(g.edges).groupBy("v").agg(F.count("*").alias("deg"))


def odd_vertices(g: Graph) -> DataFrame:
    return degrees(g).where("deg % 2 = 1")


def is_even(g: Graph) -> DataFrame:
    """One row: is_even, n_odd."""
    return degrees(g).agg(F.coalesce(F.expr("bool_and(deg % 2 = 0)"), F.lit(True)).alias("is_even"), F.count_if(F.col("deg") % 2 == 1).alias("n_odd"))


def require_even(g: Graph) -> None:
    bad = [r["v"] for r in odd_vertices(g).orderBy("v").limit(10).collect()]
    if bad:
        raise ValueError(f"no closed circuit: vertices of odd degree, the first of them {bad}")


def repair_pairs(g: Graph, pairing: str = "by_id") -> DataFrame:
    """(u, v): the edges that make every degree even, by pairing odd vertices in order.

    ``by_id`` and ``by_degree`` pair neighbours in that order over the whole graph;
    ``within_component`` pairs inside components, each of which has an even number of them.
    """
    odd = odd_vertices(g)
    if pairing == "by_id":
        order = ["v"]
    elif pairing == "by_degree":
        order = ["deg", "v"]
    elif pairing == "within_component":
        from tourspark.plans.components import components

        odd, order = odd.join(components(g), "v"), ["comp", "v"]
    else:
        raise ValueError(f"unknown pairing {pairing}")
    ranked = dense_number(odd.select(*order), order, "rk", 0)
    # a component's odd vertices are even in number, so no pair spans two components
    return ranked.groupBy(F.expr("rk div 2").alias("pair")).agg(F.min("v").alias("u"), F.max("v").alias("v")).select("u", "v")


def repair_parity(g: Graph, pairing: str = "by_id") -> Graph:
    """The even graph, its edges with a column ``added``; new edges get ids above the old."""
    extra = repair_pairs(g, pairing)
    top = g.edges.agg(F.coalesce(F.max("eid"), F.lit(-1))).first()[0]
    new = dense_number(extra, ["u", "v"], "eid", top + 1)
    both = g.edges.select("eid", "u", "v", F.lit(False).alias("added")).unionByName(new.select("eid", "u", "v", F.lit(True).alias("added")))
    return Graph(stage(both, "repaired"))


def double_edges(g: Graph) -> Graph:
    """Every edge twice: even, whatever the graph was."""
    twice = g.edges.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(1)))).select((F.col("eid") * 2 + F.col("k")).alias("eid"), "u", "v")
    return g.map_edges(twice)


def split_edges(g: Graph) -> DataFrame:
    """eid, u, v, pu, pv, is_local. With a part expression nothing is joined."""
    if g.part_of is not None:
        out = g.edges.withColumns({"pu": g.part_of(F.col("u")), "pv": g.part_of(F.col("v"))})
    else:
        # never held whole in the driver, however few bytes a row its file has
        at = g.vertices.hint("merge")
        out = g.edges.join(at.select(F.col("v").alias("u"), F.col("part").alias("pu")), "u").join(at.select("v", F.col("part").alias("pv")), "v")
    return out.select("eid", "u", "v", F.col("pu").cast("int").alias("pu"), F.col("pv").cast("int").alias("pv"), (F.col("pu") == F.col("pv")).alias("is_local"))


def classify(g: Graph) -> DataFrame:
    """v, part, d_local, d_remote, kind: I (internal), OB (odd boundary) or EB (even)."""
    side = F.explode(F.array(F.struct(F.col("u").alias("v"), F.col("pu").alias("part")), F.struct(F.col("v").alias("v"), F.col("pv").alias("part"))))
    rows = split_edges(g).select(side.alias("e"), "is_local").select("e.v", "e.part", "is_local")
    counted = rows.groupBy("v", "part").agg(F.count_if("is_local").alias("d_local"), F.count_if(~F.col("is_local")).alias("d_remote"))
    kind = F.when(F.col("d_remote") == 0, "I").when(F.col("d_local") % 2 == 1, "OB").otherwise("EB")
    return counted.withColumn("kind", kind)


def validate_partitioning(g: Graph, vertices: DataFrame | None = None) -> DataFrame:
    """Violations (rule, id): no rows if every vertex has one part, every edge's ends have
    parts, and every part has an even number of odd boundary vertices."""
    at = vertices if vertices is not None else vertex_parts(g)
    used = ends(g.edges).distinct()
    missing = used.join(at, "v", "left_anti").select(F.lit("cover").alias("rule"), F.col("v").alias("id"))
    twice = at.groupBy("v").agg(F.countDistinct("part").alias("n")).where("n > 1").select(F.lit("disjoint").alias("rule"), F.col("v").alias("id"))
    shaken = classify(Graph(g.edges, at)).where("kind = 'OB'").groupBy("part").count().where("count % 2 = 1").select(F.lit("handshake").alias("rule"), F.col("part").cast("long").alias("id"))
    return missing.unionByName(twice).unionByName(shaken)


def vertex_parts(g: Graph) -> DataFrame:
    """(v, part) of every vertex that an edge touches."""
    if g.part_of is not None:
        return ends(g.edges).distinct().withColumn("part", g.part_of(F.col("v")).cast("int"))
    return g.vertices
