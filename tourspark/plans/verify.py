"""Checks of a circuit against its graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tourspark.functions.graph import Graph, degrees

#: Positions in one piece of the chain check.
PIECE_SHIFT = 16


def chain_breaks(circuit: DataFrame) -> DataFrame:
    """(comp, n): places where an edge doesn't start where the one before ended.

    Pieces of positions are checked each on its own, with one row of the piece before, so
    the circuit is never sorted as a whole.
    """
    piece = F.shiftright("pos", PIECE_SHIFT)
    last = (F.col("pos") + 1) % (1 << PIECE_SHIFT) == 0
    rows = circuit.select("comp", "pos", "src", "dst", F.explode(F.when(last, F.array(piece, piece + 1)).otherwise(F.array(piece))).alias("piece"))
    own = Window.partitionBy("comp", "piece").orderBy("pos")
    seen = rows.withColumns({"before": F.lag("dst").over(own), "at": F.lag("pos").over(own)})
    bad = F.col("before").isNotNull() & ((F.col("before") != F.col("src")) | (F.col("at") + 1 != F.col("pos")))
    return seen.groupBy("comp").agg(F.count_if(bad).alias("n"))


def audit(g: Graph, circuit: DataFrame) -> DataFrame:
    """comp, n_edges, distinct_eids, chained, closed, complete: all true if and only if the
    rows of every component are one closed walk and all edges of the graph occur once."""
    sums = circuit.groupBy("comp").agg(
        F.count("*").alias("n_edges"), F.countDistinct("eid").alias("distinct_eids"), F.min("pos").alias("low"), F.max("pos").alias("high"),
        F.min_by("src", "pos").alias("first"), F.max_by("dst", "pos").alias("last"),
    )
    total = g.edges.agg(F.count("*").alias("m"), F.coalesce(F.sum(F.xxhash64("eid", F.least("u", "v"), F.greatest("u", "v")).cast("decimal(38,0)")), F.lit(0)).alias("x"))
    seen = circuit.agg(F.count("*").alias("m2"), F.coalesce(F.sum(F.xxhash64("eid", F.least("src", "dst"), F.greatest("src", "dst")).cast("decimal(38,0)")), F.lit(0)).alias("x2"))
    whole = total.join(seen).select(((F.col("m") == F.col("m2")) & (F.col("x") == F.col("x2"))).alias("complete"))  # one row by one row
    return sums.join(chain_breaks(circuit), "comp").join(F.broadcast(whole)).select(
        "comp", "n_edges", "distinct_eids",
        ((F.col("n") == 0) & (F.col("low") == 0) & (F.col("high") == F.col("n_edges") - 1)).alias("chained"),
        (F.col("first") == F.col("last")).alias("closed"), "complete",
    )


def vertex_visits(circuit: DataFrame) -> DataFrame:
    """(v, visits): half of the vertex's degree in any closed circuit."""
    return circuit.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("visits"))


def edge_cover(circuit: DataFrame) -> DataFrame:
    """(u, v, n): how often the circuit runs along each pair of vertices."""
    return circuit.groupBy(F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v")).agg(F.count("*").alias("n"))


def uncovered(g: Graph, circuit: DataFrame) -> DataFrame:
    """Edges that the circuit lacks or has too often: no rows for a right one."""
    own, seen = g.edges.select("eid", "u", "v"), circuit.select("eid", F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v"))
    return own.exceptAll(seen).unionByName(seen.exceptAll(own))


def parity_holds(g: Graph, visits: DataFrame) -> DataFrame:
    """Vertices whose visits aren't half of their degree: no rows for a right circuit."""
    return degrees(g).join(visits, "v", "full").where("visits IS NULL OR deg IS NULL OR visits * 2 <> deg")
