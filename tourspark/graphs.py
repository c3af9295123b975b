"""Graphs over the given tables, as pairs (u, v); ``Graph.from_edges`` makes them edges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tourspark.functions.graph import Graph, double_edges, repair_parity
from tourspark.session import read_table, stage

# Where the id ranges of the geographic tree begin.
SUPPLIER_BASE, NATION_BASE, REGION_BASE = 100_000_000, 1_000_000_000, 2_000_000_000


def _lines(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem")


def supply_multi(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part and supplier of every line; parallel edges stay."""
    return _lines(spark, sf_dir).select((F.col("l_partkey") * 2).alias("u"), (F.col("l_suppkey") * 2 + 1).alias("v"))


def supply_simple(spark, sf_dir):
    return supply_multi(spark, sf_dir).distinct()


def order_part(spark, sf_dir):
    return _lines(spark, sf_dir).select((F.col("l_orderkey") * 2).alias("u"), (F.col("l_partkey") * 2 + 1).alias("v"))


def _sold(spark, sf_dir, other):
    orders = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = _lines(spark, sf_dir).select("l_orderkey", other)
    joined = orders.join(lines, orders["o_orderkey"] == lines["l_orderkey"])
    return joined.select((F.col("o_custkey") * 2).alias("u"), (F.col(other) * 2 + 1).alias("v")).distinct()


def cust_supplier(spark, sf_dir):
    return _sold(spark, sf_dir, "l_suppkey")


def cust_part(spark, sf_dir):
    return _sold(spark, sf_dir, "l_partkey")


def copurchase(spark, sf_dir):
    """Parts that follow one another in an order."""
    own = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    rows = _lines(spark, sf_dir).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    return rows.select(F.col("l_partkey").alias("u"), F.lead("l_partkey").over(own).alias("v")).where("v is not null")


def _closed(rows: DataFrame, group: list[str], vertex: str, order: list[str]) -> DataFrame:
    """Each group's vertices in order, the last joined to the first: all degrees are even.

    Written once: what is dealt by ranges is read twice, and the window would run twice."""
    own = Window.partitionBy(*group).orderBy(*order)
    first = F.first(vertex).over(own.rowsBetween(Window.unboundedPreceding, 0))
    return stage(rows.select(F.col(vertex).alias("u"), F.coalesce(F.lead(vertex).over(own), first).alias("v")), "closed")


def supplier_loops(spark, sf_dir):
    rows = _lines(spark, sf_dir).select("l_suppkey", "l_partkey", "l_shipdate", "l_orderkey", "l_linenumber")
    return _closed(rows, ["l_suppkey"], "l_partkey", ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey"])


def _events(spark, sf_dir):
    return read_table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")


def _trail(rows: DataFrame, group: list[str]) -> DataFrame:
    """Users in order of time, closed, for each value of the group.

    Events are dealt out by ranges of group and time and numbered through; each is joined with
    the next number, and one row a group closes it. No task needs a group as a whole.
    """
    from tourspark.functions.numbering import dense_number

    rows = dense_number(rows.select(*group, "ts", "event_id", "user_id"), [*group, "ts", "event_id"], "n", 0)
    here = rows.select("n", F.col("user_id").alias("u"), F.struct(F.lit(0), *group).alias("g"))
    after = rows.select((F.col("n") - 1).alias("n"), F.col("user_id").alias("v"), F.struct(F.lit(0), *group).alias("h"))
    steps = here.join(after, "n").where(F.col("g").eqNullSafe(F.col("h"))).select("u", "v")
    ends = rows.groupBy(*group).agg(F.max_by("user_id", "n").alias("u"), F.min_by("user_id", "n").alias("v"), F.count("*").alias("k"))
    return steps.unionByName(ends.where("k > 0").select("u", "v"))


def event_trail(spark, sf_dir):
    """Users in order of time, closed."""
    return _trail(_events(spark, sf_dir), [])


def event_trail_by_type(spark, sf_dir):
    return _trail(_events(spark, sf_dir), ["event_type"])


def event_trail_by_day(spark, sf_dir):
    return _trail(_events(spark, sf_dir).withColumn("day", F.to_date("ts")), ["day"])


def event_user_hour(spark, sf_dir):
    """Users and the hours (since 1970) in which they act."""
    hour = F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 3600)
    return _events(spark, sf_dir).select((F.col("user_id") * 2).alias("u"), (hour * 2 + 1).cast("long").alias("v")).distinct()


def geo_tree(spark, sf_dir):
    """Nation to region, customer and supplier to nation: a tree for each region."""
    read = lambda t: read_table(spark, sf_dir, t)
    nation = F.col("n_nationkey") + F.lit(NATION_BASE)
    rows = [
        read("nation").select(nation.cast("long").alias("u"), (F.col("n_regionkey") + F.lit(REGION_BASE)).cast("long").alias("v")),
        read("customer").select(F.col("c_custkey").cast("long").alias("u"), (F.col("c_nationkey") + F.lit(NATION_BASE)).cast("long").alias("v")),
        read("supplier").select((F.col("s_suppkey") + F.lit(SUPPLIER_BASE)).cast("long").alias("u"), (F.col("s_nationkey") + F.lit(NATION_BASE)).cast("long").alias("v")),
    ]
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


def geo_regions(spark, sf_dir) -> DataFrame:
    """(v, part): every vertex of ``geo_tree`` with its region."""
    read = lambda t: read_table(spark, sf_dir, t)
    nation = read("nation").select("n_nationkey", F.col("n_regionkey").alias("part"))
    of = lambda t, key, at, base: read(t).join(nation, F.col(at) == F.col("n_nationkey")).select((F.col(key) + F.lit(base)).cast("long").alias("v"), "part")
    return (
        read("region").select((F.col("r_regionkey") + F.lit(REGION_BASE)).cast("long").alias("v"), F.col("r_regionkey").alias("part"))
        .unionByName(nation.select((F.col("n_nationkey") + F.lit(NATION_BASE)).cast("long").alias("v"), "part"))
        .unionByName(of("customer", "c_custkey", "c_nationkey", 0)).unionByName(of("supplier", "s_suppkey", "s_nationkey", SUPPLIER_BASE))
    )


def token_id(token) -> F.Column:
    """A vertex id for a token: 52 bits of its digest."""
    return F.conv(F.substring(F.md5(token), 1, 13), 16, 10).cast("long")


def kmer_edges(texts: DataFrame, text: str = "text", k: int = 1) -> DataFrame:
    """Neighbouring k-grams of the words of each text. Words are lower-cased runs of ASCII
    letters; the two ends of an edge overlap in k - 1 words."""
    words = F.filter(F.split(F.lower(text), "[^a-z]+"), lambda w: w != "")
    rows = texts.select(words.alias("w")).where(F.size("w") >= k + 1)
    if k > 1:
        rows = rows.select(F.transform(F.sequence(F.lit(1), F.size("w") - k + 1), lambda i: F.array_join(F.slice("w", i, k), " ")).alias("w"))
    steps = F.transform(F.sequence(F.lit(1), F.size("w") - 1), lambda i: F.struct(F.element_at("w", i).alias("a"), F.element_at("w", i + 1).alias("b")))
    return rows.select(F.explode(steps).alias("s")).select(token_id(F.col("s.a")).alias("u"), token_id(F.col("s.b")).alias("v"))


def word_trail(spark, sf_dir, lang: str = "en", k: int = 1):
    docs = read_table(spark, sf_dir, "documents").where(F.col("lang") == lang)
    return kmer_edges(docs.select("text"), "text", k)


def page_links(spark, sf_dir):
    """Page and link target, as digests; targets are the strings in the page's links."""
    pages = read_table(spark, sf_dir, "pages")
    targets = F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")
    rows = pages.select(F.parse_url("url", F.lit("HOST")).alias("host"), F.explode(targets).alias("to"))
    return rows.where("host is not null").select(token_id(F.col("host")).alias("u"), token_id(F.col("to")).alias("v"))


def dialog_roles(spark, sf_dir):
    """Roles of consecutive turns of a conversation."""
    own = Window.partitionBy("conv_id").orderBy("turn")
    rows = read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    rows = rows.select("role", F.lead("role").over(own).alias("to")).where("`to` is not null")
    return rows.select(token_id(F.col("role")).alias("u"), token_id(F.col("to")).alias("v"))


def knn_graph(spark, sf_dir, k: int = 3, block: int = 8192):
    """Each vector's k nearest by cosine, ties to the smaller id; digits beyond the ninth of
    the cosine don't count.

    Every block of vectors meets every other in a tile of its own, and a tile keeps k rows a
    vector before anything is shuffled. What is moved is the rows times the blocks, twice.
    """
    import numpy as np
    import pandas as pd

    rows = read_table(spark, sf_dir, "embeddings").where("vec_id is not null and embedding is not null").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    n_blocks = max(1, -(-rows.count() // block))
    own = F.pmod(F.col("vec_id"), F.lit(n_blocks)).cast("int")
    left = rows.withColumn("a", own).withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(n_blocks - 1))))
    right = rows.withColumn("b", own).withColumn("a", F.explode(F.sequence(F.lit(0), F.lit(n_blocks - 1))))

    def tile(p: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        if not len(p) or not len(q):
            return pd.DataFrame({"u": [], "v": [], "c": []})
        x, y = np.stack(p["e"].to_numpy()), np.stack(q["e"].to_numpy())
        i, order = p["vec_id"].to_numpy(), np.argsort(q["vec_id"].to_numpy(), kind="stable")
        j, y = q["vec_id"].to_numpy()[order], y[order]
        out = []
        for at in range(0, len(i), 256):  # a slab of rows at a time
            z = x[at : at + 256]
            c = np.round((z @ y.T) / np.sqrt((z**2).sum(1))[:, None] / np.sqrt((y**2).sum(1))[None, :], 9)
            c[i[at : at + 256, None] == j[None, :]] = -np.inf
            # columns go by id, so a stable sort leaves ties to the smaller one
            near = np.argsort(-c, axis=1, kind="stable")[:, :k]
            out.append(pd.DataFrame({"u": np.repeat(i[at : at + 256], near.shape[1]), "v": j[near].ravel(), "c": np.take_along_axis(c, near, 1).ravel()}))
        made = pd.concat(out)
        return made[np.isfinite(made["c"])]

    tiles = left.groupBy("a", "b").cogroup(right.groupBy("a", "b")).applyInPandas(tile, "u long, v long, c double")
    best = Window.partitionBy("u").orderBy(F.desc("c"), "v")
    return tiles.withColumn("r", F.row_number().over(best)).where(F.col("r") <= k).select("u", "v")


# The sample graph of fourteen vertices and its parts.
WORKED_EDGES = ((1, 2), (2, 3), (3, 4), (4, 5), (3, 5), (3, 13), (12, 13), (11, 12), (6, 11), (6, 7), (7, 8), (8, 9), (9, 10), (10, 12), (12, 14), (1, 14))
WORKED_PARTS = {1: 1, 2: 1, 3: 2, 4: 2, 5: 2, 6: 3, 7: 3, 8: 3, 9: 3, 10: 4, 11: 4, 12: 4, 13: 4, 14: 4}


def worked_example(spark: SparkSession) -> Graph:
    edges = Graph.from_edges(spark.createDataFrame(list(WORKED_EDGES), "u long, v long")).edges
    return Graph(edges, spark.createDataFrame(list(WORKED_PARTS.items()), "v long, part int"), 4)


def torus(spark: SparkSession, rows: int = 64, cols: int = 64) -> DataFrame:
    """A grid closed both ways; every vertex has degree 4."""
    cell = spark.range(rows * cols).select("id", F.expr(f"id div {cols}").alias("r"), (F.col("id") % cols).alias("c"))
    right = F.col("r") * cols + (F.col("c") + 1) % cols
    down = (F.col("r") + 1) % rows * cols + F.col("c")
    return cell.select(F.col("id").alias("u"), F.explode(F.array(right, down)).alias("v"))


def rmat(spark: SparkSession, scale: int = 10, per_vertex: int = 5, a: float = 0.57, b: float = 0.19, c: float = 0.19, seed: int = 1) -> DataFrame:
    """A power-law graph of 2**scale vertices: each bit of an edge's ends falls into one of
    four quadrants, by a digest of the edge's number, so any engine gives the same rows."""
    cuts = [round(x * 65536) for x in (a, a + b, a + b + c)]
    edge = spark.range((1 << scale) * per_vertex)
    u, v = F.lit(0).cast("long"), F.lit(0).cast("long")
    for bit in range(scale):
        draw = F.conv(F.substring(F.md5(F.concat_ws("-", F.lit(seed), F.lit(bit), F.col("id"))), 1, 4), 16, 10).cast("int")
        u = u * 2 + F.when(draw >= cuts[1], 1).otherwise(0)
        v = v * 2 + F.when((draw >= cuts[0]) & (draw < cuts[1]) | (draw >= cuts[2]), 1).otherwise(0)
    return edge.select(u.alias("u"), v.alias("v"))


def power_law(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The power-law graph whose vertices are about half as many as the orders or more."""
    orders = read_table(spark, sf_dir, "orders").count()
    return rmat(spark, max(8, max(1, orders).bit_length() - 1))


def complete_odd(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pairs of the weekdays (Sunday is 0) on which orders were made. All seven, or any
    odd number of them, have even degrees; a product of more than 21 pairs can't arise."""
    days = read_table(spark, sf_dir, "orders").select((F.dayofweek("o_orderdate") - 1).cast("long").alias("u")).where("u is not null").distinct()
    return days.crossJoin(F.broadcast(days.withColumnRenamed("u", "v"))).where("u < v")


def grid_doubled(spark: SparkSession, sf_dir: str) -> Graph:
    """The open grid of days and hours that events fall into: a cell is 24 times its day
    (since 1970) plus its hour, and joins the next hour of its day and the same hour of the
    next day where these have events. Every edge twice."""
    cells = _events(spark, sf_dir).select(F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 3600).cast("long").alias("u")).where("u is not null").distinct()
    right = F.when(F.col("u") % 24 < 23, F.col("u") + 1)
    steps = cells.select("u", F.explode(F.array(right, F.col("u") + 24)).alias("v"))
    return double_edges(Graph.from_edges(steps.join(cells.withColumnRenamed("u", "v"), "v").select("u", "v")))


BUILDERS = {f.__name__: f for f in (supply_multi, supply_simple, order_part, cust_supplier, cust_part, copurchase, supplier_loops, event_trail, event_trail_by_type, event_trail_by_day, event_user_hour, geo_tree, word_trail, page_links, dialog_roles, knn_graph)}


def even_graph(spark: SparkSession, sf_dir: str, name: str, n: int = 8) -> Graph:
    """The even graphs of the experiments, with their usual parts."""
    if name == "worked":
        return worked_example(spark)
    if name == "complete_odd":
        return Graph.from_edges(complete_odd(spark, sf_dir)).with_partition("modulo", 4)
    if name == "torus":
        return Graph.from_edges(torus(spark)).with_partition("range", n)
    if name == "geo_doubled":
        g = double_edges(Graph.from_edges(geo_tree(spark, sf_dir)))
        return g.with_partition("column", 5, mapping=geo_regions(spark, sf_dir))
    if name in ("order_part_repaired", "supply_repaired"):
        pairs = order_part if name[0] == "o" else supply_multi
        return repair_parity(Graph.from_edges(pairs(spark, sf_dir))).with_partition("modulo", n, step=2)
    if name == "rmat_repaired":
        return repair_parity(Graph.from_edges(rmat(spark))).with_partition("hash", n)
    return Graph.from_edges(BUILDERS[name](spark, sf_dir)).with_partition("modulo", n)
