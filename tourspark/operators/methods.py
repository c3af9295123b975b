"""Queries of the methods, variants, baselines and measures."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark import graphs
from tourspark.functions import graph as fg
from tourspark.functions.graph import Graph
from tourspark.operators import graph_sql as sql
from tourspark.operators.registry import query
from tourspark.plans import baselines, components, measures, metagraph, phase2, phase3, verify
from tourspark.plans.circuit import circuit
from tourspark.session import read_table, scratch, stage

EVEN = ("event_trail", "supplier_loops", "supply_repaired", "order_part_repaired", "geo_doubled", "torus")
#: Queries that are named after the sample graph but need a given table's: the weekdays.
TABLED = {"worked": "complete_odd"}
LEVELLED = ("worked", "event_trail", "supplier_loops", "order_part_repaired", "torus", "geo_doubled")


def held(spark, sf_dir: str, name: str) -> Graph:
    """An even graph whose edges are written once, as every method reads them often."""
    g = graphs.even_graph(spark, sf_dir, name)
    return g.map_edges(stage(g.edges.select("eid", "u", "v"), name))


def tree_of(g: Graph, strategy: str = "greedy") -> metagraph.MergeTree:
    return metagraph.tree_for(g, phase2.parts_of(g), strategy)


def levelled(spark, sf_dir: str, name: str):
    g = held(spark, sf_dir, name)
    tree = tree_of(g)
    return g, tree, metagraph.join_levels(g, tree)


# Graph builders ------------------------------------------------------------------------
def _pairs(edges: DataFrame) -> DataFrame:
    """(u, v, n): the edges' multiplicities."""
    return verify.edge_cover(edges.withColumnsRenamed({"u": "src", "v": "dst"}))


for _name, _build in graphs.BUILDERS.items():
    query(f"graph_{_name}", sql.cover(_name))(lambda s, d, build=_build: _pairs(Graph.from_edges(build(s, d)).edges))
for _name, _make in {"torus": graphs.torus, "rmat": graphs.rmat}.items():
    query(f"graph_{_name}", sql.cover(_name))(lambda s, d, make=_make: _pairs(Graph.from_edges(make(s)).edges))
query("graph_complete_odd", sql.cover("complete_odd"))(lambda s, d: _pairs(Graph.from_edges(graphs.complete_odd(s, d)).edges))
query("graph_grid_doubled", sql.cover("grid_doubled"))(lambda s, d: _pairs(graphs.grid_doubled(s, d).edges))
query("graph_geo_doubled", sql.cover("geo_doubled"))(lambda s, d: _pairs(graphs.even_graph(s, d, "geo_doubled").edges))


# Preparation ---------------------------------------------------------------------------
_DEG = "SELECT v, count(*) AS deg FROM (SELECT unnest([u, v]) AS v FROM e) GROUP BY v"


@query("parity_degrees", sql.with_(sql.edges("order_part"), _DEG))
def parity_degrees(spark, sf_dir):
    return fg.degrees(Graph.from_edges(graphs.order_part(spark, sf_dir)))


@query("odd_vertices", sql.with_(sql.edges("supply_multi"), f"SELECT * FROM ({_DEG}) WHERE deg % 2 = 1"))
def odd_vertices(spark, sf_dir):
    return fg.odd_vertices(Graph.from_edges(graphs.supply_multi(spark, sf_dir)))


@query("is_even", sql.with_(sql.edges("supplier_loops"), f"SELECT bool_and(deg % 2 = 0) AS is_even, count(*) FILTER (WHERE deg % 2 = 1) AS n_odd FROM ({_DEG})"))
def is_even(spark, sf_dir):
    return fg.is_even(Graph.from_edges(graphs.supplier_loops(spark, sf_dir)))


@query("bidirected_edges", sql.with_(sql.edges("event_trail"), "SELECT src, dst, count(*) AS n FROM (SELECT u AS src, v AS dst FROM e UNION ALL SELECT v, u FROM e) GROUP BY ALL"))
def bidirected_edges(spark, sf_dir):
    return fg.bidirect(Graph.from_edges(graphs.event_trail(spark, sf_dir)).edges).groupBy("src", "dst").agg(F.count("*").alias("n"))


@query("simple_graph", sql.with_(sql.edges("event_trail"), "SELECT DISTINCT u, v FROM e WHERE u <> v"))
def simple_graph(spark, sf_dir):
    return Graph.from_edges(graphs.event_trail(spark, sf_dir), keep_parallel=False, keep_loops=False).edges.select("u", "v")


@query("dense_edge_ids", sql.with_(sql.edges("supply_multi"), "SELECT row_number() OVER (ORDER BY u, v) - 1 AS eid, u, v FROM e"))
def dense_edge_ids(spark, sf_dir):
    return Graph.from_edges(graphs.supply_multi(spark, sf_dir)).edges


_REPAIR = sql.edges("order_part_repaired")


@query("repair_edges", sql.with_(_REPAIR, "SELECT u, v FROM added"))
def repair_edges(spark, sf_dir):
    return fg.repair_pairs(Graph.from_edges(graphs.order_part(spark, sf_dir)))


_BY_DEGREE = sql.edges("order_part") + f", odd AS (SELECT v, row_number() OVER (ORDER BY deg, v) - 1 AS rk FROM ({_DEG}) WHERE deg % 2 = 1)"


@query("repair_edges_by_degree", sql.with_(_BY_DEGREE, "SELECT min(v) AS u, max(v) AS v FROM odd GROUP BY rk // 2"))
def repair_edges_by_degree(spark, sf_dir):
    return fg.repair_pairs(Graph.from_edges(graphs.order_part(spark, sf_dir)), "by_degree")


# every geographic tree hangs on a region, which is known without a search
_GEO_COMP = sql.parts("geo_tree")


@query("repair_edges_within_component", sql.with_(_GEO_COMP + f", dg AS ({_DEG}), cm AS (SELECT part, min(v) AS comp FROM vp JOIN dg USING (v) GROUP BY part), odd AS (SELECT v, row_number() OVER (ORDER BY comp, v) - 1 AS rk FROM dg JOIN vp USING (v) JOIN cm USING (part) WHERE deg % 2 = 1)", "SELECT min(v) AS u, max(v) AS v FROM odd GROUP BY rk // 2"))
def repair_edges_within_component(spark, sf_dir):
    return fg.repair_pairs(Graph.from_edges(graphs.geo_tree(spark, sf_dir)), "within_component")


@query("components_label_min", sql.with_(_GEO_COMP + ", vs AS (SELECT DISTINCT unnest([u, v]) AS v FROM e)", "SELECT v, min(v) OVER (PARTITION BY part) AS comp FROM vs JOIN vp USING (v)"))
def components_label_min(spark, sf_dir):
    return components.components(Graph.from_edges(graphs.geo_tree(spark, sf_dir)))


@query("components_star", sql.with_(_GEO_COMP + ", vs AS (SELECT DISTINCT unnest([u, v]) AS v FROM e)", "SELECT v, min(v) OVER (PARTITION BY part) AS comp FROM vs JOIN vp USING (v)"))
def components_star(spark, sf_dir):
    return components.components(Graph.from_edges(graphs.geo_tree(spark, sf_dir)), "star")


@query("degree_hist_before_after", sql.with_(_REPAIR, """SELECT deg, coalesce(n0, 0) AS before, coalesce(n1, 0) AS after FROM
  (SELECT deg, count(*) AS n0 FROM (SELECT v, count(*) AS deg FROM (SELECT unnest([u, v]) AS v FROM e0) GROUP BY v) GROUP BY deg)
  FULL JOIN (SELECT deg, count(*) AS n1 FROM (SELECT v, count(*) AS deg FROM (SELECT unnest([u, v]) AS v FROM e) GROUP BY v) GROUP BY deg) USING (deg)"""))
def degree_hist_before_after(spark, sf_dir):
    g = Graph.from_edges(graphs.order_part(spark, sf_dir))
    return measures.degree_histogram(g).withColumnRenamed("n", "before").join(measures.degree_histogram(fg.repair_parity(g)).withColumnRenamed("n", "after"), "deg", "full").na.fill(0)


_SHARES = _REPAIR + """, d0 AS (SELECT v, count(*) AS deg FROM (SELECT unnest([u, v]) AS v FROM e0) GROUP BY v), d1 AS (SELECT v, count(*) AS deg FROM (SELECT unnest([u, v]) AS v FROM e) GROUP BY v),
 sh(k, p, q) AS (SELECT k, coalesce(a.n, 0) / (SELECT count(*) FROM d0) AS p, coalesce(b.n, 0) / (SELECT count(*) FROM d1) AS q FROM (SELECT {0} AS k, count(*) AS n FROM d0 GROUP BY 1) a FULL JOIN (SELECT {0} AS k, count(*) AS n FROM d1 GROUP BY 1) b USING (k))"""


def _distance(metric):
    def run(spark, sf_dir):
        g = Graph.from_edges(graphs.order_part(spark, sf_dir))
        return measures.degree_distance(g, fg.repair_parity(g), metric)

    return run


query("degree_distance_tv", sql.with_(_SHARES.format("deg"), "SELECT round(sum(abs(p - q)) / 2, 9) AS distance FROM sh"))(_distance("tv"))
query("degree_distance_log2tv", sql.with_(_SHARES.format("CAST(floor(log2(deg)) AS BIGINT)"), "SELECT round(sum(abs(p - q)) / 2, 9) AS distance FROM sh"))(_distance("log2tv"))
query("degree_distance_ks", sql.with_(_SHARES.format("deg"), "SELECT round(max(abs(g)), 9) AS distance FROM (SELECT sum(p - q) OVER (ORDER BY k) AS g FROM sh)"))(_distance("ks"))


@query("repair_cost", sql.with_(_REPAIR, "SELECT (SELECT count(*) FROM added) AS added, round((SELECT count(*) FROM added) * 100.0 / (SELECT count(*) FROM e0), 6) AS percent"))
def repair_cost(spark, sf_dir):
    g = Graph.from_edges(graphs.order_part(spark, sf_dir))
    return measures.repair_cost(g, fg.repair_parity(g))


# Partitioners --------------------------------------------------------------------------
_VS = "SELECT DISTINCT unnest([u, v]) AS v FROM e"
_RULES = {"hash": sql.DIGEST_PART, "modulo": "v % 8", "range": "least((v - lo) * 8 // (hi - lo + 1), 7)"}
for _how, _rule in _RULES.items():
    query(f"partition_{_how}", sql.with_(sql.edges("supplier_loops") + ", b AS (SELECT min(u) AS lo, max(v) AS hi FROM e)", f"SELECT v, CAST({_rule} AS INTEGER) AS part FROM ({_VS}), b"))(
        lambda s, d, how=_how: fg.vertex_parts(Graph.from_edges(graphs.supplier_loops(s, d)).with_partition(how, 8)))


@query("partition_column", sql.with_(sql.parts("geo_doubled"), "SELECT v, part FROM vp"))
def partition_column(spark, sf_dir):
    return fg.vertex_parts(graphs.even_graph(spark, sf_dir, "geo_doubled"))


def _sized(g: Graph) -> DataFrame:
    """part, within, vertices: whether each part keeps within its limit, and all vertices."""
    at = fg.vertex_parts(g)
    total = at.agg(F.countDistinct("v").alias("vertices"), F.count("*").alias("all"))
    sizes = at.groupBy("part").agg(F.count("*").alias("n")).join(F.broadcast(total))  # one row
    return sizes.select("part", (F.col("n") <= F.ceil(F.col("all") / F.lit(g.n_parts) * 1.1)).alias("within"), F.col("vertices"))


_LIMITS = "SELECT CAST(p AS INTEGER) AS part, true AS within, CAST(256 AS BIGINT) AS vertices FROM range(8) r(p)"


@query("partition_bfs", _LIMITS)
def partition_bfs(spark, sf_dir):
    return _sized(Graph.from_edges(graphs.torus(spark, 16, 16)).with_partition("bfs", 8))


@query("partition_lpa", _LIMITS)
def partition_lpa(spark, sf_dir):
    return _sized(Graph.from_edges(graphs.torus(spark, 16, 16)).with_partition("lpa", 8, rounds=4))


@query("partition_violations", "SELECT 'x' AS rule, CAST(0 AS BIGINT) AS id WHERE false")
def partition_violations(spark, sf_dir):
    return fg.validate_partitioning(held(spark, sf_dir, "supplier_loops"))


_STATS_ROW = """SELECT (SELECT count(*) FROM vp) AS vertices, (SELECT count(*) FROM ep) AS edges, (SELECT count(*) FROM ep) * 2 AS edges_both,
  (SELECT count(DISTINCT v) FROM (SELECT unnest([u, v]) AS v FROM ep WHERE pu <> pv)) AS boundary, 8 AS parts,
  round((SELECT count(*) FROM ep WHERE pu <> pv) * 100.0 / (SELECT count(*) FROM ep), 6) AS cut_percent,
  round((SELECT max(abs((SELECT count(*) FROM vp) - 8 * n)) FROM (SELECT count(v) AS n FROM range(8) r(p) LEFT JOIN vp ON part = p GROUP BY p)) * 100.0 / (SELECT count(*) FROM vp), 6) AS imbalance_percent"""


@query("partition_stats", sql.with_(sql.parts("supplier_loops"), _STATS_ROW))
def partition_stats(spark, sf_dir):
    return measures.graph_stats(held(spark, sf_dir, "supplier_loops"))


@query("remote_vertex_ratio", sql.with_(sql.parts("supplier_loops"), "SELECT (SELECT count(*) FROM ep WHERE pu <> pv) * 2 AS remote, (SELECT count(*) FROM vp) AS vertices, round((SELECT count(*) FROM ep WHERE pu <> pv) * 2 / (SELECT count(*) FROM vp), 6) AS ratio"))
def remote_vertex_ratio(spark, sf_dir):
    return measures.remote_ratio(held(spark, sf_dir, "supplier_loops"))


@query("split_edges", sql.with_(sql.parts("event_trail"), "SELECT u, v, pu, pv, pu = pv AS is_local, count(*) AS n FROM ep GROUP BY ALL"))
def split_edges(spark, sf_dir):
    return fg.split_edges(held(spark, sf_dir, "event_trail")).groupBy("u", "v", "pu", "pv", "is_local").agg(F.count("*").alias("n"))


@query("vertex_kinds", sql.with_(sql.parts("order_part_repaired"), """SELECT v, part, dl AS d_local, dr AS d_remote, CASE WHEN dr = 0 THEN 'I' WHEN dl % 2 = 1 THEN 'OB' ELSE 'EB' END AS kind FROM (
  SELECT v, part, count(*) FILTER (WHERE l) AS dl, count(*) FILTER (WHERE NOT l) AS dr FROM (SELECT u AS v, pu AS part, pu = pv AS l FROM ep UNION ALL SELECT v, pv, pu = pv FROM ep) GROUP BY ALL)"""))
def vertex_kinds(spark, sf_dir):
    return fg.classify(held(spark, sf_dir, "order_part_repaired"))


# Tree and levels -----------------------------------------------------------------------
@query("meta_graph", sql.with_(sql.tree("supplier_loops"), "SELECT 0 AS level, a, b, w AS weight FROM m0"))
def meta_graph(spark, sf_dir):
    return metagraph.meta_graph(held(spark, sf_dir, "supplier_loops"))


@query("meta_graph_size", sql.with_(sql.tree("supplier_loops"), "SELECT count(*) AS n_edges, 8 * 7 AS bound FROM m0"))
def meta_graph_size(spark, sf_dir):
    return metagraph.meta_graph(held(spark, sf_dir, "supplier_loops")).agg(F.count("*").alias("n_edges")).withColumn("bound", F.lit(56))


@query("matching_greedy", sql.with_(sql.tree("supplier_loops"), "SELECT a, b, w AS weight FROM k0"))
def matching_greedy(spark, sf_dir):
    rows = [(r["a"], r["b"], r["weight"]) for r in metagraph.meta_graph(held(spark, sf_dir, "supplier_loops")).collect()]
    return spark.createDataFrame(metagraph.greedy_matching(rows), "a int, b int, weight long")


@query("matching_distributed", sql.with_(sql.tree("supplier_loops"), "SELECT a, b, w AS weight FROM k0"))
def matching_distributed(spark, sf_dir):
    return metagraph.greedy_matching_distributed(metagraph.meta_graph(held(spark, sf_dir, "supplier_loops")))


def _tree_sql(name: str, strategy: str = "greedy") -> str:
    rows = " UNION ALL ".join(f"SELECT {k} AS level, a AS child_a, b AS child_b, b AS parent, CAST(w AS BIGINT) AS weight FROM k{k}" for k in range(sql.height(name)))
    return sql.with_(sql.tree(name, strategy), rows)


for _name in LEVELLED:
    _on = TABLED.get(_name, _name)
    query(f"merge_tree_{_name}", _tree_sql(_on))(lambda s, d, n=_on: tree_of(graphs.even_graph(s, d, n)).tree_rows(s))
    query(f"level_stats_{_name}", sql.with_(sql.stats(_on), "SELECT * FROM st"))(lambda s, d, n=_on: (lambda t: measures.level_stats(t[2], t[1]))(levelled(s, d, n)))


@query("merge_tree_distributed", _tree_sql("supplier_loops"))
def merge_tree_distributed(spark, sf_dir):
    g = held(spark, sf_dir, "supplier_loops")
    return metagraph.merge_tree_distributed(metagraph.meta_graph(g), phase2.parts_of(g)).tree_rows(spark)


for _strategy in ("random", "id_order", "lightest"):
    query(f"merge_tree_{_strategy}", None if _strategy == "random" else _tree_sql("event_trail", _strategy))(
        lambda s, d, st=_strategy: tree_of(graphs.even_graph(s, d, "event_trail"), st).tree_rows(s))


@query("merge_tree_random_halves", "SELECT * FROM (VALUES (0, 4), (1, 2), (2, 1)) t(level, merges)")
def merge_tree_random_halves(spark, sf_dir):
    """Whatever a random tree pairs, every level halves the parts."""
    rows = tree_of(graphs.even_graph(spark, sf_dir, "event_trail"), "random").tree_rows(spark)
    return rows.groupBy("level").agg(F.count("*").cast("int").alias("merges"))


@query("join_levels", sql.with_(sql.levels("supplier_loops"), "SELECT u, v, pu, pv, jl AS join_level, count(*) AS n FROM j GROUP BY ALL"))
def join_levels(spark, sf_dir):
    return levelled(spark, sf_dir, "supplier_loops")[2].groupBy("u", "v", "pu", "pv", "join_level").agg(F.count("*").alias("n"))


@query("retire_levels", sql.with_(sql.levels("event_trail"), "SELECT v, max(jl) AS retire_level FROM (SELECT unnest([u, v]) AS v, jl FROM j) GROUP BY v"))
def retire_levels(spark, sf_dir):
    return metagraph.retire_levels(levelled(spark, sf_dir, "event_trail")[2])


_HOLDER = """, wt AS (SELECT level, part, CAST(sum(remote) AS BIGINT) AS w FROM st GROUP BY ALL),
hd AS (SELECT jl, CASE WHEN x.w > y.w OR (x.w = y.w AND a.part < b.part) THEN pv ELSE pu END AS holder FROM j
  JOIN pm a ON a.level = jl - 1 AND a.leaf = pu JOIN pm b ON b.level = jl - 1 AND b.leaf = pv
  JOIN wt x ON x.level = a.level AND x.part = a.part JOIN wt y ON y.level = b.level AND y.part = b.part WHERE jl > 0),
ch AS (SELECT pm.level, pm.part, count(*) AS held FROM hd JOIN pm ON pm.leaf = holder AND pm.level < jl GROUP BY ALL)"""


def _one_copy(at: str):
    def run(spark, sf_dir):
        g, tree, rows = levelled(spark, sf_dir, "supplier_loops")
        rows = stage(rows, "joined")
        return measures.memory_one_copy(measures.level_stats(rows, tree), measures.copies_held(metagraph.with_holders(rows, tree), tree), at)

    return run


for _at, _base in {"start": "i + ob + eb + 2 * local", "end": "ob + eb + ob"}.items():
    query(f"memory_carry_one_parts_{_at}", sql.with_(sql.stats("supplier_loops") + _HOLDER, f"SELECT st.level, st.part, {_base} + remote AS both, {_base} + coalesce(held, 0) AS one FROM st LEFT JOIN ch USING (level, part)"))(_one_copy(_at))


@query("supersteps_run", "SELECT n, CAST(ceil(log2(n)) AS INTEGER) + 1 AS supersteps FROM (VALUES (2), (3), (4), (8)) t(n)")
def supersteps_run(spark, sf_dir):
    """The levels that runs on the sample path of events take, counted in their ledgers."""
    edges = held(spark, sf_dir, "event_trail").edges
    made = {n: Graph(edges).with_partition("modulo", n) for n in (2, 3, 4, 8)}
    return measures.supersteps_run(spark, {n: phase2.run_levels(g, tree_of(g)).ledger for n, g in made.items()})


@query("supersteps", "SELECT DISTINCT n, CAST(ceil(log2(n)) AS INTEGER) + 1 AS supersteps FROM (SELECT count(DISTINCT l_suppkey) AS n FROM lineitem GROUP BY l_orderkey)")
def supersteps(spark, sf_dir):
    """The levels that orders would take whose parts are their suppliers, for every number of
    parts that occurs."""
    lines = read_table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.countDistinct("l_suppkey").alias("n"))
    return measures.supersteps_of(lines.select("n").distinct())


def _on_stats(run):
    def f(spark, sf_dir, name="supplier_loops"):
        _, tree, rows = levelled(spark, sf_dir, name)
        return run(stage(measures.level_stats(rows, tree), "stats"), tree)

    return f


_ST = sql.stats("supplier_loops")
query("level_totals", sql.with_(_ST, "SELECT level, count(*) AS parts, CAST(sum(i) AS BIGINT) AS i, CAST(sum(ob) AS BIGINT) AS ob, CAST(sum(eb) AS BIGINT) AS eb, CAST(sum(local) AS BIGINT) AS local, CAST(sum(remote) // 2 AS BIGINT) AS remote FROM st GROUP BY level"))(_on_stats(lambda s, t: measures.level_totals(s)))
query("phase1_work", sql.with_(_ST, "SELECT level, part, i + ob + eb + local AS work, max(i + ob + eb + local) OVER (PARTITION BY level) AS bound FROM st"))(_on_stats(lambda s, t: measures.phase1_work(s)))
_MOVED = " UNION ALL ".join(f"SELECT {k} AS level, a AS child, b AS parent FROM k{k}" for k in range(3))
query("communication", sql.with_(_ST + f", mv AS ({_MOVED})", "SELECT mv.level, child, parent, ob + eb + remote AS sent FROM mv JOIN st ON st.level = mv.level AND st.part = child"))(_on_stats(measures.communication))
query("communication_totals", sql.with_(_ST + f", mv AS ({_MOVED})", "SELECT mv.level, CAST(sum(ob + eb + remote) AS BIGINT) AS total, max(ob + eb + remote) AS largest FROM mv JOIN st ON st.level = mv.level AND st.part = child GROUP BY mv.level"))(_on_stats(lambda s, t: measures.communication_totals(measures.communication(s, t))))


def _memory_sql(policy: str, at: str) -> str:
    carried = {"carry_both": "r", "carry_one": "r // 2"}.get(policy, "0")
    held_ = {"deferred": "r", "carry_one+deferred": "r // 2"}.get(policy, "0")
    state = f"i + b + 2 * l + {carried}" if at == "start" else f"b + ob + {carried}"
    return sql.with_(_ST + ", t AS (SELECT level, CAST(sum(i) AS BIGINT) AS i, CAST(sum(ob + eb) AS BIGINT) AS b, CAST(sum(ob) AS BIGINT) AS ob, CAST(sum(local) AS BIGINT) AS l, CAST(sum(remote) AS BIGINT) AS r, count(*) AS n FROM st GROUP BY level)", f"SELECT level, '{policy}' AS policy, {state} AS cumulative, ({state}) / n AS average, {held_} AS leaf_held FROM t")


for _label, _policy in {"current": "carry_both", "carry_one": "carry_one", "deferred": "deferred", "proposed": "carry_one+deferred"}.items():
    for _at in ("start", "end"):
        query(f"memory_{_label}_{_at}", _memory_sql(_policy, _at))(_on_stats(lambda s, t, p=_policy, a=_at: measures.memory_state(s, p, a)))

query("memory_ideal", sql.with_(_ST + ", t AS (SELECT level, sum(i + ob + eb + 2 * local + remote) / count(*) AS a, count(*) AS n FROM st GROUP BY level)", "SELECT level, 'ideal' AS policy, (SELECT a FROM t WHERE level = 0) * n AS cumulative, (SELECT a FROM t WHERE level = 0) AS average FROM t"))(_on_stats(lambda s, t: measures.memory_ideal(s)))
query("memory_reduction", sql.with_(_ST + ", t AS (SELECT level, CAST(sum(ob + eb + ob) AS DOUBLE) AS base, CAST(sum(remote) AS DOUBLE) AS r FROM st GROUP BY level)", "SELECT level, CASE WHEN base + r = 0 THEN 0.0 ELSE round((r - 0) * 100.0 / (base + r), 6) END AS percent FROM t"))(
    _on_stats(lambda s, t: measures.memory_reduction(measures.memory_state(s, "carry_both", "end"), measures.memory_state(s, "carry_one+deferred", "end"))))
query("memory_reduction_one_copy", sql.with_(_ST + ", t AS (SELECT level, CAST(sum(ob + eb + ob) AS DOUBLE) AS base, CAST(sum(remote) AS DOUBLE) AS r FROM st GROUP BY level)", "SELECT level, CASE WHEN base + r = 0 THEN 0.0 ELSE round((r / 2) * 100.0 / (base + r), 6) END AS percent FROM t"))(
    _on_stats(lambda s, t: measures.memory_reduction(measures.memory_state(s, "carry_both", "end"), measures.memory_state(s, "carry_one", "end"))))

query("complexity_fit_formula", sql.with_(_ST, "SELECT round(regr_slope(local, w), 9) AS slope, round(regr_intercept(local, w), 9) AS intercept, round(regr_r2(local, w), 9) AS r2, count(*) AS n FROM (SELECT i + ob + eb + local AS w, local FROM st)"))(
    _on_stats(lambda s, t: measures.complexity_fit(s.select((F.col("i") + F.col("ob") + F.col("eb") + F.col("local")).cast("double").alias("expected"), F.col("local").cast("double").alias("observed")))))


# Phase 1 and the ledger ------------------------------------------------------------------
def _run(spark, sf_dir, name, **options):
    g = held(spark, sf_dir, name)
    return g, phase2.run_levels(g, tree_of(g), **options)


_PATHS = "SELECT st.level, st.part, ob // 2 AS n_paths FROM st WHERE ob > 0"
for _name in ("worked", "event_trail", "torus"):
    query(f"phase1_path_counts_{_name}", sql.with_(sql.stats(_name), _PATHS))(lambda s, d, n=_name: _run(s, d, n)[1].ledger.all_frags().where("ftype = 'path'").groupBy("level", "part").agg(F.count("*").alias("n_paths")))


@query("phase1_path_ends", sql.with_(sql.parts("event_trail"), "SELECT v, 1 AS n FROM (SELECT v, count(*) FILTER (WHERE l) AS dl, count(*) FILTER (WHERE NOT l) AS dr FROM (SELECT u AS v, pu = pv AS l FROM ep UNION ALL SELECT v, pu = pv FROM ep) GROUP BY v) WHERE dl % 2 = 1 AND dr > 0"))
def phase1_path_ends(spark, sf_dir):
    """Every odd boundary vertex of level 0 ends one path."""
    frags = _run(spark, sf_dir, "event_trail", stop_after=0)[1].ledger.frags(0).where("ftype = 'path'")
    return frags.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count("*").cast("int").alias("n"))


@query("phase1_item_cover", sql.with_(sql.levels("event_trail"), "SELECT jl AS level, count(*) AS n_edges FROM j GROUP BY jl"))
def phase1_item_cover(spark, sf_dir):
    """Every edge is an item of one fragment, at its join level."""
    return _run(spark, sf_dir, "event_trail")[1].ledger.all_items().where("item_kind = 'edge'").groupBy("level").agg(F.countDistinct("item_id").alias("n_edges"))


@query("phase1_breaks", "SELECT CAST(0 AS BIGINT) AS fid, 0 AS seq WHERE false")
def phase1_breaks(spark, sf_dir):
    """Places where a fragment's item doesn't start where the one before ended: none."""
    from pyspark.sql import Window

    own = Window.partitionBy("fid").orderBy("seq")
    items = _run(spark, sf_dir, "event_trail")[1].ledger.all_items()
    return items.withColumn("before", F.lag("b").over(own)).where("before <> a").select("fid", "seq")


@query("phase1_deferred_splice", sql.audit("event_trail"))
def phase1_deferred_splice(spark, sf_dir):
    g = held(spark, sf_dir, "event_trail")
    return verify.audit(g, stage(circuit(g, merge_internal=False, check=False), "c"))


@query("phase1_degree_order", sql.audit("event_trail"))
def phase1_degree_order(spark, sf_dir):
    g = held(spark, sf_dir, "event_trail")
    return verify.audit(g, stage(circuit(g, order="degree", check=False), "c"))


@query("ledger_walks")
def ledger_walks(spark, sf_dir):
    return phase3.top_walks(_run(spark, sf_dir, "event_trail")[1].ledger)


@query("ledger_walks_length", sql.with_(sql.edges("event_trail"), "SELECT count(*) AS n_edges FROM e"))
def ledger_walks_length(spark, sf_dir):
    """However the walks fall out, together they are as long as the graph has edges."""
    return ledger_walks(spark, sf_dir).agg(F.sum("n_edges").alias("n_edges"))


@query("ledger_pivots")
def ledger_pivots(spark, sf_dir):
    return phase3.pivots(phase3.unroll(_run(spark, sf_dir, "event_trail", merge_internal=False)[1].ledger))


@query("ledger_pivots_within", "SELECT CAST(0 AS BIGINT) AS v, CAST(0 AS BIGINT) AS n_walks, CAST(0 AS BIGINT) AS deg WHERE false")
def ledger_pivots_within(spark, sf_dir):
    """Pivots on more walks than half their degree, or on fewer than two: none."""
    degree = fg.degrees(held(spark, sf_dir, "event_trail"))
    return ledger_pivots(spark, sf_dir).join(degree, "v", "left").where("n_walks < 2 OR coalesce(n_walks * 2 > deg, true)")


# Circuits ------------------------------------------------------------------------------
def _made(method):
    def run(name, check, spark, sf_dir):
        g = held(spark, sf_dir, name)
        return check(g, stage(method(g), "circuit"))

    return run


_METHODS = {
    "circuit": partial(circuit, check=False),
    "sequential": baselines.sequential_circuit,
    "sequential_one_task": partial(baselines.sequential_circuit, per_component=False),
    "pairing": baselines.pairing_circuit,
    "pairing_doubling": partial(baselines.pairing_circuit, cycle_method="doubling"),
    "hybrid": partial(baselines.hybrid_circuit, switch_level=0),
    "circuit_carry_both": partial(circuit, remote_policy="carry_both", check=False),
    "circuit_carry_one": partial(circuit, remote_policy="carry_one", check=False),
    "circuit_deferred": partial(circuit, remote_policy="deferred", check=False),
    "circuit_distributed_stitch": partial(circuit, forest="boruvka", rank="doubling", check=False),
    "circuit_random_tree": partial(circuit, strategy="random", check=False),
    "circuit_lightest_tree": partial(circuit, strategy="lightest", check=False),
    # a budget that the last levels' parts exceed, so pairing takes over
    "circuit_budget": lambda g: circuit(g, budget=max(1, g.edges.count() // 4), check=False),
    "circuit_edges_only": partial(circuit, emit_vertices=False, check=False),
    "circuit_bfs": lambda g: circuit(Graph(g.edges), 4, "bfs", check=False),
}
_AUDITED = {
    "circuit": ("worked", *EVEN, "rmat_repaired"),
    "sequential": ("worked", "event_trail", "supplier_loops", "geo_doubled"),
    "sequential_one_task": ("worked", "event_trail"),
    "pairing": ("worked", "event_trail", "geo_doubled"),
    "pairing_doubling": ("worked",),
    "hybrid": ("worked", "event_trail", "supplier_loops", "geo_doubled"),
    "circuit_carry_both": ("event_trail",), "circuit_carry_one": ("event_trail",), "circuit_deferred": ("event_trail",),
    "circuit_distributed_stitch": ("worked", "geo_doubled"), "circuit_random_tree": ("event_trail",), "circuit_lightest_tree": ("event_trail",),
    "circuit_budget": ("supplier_loops",), "circuit_edges_only": ("event_trail",), "circuit_bfs": ("event_trail",),
}
for _m, _names in _AUDITED.items():
    for _name in _names:
        _on = TABLED.get(_name, _name) if _m == "sequential_one_task" else _name
        query(f"{_m}_audit_{_name}", sql.audit(_on))(partial(_made(_METHODS[_m]), _on, verify.audit))
for _name in ("supplier_loops", "geo_doubled"):
    query(f"circuit_edge_cover_{_name}", sql.cover(_name))(partial(_made(_METHODS["circuit"]), _name, lambda g, c: verify.edge_cover(c)))
for _name in ("order_part_repaired", "event_trail"):
    query(f"circuit_vertex_visits_{_name}", sql.visits(_name))(partial(_made(_METHODS["circuit"]), _name, lambda g, c: verify.vertex_visits(c)))
query("sequential_vertex_visits", sql.visits("event_trail"))(partial(_made(_METHODS["sequential"]), "event_trail", lambda g, c: verify.vertex_visits(c)))
query("pairing_edge_cover", sql.cover("torus"))(partial(_made(_METHODS["pairing"]), "torus", lambda g, c: verify.edge_cover(c)))


@query("one_part_audit", sql.audit("event_trail"))
def one_part_audit(spark, sf_dir):
    g = held(spark, sf_dir, "event_trail")
    one = Graph(g.edges).with_partition("modulo", 1)
    return verify.audit(g, stage(circuit(one, check=False), "c"))


@query("single_token_audit", sql.audit("complete_odd"))
def single_token_audit(spark, sf_dir):
    g = held(spark, sf_dir, "complete_odd")
    return verify.audit(g, baselines.single_token_circuit(g)[0])


@query("tree_tour_cover", sql.cover("geo_doubled"))
def tree_tour_cover(spark, sf_dir):
    return verify.edge_cover(baselines.tree_tour(Graph.from_edges(graphs.geo_tree(spark, sf_dir))))


@query("circuit_closing_vertex", sql.with_(sql.edges("worked"), "SELECT CAST(1 AS BIGINT) AS comp, count(*) + 1 AS n, true AS ends_meet FROM e"))
def circuit_closing_vertex(spark, sf_dir):
    """The vertex form from vertex 1: a row more than edges, and the ends are the same."""
    rows = circuit(held(spark, sf_dir, "worked"), form="vertices", start_vertex=1)
    return rows.groupBy("comp").agg(F.count("*").alias("n"), (F.min_by("v", "pos") == F.max_by("v", "pos")).alias("ends_meet"))


@query("circuit_array_sizes", sql.with_(sql.edges("worked"), "SELECT CAST(1 AS BIGINT) AS comp, CAST(count(*) AS INTEGER) AS n FROM e"))
def circuit_array_sizes(spark, sf_dir):
    return circuit(held(spark, sf_dir, "worked"), form="array").select("comp", F.size("circuit").alias("n"))


@query("unroll_sequential_audit", sql.audit("worked"))
def unroll_sequential_audit(spark, sf_dir):
    g, run = _run(spark, sf_dir, "worked")
    return verify.audit(g, spark.createDataFrame(phase3.unroll_sequential(run.ledger), phase3.CIRCUIT))


@query("circuit_exceptall", "SELECT CAST(0 AS BIGINT) AS eid, CAST(0 AS BIGINT) AS u, CAST(0 AS BIGINT) AS v WHERE false")
def circuit_exceptall(spark, sf_dir):
    g = held(spark, sf_dir, "supplier_loops")
    return verify.uncovered(g, stage(circuit(g, check=False), "c"))


# Measures with a clock -------------------------------------------------------------------
@query("time_split")
def time_split(spark, sf_dir):
    return measures.time_split(_run(spark, sf_dir, "event_trail")[1].ledger)


@query("complexity_points")
def complexity_points(spark, sf_dir):
    g, run = _run(spark, sf_dir, "event_trail")
    return measures.complexity_points(measures.level_stats(run.levelled, run.tree), run.ledger)


@query("time_shares")
def time_shares(spark, sf_dir):
    return measures.time_shares(_run(spark, sf_dir, "event_trail")[1].ledger)


@query("time_parts", sql.with_(sql.stats("event_trail"), "SELECT level, part, local AS items, true AS timed FROM st"))
def time_parts(spark, sf_dir):
    """level, part, items, timed: every part of every level has walked its coarse edges, and
    its four clocks and its memory have been read."""
    rows = measures.time_split(_run(spark, sf_dir, "event_trail")[1].ledger)
    clocks = F.least("receive", "build", "walk", "emit") >= 0
    return rows.select("level", "part", "items", (clocks & (F.col("walk") > 0) & (F.col("peak") > 0)).alias("timed"))


@query("stage_counts")
def stage_counts(spark, sf_dir):
    g = held(spark, sf_dir, "event_trail")
    found = measures.stage_counts(lambda: circuit(g, check=False))
    return spark.createDataFrame([tuple(found.values())], "jobs long, stages long, tasks long")


@query("memory_overhead")
def memory_overhead(spark, sf_dir):
    g, run = _run(spark, sf_dir, "event_trail")
    return measures.memory_overhead(measures.level_stats(run.levelled, run.tree), run.ledger)


@query("scaling_strong")
def scaling_strong(spark, sf_dir):
    g = held(spark, sf_dir, "event_trail")
    runs = []
    for n in (1, 2, 4, 8):
        own = Graph(g.edges).with_partition("modulo", n)
        with scratch(spark):
            runs.append((n, measures.timed(lambda own=own: circuit(own, check=False))[1]["seconds"]))
    return measures.scaling(runs, spark, "strong")


@query("scaling_weak")
def scaling_weak(spark, sf_dir):
    """Orders up to a share of the keys, so that the vertices of a part stay as many, with 2,
    3, 4 and 8 parts."""
    rows = stage(graphs.order_part(spark, sf_dir), "op")
    top = rows.agg(F.max("u")).first()[0] or 0
    runs = []
    for n in (2, 3, 4, 8):
        with scratch(spark):
            own = fg.repair_parity(Graph.from_edges(rows.where(F.col("u") <= top * n // 8))).with_partition("modulo", n, step=2)
            runs.append((n, measures.timed(lambda own=own: circuit(own, check=False))[1]["seconds"]))
    return measures.scaling(runs, spark, "weak")


@query("scaling_weak_load", sql.with_(sql.edges("order_part"), """SELECT n, round(count(DISTINCT v) / n / (SELECT count(DISTINCT v) / 8 FROM (SELECT unnest([u, v]) AS v FROM e)), 9) AS load
  FROM (SELECT n, unnest([u, v]) AS v FROM e, (VALUES (2), (3), (4), (8)) t(n) WHERE least(u, v) * 0 + CASE WHEN u % 2 = 0 THEN u ELSE v END <= (SELECT max(CASE WHEN u % 2 = 0 THEN u ELSE v END) FROM e) * n // 8) GROUP BY n"""))
def scaling_weak_load(spark, sf_dir):
    """n, load: vertices a part in the weak-scaling runs, against those with 8 parts."""
    rows = stage(graphs.order_part(spark, sf_dir), "op")
    top = rows.agg(F.max("u")).first()[0] or 0
    counted = [fg.ends(rows.where(F.col("u") <= top * n // 8)).agg((F.countDistinct("v") / n).alias("x")).select(F.lit(n).alias("n"), "x") for n in (2, 3, 4, 8)]
    sizes = counted[0].unionByName(counted[1]).unionByName(counted[2]).unionByName(counted[3])
    whole = sizes.where("n = 8").select(F.col("x").alias("y"))
    return sizes.join(F.broadcast(whole)).select("n", F.round(F.col("x") / F.col("y"), 9).alias("load"))  # four rows
