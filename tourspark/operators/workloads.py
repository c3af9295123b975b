"""The experiments: weak and strong scaling, detail, power-law repair, complexity, memory, cut
sensitivity, baselines side by side, and the ablation of policies and strategies."""

from __future__ import annotations

from functools import partial, reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark import graphs
from tourspark.functions import graph as fg
from tourspark.functions.graph import Graph
from tourspark.operators import graph_sql as sql
from tourspark.operators import methods
from tourspark.operators.registry import query
from tourspark.plans import baselines, measures, metagraph, phase2
from tourspark.plans.circuit import circuit
from tourspark.plans.partitioners import ground_of
from tourspark.session import scratch, stage, stage_alone

_DEG = "SELECT v, count(*) AS deg FROM (SELECT unnest([u, v]) AS v FROM {0}) GROUP BY v"


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), frames)


def _stats(spark, sf_dir, name):
    _, tree, rows = methods.levelled(spark, sf_dir, name)
    return stage(measures.level_stats(rows, tree), "stats"), tree


# Graph characteristics of the even graphs, one row each
def _row_sql(name: str) -> str:
    n = sql.n_parts(name)
    low = 1 if name == "worked" else 0
    return f"""SELECT '{name}' AS graph, * FROM (WITH RECURSIVE {sql.parts(name)}
SELECT (SELECT count(*) FROM vp WHERE v IN (SELECT unnest([u, v]) FROM e)) AS vertices, (SELECT count(*) FROM ep) AS edges, (SELECT count(*) FROM ep) * 2 AS edges_both,
  (SELECT count(DISTINCT v) FROM (SELECT unnest([u, v]) AS v FROM ep WHERE pu <> pv)) AS boundary, CAST({n} AS INTEGER) AS parts,
  round((SELECT count(*) FROM ep WHERE pu <> pv) * 100.0 / (SELECT count(*) FROM ep), 6) AS cut_percent,
  round((SELECT max(abs((SELECT count(*) FROM vp) - {n} * n)) FROM (SELECT count(v) AS n FROM range({low}, {n + low}) r(p) LEFT JOIN vp ON part = p GROUP BY p)) * 100.0 / (SELECT count(*) FROM vp), 6) AS imbalance_percent)"""


_CUTS = ("worked", "torus", "geo_doubled", "supplier_loops", "event_trail", "order_part_repaired")


@query("workload_graph_table", " UNION ALL ".join(map(_row_sql, _CUTS)))
def workload_graph_table(spark, sf_dir):
    """The table of graphs; with it the cut runs from none (by region) to nine tenths (hash)."""
    return _union([measures.graph_stats(graphs.even_graph(spark, sf_dir, n)).withColumn("graph", F.lit(n)) for n in _CUTS])


# Power-law graph: generation, repair, degrees before and after
_RMAT = sql.edges("power_law_repaired")


@query("workload_power_law_degrees", sql.with_(_RMAT, f"SELECT deg, coalesce(a.n, 0) AS before, coalesce(b.n, 0) AS after FROM (SELECT deg, count(*) AS n FROM ({_DEG.format('e0')}) GROUP BY deg) a FULL JOIN (SELECT deg, count(*) AS n FROM ({_DEG.format('e')}) GROUP BY deg) b USING (deg)"))
def workload_power_law_degrees(spark, sf_dir):
    g = Graph.from_edges(graphs.power_law(spark, sf_dir))
    before, after = measures.degree_histogram(g).withColumnRenamed("n", "before"), measures.degree_histogram(fg.repair_parity(g)).withColumnRenamed("n", "after")
    return before.join(after, "deg", "full").na.fill(0)


@query("workload_power_law_cost", sql.with_(_RMAT, "SELECT (SELECT count(*) FROM added) AS added, round((SELECT count(*) FROM added) * 100.0 / (SELECT count(*) FROM e0), 6) AS percent"))
def workload_power_law_cost(spark, sf_dir):
    g = Graph.from_edges(graphs.power_law(spark, sf_dir))
    return measures.repair_cost(g, fg.repair_parity(g))


# Detail and complexity of two graphs
@query("workload_detail")
def workload_detail(spark, sf_dir):
    """graph, level, part: vertex kinds, coarse edges, work, the kernel's seconds by step, and
    the memory of the process that held the part."""
    out = []
    for name in ("supplier_loops", "order_part_repaired"):
        g = methods.held(spark, sf_dir, name)
        run = phase2.run_levels(g, methods.tree_of(g), keep_items=False)
        stats = measures.level_stats(run.levelled, run.tree)
        seconds = measures.time_split(run.ledger)
        work = measures.phase1_work(stats).select("level", "part", "work")
        out.append(stats.join(work, ["level", "part"]).join(seconds, ["level", "part"]).withColumn("graph", F.lit(name)))
    return _union(out)


@query("workload_complexity_fit")
def workload_complexity_fit(spark, sf_dir):
    """graph, slope, intercept, r2, n: observed kernel seconds by expected work."""
    rows = stage(workload_detail(spark, sf_dir), "detail")
    fits = [measures.complexity_fit(rows.where(F.col("graph") == n).select(F.col("work").cast("double").alias("expected"), F.col("seconds").alias("observed"))).withColumn("graph", F.lit(n)) for n in ("supplier_loops", "order_part_repaired")]
    return _union(fits)


@query("workload_time_shares")
def workload_time_shares(spark, sf_dir):
    """seconds, kernel_seconds, share of the kernel, supersteps, jobs, stages and tasks, for
    supplier_loops."""
    g = methods.held(spark, sf_dir, "supplier_loops")
    tree = methods.tree_of(g)
    held = {}
    _, clock = measures.timed(lambda: held.setdefault("run", phase2.run_levels(g, tree)).ledger.all_frags())
    run = held["run"]
    kernel = measures.time_split(run.ledger).agg(F.sum("seconds")).first()[0]
    row = (clock["seconds"], kernel, kernel / clock["seconds"], len(run.ledger.levels()), clock["jobs"], clock["stages"], clock["tasks"])
    return spark.createDataFrame([row], "seconds double, kernel_seconds double, share double, supersteps int, jobs long, stages long, tasks long")


# Memory curves of three graphs
_POLICIES = ("carry_both", "carry_one", "carry_one+deferred")


def _memory_sql(name: str) -> str:
    rows = []
    for at in ("start", "end"):
        for policy in _POLICIES:
            carried = {"carry_both": "r", "carry_one": "r // 2"}.get(policy, "0")
            state = f"i + b + 2 * l + {carried}" if at == "start" else f"b + ob + {carried}"
            rows.append(f"SELECT '{at}' AS at, level, '{policy}' AS policy, {state} AS cumulative FROM t")
    body = sql.stats(name) + ", t AS (SELECT level, CAST(sum(i) AS BIGINT) AS i, CAST(sum(ob + eb) AS BIGINT) AS b, CAST(sum(ob) AS BIGINT) AS ob, CAST(sum(local) AS BIGINT) AS l, CAST(sum(remote) AS BIGINT) AS r FROM st GROUP BY level)"
    return sql.with_(body, " UNION ALL ".join(rows))


def _memory(name):
    def run(spark, sf_dir):
        stats, _ = _stats(spark, sf_dir, name)
        return _union([measures.memory_state(stats, p, at).select(F.lit(at).alias("at"), "level", "policy", "cumulative") for at in ("start", "end") for p in _POLICIES])

    return run


for _name in ("supplier_loops", "order_part_repaired", "torus"):
    query(f"workload_memory_{_name}", _memory_sql(_name))(_memory(_name))


# Scaling
@query("workload_strong_scaling")
def workload_strong_scaling(spark, sf_dir):
    """supplier_loops with 1, 2, 4 and 8 parts: seconds beside the ideal."""
    g = methods.held(spark, sf_dir, "supplier_loops")
    runs = []
    for n in (1, 2, 4, 8):
        own = Graph(g.edges).with_partition("modulo", n)
        # the clock is kept of a run, not its tables
        with scratch(spark):
            runs.append((n, measures.timed(lambda own=own: circuit(own, check=False))[1]["seconds"]))
    return measures.scaling(runs, spark, "strong")


# Baselines on one graph
@query("workload_faceoff")
def workload_faceoff(spark, sf_dir):
    """graph, method, seconds, stages, tasks on event_trail, and with the single token, which
    needs a superstep an edge, on the sample graph; each result is written in full."""
    out = []
    for name in ("event_trail", "worked"):
        g = methods.held(spark, sf_dir, name)
        made = {
            "merge": lambda g=g: circuit(g, check=False), "sequential": lambda g=g: baselines.sequential_circuit(g),
            "pairing": lambda g=g: baselines.pairing_circuit(g), "hybrid": lambda g=g: baselines.hybrid_circuit(g, 0),
        }
        if name == "worked":
            made["token"] = lambda g=g: baselines.single_token_circuit(g)[0]
        for method, run in made.items():
            with scratch(spark):
                clock = measures.timed(run)[1]
            out.append((name, method, clock["seconds"], clock["stages"], clock["tasks"]))
    return spark.createDataFrame(out, "graph string, method string, seconds double, stages long, tasks long")


# Cuts between those of range and hash parts, by growth and by label propagation
@query("workload_partitioned")
def workload_partitioned(spark, sf_dir):
    """how, then the graph table's columns: order_part repaired, cut by growth from seeds and
    by label propagation into 2, 3, 4 and 8 parts. Random-like graphs are cut at about half to
    seven tenths of their edges by either, where hash parts cut nearly all."""
    edges = methods.held(spark, sf_dir, "order_part_repaired").edges
    rows = [(how, n) for how in ("bfs", "lpa") for n in (2, 3, 4, 8)]
    # written one by one, so the driver doesn't keep eight plans and what they broadcast
    ground = ground_of(Graph(edges))

    def measured(how: str, n: int) -> DataFrame:
        return measures.graph_stats(Graph(edges).with_partition(how, n, ground=ground)).withColumn("how", F.lit(how))

    return _union([stage_alone(spark, partial(measured, how, n), "partitioned") for how, n in rows])


@query("workload_partitioned_detail", sql.with_(sql.edges("order_part_repaired"), "SELECT level, true AS matches FROM range(4) r(level)"))
def workload_partitioned_detail(spark, sf_dir):
    """level, matches: under parts by growth, whether what the kernel walked at each level is
    what the closed forms say, part by part, imbalance and all."""
    g = methods.held(spark, sf_dir, "order_part_repaired")
    g = Graph(g.edges).with_partition("bfs", 8)
    run = phase2.run_levels(g, methods.tree_of(g), keep_items=False)
    stats = measures.level_stats(run.levelled, run.tree).where("local > 0").select("level", "part", "local")
    both = stats.join(measures.time_split(run.ledger).select("level", "part", "items"), ["level", "part"], "full")
    return both.groupBy("level").agg(F.expr("bool_and(coalesce(local = items, false))").alias("matches")).select(F.col("level").cast("long").alias("level"), "matches")


# Policies and strategies
def _ablation_sql(strategy: str) -> str:
    carried = {"carry_both": "r", "carry_one": "r // 2", "deferred": "0", "carry_one+deferred": "0"}
    body = sql.stats("event_trail", strategy) + ", t AS (SELECT level, CAST(sum(i + ob + eb + 2 * local) AS BIGINT) AS s, CAST(sum(remote) AS BIGINT) AS r FROM st GROUP BY level)"
    rows = " UNION ALL ".join(f"SELECT '{strategy}' AS strategy, '{p}' AS policy, level, s + {c} AS cumulative FROM t" for p, c in carried.items())
    return f"SELECT * FROM ({sql.with_(body, rows)})"


def _ablation(spark, sf_dir, strategies) -> DataFrame:
    g = methods.held(spark, sf_dir, "event_trail")
    out = []
    for strategy in strategies:
        tree = methods.tree_of(g, strategy)
        stats = stage(measures.level_stats(metagraph.join_levels(g, tree), tree), "stats")
        out += [measures.memory_state(stats, p).select(F.lit(strategy).alias("strategy"), "policy", "level", "cumulative") for p in phase2.POLICIES]
    return _union(out)


_FIXED = ("greedy", "id_order", "lightest")


@query("workload_ablation", " UNION ALL ".join(map(_ablation_sql, _FIXED)))
def workload_ablation(spark, sf_dir):
    """strategy, policy, level, cumulative: state at the start of each level."""
    return _ablation(spark, sf_dir, _FIXED)


@query("workload_ablation_random")
def workload_ablation_random(spark, sf_dir):
    """The same for a tree of random pairs."""
    return _ablation(spark, sf_dir, ["random"])


@query("graph_kmer_pairs", """SELECT u, v, count(*) AS n FROM (SELECT least(a, b) AS u, greatest(a, b) AS v FROM (SELECT CAST('0x' || substr(md5(x), 1, 13) AS BIGINT) AS a, CAST('0x' || substr(md5(y), 1, 13) AS BIGINT) AS b FROM (
  SELECT unnest(g[1:len(g) - 1]) AS x, unnest(g[2:len(g)]) AS y FROM (SELECT list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) AS g FROM (
    SELECT list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda x: x <> '') AS w FROM documents WHERE lang = 'en') WHERE len(w) >= 3)))) GROUP BY ALL""")
def graph_kmer_pairs(spark, sf_dir):
    """Neighbouring pairs of words, overlapping in one: the graph of an assembly with k = 2."""
    edges = Graph.from_edges(graphs.word_trail(spark, sf_dir, "en", 2)).edges
    return edges.groupBy("u", "v").agg(F.count("*").alias("n"))
