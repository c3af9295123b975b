"""Cost and accuracy measures.

The level table follows from the merge tree alone: a fragment path starts at each odd
boundary vertex, so the parity of coarse local degrees equals that of the original ones.
No level has to be run for any measure but the timings.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tourspark.functions.graph import Graph, degrees, split_edges, vertex_parts
from tourspark.plans.ledger import Ledger
from tourspark.plans.metagraph import MergeTree
from tourspark.session import lookup, stage


def supersteps_run(spark: SparkSession, ledgers: dict[int, Ledger]) -> DataFrame:
    """(n, supersteps) of runs: the levels that their ledgers hold."""
    return spark.createDataFrame([(n, len(x.levels())) for n, x in ledgers.items()], "n int, supersteps int")


def supersteps(spark: SparkSession, sizes: list[int]) -> DataFrame:
    """(n, supersteps): ceil(log2 n) + 1."""
    return supersteps_of(spark.createDataFrame([(n,) for n in sizes], "n int"))


def supersteps_of(sizes: DataFrame) -> DataFrame:
    """The same for a column ``n`` of numbers of parts, 1 or more."""
    # the binary digits of n - 1; those of 0 are none
    digits = F.when(F.col("n") > 1, F.length(F.bin((F.col("n") - 1).cast("long")))).otherwise(0)
    return sizes.select("n", (digits + 1).alias("supersteps"))


def _vertex_levels(levelled: DataFrame, tree: MergeTree) -> DataFrame:
    """v, leaf, level, dl, dr, dr_before: ends that have joined by a level, ends that haven't,
    and ends that hadn't at the level before. One exchange by vertex."""
    side = F.explode(F.array(F.struct(F.col("u").alias("v"), F.col("pu").alias("leaf")), F.struct(F.col("v").alias("v"), F.col("pv").alias("leaf"))))
    rows = levelled.select(side.alias("e"), "join_level").select("e.v", "e.leaf", "join_level")
    levels = range(tree.height + 1)
    sums = [F.count_if(F.col("join_level") <= lv).alias(f"d{lv}") for lv in levels]
    per = rows.groupBy("v", "leaf").agg(F.count("*").alias("deg"), *sums)
    made = [
        F.struct(F.lit(lv).alias("level"), F.col(f"d{lv}").alias("dl"), (F.col("deg") - F.col(f"d{lv}")).alias("dr"), (F.col("deg") - (F.col(f"d{lv - 1}") if lv else F.lit(0))).alias("dr_before"))
        for lv in levels
    ]
    return per.select("v", "leaf", F.explode(F.array(*made)).alias("x")).select("v", "leaf", "x.*")


def _part_rows(spark: SparkSession, tree: MergeTree) -> DataFrame:
    """(level, leaf, part): a row a leaf and level."""
    return lookup(spark, [(level, leaf, part) for level, m in enumerate(tree.maps()) for leaf, part in m.items()], "level int, leaf int, part int")


def copies_held(held: DataFrame, tree: MergeTree) -> DataFrame:
    """level, part, held: the remote edges whose one copy a part keeps at each level, by
    ``holder`` of the edges (see ``metagraph.with_holders``)."""
    spark = held.sparkSession
    parts = _part_rows(spark, tree)
    sums = held.where("join_level > 0").groupBy("holder", "join_level").count()
    kept = sums.join(parts, (sums["holder"] == parts["leaf"]) & (parts["level"] < sums["join_level"])).groupBy("level", "part").agg(F.sum("count").alias("held"))
    return parts.select("level", "part").distinct().join(kept, ["level", "part"], "left").select("level", "part", F.coalesce("held", F.lit(0)).alias("held"))


def memory_one_copy(stats: DataFrame, copies: DataFrame, at: str = "start") -> DataFrame:
    """level, part, both, one: the Longs of each part with both copies of its remote edges,
    and with those that the rule leaves it."""
    base = F.col("i") + F.col("ob") + F.col("eb") + 2 * F.col("local") if at == "start" else F.col("ob") + F.col("eb") + F.col("ob")
    return stats.join(copies, ["level", "part"]).select("level", "part", (base + F.col("remote")).alias("both"), (base + F.col("held")).alias("one"))


def level_stats(levelled: DataFrame, tree: MergeTree) -> DataFrame:
    """level, part, i, ob, eb, local, remote: vertex kinds, coarse local edges and remote
    edges (each seen from either of its parts) of every part at the start of each level."""
    spark = levelled.sparkSession
    parts = _part_rows(spark, tree)
    seen = _vertex_levels(levelled, tree).join(parts, ["level", "leaf"])
    live = (F.col("level") == 0) | (F.col("dr_before") > 0)
    ob = live & (F.col("dr") > 0) & (F.col("dl") % 2 == 1)
    eb = live & (F.col("dr") > 0) & (F.col("dl") % 2 == 0)
    kinds = seen.groupBy("level", "part").agg(F.count_if(live & (F.col("dr") == 0)).alias("i"), F.count_if(ob).alias("ob"), F.count_if(eb).alias("eb"), F.sum("dr").alias("remote"))
    # paths of the level before are coarse edges of the part that their part has become
    maps = tree.maps()
    moves = {(level, maps[level - 1][leaf], maps[level][leaf]) for level in range(1, len(maps)) for leaf in tree.parts}
    step = lookup(spark, sorted(moves), "next int, was int, now int")
    paths = kinds.select((F.col("level") + 1).alias("next"), F.col("part").alias("was"), (F.col("ob") / 2).cast("long").alias("paths")).join(step, ["next", "was"]).groupBy(F.col("next").alias("level"), F.col("now").alias("part")).agg(F.sum("paths").alias("paths"))
    fresh = levelled.withColumn("level", F.col("join_level")).join(_part_rows(spark, tree).withColumnRenamed("leaf", "pu"), ["level", "pu"]).groupBy("level", "part").agg(F.count("*").alias("fresh"))
    out = kinds.join(paths, ["level", "part"], "left").join(fresh, ["level", "part"], "left")
    local = F.coalesce("fresh", F.lit(0)) + F.coalesce("paths", F.lit(0))
    return out.select("level", "part", "i", "ob", "eb", local.alias("local"), "remote")


def level_totals(stats: DataFrame) -> DataFrame:
    """Sums over parts; a remote edge counts once."""
    return stats.groupBy("level").agg(F.count("*").alias("parts"), F.sum("i").alias("i"), F.sum("ob").alias("ob"), F.sum("eb").alias("eb"), F.sum("local").alias("local"), F.expr("sum(remote) div 2").alias("remote"))


def phase1_work(stats: DataFrame) -> DataFrame:
    """level, part, work: B + I + L; and the level's bound, its largest part."""
    rows = stats.select("level", "part", (F.col("i") + F.col("ob") + F.col("eb") + F.col("local")).alias("work"))
    return rows.withColumn("bound", F.max("work").over(Window.partitionBy("level")))


def communication(stats: DataFrame, tree: MergeTree) -> DataFrame:
    """level, child, parent, sent: boundary vertices and remote edges of each child that a
    merge moves (the child that is not the parent)."""
    moved = [(lv, a if p == b else b, p) for lv, a, b, p, _ in tree.merges]
    merges = lookup(stats.sparkSession, moved, "level int, part int, parent int")
    return stats.join(merges, ["level", "part"]).select("level", F.col("part").alias("child"), "parent", (F.col("ob") + F.col("eb") + F.col("remote")).alias("sent"))


def communication_totals(sent: DataFrame) -> DataFrame:
    return sent.groupBy("level").agg(F.sum("sent").alias("total"), F.max("sent").alias("largest"))


def memory_state(stats: DataFrame, policy: str, at: str = "start") -> DataFrame:
    """level, policy, cumulative, average, leaf_held: state in Longs over the parts.

    At the start of a level a part holds its vertices, two Longs for each local edge and its
    remote entries; at its end the boundary, its paths' two ends, and the remote entries.
    ``remote`` of the stats counts both directions: all are carried, or half, or none (then
    half of them stay with the leaves).
    """
    carried = {"carry_both": F.col("r"), "carry_one": F.expr("r div 2"), "deferred": F.lit(0), "carry_one+deferred": F.lit(0)}[policy]
    held = F.lit(0) if policy.startswith("carry_") and "+" not in policy else F.col("r") if policy == "deferred" else F.expr("r div 2")
    sums = stats.groupBy("level").agg(F.sum("i").alias("i"), F.sum(F.col("ob") + F.col("eb")).alias("b"), F.sum("ob").alias("ob"), F.sum("local").alias("l"), F.sum("remote").alias("r"), F.count("*").alias("n"))
    state = F.col("i") + F.col("b") + 2 * F.col("l") + carried if at == "start" else F.col("b") + F.col("ob") + carried
    return sums.select("level", F.lit(policy).alias("policy"), state.cast("long").alias("cumulative"), (state / F.col("n")).cast("double").alias("average"), held.cast("long").alias("leaf_held"))


def memory_ideal(stats: DataFrame) -> DataFrame:
    """The line that would scale: the average of level 0 at every level."""
    first = memory_state(stats, "carry_both").where("level = 0").select(F.col("average").alias("a0"))
    return stats.groupBy("level").agg(F.count("*").alias("n")).join(F.broadcast(first)).select("level", F.lit("ideal").alias("policy"), (F.col("a0") * F.col("n")).alias("cumulative"), F.col("a0").alias("average"))


def memory_reduction(a: DataFrame, b: DataFrame) -> DataFrame:
    """level, percent: by how much ``b`` lies below ``a``, cumulative."""
    return a.select("level", F.col("cumulative").alias("x")).join(b.select("level", F.col("cumulative").alias("y")), "level").select("level", F.when(F.col("x") == 0, 0.0).otherwise(F.round((F.col("x") - F.col("y")) * 100.0 / F.col("x"), 6)).alias("percent"))


def graph_stats(g: Graph) -> DataFrame:
    """One row: vertices, edges (and in both directions), boundary vertices, parts, cut and
    imbalance in percent."""
    split = split_edges(g)
    if g.part_of is None:
        split = stage(split.select("u", "v", "is_local"), "split")  # read twice: the parts are joined once
    cut = split.agg(F.count("*").alias("edges"), F.count_if(~F.col("is_local")).alias("cut"))
    sizes = vertex_parts(g).groupBy("part").count()
    side = split.where(~F.col("is_local")).select(F.explode(F.array("u", "v")).alias("v")).distinct().agg(F.count("*").alias("boundary"))
    n = F.lit(g.n_parts).cast("int")
    size = sizes.agg(F.sum("count").alias("vertices"), F.max("count").alias("most"), F.min("count").alias("least"), F.count("*").alias("used"))
    off = F.greatest(F.abs(F.col("vertices") - n * F.col("most")), F.abs(F.col("vertices") - n * F.when(F.col("used") < n, 0).otherwise(F.col("least"))))
    return cut.join(F.broadcast(size)).join(F.broadcast(side)).select(
        "vertices", "edges", (F.col("edges") * 2).alias("edges_both"), "boundary", n.alias("parts"),
        F.round(F.col("cut") * 100.0 / F.col("edges"), 6).alias("cut_percent"), F.round(off * 100.0 / F.col("vertices"), 6).alias("imbalance_percent"),
    )


def repair_cost(before: Graph, after: Graph) -> DataFrame:
    """added, percent of the edges there were."""
    m = before.edges.agg(F.count("*").alias("m"))
    return after.edges.agg(F.count_if("added").alias("added")).join(F.broadcast(m)).select("added", F.round(F.col("added") * 100.0 / F.col("m"), 6).alias("percent"))


def degree_histogram(g: Graph) -> DataFrame:
    return degrees(g).groupBy("deg").agg(F.count("*").alias("n"))


def degree_distance(g0: Graph, g1: Graph, metric: str = "ks") -> DataFrame:
    """One row ``distance`` between degree distributions: total variation, the same over
    powers of two, or the largest gap of the cumulated shares."""
    bin_of = F.floor(F.log2("deg")).cast("long") if metric == "log2tv" else F.col("deg")
    share = lambda g, name: degree_histogram(g).groupBy(bin_of.alias("bin")).agg(F.sum("n").alias("n")).withColumn(name, F.col("n") / F.sum("n").over(Window.partitionBy(F.lit(0)))).select("bin", name)  # noqa: E731  a row a degree: few
    both = share(g0, "p").join(share(g1, "q"), "bin", "full").select("bin", F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("q", F.lit(0.0)).alias("q"))
    if metric in ("tv", "log2tv"):
        return both.agg(F.round(F.sum(F.abs(F.col("p") - F.col("q"))) / 2, 9).alias("distance"))
    run = Window.partitionBy(F.lit(0)).orderBy("bin")
    return both.select(F.abs(F.sum(F.col("p") - F.col("q")).over(run)).alias("gap")).agg(F.round(F.max("gap"), 9).alias("distance"))


def remote_ratio(g: Graph) -> DataFrame:
    """One row: remote edges in both directions to vertices."""
    cut = split_edges(g).agg((F.count_if(~F.col("is_local")) * 2).alias("remote"))
    v = degrees(g).agg(F.count("*").alias("v"))
    return cut.join(F.broadcast(v)).select("remote", F.col("v").alias("vertices"), F.round(F.col("remote") / F.col("v"), 6).alias("ratio"))


def time_split(ledger: Ledger) -> DataFrame:
    """level, part, items, receive, build, walk, emit, seconds, peak: the kernel's own figures.

    ``receive``: until a part's rows are there, which is moving and merging; ``build``: the
    arrays; ``walk``: paths, cycles and splicing; ``emit``: the output rows. ``seconds``: the
    last three. ``peak``: the most bytes that the worker process had held by then.
    """
    return ledger.all_figures()


def time_shares(ledger: Ledger) -> DataFrame:
    """level, and the shares of the four steps in their sum over the level's parts."""
    steps = ("receive", "build", "walk", "emit")
    sums = time_split(ledger).groupBy("level").agg(*[F.sum(c).alias(c) for c in steps])
    whole = sum((F.col(c) for c in steps), F.lit(0.0))
    return sums.select("level", *[(F.col(c) / whole).alias(c) for c in steps])


def complexity_fit(points: DataFrame) -> DataFrame:
    """One row over (expected, observed): slope, intercept, r2, n."""
    return points.agg(F.round(F.regr_slope("observed", "expected"), 9).alias("slope"), F.round(F.regr_intercept("observed", "expected"), 9).alias("intercept"), F.round(F.regr_r2("observed", "expected"), 9).alias("r2"), F.count("*").alias("n"))


def complexity_points(stats: DataFrame, ledger: Ledger) -> DataFrame:
    """level, part, expected (work), observed (kernel seconds): 2n - 1 points for n parts."""
    work = phase1_work(stats).select("level", "part", F.col("work").cast("double").alias("expected"))
    return work.join(time_split(ledger).select("level", "part", F.col("seconds").alias("observed")), ["level", "part"])


def scaling(runs: list[tuple[int, float]], spark: SparkSession, kind: str = "strong") -> DataFrame:
    """n, seconds, ratio to the first run; strong scaling: also the ideal, n0 / n."""
    n0, t0 = runs[0]
    rows = [(n, t, t / t0, 1.0 if kind == "weak" else n0 / n) for n, t in runs]
    return spark.createDataFrame(rows, "n int, seconds double, ratio double, ideal double")


def timed(run: Callable[[], DataFrame]) -> tuple[DataFrame, dict[str, float]]:
    """The staged result of ``run``, and its seconds, jobs, stages and tasks.

    Jobs are those of a group of its own; stages and tasks those that the status tracker still
    knows for them.
    """
    group = f"tourspark-timed-{uuid.uuid4().hex}"
    # any session will do: the context is that of the application
    context = SparkSession.getActiveSession().sparkContext
    context.setJobGroup(group, group)
    began = time.perf_counter()
    try:
        out = stage(run(), "timed")
    finally:
        spent = time.perf_counter() - began
        context.setLocalProperty("spark.jobGroup.id", None)
    tracker, stages = context.statusTracker(), {}
    jobs = tracker.getJobIdsForGroup(group)
    for j in jobs:
        info = tracker.getJobInfo(j)
        for s in info.stageIds if info else ():
            known = tracker.getStageInfo(s)
            if known and known.numCompletedTasks:
                stages[s] = known.numTasks
    return out, {"seconds": spent, "jobs": len(jobs), "stages": len(stages), "tasks": sum(stages.values())}


def stage_counts(run: Callable[[], DataFrame]) -> dict[str, int]:
    """Jobs, stages and tasks of a run."""
    found = timed(run)[1]
    return {k: found[k] for k in ("jobs", "stages", "tasks")}


def memory_overhead(stats: DataFrame, ledger: Ledger) -> DataFrame:
    """level, part, raw_bytes, process_bytes, ratio: a part's state at the start of a level at
    8 bytes a Long, both copies of remote edges counted, against the most memory that the
    worker process which walked it has held."""
    raw = ((F.col("i") + F.col("ob") + F.col("eb") + 2 * F.col("local") + F.col("remote")) * 8).alias("raw_bytes")
    both = stats.select("level", "part", raw).join(time_split(ledger).select("level", "part", F.col("peak").alias("process_bytes")), ["level", "part"])
    return both.withColumn("ratio", F.col("process_bytes") / F.greatest("raw_bytes", F.lit(1)))
