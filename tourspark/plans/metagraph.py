"""The meta-graph of parts, matchings on it, and the merge tree."""

from __future__ import annotations

import random
import zlib
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tourspark import schemas
from tourspark.functions.graph import Graph, split_edges
from tourspark.session import lookup, stage

Row = tuple[int, int, int]  # a, b, weight with a < b


def meta_graph(g: Graph, level: int = 0) -> DataFrame:
    """level, a, b, weight: how many edges run between two parts."""
    remote = split_edges(g).where(~F.col("is_local"))
    pairs = remote.groupBy(F.least("pu", "pv").alias("a"), F.greatest("pu", "pv").alias("b"))
    return pairs.agg(F.count("*").alias("weight")).select(F.lit(level).alias("level"), "a", "b", "weight")


def greedy_matching(rows: list[Row], ties: str = "id") -> list[Row]:
    """Heaviest first, in a total order, so the answer is unique. ``ties``: by the smaller ids,
    or by a ``digest`` of the pair and then the ids."""
    tie = (lambda r: 0) if ties == "id" else (lambda r: zlib.crc32(f"{r[0]}-{r[1]}".encode()))
    return _taken(sorted(rows, key=lambda r: (-r[2], tie(r), r[0], r[1])))


def _taken(order: list[Row]) -> list[Row]:
    taken: set[int] = set()
    out = []
    for a, b, w in order:
        if not {a, b} & taken:
            taken |= {a, b}
            out.append((a, b, w))
    return out


def greedy_matching_distributed(meta: DataFrame, ties: str = "id") -> DataFrame:
    """The same matching in rounds: an edge that is best for both of its ends is in it.

    The order of edges is total, so every round takes at least the best edge that is left, and
    many at once; edges at a taken end then drop out, until none is left. Equal weights along
    a chain of parts settle one by one under ties by id, and many at a time by digest.
    """
    tie = F.lit(0).cast("long") if ties == "id" else -F.crc32(F.concat_ws("-", "a", "b").cast("binary"))
    rank = F.struct(F.col("weight").alias("w"), tie.alias("t"), (-F.col("a")).alias("na"), (-F.col("b")).alias("nb"))
    live = stage(meta.select("a", "b", "weight"), "meta")
    found = live.where("false")
    while not live.isEmpty():
        sides = live.select("a", "b", rank.alias("r")).select(F.explode(F.array("a", "b")).alias("p"), "r")
        best = sides.groupBy("p").agg(F.max("r").alias("r"))
        votes = best.groupBy("r").count().where("count = 2")
        taken = stage(votes.select((-F.col("r.na")).alias("a"), (-F.col("r.nb")).alias("b"), F.col("r.w").alias("weight")), "matched")
        found = found.unionByName(taken)
        gone = taken.select(F.explode(F.array("a", "b")).alias("p"))
        live = stage(live.join(gone, live["a"] == gone["p"], "left_anti").join(gone, live["b"] == gone["p"], "left_anti"), "meta")
    return found


def rebuild_meta(rows: list[Row], merged: dict[int, int]) -> list[Row]:
    """The meta-graph after merging: inner edges go, parallel ones are summed."""
    out: dict[tuple[int, int], int] = {}
    for a, b, w in rows:
        a, b = merged.get(a, a), merged.get(b, b)
        if a != b:
            key = (min(a, b), max(a, b))
            out[key] = out.get(key, 0) + w
    return sorted((a, b, w) for (a, b), w in out.items())


@dataclass
class MergeTree:
    """``merges``: (level, child_a, child_b, parent, weight), the merges after that level."""

    parts: list[int]
    merges: list[tuple[int, int, int, int, int]] = field(default_factory=list)

    @property
    def height(self) -> int:
        return max((m[0] for m in self.merges), default=-1) + 1

    def maps(self) -> list[dict[int, int]]:
        """For each level from 0 to the height: leaf -> the part that holds it."""
        out = [{p: p for p in self.parts}]
        for level in range(self.height):
            step = {c: m[3] for m in self.merges if m[0] == level for c in m[1:3]}
            out.append({leaf: step.get(p, p) for leaf, p in out[-1].items()})
        return out

    def tree_rows(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.merges, schemas.TREE)

    def partmap(self, spark: SparkSession) -> DataFrame:
        rows = [(level, leaf, part) for level, m in enumerate(self.maps()) for leaf, part in m.items()]
        return spark.createDataFrame(rows, schemas.PARTMAP)


def _match(rows: list[Row], strategy: str, rng: random.Random, ties: str) -> list[Row]:
    if strategy == "greedy":
        return greedy_matching(rows, ties)
    order = sorted(rows)
    if strategy == "random":
        rng.shuffle(order)
    elif strategy == "lightest":
        order.sort(key=lambda r: (r[2], r[0], r[1]))
    elif strategy != "id_order":
        raise ValueError(f"unknown strategy {strategy}")
    return _taken(order)


def merge_tree(meta: DataFrame | list[Row], parts: list[int], strategy: str = "greedy", zero_weight: str = "pair", parent: str = "larger", seed: int = 0, sizes: dict[int, int] | None = None, ties: str = "id") -> MergeTree:
    """The tree of merges.

    ``zero_weight='pair'`` also pairs parts that the matching leaves over, in id order, so
    every level halves their number; ``'stop'`` ends when no edge is left between parts, and
    each root finishes alone. ``parent``: the larger id, the smaller id, or the larger part
    by ``sizes``. The meta-graph comes to the driver: n(n-1)/2 rows at most; for more parts
    than a driver holds, use ``merge_tree_distributed``.
    """
    rows = [tuple(r)[-3:] for r in meta.collect()] if isinstance(meta, DataFrame) else list(meta)
    weigh, rng = dict(sizes or {}), random.Random(seed)

    def lead(a: int, b: int) -> int:
        if parent == "smaller":
            return min(a, b)
        if parent == "larger_part":
            return max(a, b, key=lambda p: (weigh.get(p, 0), p))
        return max(a, b)

    tree, live, level = MergeTree(sorted(parts)), sorted(parts), 0
    while len(live) > 1:
        pairs = _match(rows, strategy, rng, ties)
        if zero_weight == "pair":
            used = {p for a, b, _ in pairs for p in (a, b)}
            idle = [p for p in live if p not in used]
            pairs += [(a, b, 0) for a, b in zip(idle[::2], idle[1::2], strict=False)]
        if not pairs:
            break
        merged: dict[int, int] = {}
        for a, b, w in pairs:
            top = lead(a, b)
            tree.merges.append((level, a, b, top, w))
            merged |= {a: top, b: top}
            weigh[top] = weigh.get(a, 0) + weigh.get(b, 0)
        rows, live, level = rebuild_meta(rows, merged), sorted({merged.get(p, p) for p in live}), level + 1
    return tree


def merge_tree_distributed(meta: DataFrame, parts: list[int], ties: str = "id") -> MergeTree:
    """As ``merge_tree`` with its defaults, but the meta-graph stays in the cluster and only
    the matched pairs, n/2 a level at most, come to the driver. Idle parts are paired, so the
    number of parts halves with every level."""
    tree, live, level = MergeTree(sorted(parts)), sorted(parts), 0
    rows, spark = meta.select("a", "b", "weight"), meta.sparkSession
    while len(live) > 1:
        pairs = greedy_matching([(r["a"], r["b"], r["weight"]) for r in greedy_matching_distributed(rows, ties).collect()], ties)
        used = {p for a, b, _ in pairs for p in (a, b)}
        idle = [p for p in live if p not in used]
        pairs += [(a, b, 0) for a, b in zip(idle[::2], idle[1::2], strict=False)]
        merged = {p: max(a, b) for a, b, _ in pairs for p in (a, b)}
        tree.merges += [(level, a, b, max(a, b), w) for a, b, w in pairs]
        step = list(merged.items())
        rows = rows.join(lookup(spark, step, "a int, na int"), "a", "left").join(lookup(spark, step, "b int, nb int"), "b", "left")
        rows = rows.select(F.coalesce("na", "a").alias("x"), F.coalesce("nb", "b").alias("y"), "weight").where("x <> y")
        rows = stage(rows.groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.sum("weight").alias("weight")), "meta")
        live, level = sorted({merged.get(p, p) for p in live}), level + 1
    return tree


#: Meta-edges that a driver takes; a meta-graph of more stays in the cluster.
DRIVER_META = 500_000


def tree_for(g: Graph, parts: list[int], strategy: str = "greedy", zero_weight: str = "pair") -> MergeTree:
    """The merge tree of a graph: on the driver while n(n-1)/2 meta-edges fit there, else in
    rounds on the cluster, with ties by digest."""
    n = len(parts)
    if n * (n - 1) // 2 <= DRIVER_META:
        return merge_tree(meta_graph(g), parts, strategy, zero_weight)
    if (strategy, zero_weight) != ("greedy", "pair"):
        raise ValueError(f"{n} parts: only the greedy tree with paired idle parts is built on the cluster")
    return merge_tree_distributed(meta_graph(g), parts, "digest")


def join_levels(g: Graph, tree: MergeTree) -> DataFrame:
    """eid, u, v, pu, pv, join_level: the level at which both ends lie in one part.

    An edge between roots of a forest never joins; its level is null (none exists if the tree
    was built to its end). The map of parts is small: a row a leaf.
    """
    maps, spark = tree.maps(), g.edges.sparkSession
    rows = [(p, [m[p] for m in maps]) for p in tree.parts]
    both = split_edges(g).join(lookup(spark, rows, "pu int, xu array<int>"), "pu").join(lookup(spark, rows, "pv int, xv array<int>"), "pv")
    level = F.array_position(F.zip_with("xu", "xv", lambda a, b: a == b), True) - 1
    return both.select("eid", "u", "v", "pu", "pv", F.when(level >= 0, level).cast("int").alias("join_level"))


def with_holders(levelled: DataFrame, tree: MergeTree) -> DataFrame:
    """``levelled`` and ``holder``: the leaf part that keeps the one copy of a remote edge.

    Of the two subtrees that an edge joins, the heavier one drops it: the one with more remote
    edges just before they merge, and of equal ones that of the smaller id. What a subtree has
    is summed from its leaves: a row a leaf and level comes to the driver. Edges inside a part
    are held there.
    """
    side = F.explode(F.array(F.struct(F.col("pu").alias("leaf"), "join_level"), F.struct(F.col("pv").alias("leaf"), "join_level")))
    ends = levelled.where("join_level > 0").select(side.alias("e")).groupBy("e.leaf", "e.join_level").count().collect()
    maps, rows = tree.maps(), []
    for join in range(1, tree.height + 1):
        top, weight = maps[join - 1], {}
        for r in ends:
            if r["join_level"] >= join:
                weight[top[r["leaf"]]] = weight.get(top[r["leaf"]], 0) + r["count"]
        rows += [(leaf, join, top[leaf], weight.get(top[leaf], 0)) for leaf in tree.parts]
    left, right = (lookup(levelled.sparkSession, rows, f"p{x} int, join_level int, t{x} int, w{x} long") for x in "uv")
    both = levelled.join(left, ["pu", "join_level"], "left").join(right, ["pv", "join_level"], "left")
    drops_u = (F.col("wu") > F.col("wv")) | ((F.col("wu") == F.col("wv")) & (F.col("tu") < F.col("tv")))
    return both.select(*[levelled[c] if c not in ("pu", "pv", "join_level") else F.col(c) for c in levelled.columns], F.when(drops_u, F.col("pv")).otherwise(F.col("pu")).alias("holder"))


def retire_levels(levelled: DataFrame) -> DataFrame:
    """(v, retire_level): the last level at which an edge of the vertex joins."""
    return levelled.select(F.explode(F.array("u", "v")).alias("v"), "join_level").groupBy("v").agg(F.max("join_level").alias("retire_level"))
