"""Exact top-k search by M-trees.

Maximum inner product becomes nearest neighbour in a metric space: every vector gets one
more coordinate that lifts all of them to the norm R of the longest, and a query gets 0
there; then d(q, x)^2 = |q|^2 + R^2 - 2 q.x. An M-tree pages the vectors: a node holds
entries with their distance to the node's own pivot (the parent distance), and inner
entries also a covering radius. A search takes pages from a queue by lower bound. Within a
page the stored parent distances rule out entries by the triangle inequality before any
distance to them is computed; a page whose bound exceeds the k-th best distance ends the
search. Bounds are widened by a slack far above rounding, and scores are exact integers, so
no true answer, ties included, is pruned.

The table is cut into blocks around pivots, one tree a block. A query first searches the
block whose pivot is nearest; then only blocks whose ball reaches its k-th best distance.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark.llm.vectors import best, common_width, matrix, usable
from tourspark.session import stage

SLACK = 1e-6
SEED = 7


class Page:
    """A node: entry rows (or pivots), parent distances, and for inner nodes radii and children."""

    __slots__ = ("points", "parent", "radius", "child", "ids")

    def __init__(self, points, parent, radius=None, child=None, ids=None):
        self.points, self.parent, self.radius, self.child, self.ids = points, parent, radius, child, ids


class MTree:
    """A bulk-loaded M-tree over lifted vectors; ``capacity`` entries a page."""

    def __init__(self, ids: np.ndarray, points: np.ndarray, capacity: int = 256):
        self.capacity, self.pages = capacity, []
        pivot = points.mean(axis=0) if len(points) else np.zeros(points.shape[1])
        self.root = self._load(ids, points, pivot, np.random.default_rng(SEED))
        self.pivot = pivot

    def _load(self, ids, points, pivot, rng) -> int:
        far = np.sqrt(((points - pivot) ** 2).sum(axis=1))
        at = len(self.pages)
        self.pages.append(None)
        if len(points) <= self.capacity:
            self.pages[at] = Page(points, far, ids=ids)
            return at
        want = min(self.capacity, max(2, math.ceil(2 * len(points) / self.capacity)))
        seeds = points[rng.choice(len(points), want, replace=False)]
        near = ((seeds**2).sum(axis=1) - 2 * points @ seeds.T).argmin(axis=1)
        if (near == near[0]).all():  # copies of one point: any cut is as good
            near = np.arange(len(points)) * want // len(points)
        used = np.unique(near)
        tops, radii, child = [], [], []
        for g in used:
            own = near == g
            top = points[own].mean(axis=0)
            tops.append(top)
            radii.append(math.sqrt(((points[own] - top) ** 2).sum(axis=1).max()))
            child.append(self._load(ids[own], points[own], top, rng))
        tops = np.array(tops)
        self.pages[at] = Page(tops, np.sqrt(((tops - pivot) ** 2).sum(axis=1)), np.array(radii), child)
        return at

    def search(self, q: np.ndarray, k: int, bound: float = math.inf, skip: int | None = None) -> list[tuple[float, int]]:
        """The k nearest (squared distance, id) within ``bound``, and all that tie with the
        last up to the slack; the caller ranks them by exact score."""
        held: list[tuple[float, int]] = []
        heap: list[float] = []  # the k least squared distances, negated
        limit = bound
        queue = [(0.0, self.root, math.sqrt(((q - self.pivot) ** 2).sum()))]
        while queue:
            low, at, to_pivot = heapq.heappop(queue)
            if low > limit + SLACK:
                break
            page = self.pages[at]
            reach = limit + SLACK if page.radius is None else limit + SLACK + page.radius
            pick = np.flatnonzero(np.abs(to_pivot - page.parent) <= reach)
            if not len(pick):
                continue
            gap = page.points[pick] - q
            d2 = np.einsum("ij,ij->i", gap, gap)
            if page.radius is None:
                near = pick[d2 <= (limit + SLACK) ** 2]
                for i, x in zip(near.tolist(), d2[d2 <= (limit + SLACK) ** 2].tolist(), strict=True):
                    own = int(page.ids[i])
                    if own == skip:
                        continue
                    held.append((x, own))
                    if len(heap) < k:
                        heapq.heappush(heap, -x)
                    elif x < -heap[0]:
                        heapq.heapreplace(heap, -x)
                if len(heap) == k:
                    limit = min(limit, math.sqrt(-heap[0]))
            else:
                d = np.sqrt(d2)
                least = np.maximum(0.0, d - page.radius[pick])
                for j in np.flatnonzero(least <= limit + SLACK).tolist():
                    heapq.heappush(queue, (float(least[j]), page.child[pick[j]], float(d[j])))
        return [(x, i) for x, i in held if x <= (limit + SLACK) ** 2]


def lift(points: np.ndarray, top: float) -> np.ndarray:
    rest = np.sqrt(np.maximum(0.0, top - (points**2).sum(axis=1)))
    return np.column_stack([points, rest])


def quantise(table: DataFrame, id_col: str, vec_col: str, scale: int) -> DataFrame:
    rows = usable(table, id_col, vec_col, nonzero=False)
    return rows.select("id", F.transform("vec", lambda x: F.floor(x * scale).cast("double")).alias("vec"))


def top_k(
    table: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", every: int = 50, k: int = 5, scale: int = 256,
    block_rows: int = 8192, most_pivots: int = 2048, query_rows: int = 2048, capacity: int = 256,
) -> DataFrame:
    """The k best rows (query_id, rank, vec_id, score) for each row whose id ``every`` divides.

    Vectors that are null, empty, hold null or non-finite components, or are not of the
    commonest length take no part, nor do null ids. Rows that repeat an id each count as a
    candidate, but never for a query of that id; a repeated query id answers once for each
    row. Ties go to the smaller id. No rows give no rows.
    """
    rows = stage(quantise(table, id_col, vec_col, scale), "mtree-rows")
    n, width = common_width(rows)
    out = "query_id long, copy long, vec_id long, score double"
    if not n:
        return rows.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    rows = rows.where(F.size("vec") == width)
    norm = F.aggregate("vec", F.lit(0.0), lambda a, x: a + x * x)
    top = rows.agg(F.max(norm)).first()[0]
    # pivots: the rows first in hash order, at most most_pivots of them, whatever the table's size
    pivots = matrix(pd.Series([r["vec"] for r in rows.select("vec").orderBy(F.xxhash64("id", "vec"), "id").limit(min(most_pivots, max(1, n // block_rows))).collect()]))
    pivots = lift(pivots, top)

    def route(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in batches:
            x = lift(matrix(part["vec"]), top)
            d2 = np.maximum(0, (x**2).sum(axis=1)[:, None] + (pivots**2).sum(axis=1)[None, :] - 2 * x @ pivots.T)
            yield pd.DataFrame({"id": part["id"], "vec": part["vec"], "block": d2.argmin(axis=1), "far": np.sqrt(d2.min(axis=1))})

    placed = stage(rows.mapInPandas(route, "id long, vec array<double>, block long, far double"), "mtree-placed")
    # the directory: one row a pivot, so its size is bounded by most_pivots
    directory = placed.groupBy("block").agg(F.count("*").alias("n"), F.max("far").alias("radius")).orderBy("block").collect()
    blocks = np.array([r["block"] for r in directory])
    radius = np.array([r["radius"] for r in directory])
    parts = {int(r["block"]): max(1, math.ceil(r["n"] / block_rows)) for r in directory}
    centres = pivots[blocks]

    asked = placed.where(F.col("id") % every == 0)
    queries = stage(asked.select(F.col("id").alias("query_id"), F.row_number().over(_by_id()).cast("long").alias("copy"), "vec", "block"), "mtree-queries")
    per_block = lambda rows, name: F.broadcast(placed.sparkSession.createDataFrame(list(rows.items()), f"block long, {name} int"))  # noqa: E731  a row a pivot
    # a cell is a slice of a block with a chunk of its queries; hot blocks have many slices
    slices = placed.join(per_block(parts, "n_slices"), "block").select(
        "id", "vec", "block", F.pmod(F.xxhash64("id", "vec", F.monotonically_increasing_id()), F.col("n_slices")).cast("int").alias("slice"),
    )
    slices = stage(slices, "mtree-slices")

    def answer(cell, asks: pd.DataFrame, own: pd.DataFrame) -> pd.DataFrame:
        if not len(asks) or not len(own):
            return pd.DataFrame({"query_id": [], "copy": [], "vec_id": [], "score": []})
        raw = matrix(own["vec"])
        ids = own["id"].to_numpy()
        tree = MTree(np.arange(len(ids)), lift(raw, top), capacity)
        got: list[tuple[int, int, int, float]] = []
        for qid, copy, vec, bound in zip(asks["query_id"].tolist(), asks["copy"].tolist(), asks["vec"], asks["bound"].tolist(), strict=True):
            q = np.append(vec, 0.0)
            # rows with the query's own id are left out, so ask for that many more
            spare = int((ids == qid).sum())
            near = np.array([i for _, i in tree.search(q, k + spare, bound)], int)
            near = near[ids[near] != qid]
            score = raw[near] @ np.asarray(vec)
            order = np.lexsort((ids[near], -score))[:k]
            got += [(qid, copy, int(ids[near[o]]), float(score[o])) for o in order]
        return pd.DataFrame(got, columns=["query_id", "copy", "vec_id", "score"])

    def run(asks: DataFrame) -> DataFrame:
        """asks: query_id, copy, vec, block, bound. A block's rows are sent once for each
        chunk of the queries that ask it, and not at all if none does."""
        wanted = {r["block"]: max(1, math.ceil(r["count"] / query_rows)) for r in asks.groupBy("block").count().collect()}
        if not wanted:
            return asks.sparkSession.createDataFrame([], out)
        sizes = {b: (parts[b], n) for b, n in wanted.items()}
        known = F.broadcast(asks.sparkSession.createDataFrame([(b, s, n) for b, (s, n) in sizes.items()], "block long, n_slices int, n_chunks int"))
        upto = lambda c: F.explode(F.sequence(F.lit(0), F.col(c) - 1))
        dealt = asks.join(known, "block").withColumn("chunk", F.pmod(F.xxhash64("query_id", "copy"), F.col("n_chunks")).cast("int"))
        spread = dealt.withColumn("slice", upto("n_slices")).drop("n_slices", "n_chunks")
        copies = slices.join(known, "block").withColumn("chunk", upto("n_chunks")).drop("n_slices", "n_chunks")
        key = ["block", "slice", "chunk"]
        return spread.groupBy(*key).cogroup(copies.groupBy(*key)).applyInPandas(answer, out)

    first = stage(best_rows(run(queries.withColumn("bound", F.lit(math.inf))), k), "mtree-first")
    worst = first.groupBy("query_id", "copy").agg(F.count("*").alias("n"), F.min("score").alias("low"))

    def remaining(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in batches:
            q = np.column_stack([matrix(part["vec"]), np.zeros(len(part))])
            d2 = np.maximum(0, (q**2).sum(axis=1)[:, None] + (centres**2).sum(axis=1)[None, :] - 2 * q @ centres.T)
            reach = np.where(part["n"].fillna(0).to_numpy() >= k, np.sqrt(np.maximum(0, (q**2).sum(axis=1) + top - 2 * part["low"].fillna(0).to_numpy())), math.inf)
            # rounding of the product form is far below this slack
            i, j = np.nonzero((np.sqrt(d2) - radius[None, :] <= reach[:, None] + 1e-3) & (blocks[None, :] != part["block"].to_numpy()[:, None]))
            yield pd.DataFrame({"query_id": part["query_id"].to_numpy()[i], "copy": part["copy"].to_numpy()[i], "vec": part["vec"].to_numpy()[i], "block": blocks[j], "bound": reach[i]})

    rest = queries.join(worst, ["query_id", "copy"], "left").mapInPandas(remaining, "query_id long, copy long, vec array<double>, block long, bound double")
    every_row = first.unionByName(run(stage(rest, "mtree-rest")))
    return best(every_row, k).withColumn("score", F.col("score").cast("long"))


def _by_id():
    from pyspark.sql import Window

    return Window.partitionBy("id").orderBy("vec")


def best_rows(found: DataFrame, k: int) -> DataFrame:
    """As ``best``, with the query's copy number kept."""
    from pyspark.sql import Window

    order = Window.partitionBy("query_id", "copy").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).drop("rank")


ORACLE = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS DOUBLE)) AS vec FROM embeddings
  WHERE embedding IS NOT NULL AND vec_id IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.vec, c.vec) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id
)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM scored) WHERE rank <= 5
"""
