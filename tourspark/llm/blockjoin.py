"""Nearest neighbours by a block matrix join.

Vectors are cut to 8 bits a component, each with its own scale. A tile of queries times a
tile of candidates is an exact integer matrix product of the 8-bit forms; with the scales
it approximates the inner products, and the lengths of what was cut off bound the error:
|x.y - x'.y'| <= |x'| |ey| + |ex| |y|. A candidate whose upper bound is below the query's
k-th best lower bound is gone; the others are recomputed on the original doubles, and a
heap of k rows a query merges the tiles.

A cell of work is a chunk of queries with a share of the candidates. Its rows stream
through one task, queries first, so memory holds the chunk and one batch. What is moved is
every candidate once for each chunk of queries: rows times chunks.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark.llm.vectors import best, common_width, dots, matrix, usable
from tourspark.session import stage


class Cut:
    """8-bit forms of rows: integers (as floats, in which their products are exact), scales,
    lengths of the forms, of the rows, and of what was cut off."""

    def __init__(self, x: np.ndarray):
        top = np.abs(x).max(axis=1)
        self.scale = np.where(top > 0, top, 1.0) / 127.0
        self.q = np.rint(x / self.scale[:, None]).astype(np.int8)
        form = self.q * self.scale[:, None]
        self.form, self.full = np.sqrt((form**2).sum(axis=1)), np.sqrt((x**2).sum(axis=1))
        self.off = np.sqrt(((x - form) ** 2).sum(axis=1))


def tile_bounds(a: Cut, b: Cut) -> tuple[np.ndarray, np.ndarray]:
    """(approximate products, error bounds) of every row of ``a`` with every row of ``b``."""
    product = (a.q.astype(np.float32) @ b.q.astype(np.float32).T).astype(np.float64)  # below 2^24: exact
    near = product * a.scale[:, None] * b.scale[None, :]
    error = a.form[:, None] * b.off[None, :] + a.off[:, None] * b.full[None, :]
    return near, error * (1 + 1e-9) + 1e-9 * (a.full[:, None] * b.full[None, :] + 1e-300)


class Heaps:
    """The k best candidates of each query so far: larger score, then smaller id."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, k: int):
        self.ids, self.x, self.cut, self.k = ids, x, Cut(x), k
        self.score = np.full((len(ids), k), -np.inf)
        self.near = np.full((len(ids), k), np.iinfo(np.int64).max)

    def offer(self, ids: np.ndarray, y: np.ndarray, rows: int = 256) -> None:
        cut = Cut(y)
        for at in range(0, len(self.ids), rows):
            part = slice(at, at + rows)
            a = Cut.__new__(Cut)
            for f in ("scale", "q", "form", "full", "off"):
                setattr(a, f, getattr(self.cut, f)[part])
            near, error = tile_bounds(a, cut)
            own = self.ids[part, None] == ids[None, :]
            low = np.where(own, -np.inf, near - error)
            kept = min(self.k, low.shape[1])
            floor = np.maximum(self.score[part].min(axis=1), np.partition(low, -kept, axis=1)[:, -kept] if kept == self.k else -np.inf)
            i, j = np.nonzero((near + error >= floor[:, None]) & ~own)
            if len(i):
                self._merge(at + i, ids[j], dots(self.x[at + i], y[j]))

    def _merge(self, row: np.ndarray, ids: np.ndarray, score: np.ndarray) -> None:
        touched = np.unique(row)
        row = np.r_[row, np.repeat(touched, self.k)]
        ids = np.r_[ids, self.near[touched].ravel()]
        score = np.r_[score, self.score[touched].ravel()]
        order = np.lexsort((ids, -score, row))
        row, ids, score = row[order], ids[order], score[order]
        first = np.flatnonzero(np.r_[True, row[1:] != row[:-1]])
        place = np.arange(len(row)) - np.repeat(first, np.diff(np.r_[first, len(row)]))
        keep = place < self.k
        self.score[row[keep], place[keep]], self.near[row[keep], place[keep]] = score[keep], ids[keep]

    def rows(self, copy: np.ndarray) -> pd.DataFrame:
        i, j = np.nonzero(np.isfinite(self.score))
        return pd.DataFrame({"query_id": self.ids[i], "copy": copy[i], "vec_id": self.near[i, j], "score": self.score[i, j]})


def neighbours(
    table: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", every: int = 20, k: int = 20,
    query_rows: int = 16384, share_rows: int = 8192, most_shares: int = 256,
) -> DataFrame:
    """The k nearest rows (query_id, rank, vec_id, score) for each row whose id ``every`` divides.

    ``score`` is the inner product in doubles, summed in order of the components. The result
    is exact. Vectors that are null, empty, zero, hold null or non-finite components, or are
    not of the commonest length take no part, nor do null ids. A repeated id counts once for
    each row, never for itself. Ties go to the smaller id; no rows give no rows.
    """
    rows = stage(usable(table, id_col, vec_col, nonzero=True), "tiles-rows")
    n, width = common_width(rows)
    if not n:
        return rows.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    rows = rows.where(F.size("vec") == width)
    asked = rows.where(F.col("id") % every == 0)
    chunks = max(1, math.ceil(asked.count() / query_rows))
    shares = min(most_shares, max(1, math.ceil(n / share_rows)))
    pick = lambda m, *c: F.pmod(F.xxhash64(*c), F.lit(m)).cast("int")
    one = asked.withColumn("chunk", pick(chunks, "id", "vec")).withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(shares - 1))))
    two = rows.withColumn("share", pick(shares, "id", "vec")).withColumn("chunk", F.explode(F.sequence(F.lit(0), F.lit(chunks - 1))))
    both = one.withColumn("side", F.lit(0)).unionByName(two.withColumn("side", F.lit(1))).select(
        (F.col("chunk").cast("long") * shares + F.col("share")).alias("cell"), "side", "id", "vec",
    )

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        cell, asks, heaps = None, [], None

        def opened():
            whole = pd.concat(asks)
            return Heaps(whole["id"].to_numpy(), matrix(whole["vec"]), k)

        for batch in batches:
            for own, part in batch.groupby("cell", sort=True):
                if own != cell:
                    if heaps:
                        yield heaps.rows(np.arange(len(heaps.ids)) + (cell // shares << 32))
                    cell, asks, heaps = own, [], None
                q, c = part[part["side"] == 0], part[part["side"] == 1]
                if len(q):
                    asks.append(q)
                if len(c) and asks:
                    heaps = heaps or opened()
                    heaps.offer(c["id"].to_numpy(), matrix(c["vec"]))
        if heaps:
            yield heaps.rows(np.arange(len(heaps.ids)) + (cell // shares << 32))

    dealt = both.repartition(chunks * shares, "cell").sortWithinPartitions("cell", "side", "id", "vec")
    return best(dealt.mapInPandas(run, "query_id long, copy long, vec_id long, score double"), k)


ORACLE = """
WITH v AS (
  SELECT vec_id, CAST(embedding AS DOUBLE[]) AS vec FROM embeddings
  WHERE embedding IS NOT NULL AND vec_id IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    AND len(list_filter(embedding, lambda x: x <> 0)) > 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.vec, c.vec) AS score
  FROM v q JOIN v c ON q.vec_id % 20 = 0 AND c.vec_id <> q.vec_id
)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM scored) WHERE rank <= 20
"""
