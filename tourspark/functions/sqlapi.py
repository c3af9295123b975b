"""The methods in SQL: table functions, aggregates and scalar functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf
from pyspark.sql.types import LongType

from tourspark.plans.baselines import closed_tour
from tourspark.plans.metagraph import merge_tree
from tourspark.session import ship


@F.pandas_udf(LongType())
def edge_mark(u: pd.Series, v: pd.Series) -> pd.Series:
    """A number for an edge, in batches."""
    return u * 31 + v


@F.pandas_udf(LongType())
def walk_checksum(v: pd.Series) -> int:
    """A checksum of the vertices of a group."""
    return int(v.sum() % 1_000_003)


@udtf(returnType="comp long, pos long, eid long, src long, dst long")
class CircuitOf:
    """circuit_of(TABLE(edges) PARTITION BY comp): a closed tour of each component that a
    task can hold. Columns of the input: comp, eid, u, v."""

    def __init__(self):
        self.rows: list[tuple[int, int, int]] = []
        self.comp = None

    def eval(self, row):
        self.comp = row["comp"]
        self.rows.append((row["eid"], row["u"], row["v"]))

    def terminate(self):
        if self.rows:
            eid, u, v = np.array(sorted(self.rows), np.int64).T
            for pos, (_, e, a, b) in enumerate(closed_tour(eid, u, v)):
                yield self.comp, pos, e, a, b


@udtf(returnType="level int, child_a int, child_b int, parent int, weight long")
class MergeTreeOf:
    """merge_tree_of(TABLE(weights) WITH SINGLE PARTITION): merges from (a, b, weight)."""

    def __init__(self):
        self.rows: list[tuple[int, int, int]] = []

    def eval(self, row):
        self.rows.append((row["a"], row["b"], row["weight"]))

    def terminate(self):
        yield from merge_tree(self.rows, sorted({p for a, b, _ in self.rows for p in (a, b)})).merges


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.udtf.register("circuit_of", CircuitOf)
    spark.udtf.register("merge_tree_of", MergeTreeOf)
    spark.udf.register("edge_mark", edge_mark)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION is_even_degree(d BIGINT) RETURNS BOOLEAN RETURN d % 2 = 0")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION join_level(x ARRAY<INT>, y ARRAY<INT>) RETURNS INT RETURN CAST(array_position(zip_with(x, y, (a, b) -> a = b), true) - 1 AS INT)")
