"""What the two vector searches share: valid vectors, cells of work, and exact sums."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def finite(vec: Column) -> Column:
    """Whether a vector is there and holds finite components only."""
    bad = F.exists(vec, lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == float("inf")))
    return vec.isNotNull() & (F.size(vec) > 0) & ~bad


def usable(table: DataFrame, id_col: str, vec_col: str, nonzero: bool) -> DataFrame:
    """(id, vec): rows with an id and a finite vector of doubles, of the commonest length."""
    keep = finite(F.col(vec_col)) & F.col(id_col).isNotNull()
    if nonzero:
        keep &= F.exists(vec_col, lambda x: x != 0)
    return table.where(keep).select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("vec"))


def common_width(rows: DataFrame) -> tuple[int, int]:
    """(rows, length): how many rows have the commonest vector length, and that length."""
    top = rows.groupBy(F.size("vec").alias("w")).count().orderBy(F.desc("count"), "w").limit(1).collect()
    return (top[0]["count"], top[0]["w"]) if top else (0, 0)


def matrix(column: pd.Series) -> np.ndarray:
    return np.stack(column.to_numpy()) if len(column) else np.zeros((0, 0))


def dots(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row-wise inner products, summed component by component in order."""
    total = np.zeros(len(a))
    for j in range(a.shape[1]):
        total += a[:, j] * b[:, j]
    return total


def best(found: DataFrame, k: int) -> DataFrame:
    """The k best rows of each query: larger score, then smaller id. The engine cuts each
    task's rows to k a query before they are shuffled."""
    order = Window.partitionBy("query_id", "copy").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
