"""The next row of a ring, where a ring may hold more rows than a task should sort."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def with_next(df: DataFrame, key: list[str], order: list[str], block: Column, columns: dict[str, str]) -> DataFrame:
    """``df`` and, under new names, ``columns`` of the row that comes next in its key's ring.

    Rows go by block, then by ``order``, and the last is followed by the first. A task sorts
    one block of a key; the blocks' first rows, one each, lead from block to block.
    """
    rows = df.withColumn("__block", block)
    here = F.struct(*[F.col(c).alias(f"c{i}") for i, c in enumerate(columns)])
    own = Window.partitionBy(*key, "__block").orderBy(*order)
    firsts = rows.groupBy(*key, "__block").agg(F.min(F.struct(*[F.col(c).alias(f"o{i}") for i, c in enumerate(order)], here.alias("row"))).alias("f"))
    ring = Window.partitionBy(*key).orderBy("__block")
    whole = ring.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    onward = firsts.select(*key, "__block", F.coalesce(F.lead("f.row").over(ring), F.first("f.row").over(whole)).alias("__onward"))
    both = rows.withColumn("__lead", F.lead(here).over(own)).join(onward, [*key, "__block"])
    found = F.coalesce("__lead", "__onward")
    return both.select(*df.columns, *[found[f"c{i}"].alias(new) for i, new in enumerate(columns.values())])
