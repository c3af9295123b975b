"""Dense numbering 1..N without a global window."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark.session import stage

#: monotonically_increasing_id holds the task in the bits from here up.
TASK_SHIFT = 33


def dense_number(df: DataFrame, order: list[str], name: str = "n", first: int = 1) -> DataFrame:
    """``df`` with ``name`` = first, first + 1, ... in the order of the given columns.

    Rows are dealt out by ranges and sorted in their range; the place in the range comes from
    the row's position, and the ranges' sizes, one row a range, give the offsets. Rows that
    tie in all columns are numbered in any order, and dealt by where they came from, so that
    many of one kind aren't one range.
    """
    ranged = df.withColumn("__tie", F.monotonically_increasing_id()).repartitionByRange(*order, "__tie").drop("__tie")
    placed = stage(ranged.sortWithinPartitions(*order).withColumn("__at", F.monotonically_increasing_id()), "numbered")
    task = F.shiftright("__at", TASK_SHIFT)
    sizes = placed.groupBy(task.alias("task")).count().orderBy("task").collect()  # one row a task
    starts, total = [], first
    for r in sizes:
        starts.append((r["task"], total))
        total += r["count"]
    known = F.broadcast(df.sparkSession.createDataFrame(starts, "__task long, __first long"))
    place = F.col("__first") + F.col("__at").bitwiseAND(F.lit((1 << TASK_SHIFT) - 1))
    return placed.withColumn("__task", task).join(known, "__task").select(*df.columns, place.alias(name))
