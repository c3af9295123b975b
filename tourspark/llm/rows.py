"""Rows of (id, text) on their way through Python and back."""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator
from typing import Any

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tourspark.session import ship, stage

#: Rows of one key beyond which they are dealt over several cells of a join.
CELL = 512


def text_rows(docs: DataFrame, id_col: str, text: str, *more: Column, empty: bool = False) -> DataFrame:
    """id, t and more columns of every row, whatever other columns ``docs`` has.

    The id goes as text, since pandas turns numbers with nulls among them into floats.
    ``empty``: null texts become empty ones.
    """
    ship(docs.sparkSession)
    body = F.coalesce(F.col(text), F.lit("")) if empty else F.col(text)
    return docs.select(F.col(id_col).cast("string").alias("id"), *more, body.alias("t"))


def few_rows(batches: Iterator[pd.DataFrame], most: int) -> Iterator[pd.DataFrame]:
    """All rows of the batches in turn, ``most`` at a time, so that what is made from them is
    not held for a whole batch."""
    for rows in batches:
        for at in range(0, len(rows), most):
            yield rows.iloc[at : at + most]


def named(made: DataFrame, docs: DataFrame, id_col: str) -> DataFrame:
    """``made`` with its id in the type and under the name that it has in ``docs``."""
    rest = [c for c in made.columns if c != "id"]
    return made.select(F.col("id").cast(docs.schema[id_col].dataType).alias(id_col), *rest)


def fresh(name: str, columns: list[str]) -> str:
    """``name``, or a longer one that isn't among ``columns``."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name += "_"
    return name


def join_spread(many: DataFrame, one: DataFrame, key: str, size: str, most: int = CELL, spread: list[str] | None = None) -> DataFrame:
    """``many`` joined with ``one``, which has a row a key and in ``size`` how many rows of
    ``many`` have that key; ``size`` is dropped.

    A key of more than ``most`` rows is dealt over cells by its rows' digests, and its row of
    ``one`` is repeated for each cell, so no task gets a hot key whole. ``spread``: the columns
    whose digest deals the rows, all if none are named. The table of hot keys
    has a row for ``most`` rows at the least; the engine broadcasts it while it is small and
    splits the join where it isn't.
    """
    tiles = F.ceil(F.col(size) / most).cast("int")
    hot = stage(one.where(F.col(size) > most).select(key, tiles.alias("__tiles")), "hot")
    cell = F.coalesce(F.pmod(F.xxhash64(*(spread or many.columns)), F.col("__tiles")), F.lit(0)).cast("int")
    dealt = many.join(hot, key, "left").withColumn("__cell", cell).drop("__tiles")
    copies = one.withColumn("__cell", F.explode(F.sequence(F.lit(0), F.greatest(tiles - 1, F.lit(0))))).drop(size)
    return dealt.join(copies, [key, "__cell"]).drop("__cell")


class Packed:
    """A model as bytes, for the driver to hand on: what is unpickled elsewhere is the model."""

    def __init__(self, data: bytes):
        self.data = data

    def __reduce__(self) -> tuple:
        return pickle.loads, (self.data,)

    def open(self) -> Any:
        return pickle.loads(self.data)


def in_one_task(rows: DataFrame, make: Callable[[pd.DataFrame], Any]) -> Packed | None:
    """What ``make`` makes of all ``rows``, which are in one partition, made in its task; none
    if there are no rows. Rows must be bounded by their caller."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = [b for b in batches if len(b)]
        if held:
            yield pd.DataFrame({"made": [pickle.dumps(make(pd.concat(held, ignore_index=True)), pickle.HIGHEST_PROTOCOL)]})

    found = rows.mapInPandas(run, "made binary").collect()
    return Packed(bytes(found[0]["made"])) if found else None
