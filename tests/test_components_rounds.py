"""Rings numbered in turn, as tours and runs of a hub are: few rounds, and the same names."""

from pyspark.sql import functions as F

from tourspark.plans.components import min_label_components


def test_a_ring_numbered_in_turn_settles_in_few_rounds(spark):
    n = 3000
    ring = spark.range(n).select((F.col("id") + 5).alias("u"), ((F.col("id") + 1) % n + 5).alias("v"))
    two = spark.createDataFrame([(9000, 8999), (4, 4)], "u long, v long")
    found = min_label_components(ring.unionByName(two), max_rounds=14)
    counted = {tuple(r) for r in found.groupBy("comp").agg(F.count("*"), F.min("v")).collect()}
    assert counted == {(5, n, 5), (8999, 2, 8999), (4, 1, 4)}


def test_runs_of_a_hub_numbered_in_turn_are_ranked(spark):
    """One ring of 400 runs, each followed by the one numbered next, as at a hub of pairs."""
    from tourspark.plans.phase3 import rank_doubling

    runs = spark.range(400).select(F.col("id").alias("walk"), F.lit(0).cast("long").alias("start"), F.lit(2).cast("long").alias("size"), (F.col("id") + 3).alias("low"), ((F.col("id") + 1) % 400).alias("next_walk"), F.lit(0).cast("long").alias("next_start"))
    found = sorted(map(tuple, rank_doubling(runs).collect()))
    assert found == [(i, 0, 3, 2 * i) for i in range(400)]
