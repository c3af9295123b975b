"""Matchings and merge trees, on the driver and in rounds."""

import random

import pytest

from tourspark.plans.metagraph import greedy_matching, greedy_matching_distributed, merge_tree, merge_tree_distributed, rebuild_meta

WORKED = [(1, 2, 1), (2, 4, 1), (3, 4, 2), (1, 4, 1)]


def test_worked_tree():
    tree = merge_tree(WORKED, [1, 2, 3, 4])
    assert [m[:4] for m in tree.merges] == [(0, 3, 4, 4), (0, 1, 2, 2), (1, 2, 4, 4)]
    assert tree.height == 2
    assert tree.maps()[1] == {1: 2, 2: 2, 3: 4, 4: 4}


def test_rebuild_sums_parallel_edges():
    assert rebuild_meta(WORKED, {1: 2, 2: 2, 3: 4, 4: 4}) == [(2, 4, 2)]


def test_no_edges_between_parts_ends():
    assert merge_tree([], [0, 1, 2, 3, 4]).height == 3
    assert merge_tree([], [0, 1, 2], zero_weight="stop").merges == []


def test_a_star_takes_a_logarithm_of_levels_when_idle_parts_are_paired():
    star = [(0, i, 1) for i in range(1, 8)]
    assert merge_tree(star, list(range(8))).height == 3
    assert merge_tree(star, list(range(8)), zero_weight="stop").height == 7


@pytest.mark.parametrize("n", [1, 2, 3, 4, 5, 8, 13, 16])
def test_height(n):
    assert merge_tree([], list(range(n))).height == (n - 1).bit_length()


def test_parents():
    assert merge_tree([(0, 1, 1)], [0, 1], parent="smaller").merges[0][3] == 0
    assert merge_tree([(0, 1, 1)], [0, 1], parent="larger_part", sizes={0: 9, 1: 2}).merges[0][3] == 0


def test_matching_in_rounds_equals_the_greedy_one(spark):
    rng = random.Random(3)
    rows = [(a, b, rng.randint(1, 5)) for a in range(14) for b in range(a + 1, 14) if rng.random() < 0.5]
    found = greedy_matching_distributed(spark.createDataFrame(rows, "a int, b int, weight long"))
    assert sorted(map(tuple, found.collect())) == sorted(greedy_matching(rows))


def test_tree_in_rounds_equals_the_driver_one(spark):
    rng = random.Random(5)
    rows = [(a, b, rng.randint(1, 9)) for a in range(7) for b in range(a + 1, 7) if rng.random() < 0.6]
    found = merge_tree_distributed(spark.createDataFrame(rows, "a int, b int, weight long"), list(range(7)))
    assert found.merges == merge_tree(rows, list(range(7))).merges
