import random

import pytest

from relpress.model import Relation
from relpress.operators import compression, mining

from .fixtures import EXAMPLE, X, brute_closed, brute_frequent, brute_maximal, example, sets_of


@pytest.mark.parametrize("s_min, n_frequent, n_closed, n_maximal", [(2, 65, 23, 11), (3, 25, 13, 8), (4, 11, 7, 3), (5, 7, 5, 3)])
def test_example_counts(spark, s_min, n_frequent, n_closed, n_maximal):
    rel = example(spark)
    sets = mining.frequent(rel, s_min)
    freq = brute_frequent(EXAMPLE, s_min)
    assert sets_of(sets) == set(freq.items()) and sets.count() == n_frequent
    assert sets_of(mining.closed(sets)) == brute_closed(freq) == sets_of(mining.closed_shards(rel, s_min))
    assert sets_of(mining.maximal(sets)) == brute_maximal(freq) == sets_of(mining.maximal_shards(rel, s_min))
    assert (len(brute_closed(freq)), len(brute_maximal(freq))) == (n_closed, n_maximal)


def test_levelwise_equals_cube(spark):
    rel = example(spark)
    assert sets_of(mining.frequent_levelwise(rel, 2)) == sets_of(mining.frequent(rel, 2))
    assert sets_of(mining.frequent_levelwise(rel, 2, 2)) == sets_of(mining.frequent(rel, 2, 2))


def test_random_relations_agree(spark):
    rng = random.Random(3)
    for _ in range(2):
        rows = list({tuple(rng.randrange(3) for _ in range(4)) for _ in range(25)})
        rel = Relation.of(spark.createDataFrame(rows, "a int, b int, c int, d int"))
        freq = brute_frequent(rows, 2)
        for most_rows in (1000, 8, 3):  # whole shards, and shards split once and more
            assert sets_of(mining.closed_shards(rel, 2, most_rows)) == brute_closed(freq)
            assert sets_of(mining.maximal_shards(rel, 2, most_rows)) == brute_maximal(freq)


def test_thresholds(spark):
    closed = compression.candidates(example(spark), 2, "closed").cache()
    assert mining.threshold(closed, 10, "min") == 3
    assert mining.threshold(closed, 10, "mean") == 5  # 4.5 rounded up
    assert mining.threshold(closed, 14, "min") == 2
    assert mining.threshold(closed, 0) == 2 and mining.threshold(closed, 10_000, "min") == 2
    assert mining.count_of(0.2, 3) == 1 and mining.count_of(7, 3) == 7
    assert [r["freq"] for r in mining.top(closed, 10).orderBy("freq", ascending=False).collect()] == [7, 6, 5, 5, 5, 4, 4, 3, 3, 3]
    assert mining.top(closed, 8, ties="include").count() == 13
    assert {(r["threshold"], r["n_sets"]) for r in mining.curve(closed, [2, 3, 4, 5, 99]).collect()} == {(2, 23), (3, 13), (4, 7), (5, 5), (99, 0)}


def test_edges(spark):
    empty = Relation(spark.createDataFrame([], ", ".join(f"{c} int" for c in X)), X)
    one = Relation.of(spark.createDataFrame([(1, 2)], "a int, b int"))
    for rel in (empty, one):
        for sets in (mining.frequent(rel, 2), mining.closed_shards(rel, 2), mining.maximal_shards(rel, 2), mining.frequent_levelwise(rel, 2)):
            assert sets.count() == 0
    assert mining.frequent(example(spark), 12).count() == 0
    twice = Relation.of(spark.createDataFrame([(1,), (1,), (2,)], "a int"))
    assert twice.df.count() == 2
