"""Buckets, cycles of pointers, and what rests on them."""

import pytest
from micro import clique, graph
from pyspark.sql import functions as F

from sparkgraphs.algo import covering, relax
from sparkgraphs.core.buckets import Buckets
from sparkgraphs.core.contract import has_cycle
from sparkgraphs.core.rounds import Rounds, RunStats


def test_buckets_come_in_order_and_follow_updates(spark):
    rows = spark.createDataFrame([(1, 5), (2, 3), (3, 3), (4, None)], "v bigint, d bigint")
    held = Buckets(Rounds(spark, "t"), F.col("d")).put(rows)
    got = lambda: (held.next()[0], sorted(r.v for r in held.next()[1].collect()))
    assert got() == (3, [2, 3])
    held.update(spark.createDataFrame([(2, 9), (3, None)], "v bigint, d bigint"), "v")
    assert got() == (5, [1])
    held.update(spark.createDataFrame([(1, None), (2, None)], "v bigint, d bigint"), "v")
    assert held.id is None
    assert Buckets(Rounds(spark, "t"), F.col("d"), "max").put(rows).id == 5
    with pytest.raises(ValueError):
        Buckets(Rounds(spark, "t"), F.col("d"), "any")


@pytest.mark.parametrize("pairs, cyclic", [([], False), ([(0, None), (1, 0), (2, 1), (3, 2), (4, 3)], False), ([(0, None), (1, 0), (2, 3), (3, 2)], True), ([(5, 5)], True), ([(i, (i + 1) % 7) for i in range(7)], True)])
def test_cycles_of_pointers(spark, pairs, cyclic):
    assert has_cycle(spark.createDataFrame(pairs, "v bigint, p bigint")) == cyclic


def test_a_negative_cycle_shows_early(spark):
    arcs = [(i, i + 1, 1) for i in range(60)] + [(2, 1, -3)]
    g, stats = graph(spark, arcs, directed=True), RunStats()
    assert {r.dist for r in relax.bellman_ford(g, 0, stats=stats).collect()} == {float("-inf")}
    assert stats.depth <= 10
    assert {r.v: r.dist for r in relax.bellman_ford(g, 5).collect()}[9] == 4


def test_zero_cycles_are_no_negative_ones(spark):
    arcs = [(0, 1, 2), (1, 2, -2), (2, 1, 2), (2, 3, 1)] + [(i, i + 1, 1) for i in range(3, 14)]
    found = {r.v: r.dist for r in relax.bellman_ford(graph(spark, arcs, directed=True), 0).collect()}
    assert found[2] == 0 and found[1] == 2 and found[14] == 12


def test_degrees_of_sets_are_refreshed_when_their_bucket_is_taken(spark):
    rows = [(1, e) for e in range(20)] + [(2, e) for e in range(1, 20)] + [(3, e) for e in range(18, 23)] + [(4, 30)]
    sets = spark.createDataFrame(rows, "set_id bigint, elem_id bigint")
    got = sorted(r.set_id for r in covering.set_cover(sets, eps=0.01).collect())
    assert got == [1, 3, 4]
    assert covering.set_cover(sets.limit(0)).count() == 0


def test_every_set_of_a_clique_covers_the_rest(spark):
    sets = covering.cover_from_graph(clique(spark, 6))
    cover = covering.set_cover(sets, eps=0.1)
    assert cover.count() == 2 and sets.join(cover, "set_id", "left_semi").select("elem_id").distinct().count() == 6
