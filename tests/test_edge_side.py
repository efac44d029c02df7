"""Plans of a round, zero weights, the dense switch, local counts."""

import micro
import pytest
from micro import values
from pyspark.sql import functions as F

from sparkgraphs.algo import relax
from sparkgraphs.core.edge_map import edge_map
from sparkgraphs.core.histogram import histogram


def test_a_round_does_not_shuffle_the_edges(spark):
    """With broadcasts off: the frontier and the messages are dealt, the edges are read where they lie."""
    g = micro.clique(spark, 20).layout()
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        live = g.vertices.where("v > 9")
        for mode, most in (("blocked", 3), ("push", 3)):
            out = edge_map(g.edges, g.vertices.where("v < 10"), [F.min("src").alias("m")], live=live, mode=mode)
            plan = out._jdf.queryExecution().executedPlan().toString()
            edge_side = plan[: plan.index("by_src_")]
            assert plan.count("Exchange hashpartitioning") <= most and edge_side.rsplit("\n", 4)[-1].count("Exchange") == 0, plan
            assert values(out) == [(v, 0) for v in range(10, 20)]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)


def test_weighted_search_with_zero_weights_and_the_dense_switch(spark):
    g = micro.graph(spark, [(0, 1, 0), (1, 2, 0), (0, 2, 3), (2, 3, 2), (3, 4, 0)], vertices=[9])
    want = [(0, 0), (1, 0), (2, 0), (3, 2), (4, 2), (9, None)]
    for switch in (True, False):
        assert values(relax.weighted_bfs(g, 0, allow_zero=True, dense_switch=switch)) == want
    with pytest.raises(ValueError):
        relax.weighted_bfs(g, 0)


def test_local_counts_need_no_shuffle(spark):
    df = spark.range(5000).select((F.col("id") % 7).alias("k"))
    out = histogram(df, "k", strategy="local_first")
    assert out._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") == 1
    assert values(out) == values(histogram(df, "k"))
