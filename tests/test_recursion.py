"""Recursion in SQL against brute force."""

from micro import values

from sparkgraphs.model import catalog
from sparkgraphs.ops import queries as ops
from sparkgraphs.ops import relational as rel


def reached(arcs):
    near = {}
    for a, b in arcs:
        near.setdefault(a, []).append(b)
    dist = {min(near): 0}
    for v in (order := list(dist)):
        for u in near.get(v, []):
            if u not in dist:
                dist[u] = dist[v] + 1
                order.append(u)
    return sorted(dist.items(), key=repr)


def test_recursion_runs_until_nothing_is_new(spark, sf):
    chain = [(i, i + 1) for i in range(14)] + [(14, 3), (2, 2), (20, 0)]
    got = values(rel.recursive_reach(spark.createDataFrame(chain, "src bigint, dst bigint")))
    assert got == reached(chain) and max(d for _, d in got) == 14
    assert rel.recursive_reach(spark.createDataFrame([], "src bigint, dst bigint")).count() == 0
    arcs = [(r.src, r.dst) for r in catalog.load(spark, sf, "event_succession").edges.collect()]
    assert values(ops.recursive_sql_whole(spark, sf)) == reached(arcs)
