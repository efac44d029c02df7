from itertools import product

import micro
from micro import values

from sparkgraphs.algo import bfs
from sparkgraphs.model import catalog
from sparkgraphs.queries import QUERIES


def test_betweenness_of_a_torus_takes_no_job_a_level(spark, sf, monkeypatch):
    g = catalog.load(spark, sf, "torus", layout=True)
    want = bfs.betweenness(g, 0)
    got = bfs.betweenness(g, 0, fits=bfs.FITS)
    assert [(v, round(x, 9)) for v, x in values(got)] == [(v, round(x, 9)) for v, x in values(want)]
    monkeypatch.setattr(bfs, "edge_map", None)
    dist = [sum(min(x, 5 - x) for x in at) for at in product(range(5), repeat=3)]
    assert values(QUERIES["betweenness_torus"](spark, sf)) == [(125, sum(d - 1 for d in dist if d))]


def test_betweenness_in_a_task_on_odd_graphs(spark):
    diamond = micro.graph(spark, [(0, 1), (0, 2), (1, 3), (2, 3), (3, 4), (4, 0)], vertices=[9], directed=True)
    for g in (diamond, micro.empty(spark), micro.graph(spark, [(5, 6), (7, 8)], vertices=[0])):
        for source in (0, 5):
            assert values(bfs.betweenness(g, source, fits=100)) == values(bfs.betweenness(g, source))
    assert values(bfs.betweenness(diamond, 0, fits=3)) == values(bfs.betweenness(diamond, 0))
