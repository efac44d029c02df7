import micro
import pytest
from micro import values

from sparkgraphs.algo import covering
from sparkgraphs.model import catalog


@pytest.mark.parametrize("heuristic", ["llf"])
def test_colours_by_prefixes(spark, sf, monkeypatch, heuristic):
    monkeypatch.setattr(covering, "PREFIX", 700)
    g = catalog.load(spark, sf, "cust_part_urgent").layout()
    for one in (g, micro.graph(spark, [(1, 2)], vertices=[7])):
        stats = covering.RunStats()
        assert values(covering.color(one, heuristic=heuristic, method="prefix", stats=stats)) == values(covering.color(one, heuristic=heuristic))
        assert stats.depth < 20
